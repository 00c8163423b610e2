"""One module per section of the inventory; importing this package registers them all."""
from relanom.queries import labels_metrics  # noqa: F401
from relanom.queries import graph_views  # noqa: F401
from relanom.queries import rule_queries  # noqa: F401
from relanom.queries import experiment_queries  # noqa: F401
from relanom.queries import operators, stream_queries  # noqa: F401
from relanom.queries import layer_queries  # noqa: F401
from relanom.queries import extension_queries  # noqa: F401

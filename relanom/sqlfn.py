"""Functions of one's own for SQL users: a table function over rules, a grouped aggregate, Arrow kernels."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, StringType, StructType

_PART = re.compile(r"\s*(.+?)\s*(<=|>=|<|>|=)\s*(\S+)\s*$")


# Types as objects: this module is imported before there is a session that could parse them.
_CONDITION = StructType().add("place", IntegerType()).add("feature", StringType()).add("op", StringType()).add("threshold", DoubleType())


@F.udtf(returnType=_CONDITION)
class RuleConditions:
    """Rows of a rule's conjunction; a part that is no comparison with a number is left out, null gives no row."""

    def eval(self, text: str):
        for place, part in enumerate((text or "").split(" AND ")):
            found = _PART.match(part)
            try:
                if found:
                    yield place, found[1], found[2], float(found[3])
            except ValueError:
                continue


@F.pandas_udf(DoubleType())
def group_auroc(score: pd.Series, y: pd.Series) -> float:
    """AUROC of a small group, ties as one half; null without both classes. Large groups belong to ``metrics.ranking``."""
    rank, positive = score.rank(), y == 1
    p, n = int(positive.sum()), int((y == 0).sum())
    return float((rank[positive].sum() - p * (p + 1) / 2) / (p * n)) if p and n else None


def register(spark: SparkSession) -> None:
    """``rule_conditions`` and ``group_auroc`` for SQL."""
    spark.udtf.register("rule_conditions", RuleConditions)
    spark.udf.register("group_auroc", group_auroc)


def row_norms(rows: DataFrame, key: str, vector: str) -> DataFrame:
    """(key, norm2) by an Arrow kernel, a batch at a time; a null vector gives null."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            norms = [None if v is None else float(sum(x * x for x in v if x is not None)) for v in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(norms, pa.float64())], names=[key, "norm2"])

    return rows.select(F.col(key).cast("long").alias(key), F.col(vector).cast("array<double>").alias(vector)).mapInArrow(run, f"{key} long, norm2 double")

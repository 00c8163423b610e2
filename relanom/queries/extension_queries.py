"""Extensions, costs and functions of one's own, with oracles where SQL can tell."""

from __future__ import annotations

from pyspark.sql import functions as F

from relanom import cost, detector, extensions, graph, isolation, nn, sqlfn, tasks, views
from relanom.queries.layer_queries import _C, _O, _ROW, AWAY, W_PLACED, W_REVERSE, W_SELF, _states
from relanom.registry import query
from relanom.sources import load

TX = tasks.TX_SQL
_CUTS = ("1997-01-01", "1999-06-01")


# ---- aggregators
_W = "exp(0.7 * o.x0 - 0.4 * o.x1)"
_AGG = {
    "mean": ("avg(o.x0)", "avg(o.x1)"),
    "sum": ("sum(o.x0)", "sum(o.x1)"),
    "max": ("max(o.x0)", "max(o.x1)"),
    "attention": (f"sum({_W} * o.x0) / sum({_W})", f"sum({_W} * o.x1) / sum({_W})"),
}

for _kind, (_a, _b) in _AGG.items():

    @query(f"mp_aggregate_{_kind}", f"WITH {_O} SELECT cust AS dst, round({_a} + 1e-8, 6) AS m0, round({_b} + 1e-8, 6) AS m1 FROM o GROUP BY cust")
    def _aggregate(spark, sf_dir, kind=_kind):
        o, c, e = _states(spark, sf_dir)
        q = c.select("nid", F.array(F.lit(0.7), F.lit(-0.4)).alias("q"))
        m = extensions.messages(e, o, 2, kind, q)
        return m.select((F.col("dst") - AWAY).alias("dst"), *(F.round(F.col("m")[i] + 1e-8, 6).alias(f"m{i}") for i in (0, 1)))


# ---- incremental construction
def _slices(e):
    a, b = (F.lit(c).cast("timestamp_ntz") for c in _CUTS)
    return e.filter(F.col("t") < a), e.filter((F.col("t") >= a) & (F.col("t") < b)), e.filter(F.col("t") >= b)


@query("incremental_means", f"WITH {_O} SELECT cust AS dst, count(*)::BIGINT AS n, round(avg(x0) + 1e-8, 6) AS m0, round(avg(x1) + 1e-8, 6) AS m1 FROM o GROUP BY cust")
def _incremental(spark, sf_dir):
    """Three slices of orders, added one after the other, give the means of all orders."""
    o, _, e = _states(spark, sf_dir)
    first, *later = [extensions.running_means(s, o, 2) for s in _slices(e)]
    for new in later:
        first = extensions.merged(first, new)
    return first.select((F.col("dst") - AWAY).alias("dst"), "n", *(F.round(F.col(f"s{i}") / F.col("n") + 1e-8, 6).alias(f"m{i}") for i in (0, 1)))


@query("incremental_touched", f"SELECT DISTINCT o_custkey AS nid FROM orders WHERE o_orderdate >= TIMESTAMP '{_CUTS[1]}'")
def _touched(spark, sf_dir):
    """Customers that the newest slice reaches."""
    o, c, e = _states(spark, sf_dir)
    return extensions.touched(c, _slices(e)[2]).select((F.col("nid") - AWAY).alias("nid"))


# ---- rules without labels, two-hop view
@query("rules_unsupervised")
def _unsupervised(spark, sf_dir):
    """Rare short paths of an isolation forest over the purchase view."""
    view = views.purchase(spark, sf_dir)
    names = ["bought_180d", "price_max", "articles", "span", "since_last", "trend"]
    rows = view.select(F.col("entity").alias("target"), F.array(*(F.col(n).cast("double") for n in names)).alias("x"))
    return extensions.rare_rules(view, isolation.fit(rows, 50, 256), names)


@query("flat_purchase_two_hop", f"WITH {TX} SELECT customer AS entity, count(*)::BIGINT AS bought, round(avg(p_size) + 1e-8, 6) AS size_mean, round(avg(p_retailprice) + 1e-7, 4) AS list_price_mean, max(p_retailprice) AS list_price_max, count(DISTINCT p_brand)::BIGINT AS brands FROM tx JOIN part ON part = p_partkey WHERE age >= 0 GROUP BY customer")
def _two_hop(spark, sf_dir):
    v = extensions.purchase_two_hop(spark, sf_dir)
    return v.select("entity", "bought", F.round(F.col("size_mean") + 1e-8, 6).alias("size_mean"), F.round(F.col("list_price_mean") + 1e-7, 4).alias("list_price_mean"), "list_price_max", "brands")


# ---- explanations
@query("explain_coordinates", """WITH c AS (SELECT vec_id AS target, unnest(range(1, 65)) AS i, embedding FROM embeddings),
e AS (SELECT target, i, pow(embedding[i]::DOUBLE - 0.1 * ((i - 1) % 3), 2) AS error FROM c),
k AS (SELECT *, row_number() OVER (PARTITION BY target ORDER BY error DESC, i) AS place FROM e)
SELECT target, place::BIGINT AS place, 'v' || (i - 1) AS name, round(error, 6) AS error FROM k WHERE place <= 3""")
def _coordinates(spark, sf_dir):
    fixed = F.array(*(F.lit(0.1 * (i % 3)) for i in range(64)))
    rows = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("target"), F.col("embedding").cast("array<double>").alias("x"), fixed.alias("out"))
    return extensions.coordinate_errors(rows, [f"v{i}" for i in range(64)]).select("target", "place", "name", F.round("error", 6).alias("error"))


_Z = lambda i, m: f"greatest(0.0, {_ROW(W_SELF[i], 'c.x0', 'c.x1')} + {m})"
_M = lambda i: f"coalesce({_ROW(W_PLACED[i], 'm.a', 'm.b')}, 0)"


@query("explain_relations", f"""WITH {_O}, {_C}, m AS (SELECT cust, avg(x0) AS a, avg(x1) AS b FROM o GROUP BY cust)
SELECT c.id AS nid, round(pow({_Z(0, _M(0))} - {_Z(0, 0)}, 2) + pow({_Z(1, _M(1))} - {_Z(1, 0)}, 2) + 1e-7, 4) AS effect FROM c LEFT JOIN m ON c.id = m.cust""")
def _relations(spark, sf_dir):
    """How far a customer's state moves when the relation to its orders is left out."""
    o, c, e = _states(spark, sf_dir)
    effects = extensions.relation_effects(graph.with_reverse(e), o.unionByName(c), W_SELF, {"placed_by": W_PLACED, "placed_by_rev": W_REVERSE})
    kept = effects.filter((F.col("rel") == "placed_by") & (F.col("nid") >= AWAY))
    return kept.select((F.col("nid") - AWAY).alias("nid"), F.round(F.col("effect") + 1e-7, 4).alias("effect"))


# ---- costs
@query("cost_steps")
def _cost(spark, sf_dir):
    """Rows and seconds of the steps before training on the cyber task."""
    return cost.timed(spark, {"log": lambda: tasks.auth_log(spark, sf_dir), "flat_view": lambda: views.cyber(spark, sf_dir), "receptive_fields": lambda: detector.cyber_task(spark, sf_dir).rows, "edges": lambda: graph.event_graph(spark, sf_dir)})


@query("cost_parameters", "WITH d AS (SELECT max(len(embedding)) AS d FROM embeddings) SELECT 'autoencoder' AS model, sum((i + 1) * o)::BIGINT AS parameters FROM (SELECT unnest([d, 16, 4, 16]) AS i, unnest([16, 4, 16, d]) AS o FROM d)")
def _parameters(spark, sf_dir):
    """Parameters of an autoencoder as wide as the vectors are."""
    width = load(spark, sf_dir, "embeddings").agg(F.max(F.size("embedding"))).first()[0]
    model = nn.Autoencoder(nn.Spec(width, ()), 16)
    return spark.createDataFrame([("autoencoder", cost.parameters(model.shapes()))], "model string, parameters long")


# ---- functions of one's own
_RULE_TEXTS = ["bought <= 3.0", "bought <= 3.0 AND since_last > 30.0", "f = 2.5 AND g >= 1 AND no comparison"]


@query("udtf_conditions", "SELECT * FROM (VALUES (0, 0, 'bought', '<=', 3.0), (1, 0, 'bought', '<=', 3.0), (1, 1, 'since_last', '>', 30.0), (2, 0, 'f', '=', 2.5), (2, 1, 'g', '>=', 1.0)) t(rule, place, feature, op, threshold)".replace("SELECT *", "SELECT rule::BIGINT AS rule, place::BIGINT AS place, feature, op, threshold::DOUBLE AS threshold"))
def _conditions(spark, sf_dir):
    """A table function over rule texts, called laterally."""
    sqlfn.register(spark)
    spark.createDataFrame(list(enumerate(_RULE_TEXTS)), "rule long, text string").createOrReplaceTempView("relanom_rule_texts")
    return spark.sql("SELECT rule, CAST(place AS BIGINT) AS place, feature, op, threshold FROM relanom_rule_texts, LATERAL rule_conditions(text)")


@query("udaf_auroc", """WITH t AS (SELECT n_regionkey AS region, round(c_acctbal / 500) AS s, (c_mktsegment = 'BUILDING')::INT AS y FROM customer JOIN nation ON c_nationkey = n_nationkey)
SELECT a.region::BIGINT AS region, round(avg(CASE WHEN a.s > b.s THEN 1.0 WHEN a.s = b.s THEN 0.5 ELSE 0.0 END), 6) AS auroc FROM t a JOIN t b ON a.region = b.region AND a.y = 1 AND b.y = 0 GROUP BY 1""")
def _udaf(spark, sf_dir):
    c = load(spark, sf_dir, "customer").join(F.broadcast(load(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    g = c.groupBy(F.col("n_regionkey").cast("long").alias("region"))
    return g.agg(sqlfn.group_auroc(F.round(F.col("c_acctbal") / 500).cast("double"), (F.col("c_mktsegment") == "BUILDING").cast("int")).alias("auroc")).select("region", F.round("auroc", 6).alias("auroc"))


@query("kernel_arrow", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS norm2 FROM embeddings")
def _kernel(spark, sf_dir):
    return sqlfn.row_norms(load(spark, sf_dir, "embeddings"), "vec_id", "embedding").select("vec_id", F.round("norm2", 4).alias("norm2"))


for _hint in ("broadcast", "merge", "shuffle_hash"):

    @query(f"join_hint_{_hint}", "SELECT n_regionkey::BIGINT AS region, count(*)::BIGINT AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
    def _hinted(spark, sf_dir, hint=_hint):
        """One join, three physical ways; nations are a fixed table of 25 rows, so broadcasting them is bounded."""
        c, n = load(spark, sf_dir, "customer", ["c_nationkey"]), load(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"])
        return c.join(n.hint(hint), F.col("c_nationkey") == F.col("n_nationkey")).groupBy(F.col("n_regionkey").cast("long").alias("region")).agg(F.count("*").alias("n"))


@query("sketch_distinct")
def _sketches(spark, sf_dir):
    """Distinct machines per user by mergeable sketches: daily sketches are kept and united."""
    daily = tasks.auth_log(spark, sf_dir).groupBy("user", F.to_date("t").alias("day")).agg(F.hll_sketch_agg("machine").alias("s"))
    return daily.groupBy("user").agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("machines"))

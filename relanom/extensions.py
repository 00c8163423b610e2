"""Beyond the core: other aggregators, incremental means, rules without labels, two-hop views, explanations."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relanom import graph, layers, rules, tasks, views
from relanom.sources import load

AGGREGATORS = ("mean", "sum", "max", "attention")


def messages(e: DataFrame, h: DataFrame, width: int, kind: str = "mean", query: DataFrame | None = None) -> DataFrame:
    """(rel, dst, m) by any of ``AGGREGATORS``; all are sums or maxima, so they combine before the shuffle.

    Attention weighs a neighbour by the softmax of its product with ``query`` (nid, q) of the target.
    The largest logit per target is taken off first, in a pass of its own.
    """
    if kind not in AGGREGATORS:
        raise ValueError(f"no aggregator {kind}")
    if kind == "mean":
        return graph.mean_messages(e, h, width)
    joined = e.join(h, e["src"] == h["nid"]).select("rel", "dst", "h")
    if kind == "attention":
        if query is None:
            raise ValueError("attention needs a query per target")
        logit = joined.join(query.select(F.col("nid").alias("dst"), "q"), "dst").withColumn("logit", layers.dot(F.col("h"), F.col("q")))
        top = logit.groupBy("rel", "dst").agg(F.max("logit").alias("top"))
        joined = logit.join(top, ["rel", "dst"]).withColumn("w", F.exp(F.col("logit") - F.col("top")))
        parts = [(F.sum(F.col("w") * F.col("h")[i]) / F.sum("w")).alias(f"m{i}") for i in range(width)]
    else:
        f = F.sum if kind == "sum" else F.max
        parts = [f(F.col("h")[i]).alias(f"m{i}") for i in range(width)]
    out = joined.groupBy("rel", "dst").agg(*parts)
    return out.select("rel", "dst", F.array(*[f"m{i}" for i in range(width)]).alias("m"))


# ---- incremental construction
def running_means(e: DataFrame, h: DataFrame, width: int) -> DataFrame:
    """State of one slice of edges: (rel, dst, n, s0, s1, ...), counts and sums that later slices add to."""
    joined = e.join(h, e["src"] == h["nid"])
    return joined.groupBy("rel", "dst").agg(F.count("*").alias("n"), *[F.sum(F.col("h")[i]).alias(f"s{i}") for i in range(width)])


def merged(state: DataFrame, new: DataFrame) -> DataFrame:
    """State after a further slice; equal to the state of both slices together."""
    return state.unionByName(new).groupBy("rel", "dst").agg(*[F.sum(c).alias(c) for c in state.columns if c not in ("rel", "dst")])


def touched(targets: DataFrame, new: DataFrame) -> DataFrame:
    """Targets (nid, ...) that a new slice reaches: only these need to be scored again."""
    return targets.join(new.select(F.col("dst").alias("nid")).distinct(), "nid", "left_semi")


# ---- rules without labels
def rare_rules(rows: DataFrame, forest: DataFrame, features: list[str], min_support: int = 3, max_share: float = 0.05, depth: int = 3, keep: int = 64) -> DataFrame:
    """(text, support, share): short paths of an isolation forest that few rows satisfy, rarest first; no label is read.

    ``rows`` has the features as columns, ``forest`` is a node table. Only leaves at ``depth`` or above
    count: rows that so few random cuts set apart are unusual. They are measured in the same scan as labelled rules.
    """
    nodes = forest.withColumnRenamed("size", "rows").withColumn("p", F.lit(0.0))
    found = rules.paths(nodes, 1 << 30).filter(F.size("conditions") <= depth).select("conditions").distinct().collect()  # trees x nodes of the forest, which is broadcast anyway
    texts: dict[str, None] = {}
    for r in found:
        short = rules.canonical((features[c["feature"]], c["op"], c["threshold"]) for c in r["conditions"])
        if short:
            texts[rules.text_of(short)] = None
    total = rows.agg(F.count("*").alias("total"))
    measured = rules.measure(rows.withColumn("y", F.lit(0)), sorted(texts)).select("text", "support")
    out = measured.join(F.broadcast(total)).withColumn("share", F.col("support") / F.col("total"))
    return out.filter((F.col("support") >= min_support) & (F.col("share") <= max_share)).orderBy("share", "text").limit(keep).select("text", "support", "share")


# ---- two-hop view
def purchase_two_hop(spark, sf_dir: str, cut: str = tasks.CUT) -> DataFrame:
    """The purchase view with aggregates of the bought articles, two hops away; an option, as flat baselines otherwise see one hop."""
    age = F.datediff(F.lit(cut), "t")
    bought = tasks.transactions(spark, sf_dir).filter(age >= 0).select("customer", "part")
    parts = load(spark, sf_dir, "part", ["p_partkey", "p_brand", "p_size", "p_retailprice"])
    joined = bought.join(parts, F.col("part") == F.col("p_partkey"))
    far = joined.groupBy("customer").agg(F.avg("p_size").alias("size_mean"), F.avg("p_retailprice").alias("list_price_mean"), F.max("p_retailprice").alias("list_price_max"), F.count_distinct("p_brand").alias("brands"))
    return views.purchase(spark, sf_dir, cut).join(far, F.col("entity") == F.col("customer"), "left").drop("customer")


# ---- explanations
def coordinate_errors(rows: DataFrame, names: list[str], top: int = 3) -> DataFrame:
    """(target, place, name, error): the coordinates of (target, x, out) that a reconstruction misses most, ties by place in x."""
    each = F.zip_with("x", "out", lambda a, b: (a - b) * (a - b))
    pairs = F.transform(each, lambda v, i: F.struct((-v).alias("minus"), i.alias("i")))
    best = rows.select("target", F.posexplode(F.slice(F.array_sort(pairs), 1, top)).alias("place", "c"))
    return best.select("target", (F.col("place") + 1).cast("long").alias("place"), F.array(*map(F.lit, names))[F.col("c.i")].alias("name"), (-F.col("c.minus")).alias("error"))


def relation_effects(e: DataFrame, h: DataFrame, w_self, w_rel: dict) -> DataFrame:
    """(nid, rel, effect): squared distance of a node's state with all relations to that without one."""
    whole = layers.layer(e, h, w_self, w_rel).select("nid", F.col("h").alias("z"))
    out = None
    for left_out in w_rel:
        rest = {r: w for r, w in w_rel.items() if r != left_out}
        without = layers.layer(e, h, w_self, rest) if rest else h.select("nid", layers.update(F.col("h"), [], w_self).alias("h"))
        part = whole.join(without, "nid").select("nid", F.lit(left_out).alias("rel"), layers.squared_distance(F.col("z"), F.col("h")).alias("effect"))
        out = part if out is None else out.unionByName(part)
    return out

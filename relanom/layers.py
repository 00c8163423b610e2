"""Layers, decoders and losses as column expressions, for fixed weights and exact checks.

Training runs on numpy (``nn``); these forms stay in generated code and scale with the rows.
A null vector gives null; a relation without a message adds nothing.
"""

from __future__ import annotations

from functools import reduce
from operator import add

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from relanom import graph
from relanom.draws import u

Matrix = list[list[float]]


def affine(x: Column, weights: Matrix, bias: list[float] | None = None) -> Column:
    """W x + b, one row of ``weights`` per output coordinate."""
    rows = [reduce(add, (x[i] * F.lit(float(w)) for i, w in enumerate(row))) + F.lit(float(bias[k] if bias else 0.0)) for k, row in enumerate(weights)]
    return F.when(x.isNotNull(), F.array(*rows))


def project(nodes: DataFrame, weights: Matrix, bias: list[float]) -> DataFrame:
    """Type-specific input projection without a non-linearity: (nid, x) to (nid, h)."""
    return nodes.select("nid", affine(F.col("x"), weights, bias).alias("h"))


def update(own: Column, messages: list[tuple[Column, Matrix]], w_self: Matrix) -> Column:
    """Rectified sum of the projected own state and the projected messages."""
    total = affine(own, w_self)
    for m, weights in messages:
        total = F.when(m.isNull(), total).otherwise(F.zip_with(total, affine(m, weights), lambda a, b: a + b))
    return F.transform(total, lambda v: F.greatest(v, F.lit(0.0)))


def layer(e: DataFrame, h: DataFrame, w_self: Matrix, w_rel: dict[str, Matrix]) -> DataFrame:
    """One step over the whole graph: a shuffle for the means, one to bring them to their node."""
    means = graph.mean_messages(e.filter(F.col("rel").isin(*w_rel)), h, len(w_self[0]))
    wide = means.groupBy("dst").agg(*[F.first(F.when(F.col("rel") == r, F.col("m")), True).alias(f"m{k}") for k, r in enumerate(w_rel)])
    joined = h.join(wide, h["nid"] == wide["dst"], "left")
    return joined.select("nid", update(F.col("h"), [(F.col(f"m{k}"), w) for k, w in enumerate(w_rel.values())], w_self).alias("h"))


def encode(e: DataFrame, h: DataFrame, layers: list[tuple[Matrix, dict[str, Matrix]]]) -> DataFrame:
    """Stacked layers; node ids must differ between types."""
    for w_self, w_rel in layers:
        h = layer(e, h, w_self, w_rel)
    return h


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)


def edge_probability(e: DataFrame, z_src: DataFrame, z_dst: DataFrame, weights: Matrix) -> DataFrame:
    """Logistic bilinear decoder; the relation's matrix is applied to the source side before the edges are joined."""
    left = z_src.select(F.col("nid").alias("src"), affine(F.col("h"), weights).alias("p"))
    right = z_dst.select(F.col("nid").alias("dst"), F.col("h").alias("q"))
    return e.join(left, "src").join(right, "dst").select("rel", "src", "dst", (1 / (1 + F.exp(-dot(F.col("p"), F.col("q"))))).alias("prob"))


def squared_distance(x: Column, y: Column) -> Column:
    return F.aggregate(F.zip_with(x, y, lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)


def objective(rows: DataFrame, edges: DataFrame, pairs: DataFrame, alpha: float, beta: float) -> DataFrame:
    """Mean attribute error + alpha * mean edge cross-entropy of (logit, label) + beta * mean softplus of (negative - positive)."""
    softplus = lambda v: F.greatest(v, F.lit(0.0)) + F.log1p(F.exp(-F.abs(v)))
    terms = rows.select(F.lit("attr").alias("term"), F.col("error").alias("v"))
    terms = terms.unionByName(edges.select(F.lit("struct").alias("term"), softplus(F.when(F.col("label") == 1, -F.col("logit")).otherwise(F.col("logit"))).alias("v")))
    terms = terms.unionByName(pairs.select(F.lit("rank").alias("term"), softplus(F.col("negative") - F.col("positive")).alias("v")))
    part = lambda t: F.coalesce(F.avg(F.when(F.col("term") == t, F.col("v"))), F.lit(0.0))
    out = terms.agg(part("attr").alias("attr"), part("struct").alias("struct"), part("rank").alias("rank"))
    return out.withColumn("total", F.col("attr") + alpha * F.col("struct") + beta * F.col("rank"))


def sample_pairs(rows: DataFrame, per_positive: int, buckets: int = 256, hard: bool = False, salt: str = "pair") -> DataFrame:
    """(positive, negative) of (target, y, score): every positive draws ``per_positive`` buckets of negatives.

    A bucket lends its negative of least draw, or with ``hard`` of highest score. Only one row per bucket
    is kept, so it is joined as a broadcast; draws that hit an empty bucket drop out.
    """
    place = lambda c: F.floor(c * buckets).cast("int")
    negative = rows.filter("y = 0").withColumn("bucket", place(u(F.col("target"), salt)))
    order = F.struct(-F.col("score"), F.col("target")) if hard else F.struct(u(F.col("target"), f"{salt}-in"), F.col("target"))
    lent = negative.groupBy("bucket").agg(F.min_by("target", order).alias("negative"))
    drawn = rows.filter("y = 1").select(F.col("target").alias("positive"), F.explode(F.sequence(F.lit(1), F.lit(per_positive))).alias("j"))
    drawn = drawn.withColumn("bucket", place(u(F.concat_ws(":", "positive", "j"), salt)))
    return drawn.join(F.broadcast(lent), "bucket").select("positive", F.col("j").cast("long").alias("j"), "negative")


def sampled_rank_loss(rows: DataFrame, per_positive: int, buckets: int = 256, hard: bool = False) -> DataFrame:
    """(pairs, loss): mean softplus of negative minus positive score over the drawn pairs of (target, y, score)."""
    score = lambda name: rows.select(F.col("target").alias(name), F.col("score").alias(f"{name}_score"))
    drawn = sample_pairs(rows, per_positive, buckets, hard).join(score("positive"), "positive").join(score("negative"), "negative")
    d = F.col("negative_score") - F.col("positive_score")
    return drawn.agg(F.count("*").alias("pairs"), F.avg(F.greatest(d, F.lit(0.0)) + F.log1p(F.exp(-F.abs(d)))).alias("loss"))


def combined_score(errors: DataFrame, incident: DataFrame, weight: float) -> DataFrame:
    """Attribute error of (nid, error) plus ``weight`` times the mean cross-entropy of the node's edges (dst, prob); no edge adds nothing."""
    edge = incident.groupBy("dst").agg(F.avg(-F.ln("prob")).alias("edge"))
    joined = errors.join(edge, F.col("nid") == F.col("dst"), "left")
    return joined.select("nid", (F.col("error") + weight * F.coalesce("edge", F.lit(0.0))).alias("score"))


def field_sizes(near: DataFrame, fanout: int) -> DataFrame:
    """Per target the neighbours it has and the neighbours a receptive field of ``fanout`` keeps, per relation."""
    return near.groupBy("rel", "dst").agg(F.count("*").alias("degree")).withColumn("kept", F.least(F.col("degree"), F.lit(fanout)).cast("long"))

"""Ranking measures with exact ties: AUROC, AUPRC, precision at k, curves, ranks over methods.

Scores are first counted per distinct value; cumulative counts then come from sums per score
range plus sums within the range, so no window spans the whole table.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def cumulative(scores: DataFrame, by: list[str] | None = None, ranges: int = 64) -> DataFrame:
    """Per group and distinct score: pos, neg and tp, fp at or above it, P, N in total."""
    by = by or []
    counts = scores.groupBy(*by, "score").agg(F.sum("y").cast("long").alias("pos"), F.count_if(F.col("y") == 0).alias("neg"))
    bounds = counts.groupBy(*by).agg(F.percentile_approx("score", [i / ranges for i in range(1, ranges)], 1000).alias("bounds"), F.sum("pos").alias("P"), F.sum("neg").alias("N"))
    joined = counts.join(F.broadcast(bounds), by) if by else counts.join(F.broadcast(bounds))
    # A range is the number of bounds below the score.
    placed = joined.withColumn("range", F.expr("aggregate(bounds, 0, (n, b) -> n + int(b < score))")).drop("bounds")
    sums = placed.groupBy(*by, "range").agg(F.sum("pos").alias("rp"), F.sum("neg").alias("rn"))
    above = Window.partitionBy(*by, F.lit(0)).orderBy(F.col("range").desc()).rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.select(*by, "range", F.coalesce(F.sum("rp").over(above), F.lit(0)).alias("ap"), F.coalesce(F.sum("rn").over(above), F.lit(0)).alias("an"))
    within = Window.partitionBy(*by, "range").orderBy(F.col("score").desc())
    out = placed.join(F.broadcast(sums), [*by, "range"])
    return out.select(*by, "score", "pos", "neg", "P", "N", (F.col("ap") + F.sum("pos").over(within)).alias("tp"), (F.col("an") + F.sum("neg").over(within)).alias("fp"))


def ranking(scores: DataFrame, by: list[str] | None = None) -> DataFrame:
    """auroc, auprc and precision at k = P (expected over ties at the cut) per group of (score, y)."""
    by, c = by or [], cumulative(scores, by)
    better = F.col("N") - F.col("fp")  # negatives strictly below
    auroc = F.try_divide(F.sum(F.col("pos") * (better + F.col("neg") / 2)), F.first(F.col("P") * F.col("N")))
    auprc = F.sum(F.try_divide(F.col("pos"), F.col("P")) * F.try_divide(F.col("tp"), F.col("tp") + F.col("fp")))
    size, start = F.col("pos") + F.col("neg"), F.col("tp") + F.col("fp") - F.col("pos") - F.col("neg")
    share = F.greatest(F.lit(0), F.least(size, F.col("P") - start)) / size
    at_k = F.try_divide(F.sum(F.col("pos") * share), F.first("P"))
    # Without positives or negatives no measure is defined.
    return c.groupBy(*by).agg(F.when((F.first("P") > 0) & (F.first("N") > 0), auroc).alias("auroc"), F.when(F.first("P") > 0, auprc).alias("auprc"), F.when(F.first("P") > 0, at_k).alias("p_at_k"))


def precision_at_k(scores: DataFrame, key: str) -> DataFrame:
    """Precision at k = P with ties at the cut broken by ``key``; only scores at the cut are ranked."""
    c = cumulative(scores)
    cut = c.filter("tp + fp >= P and tp + fp - pos - neg < P").select(F.col("score").alias("cut"), "P", (F.col("tp") - F.col("pos")).alias("hits"), (F.col("P") - (F.col("tp") + F.col("fp") - F.col("pos") - F.col("neg"))).alias("room"))
    tied = scores.join(F.broadcast(cut), F.col("score") == F.col("cut"))
    tied = tied.withColumn("k", F.row_number().over(Window.partitionBy("cut").orderBy(key))).filter("k <= room")
    return tied.groupBy("P", "hits").agg(F.sum("y").alias("more")).select(((F.col("hits") + F.col("more")) / F.col("P")).alias("p_at_k"))


def binned(scores: DataFrame, bins: int = 1000) -> DataFrame:
    """AUROC from a histogram over [0, 1], and how far it can be off: half the pairs that share a bin."""
    b = F.least(F.floor(F.col("score") * bins), F.lit(bins - 1))
    counts = scores.groupBy(b.alias("score")).agg(F.sum("y").alias("pos"), F.count_if(F.col("y") == 0).alias("neg"))
    w = Window.partitionBy(F.lit(0)).orderBy("score").rowsBetween(Window.unboundedPreceding, -1)
    c = counts.withColumn("below", F.coalesce(F.sum("neg").over(w), F.lit(0)))
    pairs = F.sum("pos") * F.sum("neg")
    return c.agg((F.sum(F.col("pos") * (F.col("below") + F.col("neg") / 2)) / pairs).alias("auroc"), (F.sum(F.col("pos") * F.col("neg")) / 2 / pairs).alias("bound"))


def average_rank(results: DataFrame) -> DataFrame:
    """Mean over datasets of each method's rank per metric; ties share the middle rank."""
    w = Window.partitionBy("dataset", "metric")
    ranked = results.withColumn("r", F.rank().over(w.orderBy(F.col("value").desc())) + (F.count("*").over(Window.partitionBy("dataset", "metric", "value")) - 1) / 2)
    return ranked.groupBy("method", "metric").agg(F.avg("r").alias("avg_rank"))


def over_seeds(results: DataFrame) -> DataFrame:
    return results.groupBy("method", "task", "metric").agg(F.avg("value").alias("mean"), F.stddev_samp("value").alias("std"), F.count("*").alias("seeds"))


def paired(results: DataFrame, a: str, b: str) -> DataFrame:
    """Per task and metric the difference of two methods over the seeds both ran: mean, std, seeds and wins of ``a``."""
    value = lambda m: F.max(F.when(F.col("method") == m, F.col("value")))  # noqa: E731  one row per method and seed
    both = results.filter(F.col("method").isin(a, b)).groupBy("task", "metric", "seed").agg(value(a).alias("a"), value(b).alias("b")).filter("a is not null and b is not null")
    d = F.col("a") - F.col("b")
    return both.groupBy("task", "metric").agg(F.avg(d).alias("mean"), F.stddev_samp(d).alias("std"), F.count("*").alias("seeds"), F.count_if(d > 0).alias("wins"))

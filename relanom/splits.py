"""Splits, caps and class weights."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from relanom.draws import u


def by_hash(key: Column, salt: str = "split") -> Column:
    draw = u(key, salt)
    return F.when(draw < 0.7, "train").when(draw < 0.85, "valid").otherwise("test")


def by_time(t: Column, valid_from: str, test_from: str) -> Column:
    return F.when(t < F.lit(valid_from).cast("timestamp_ntz"), "train").when(t < F.lit(test_from).cast("timestamp_ntz"), "valid").otherwise("test")


def cap(rows: DataFrame, n: int, key: str, salt: str = "cap") -> DataFrame:
    """At most n rows: all positives first, then by draw; top-n keeps n rows per task, nothing is sorted globally."""
    return rows.orderBy(F.col("y").desc(), u(F.col(key), salt), key).limit(n)


def drawn_cap(rows: DataFrame, n: int, key: Column, salt: str = "cap") -> DataFrame:
    """About n rows in one scan, nothing sorted: all positives if they fit, and negatives whose draw is below the share that fills up."""
    counts = rows.agg(F.count_if(F.col("y") == 1).alias("p"), F.count_if(F.col("y") == 0).alias("q")).first()
    share = lambda room, size: min(1.0, room / size) if size else 1.0
    kept = min(counts["p"], n)
    draw = u(key, salt)
    return rows.filter(F.when(F.col("y") == 1, draw < share(n, counts["p"])).when(F.col("y") == 0, draw < share(n - kept, counts["q"])).otherwise(False))


def class_weights(rows: DataFrame) -> DataFrame:
    """(y, weight) with n / (2 n_c)."""
    counts = rows.groupBy("y").agg(F.count("*").alias("n_c"))
    total = counts.agg(F.sum("n_c").alias("n"))
    return counts.join(F.broadcast(total)).select("y", (F.col("n") / (2 * F.col("n_c"))).alias("weight"))


def context_window(partition: str, order: str, seconds: int | None = None):
    """Rows of the same entity strictly before the current one, within ``seconds`` if given."""
    w = Window.partitionBy(partition).orderBy(order)
    return w.rangeBetween(-seconds * 1_000_000 if seconds else Window.unboundedPreceding, -1)

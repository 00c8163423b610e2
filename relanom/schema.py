"""Candidate links between tables from the data alone."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WHOLE = ("int", "bigint", "smallint")


def _statistics(name: str, df: DataFrame) -> list[dict]:
    """Per whole-number column: rows, distinct values (sketched), least and greatest; one scan."""
    columns = [c for c, t in df.dtypes if t in WHOLE]
    if not columns:
        return []
    aggs = [f(c).alias(f"{k}{i}") for i, c in enumerate(columns) for k, f in (("n", F.count), ("d", F.approx_count_distinct), ("a", F.min), ("b", F.max))]
    row = df.agg(*aggs).first()
    return [{"table": name, "column": c, "n": row[f"n{i}"], "d": row[f"d{i}"], "a": row[f"a{i}"], "b": row[f"b{i}"]} for i, c in enumerate(columns) if row[f"n{i}"]]


def infer_links(tables: dict[str, DataFrame], min_inclusion: float = 1.0) -> DataFrame:
    """(child, foreign, parent, parent_key, inclusion) of column pairs whose child values lie in a key of another table.

    Sketched distinct counts and ranges rule out most pairs; a key is then confirmed exactly, and the
    inclusion is the share of distinct child values found. Small whole numbers fit many keys by
    chance, so candidates are proposals to choose from. Tables without whole numbers give none.
    """
    spark = next(iter(tables.values())).sparkSession
    stats = [s for name, df in tables.items() for s in _statistics(name, df)]
    keys = [s for s in stats if s["d"] >= 0.85 * s["n"]]
    exact = [s for s in keys if tables[s["table"]].select(s["column"]).na.drop().groupBy(s["column"]).count().filter("count > 1").isEmpty()]
    out = spark.createDataFrame([], "child string, foreign string, parent string, parent_key string, inclusion double")
    for key in exact:
        parent = tables[key["table"]].select(F.col(key["column"]).cast("long").alias("k"))
        for s in stats:
            if s["table"] == key["table"] or s["d"] > 1.15 * key["d"] or (min_inclusion >= 1 and (s["a"] < key["a"] or s["b"] > key["b"])):
                continue
            values = tables[s["table"]].select(F.col(s["column"]).cast("long").alias("v")).na.drop().distinct()
            share = values.join(parent, F.col("v") == F.col("k"), "left").agg(F.avg(F.col("k").isNotNull().cast("double")).alias("inclusion"))
            out = out.unionByName(share.select(*(F.lit(v).alias(c) for c, v in (("child", s["table"]), ("foreign", s["column"]), ("parent", key["table"]), ("parent_key", key["column"]))), "inclusion"))
    return out.filter(F.col("inclusion") >= min_inclusion)

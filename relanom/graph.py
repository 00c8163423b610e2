"""Typed relational graph: nodes per type, edges per relation, as-of cuts and sampling."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from relanom import tasks
from relanom.draws import u
from relanom.sources import load


@dataclass(frozen=True)
class Link:
    """A foreign key: relation name, child table and columns, parent table and key."""

    name: str
    child: str
    key: str
    foreign: str
    parent: str
    parent_key: str
    time: str | None = None


LINKS = [
    Link("placed_by", "orders", "o_orderkey", "o_custkey", "customer", "c_custkey", "o_orderdate"),
    Link("customer_in", "customer", "c_custkey", "c_nationkey", "nation", "n_nationkey"),
    Link("supplier_in", "supplier", "s_suppkey", "s_nationkey", "nation", "n_nationkey"),
    Link("nation_in", "nation", "n_nationkey", "n_regionkey", "region", "r_regionkey"),
    Link("event_of", "events", "event_id", "user_id", "customer", "c_custkey", "ts"),
]


def nodes(spark: SparkSession, sf_dir: str, table: str, key: str, time: str | None = None, features: list[str] | None = None) -> DataFrame:
    x = F.array(*(F.col(c).cast("double") for c in features or []))
    return load(spark, sf_dir, table).select(F.lit(table).alias("ntype"), F.col(key).cast("long").alias("nid"), (F.col(time) if time else F.lit(None).cast("timestamp_ntz")).alias("t"), x.alias("x"))


def edges(spark: SparkSession, sf_dir: str, links: list[Link] = LINKS) -> DataFrame:
    """(rel, src, dst, t); a projection of each child: no join, since the key's integrity is audited once by ``orphans``."""
    parts = [load(spark, sf_dir, k.child).select(F.lit(k.name).alias("rel"), F.col(k.key).cast("long").alias("src"), F.col(k.foreign).cast("long").alias("dst"), (F.col(k.time) if k.time else F.lit(None).cast("timestamp_ntz")).alias("t")).filter("dst is not null") for k in links]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def with_reverse(e: DataFrame) -> DataFrame:
    return e.unionByName(e.select(F.concat(F.col("rel"), F.lit("_rev")).alias("rel"), F.col("dst").alias("src"), F.col("src").alias("dst"), "t"))


def orphans(spark: SparkSession, sf_dir: str, link: Link) -> DataFrame:
    child, parent = load(spark, sf_dir, link.child), load(spark, sf_dir, link.parent)
    return child.join(parent, F.col(link.foreign) == F.col(link.parent_key), "left_anti").filter(F.col(link.foreign).isNotNull()).select(F.lit(link.name).alias("rel"), F.col(link.key).cast("long").alias("src"))


def as_of(e: DataFrame, cut: str) -> DataFrame:
    """Edges known at the cut; untimed ones always are."""
    return e.filter(F.col("t").isNull() | (F.col("t") <= F.lit(cut).cast("timestamp_ntz")))


def degrees(e: DataFrame) -> DataFrame:
    return e.groupBy("rel", "dst").agg(F.count("*").alias("degree"))


def fanout(e: DataFrame, f: int, salt: str = "fan") -> DataFrame:
    """At most f edges per (rel, dst), chosen by draw; a hub's rows are first cut per salted part, so no task sorts a hub alone."""
    draw = u(F.concat_ws(":", "rel", "src", "dst"), salt)
    part = F.pmod(F.xxhash64("src"), F.lit(16))
    local = e.withColumn("draw", draw).withColumn("part", part).withColumn("k", F.row_number().over(Window.partitionBy("rel", "dst", "part").orderBy("draw", "src"))).filter(F.col("k") <= f)
    return local.withColumn("k", F.row_number().over(Window.partitionBy("rel", "dst").orderBy("draw", "src"))).filter(F.col("k") <= f).drop("k", "part", "draw")


def negative_edges(e: DataFrame, n_dst: Column | int, salt: str = "neg") -> DataFrame:
    """For every edge a drawn endpoint in [0, n_dst) that is no edge; draws that hit an edge drop out by the anti join."""
    drawn = e.select("rel", "src", F.floor(u(F.concat_ws(":", "rel", "src", "dst"), salt) * n_dst).cast("long").alias("dst")).distinct()
    return drawn.join(e.select("rel", "src", "dst"), ["rel", "src", "dst"], "left_anti")


def khop(e: DataFrame, seeds: DataFrame, k: int, f: int) -> DataFrame:
    """(nid, hop) reached from the seeds along capped edges, dst to src; one join per hop."""
    capped, reached = fanout(e, f).select("src", "dst"), seeds.select("nid", F.lit(0).alias("hop"))
    front = reached
    for hop in range(1, k + 1):
        front = front.join(capped, front["nid"] == capped["dst"]).select(F.col("src").alias("nid"), F.lit(hop).alias("hop")).distinct()
        reached = reached.unionByName(front)
    return reached.groupBy("nid").agg(F.min("hop").alias("hop"))


def anchors(targets: DataFrame, per_bucket: int, buckets: int, start: str, days: int) -> DataFrame:
    """All positives, and in each time bucket the first negatives by draw."""
    b = F.least(F.floor(F.datediff("t", F.lit(start)) * buckets / days), F.lit(buckets - 1)).cast("int")
    rows = targets.withColumn("bucket", b)
    ranked = rows.filter("y = 0").withColumn("k", F.row_number().over(Window.partitionBy("bucket").orderBy(u(F.col("event"), "anchor"), "event"))).filter(F.col("k") <= per_bucket).drop("k")
    return rows.filter("y = 1").unionByName(ranked)


def context(anchor: DataFrame, logs: DataFrame, seconds: int, cap: int) -> DataFrame:
    """Log rows of the anchor's user within the seconds before it: an equality join on user and time bin, then the exact interval."""
    width = F.lit(seconds * 1_000_000)
    a = anchor.select("event", "user", F.unix_micros(F.col("t").cast("timestamp")).alias("us")).withColumn("bin", F.explode(F.array(F.floor(F.col("us") / width), F.floor(F.col("us") / width) - 1)))
    rows = logs.select(F.col("event").alias("other"), F.col("user").alias("who"), "log", F.unix_micros(F.col("t").cast("timestamp")).alias("at")).withColumn("b", F.floor(F.col("at") / width))
    near = a.join(rows, (F.col("user") == F.col("who")) & (F.col("bin") == F.col("b")) & (F.col("at") < F.col("us")) & (F.col("at") >= F.col("us") - width))
    ranked = near.withColumn("k", F.row_number().over(Window.partitionBy("event").orderBy(F.col("at").desc(), "other")))
    return ranked.filter(F.col("k") <= cap).select("event", "other", "log")


def mean_messages(e: DataFrame, h: DataFrame, width: int) -> DataFrame:
    """Mean of the neighbours' vectors per (rel, dst): partial sums before the shuffle; no neighbour, no row."""
    joined = e.join(h, e["src"] == h["nid"]).select("rel", "dst", "h")
    sums = joined.groupBy("rel", "dst").agg(*[F.avg(F.col("h")[i]).alias(f"m{i}") for i in range(width)])
    return sums.select("rel", "dst", F.array(*[f"m{i}" for i in range(width)]).alias("m"))


def event_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges of the cyber task: log rows to their user and machine."""
    logs = tasks.auth_log(spark, sf_dir)
    to = lambda name, c: logs.select(F.concat(F.col("log"), F.lit(f"_{name}")).alias("rel"), F.col("event").alias("src"), F.col(c).cast("long").alias("dst"), "t")
    return to("user", "user").unionByName(to("machine", "machine"))

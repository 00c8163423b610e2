"""The three tasks: their logs, targets and presets, derived from the star-schema and event tables."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relanom.sources import load

CUT = "2001-02-01"
HORIZON = WINDOW = 180
PREVIOUS = 4


@dataclass(frozen=True)
class Preset:
    """Settings of rule mining; max_depth 30 is the deepest tree that MLlib grows. ``train_cap`` None: the forest grows from all train rows."""

    train_cap: int | None
    trees: int
    max_depth: int
    min_leaf: int
    first_trees: int
    leaf_rows: int
    select_on: str
    min_support: int
    min_confidence: float
    leaf_positive: float = 0.5
    seeds: int = 30
    pool: int = 2000
    max_rules: int = 64


#: Settings of the three tasks. The published caps (500,000, 200,000 and 200,000 train rows) can be set, but are not.
PRESETS = {
    "cyber": Preset(None, 1200, 30, 1, 200, 8, "valid", 3, 0.02),
    "review": Preset(None, 200, 10, 5, 100, 5, "train", 1, 0.0),
    "purchase": Preset(None, 200, 10, 5, 100, 5, "train", 1, 0.0),
}


def small(preset: Preset, trees: int = 12, depth: int = 5) -> Preset:
    """A preset for one machine: fewer and flatter trees, the same filters."""
    return Preset(preset.train_cap, trees, depth, max(2, preset.min_leaf), min(trees, preset.first_trees), preset.leaf_rows, preset.select_on, preset.min_support, preset.min_confidence)


def transactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items with their order's customer and date: customer, part, t, price, quantity, flag."""
    lines = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", "l_quantity", "l_extendedprice", "l_discount", "l_returnflag"])
    orders = load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderdate"])
    joined = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return joined.select(F.col("o_custkey").alias("customer"), F.col("l_partkey").alias("part"), F.col("o_orderdate").alias("t"), (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("price"), F.col("l_quantity").alias("quantity"), F.col("l_returnflag").alias("flag"))


def reviews(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Returned or accepted items as reviews with a rating of 1 to 5."""
    return transactions(spark, sf_dir).filter("flag <> 'N'").withColumn("rating", 1 + F.floor((F.col("quantity") - 1) / 10))


def auth_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All logs of the cyber task: event, t, user, machine, kind, value, log."""
    events = load(spark, sf_dir, "events")
    log = F.when(F.col("event_type").isin("signup", "purchase"), "auth").when(F.col("event_type") == "click", "process").when(F.col("event_type") == "view", "dns").otherwise("flow")
    return events.select(F.col("event_id").alias("event"), F.col("ts").alias("t"), F.col("user_id").alias("user"), F.get_json_object("props", "$.k").cast("int").alias("machine"), F.col("event_type").alias("kind"), "value", log.alias("log"))


TX_SQL = """tx AS (
  SELECT o_custkey AS customer, l_partkey AS part, o_orderdate AS t, l_extendedprice * (1 - l_discount) AS price, l_quantity AS quantity, l_returnflag AS flag,
         (1 + floor((l_quantity - 1) / 10))::BIGINT AS rating, date_diff('day', o_orderdate, TIMESTAMP '2001-02-01') AS age
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey
)"""
LOG_SQL = """log AS (
  SELECT event_id AS event, ts AS t, user_id AS "user", json_extract_string(props, '$.k')::INT AS machine, event_type AS kind, value,
         CASE WHEN event_type IN ('signup', 'purchase') THEN 'auth' WHEN event_type = 'click' THEN 'process' WHEN event_type = 'view' THEN 'dns' ELSE 'flow' END AS log
  FROM events
)"""

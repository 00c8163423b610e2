"""Flattened views: one row per target, for rule mining and tabular baselines only.

Every value uses rows at or before the target's time; windows end strictly before it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from relanom import tasks

WIDTHS = {"10m": 600, "1h": 3600, "1d": 86400}


def _micros(c: str = "t"):
    return F.unix_micros(F.col(c).cast("timestamp"))


def distinct_within(rows: DataFrame, key: str, item: str, seconds: int, name: str) -> DataFrame:
    """Adds the number of distinct items of the key in the ``seconds`` before each row (``us``), exactly and without a set.

    A use of an item keeps it in the window until ``seconds`` later; overlapping stays of one item
    merge. Each merged stay is +1 at its start and -1 at an added row at its end, and one running sum counts them.
    """
    wide = seconds * 1_000_000
    uses = Window.partitionBy(key, item).orderBy("us")
    before, after, known = F.lag("us").over(uses), F.lead("us").over(uses), F.col(item).isNotNull()
    marked = rows.withColumn("_starts", (known & (before.isNull() | (F.col("us") - before > wide))).cast("int")).withColumn("_ends", known & (after.isNull() | (after - F.col("us") > wide)))
    step = lambda us, delta, end: F.struct(us.alias("us"), delta.alias("delta"), F.lit(end).alias("end"))
    steps = F.array_compact(F.array(step(F.col("us"), F.col("_starts"), False), F.when(F.col("_ends"), step(F.col("us") + wide, F.lit(-1), True))))
    placed = marked.withColumn("_step", F.explode(steps)).withColumn("us", F.col("_step.us"))
    running = Window.partitionBy(key).orderBy("us").rangeBetween(Window.unboundedPreceding, -1)
    counted = placed.withColumn(name, F.coalesce(F.sum("_step.delta").over(running), F.lit(0)))
    return counted.filter("not _step.end").drop("_starts", "_ends", "_step")


def cyber(spark, sf_dir: str) -> DataFrame:
    """Features of each authentication event: attributes, pair novelty, recent activity of user and machine, fan-out.

    Windows over the user's rows share one shuffle, those over the machine's another.
    """
    logs = distinct_within(tasks.auth_log(spark, sf_dir).withColumn("us", _micros()), "user", "machine", 86400, "fanout_1d")
    # Rows of one entity at one instant are not before each other.
    back = lambda key, seconds=None: Window.partitionBy(key).orderBy("us").rangeBetween(-seconds * 1_000_000 if seconds else Window.unboundedPreceding, -1)
    pair = Window.partitionBy("user", "machine").orderBy("us").rangeBetween(Window.unboundedPreceding, -1)
    auth = F.col("log") == "auth"
    out = logs.withColumns({"pair_before": F.coalesce(F.count_if(auth).over(pair), F.lit(0)), "pair_last": F.max(F.when(auth, F.col("us"))).over(pair)})
    out = out.withColumns({f"user_{log}_{name}": F.count_if(F.col("log") == log).over(back("user", s)) for log in ("auth", "dns", "flow", "process") for name, s in WIDTHS.items()})
    first = (auth & (F.col("pair_before") == 0)).cast("int")
    out = out.withColumn("first_pair", first)
    out = out.withColumns({f"machine_auth_{name}": F.count_if(auth).over(back("machine", s)) for name, s in WIDTHS.items()} | {"machine_users": F.coalesce(F.sum("first_pair").over(back("machine")), F.lit(0))})
    out = out.filter("log = 'auth'")
    since = (F.col("us") - F.col("pair_last")) / 1e6
    return out.select("event", "t", "user", "machine", "value", F.when(F.col("kind") == "signup", 0).otherwise(1).alias("kind_code"), F.hour("t").alias("hour"), F.weekday("t").alias("weekday"), "pair_before", since.alias("pair_seconds"), F.col("first_pair").alias("novel"), *[c for c in out.columns if c.startswith("user_")], *[c for c in out.columns if c.startswith("machine_auth")], "machine_users", "fanout_1d")


def review(spark, sf_dir: str, cut: str = tasks.CUT) -> DataFrame:
    """Customer features from reviews up to the cut: recency counts, ratings, product count, span; no product attributes."""
    age = F.datediff(F.lit(cut), "t")
    rows = tasks.reviews(spark, sf_dir).withColumn("age", age).filter("age >= 0")
    r, n = F.col("rating"), F.count("rating")
    # Sums of whole numbers are the same in any order, and so are the rules that are mined from them.
    spread = F.when(n > 1, F.sqrt((n * F.sum(r * r) - F.sum(r) * F.sum(r)) / (n * (n - 1))))
    return rows.groupBy(F.col("customer").alias("entity")).agg(
        *[F.count_if(F.col("age") < d).alias(f"reviews_{d}d") for d in (30, 90, 180)],
        F.count("*").alias("reviews"), F.avg(r).alias("rating_mean"), spread.alias("rating_std"), F.min(r).alias("rating_min"), F.max(r).alias("rating_max"),
        F.max(F.struct(-F.col("age"), r)).getField("rating").alias("rating_last"), F.avg((r == 1).cast("int")).alias("lowest_share"),
        F.count_distinct("part").alias("products"), (F.max("age") - F.min("age")).alias("span"), F.min("age").alias("since_last"),
    )


def purchase(spark, sf_dir: str, cut: str = tasks.CUT) -> DataFrame:
    """Customer features from transactions up to the cut: recency, prices, article count, span, trend and level."""
    age = F.datediff(F.lit(cut), "t")
    rows = tasks.transactions(spark, sf_dir).withColumn("age", age).filter("age >= 0")
    period = F.floor(F.col("age") / tasks.WINDOW)
    # Prices have at most four places; a sum of doubles would depend on the order of the rows.
    mean = F.try_divide(F.sum(F.round(F.col("price") * 10000).cast("long")), F.count("price")) / 10000
    per = [F.count_if(period == i).alias(f"c{i}") for i in range(5)]
    out = rows.groupBy(F.col("customer").alias("entity")).agg(
        *[F.count_if(F.col("age") < d).alias(f"bought_{d}d") for d in (30, 90, 180)], F.count("*").alias("bought"),
        F.sum(F.col("price").cast("decimal(18,2)")).cast("double").alias("price_sum"), mean.alias("price_mean"), F.max("price").alias("price_max"),
        F.count_distinct("part").alias("articles"), (F.max("age") - F.min("age")).alias("span"), F.min("age").alias("since_last"), *per,
    )
    trend = (2 * F.col("c0") + F.col("c1") - F.col("c3") - 2 * F.col("c4")) / 10
    return out.withColumns({"trend": trend, "level": (F.col("c1") + F.col("c2") + F.col("c3") + F.col("c4")) / 4}).drop(*[f"c{i}" for i in range(5)])


def documents(spark, sf_dir: str) -> DataFrame:
    from relanom.sources import load

    docs = load(spark, sf_dir, "documents", ["doc_id", "text", "lang", "source"])
    size = F.greatest(F.length("text"), F.lit(1))
    share = lambda pattern: F.coalesce(F.length(F.regexp_replace("text", pattern, "")) / size, F.lit(0.0))
    return docs.select(F.col("doc_id").alias("entity"), F.length("text").alias("chars"), (F.length("text") - F.length(F.replace("text", F.lit(" "), F.lit("")))).alias("spaces"), share("[^0-9]").alias("digit_share"), share("[^A-Z]").alias("upper_share"), share("[^!?.,;:]").alias("mark_share"), "lang", "source")


def align(view: DataFrame, targets: DataFrame) -> DataFrame:
    """Every target node once with its flat row, nulls where the view has none."""
    return targets.join(view, F.col("nid") == F.col("entity"), "left")

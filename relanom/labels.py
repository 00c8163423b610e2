"""Unexpected-churn labels: activity change, adaptive threshold, prevalence control."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from relanom.draws import u

LAMBDA = (0.05, 10.0, 0.02)


def activity(rows: DataFrame, cut: str, window: int, previous: int, horizon: int, change: str = "diff") -> DataFrame:
    """Per entity of (entity, t): recent count, level mu, change g, whether active before and after the cut; one pass."""
    age = F.datediff(F.lit(cut), "t")
    period = F.floor(age / window)
    counts = [F.count_if((age >= 0) & (period == i)).alias(f"c{i}") for i in range(previous + 1)]
    base = rows.groupBy("entity").agg(*counts, F.count_if(age >= 0).alias("before"), F.count_if((age < 0) & (age >= -horizon)).alias("after")).filter("before > 0")
    level = sum(F.col(f"c{i}") for i in range(1, previous + 1)) / previous
    if change == "diff":
        g = F.col("c0") - F.col("mu")
    elif change == "ratio":
        g = F.try_divide(F.col("c0") - F.col("mu"), F.col("mu"))
    elif change == "slope":
        centre = previous / 2
        g = sum((centre - i) * F.col(f"c{i}") for i in range(previous + 1)) / sum((centre - i) ** 2 for i in range(previous + 1))
    else:
        raise ValueError(f"no change measure {change}")
    return base.withColumn("mu", level).select("entity", F.col("c0").alias("recent"), "mu", g.alias("g"), (F.col("after") == 0).cast("int").alias("churn"))


def theta(mu: Column, base: float = LAMBDA[0], root: float = LAMBDA[1], growth: float = LAMBDA[2]) -> Column:
    """Decline that is still expected at level mu: a floor plus a logarithm that grows with the level."""
    return base + F.ln(mu + 1) / F.ln(F.lit(root)) * (1 + growth * mu)


def expected_decline(g: Column, mu: Column) -> Column:
    return F.coalesce((g <= -theta(mu)).cast("int"), F.lit(0))


def unexpected(active: DataFrame, expected: str = "negative") -> DataFrame:
    """y = churned without an expected decline; expected decliners are negatives or dropped."""
    out = active.withColumn("expected", expected_decline(F.col("g"), F.col("mu")))
    out = out.withColumn("y", ((F.col("churn") == 1) & (F.col("expected") == 0)).cast("int"))
    return out.filter("not (churn = 1 and expected = 1)") if expected == "drop" else out


def first_by_draw(rows: DataFrame, k: DataFrame, key: str, salt: str, parts: int = 4096) -> DataFrame:
    """The first rows by draw, as many as the one value of ``k`` (k).

    Rows are counted per part of the range of draws; whole parts are taken or left, and only the part in which the count
    is reached is ranked, so no task sees more than one part.
    """
    draw = u(F.col(key), salt)
    placed = rows.withColumn("_draw", draw).withColumn("_part", F.floor(F.col("_draw") * parts))
    counts = placed.groupBy("_part").agg(F.count("*").alias("_n"))
    room = F.col("k") - (F.sum("_n").over(Window.partitionBy(F.lit(0)).orderBy("_part")) - F.col("_n"))
    open_ = counts.join(F.broadcast(k)).withColumn("_room", room).filter("_room > 0").select("_part", "_room")
    ranked = placed.join(F.broadcast(open_), "_part").withColumn("_rank", F.row_number().over(Window.partitionBy("_part").orderBy("_draw", key)))
    return ranked.filter(F.col("_rank") <= F.col("_room")).select(*rows.columns)


def to_prevalence(rows: DataFrame, prevalence: float, key: str = "entity", salt: str = "prev") -> DataFrame:
    """Keep all negatives and so many positives, first by draw, that they make ``prevalence``."""
    kept = rows.agg(F.floor(prevalence * F.count_if(F.col("y") == 0) / (1 - prevalence)).alias("k"))
    return rows.filter("y = 0").unionByName(first_by_draw(rows.filter("y = 1"), kept, key, salt))


def match_prevalence(valid: DataFrame, train: DataFrame, key: str = "entity", salt: str = "prev") -> DataFrame:
    """Validation rows with so many positives, first by draw, that their share equals that of ``train`` as it is now."""
    counts = lambda rows, p, n: rows.agg(F.count_if(F.col("y") == 1).alias(p), F.count_if(F.col("y") == 0).alias(n))
    kept = counts(train, "tp", "tn").join(counts(valid, "vp", "vn")).select(F.expr("coalesce(try_divide(vn * tp, tn), 0)").alias("k"))
    return valid.filter("y = 0").unionByName(first_by_draw(valid.filter("y = 1"), kept, key, salt))


def threshold_for(active: DataFrame, levels: list[float], root: float = LAMBDA[1], growth: float = LAMBDA[2]) -> DataFrame:
    """(prevalence, base, positives): the greatest base of the threshold that labels at most the wanted share of all entities.

    A churned entity is positive while the base exceeds what its decline leaves over, so the base is an
    order statistic of that rest; it is looked up among its distinct values, which are few.
    """
    rest = F.round(-F.col("g") - F.ln(F.col("mu") + 1) / F.ln(F.lit(root)) * (1 + growth * F.col("mu")), 9)
    counts = active.withColumn("q", rest).filter("churn = 1").groupBy("q").agg(F.count("*").alias("n"))
    upto = counts.withColumn("upto", F.sum("n").over(Window.partitionBy(F.lit(0)).orderBy("q")))
    total = active.agg(F.count("*").alias("total"))
    wanted = total.select(F.explode(F.array(*map(F.lit, levels))).alias("prevalence"), "total")
    wanted = wanted.select("prevalence", F.floor(F.col("prevalence") * F.col("total")).alias("k"))
    found = upto.join(F.broadcast(wanted), F.col("upto") > F.col("k"))
    return found.groupBy("prevalence").agg(F.min("q").alias("base"), F.min(F.col("upto") - F.col("n")).cast("long").alias("positives"))


def planted_campaigns(log: DataFrame, start: str = "2024-01-01", days: int = 29) -> DataFrame:
    """Authentication rows with y, and bursts of four to six rows on distinct machines within ten minutes.

    A fifth of the users get a burst, a fifth of those a harmless one; single rows are incidents
    without a burst, so no one feature decides.
    """
    real = log.filter("log = 'auth'").select("event", "user", "machine", "t", (u(F.col("event"), "lone") < 0.005).cast("int").alias("y"))
    user = F.col("user")
    burst = log.select("user").distinct().filter(u(user, "camp") < 0.2)
    burst = burst.withColumn("i", F.explode(F.sequence(F.lit(0).cast("long"), 3 + F.floor(u(user, "size") * 3))))
    at = F.floor(u(user, "when") * days * 86400) + 100 * F.col("i")
    made = burst.select(
        (10**9 + user * 10 + F.col("i")).alias("event"),
        "user",
        ((F.floor(u(user, "first") * 100) + 17 * F.col("i")) % 100).cast("int").alias("machine"),
        (F.lit(start).cast("timestamp_ntz") + F.make_dt_interval(secs=at.cast("decimal(18,6)"))).alias("t"),
        (u(user, "benign") >= 0.2).cast("int").alias("y"),
    )
    return real.unionByName(made)


def behavioural(logs: DataFrame, machines: int = 6) -> DataFrame:
    """(event, y) of authentications: the user's first use of the machine in any log, which makes it at least ``machines`` within a day.

    Rows of one instant are not before each other. As the machine is new, it adds one to those of the day before.
    """
    from relanom.views import distinct_within

    rows = distinct_within(logs.withColumn("us", F.unix_micros(F.col("t").cast("timestamp"))), "user", "machine", 86400, "others")
    pair = Window.partitionBy("user", "machine").orderBy("us").rangeBetween(Window.unboundedPreceding, -1)
    new = F.count("*").over(pair) == 0
    return rows.withColumn("y", (new & (F.col("others") + 1 >= machines)).cast("int")).filter("log = 'auth'").select("event", "y")

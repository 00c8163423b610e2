"""Operators around the methods: joins, aggregates, windows, sets, functions, recursion, functions of one's own."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from relanom.registry import query
from relanom.sources import load

long = lambda c, name=None: (F.col(c) if isinstance(c, str) else c).cast("long").alias(name or c)


def _co(spark, sf_dir):
    return load(spark, sf_dir, "customer", ["c_custkey", "c_nationkey", "c_acctbal"]), load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_totalprice", "o_orderdate"])


for _how, _sql in (("inner", "JOIN"), ("left", "LEFT JOIN"), ("full", "FULL JOIN")):

    @query(f"join_{_how}", f"SELECT c_custkey, count(o_orderkey)::BIGINT AS n FROM (SELECT * FROM customer WHERE c_acctbal > 0) {_sql} (SELECT * FROM orders WHERE o_totalprice > 100000) ON c_custkey = o_custkey GROUP BY 1")
    def _join(spark, sf_dir, how=_how):
        c, o = _co(spark, sf_dir)
        return c.filter("c_acctbal > 0").join(o.filter("o_totalprice > 100000"), F.col("c_custkey") == F.col("o_custkey"), how).groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


for _how, _not in (("semi", ""), ("anti", "NOT ")):

    @query(f"join_{_how}", f"SELECT c_custkey FROM customer WHERE {_not}EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
    def _half(spark, sf_dir, how=_how):
        c, o = _co(spark, sf_dir)
        return c.join(o.filter("o_totalprice > 400000"), F.col("c_custkey") == F.col("o_custkey"), f"left_{how}").select("c_custkey")


@query("join_theta_pairs", "SELECT a.r_regionkey::BIGINT AS a, b.n_nationkey::BIGINT AS b FROM region a JOIN nation b ON a.r_regionkey < b.n_regionkey")
def _theta(spark, sf_dir):
    a, b = load(spark, sf_dir, "region"), load(spark, sf_dir, "nation")
    return b.join(F.broadcast(a), F.col("r_regionkey") < F.col("n_regionkey")).select(long("r_regionkey", "a"), long("n_nationkey", "b"))


@query("join_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _interval(spark, sf_dir):
    """Events of one user within an hour: equality on user and hour bin, then the exact bounds."""
    e = load(spark, sf_dir, "events", ["event_id", "user_id", "ts"]).withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    hour = 3_600_000_000
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("us").alias("at"), F.explode(F.array(F.floor(F.col("us") / hour), F.floor(F.col("us") / hour) + 1)).alias("bin"))
    b = e.select(F.col("event_id").alias("b"), F.col("user_id").alias("who"), F.col("us").alias("then"), F.floor(F.col("us") / hour).alias("slot"))
    return a.join(b, (F.col("user_id") == F.col("who")) & (F.col("bin") == F.col("slot")) & (F.col("then") > F.col("at")) & (F.col("then") <= F.col("at") + hour)).select("a", "b")


@query("join_asof", "SELECT e.event_id, o.o_orderkey FROM (SELECT * FROM events WHERE event_type = 'purchase') e ASOF LEFT JOIN (SELECT event_id AS o_orderkey, user_id, ts FROM events WHERE event_type = 'view') o ON e.user_id = o.user_id AND e.ts >= o.ts")
def _as_of(spark, sf_dir):
    """The last view at or before each purchase: one sorted pass over the union, no pairs."""
    e = load(spark, sf_dir, "events", ["event_id", "user_id", "ts", "event_type"]).filter("event_type in ('purchase', 'view')")
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "view", 0).otherwise(1)).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    last = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("o_orderkey", last).filter("event_type = 'purchase'").select("event_id", "o_orderkey")


@query("join_lateral_topk", "SELECT o_custkey AS customer, o_orderkey AS order_ FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) WHERE k <= 2")
def _lateral(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    return load(spark, sf_dir, "orders").withColumn("k", F.row_number().over(w)).filter("k <= 2").select(F.col("o_custkey").alias("customer"), F.col("o_orderkey").alias("order_"))


@query("agg_conditional", "SELECT l_returnflag AS flag, count(*) FILTER (l_quantity > 25)::BIGINT AS many, round(max(l_extendedprice), 4) AS top, arg_max(l_orderkey, l_extendedprice) AS best FROM lineitem GROUP BY 1")
def _conditional(spark, sf_dir):
    """Of several rows at the top the smallest key is taken, whatever order the rows come in."""
    best = F.when(F.col("l_orderkey").isNotNull() & F.col("l_extendedprice").isNotNull(), F.struct("l_extendedprice", F.bitwise_not("l_orderkey")))
    return load(spark, sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("flag")).agg(F.count_if(F.col("l_quantity") > 25).alias("many"), F.round(F.max("l_extendedprice"), 4).alias("top"), F.max_by("l_orderkey", best).alias("best"))


@query("agg_distinct", "SELECT l_returnflag AS flag, count(DISTINCT l_partkey)::BIGINT AS parts, count(DISTINCT l_suppkey)::BIGINT AS suppliers FROM lineitem GROUP BY 1")
def _distinct(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("flag")).agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


for _name, _sql in (("cube", "CUBE (l_returnflag, l_linestatus)"), ("rollup", "ROLLUP (l_returnflag, l_linestatus)"), ("grouping_sets", "GROUPING SETS ((l_returnflag), (l_linestatus))")):

    @query(f"agg_{_name}", f"SELECT l_returnflag AS flag, l_linestatus AS status, count(*)::BIGINT AS n FROM lineitem GROUP BY {_sql}")
    def _sets(spark, sf_dir, name=_name):
        rows, by = load(spark, sf_dir, "lineitem").select(F.col("l_returnflag").alias("flag"), F.col("l_linestatus").alias("status")), ("flag", "status")
        if name == "grouping_sets":
            return rows.groupingSets([("flag",), ("status",)], *by).agg(F.count("*").alias("n")).select(*by, "n")
        return getattr(rows, name)(*by).agg(F.count("*").alias("n"))


@query("pivot_results", "SELECT o_orderpriority AS priority, count(*) FILTER (o_orderstatus = 'F')::BIGINT AS f, count(*) FILTER (o_orderstatus = 'O')::BIGINT AS o FROM orders GROUP BY 1")
def _pivot(spark, sf_dir):
    p = load(spark, sf_dir, "orders").groupBy(F.col("o_orderpriority").alias("priority")).pivot("o_orderstatus", ["F", "O"]).count()
    return p.select("priority", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))


@query("win_ranking", "SELECT o_orderkey, rank() OVER w::BIGINT AS r, dense_rank() OVER w::BIGINT AS d, ntile(4) OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)::BIGINT AS q, round(percent_rank() OVER w, 6) AS p FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate)".replace("OVER w::BIGINT", "OVER w"))
def _ranking(spark, sf_dir):
    w, v = Window.partitionBy("o_custkey").orderBy("o_orderdate"), Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
    return load(spark, sf_dir, "orders").select("o_orderkey", long(F.rank().over(w), "r"), long(F.dense_rank().over(w), "d"), long(F.ntile(4).over(v), "q"), F.round(F.percent_rank().over(w), 6).alias("p"))


@query("win_analytic", "SELECT event_id, lag(event_id) OVER w AS before_, lead(event_id) OVER w AS after_, first(event_id) OVER w AS first_ FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def _analytic(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, sf_dir, "events").select("event_id", F.lag("event_id").over(w).alias("before_"), F.lead("event_id").over(w).alias("after_"), F.first("event_id").over(w).alias("first_"))


@query("win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND INTERVAL 1 MICROSECOND PRECEDING)::BIGINT AS n FROM events".replace(")::BIGINT", ")"))
def _range(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-86_400_000_000, -1)
    return load(spark, sf_dir, "events").select("event_id", F.count("*").over(w).alias("n"))


@query("win_rows", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) + 1e-9, 5) AS m FROM events")
def _rows(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    return load(spark, sf_dir, "events").select("event_id", F.round(F.avg("value").over(w) + 1e-9, 5).alias("m"))


@query("topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def _topk(spark, sf_dir):
    return load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]).orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(25)


@query("topk_group", "SELECT event_type, event_id FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY value DESC, event_id) AS k FROM events) WHERE k <= 3")
def _topk_group(spark, sf_dir):
    """Top rows per group, cut in salted parts first so that a hot group is not sorted in one task."""
    order = (F.col("value").desc(), "event_id")
    rows = load(spark, sf_dir, "events", ["event_type", "event_id", "value"]).withColumn("part", F.pmod(F.xxhash64("event_id"), F.lit(8)))
    rows = rows.withColumn("k", F.row_number().over(Window.partitionBy("event_type", "part").orderBy(*order))).filter("k <= 3")
    return rows.withColumn("k", F.row_number().over(Window.partitionBy("event_type").orderBy(*order))).filter("k <= 3").select("event_type", "event_id")


for _name, _sql in (("union", "UNION ALL"), ("intersect", "INTERSECT"), ("except", "EXCEPT")):

    @query(f"set_{_name}", f"SELECT o_custkey AS k FROM orders WHERE o_orderstatus = 'F' {_sql} SELECT o_custkey FROM orders WHERE o_orderstatus = 'P'")
    def _set(spark, sf_dir, name=_name):
        o = load(spark, sf_dir, "orders", ["o_custkey", "o_orderstatus"])
        a, b = (o.filter(F.col("o_orderstatus") == s).select(F.col("o_custkey").alias("k")) for s in ("F", "P"))
        return {"union": a.unionByName, "intersect": a.intersect, "except": a.subtract}[name](b)


@query("fn_string", "SELECT page_id, lower(trim(url)) AS u, length(url)::BIGINT AS n, md5(url) AS h, string_split(url, '/')[3] AS host FROM pages")
def _string(spark, sf_dir):
    return load(spark, sf_dir, "pages").select("page_id", F.lower(F.trim("url")).alias("u"), long(F.length("url"), "n"), F.md5("url").alias("h"), F.split("url", "/")[2].alias("host"))


@query("fn_date", "SELECT o_orderkey, date_diff('day', o_orderdate, TIMESTAMP '2001-02-01')::BIGINT AS age, year(o_orderdate)::BIGINT AS y, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS m FROM orders")
def _date(spark, sf_dir):
    return load(spark, sf_dir, "orders").select("o_orderkey", long(F.datediff(F.lit("2001-02-01"), "o_orderdate"), "age"), long(F.year("o_orderdate"), "y"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("m"))


@query("fn_math", "SELECT c_custkey, round(ln(abs(c_acctbal) + 1), 6) AS l, round(sqrt(abs(c_acctbal)), 6) AS s, round(greatest(c_acctbal / 1000, 0) + ln(1 + exp(-abs(c_acctbal / 1000))), 6) AS softplus FROM customer")
def _math(spark, sf_dir):
    x = F.col("c_acctbal")
    return load(spark, sf_dir, "customer").select("c_custkey", F.round(F.ln(F.abs(x) + 1), 6).alias("l"), F.round(F.sqrt(F.abs(x)), 6).alias("s"), F.round(F.greatest(x / 1000, F.lit(0.0)) + F.log1p(F.exp(-F.abs(x / 1000))), 6).alias("softplus"))


@query("fn_array", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS n2, len(embedding)::BIGINT AS d FROM embeddings")
def _array(spark, sf_dir):
    total = F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(total, 4).alias("n2"), long(F.size("embedding"), "d"))


@query("fn_map", "SELECT event_type, count(*)::BIGINT AS n FROM events GROUP BY 1")
def _map(spark, sf_dir):
    counts = load(spark, sf_dir, "events").groupBy("event_type").agg(F.count("*").alias("n")).agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return counts.select(F.explode("m").alias("event_type", "n"))


@query("fn_json", "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k FROM events")
def _json(spark, sf_dir):
    return load(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("fn_try", "SELECT c_custkey, try_cast(c_name AS INT)::BIGINT AS n, round(c_acctbal / nullif(c_nationkey, 0), 6) AS d FROM customer")
def _try(spark, sf_dir):
    return load(spark, sf_dir, "customer").select("c_custkey", F.expr("try_cast(c_name AS INT)").cast("long").alias("n"), F.round(F.try_divide(F.col("c_acctbal"), F.col("c_nationkey")), 6).alias("d"))


_TREE = "WITH RECURSIVE t(node, depth) AS (SELECT c_custkey, 0 FROM {0} WHERE c_custkey = 1 UNION ALL SELECT c_custkey, depth + 1 FROM t JOIN {0} ON c_custkey {1} 2 = node) SELECT CAST(depth AS BIGINT) AS depth, CAST(count(*) AS BIGINT) AS n, CAST(sum(node) AS BIGINT) AS s FROM t GROUP BY depth"


@query("recursive_tree", _TREE.format("customer", "//"))
def _recursive(spark, sf_dir):
    """All customers below the first one where each hangs from half its key; a path is at most as deep as a key has bits."""
    # Spark ends a recursion with an error at a million rows; this one ends by itself.
    spark.conf.set("spark.sql.cteRecursionRowLimit", "-1")
    return spark.sql(_TREE.format(f"parquet.`{sf_dir}/customer.parquet`", "DIV"))


@query("agg_vector_mean", "SELECT label::BIGINT AS label, round(avg(embedding[1]::DOUBLE), 5) AS m0, round(avg(embedding[2]::DOUBLE), 5) AS m1 FROM embeddings GROUP BY 1")
def _vector_mean(spark, sf_dir):
    g = load(spark, sf_dir, "embeddings").groupBy(long("label"))
    return g.agg(*[F.round(F.avg(F.col("embedding")[i].cast("double")), 5).alias(f"m{i}") for i in range(2)])


@query("udf_dot", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE)) / 64, 5) AS m FROM embeddings")
def _udf(spark, sf_dir):
    """A vectorised function of one's own over arrays."""

    @F.pandas_udf("double")
    def average(x: pd.Series) -> pd.Series:
        return x.map(lambda v: float(sum(map(float, v))) / len(v))

    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(average(F.col("embedding").cast("array<double>")), 5).alias("m"))


@query("sketch_quantiles")
def _sketch(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").agg(F.percentile_approx("l_extendedprice", [0.25, 0.5, 0.75], 10000).alias("q"), F.approx_count_distinct("l_partkey").alias("parts"))

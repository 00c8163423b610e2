"""Labels, prevalence, splits and ranking measures with their oracles."""

from __future__ import annotations

from pyspark.sql import functions as F

from relanom import labels, metrics, splits, tasks
from relanom.draws import u, u_sql
from relanom.registry import query
from relanom.sources import load

TX = tasks.TX_SQL


def _active_sql(where: str, change: str) -> str:
    g = {
        "diff": "c0 - mu",
        "ratio": "CASE WHEN mu <> 0 THEN (c0 - mu) / mu END",
        "slope": "(2 * c0 + c1 - c3 - 2 * c4) / 10.0",
    }[change]
    counts = ", ".join(f"count(*) FILTER (age >= 0 AND floor(age / 180.0) = {i}) AS c{i}" for i in range(5))
    return f"""{TX}, counted AS (
  SELECT customer AS entity, {counts}, count(*) FILTER (age >= 0) AS before_cut, count(*) FILTER (age < 0 AND age >= -180) AS after_cut
  FROM tx WHERE {where} GROUP BY customer
), levelled AS (SELECT *, (c1 + c2 + c3 + c4) / 4.0 AS mu FROM counted WHERE before_cut > 0),
active AS (SELECT entity, c0 AS recent, mu::DOUBLE AS mu, ({g})::DOUBLE AS g, (after_cut = 0)::INT AS churn FROM levelled),
judged AS (SELECT *, coalesce((g <= -(0.05 + ln(mu + 1) / ln(10.0) * (1 + 0.02 * mu)))::INT, 0) AS expected FROM active),
labelled AS (SELECT *, (churn = 1 AND expected = 0)::INT AS y FROM judged)"""


REVIEW, PURCHASE = "flag <> 'N'", "true"


def _active(spark, sf_dir, kind, change="diff"):
    rows = tasks.reviews(spark, sf_dir) if kind == "review" else tasks.transactions(spark, sf_dir)
    return labels.activity(rows.select(F.col("customer").alias("entity"), "t"), tasks.CUT, tasks.WINDOW, tasks.PREVIOUS, tasks.HORIZON, change)


def labelled(spark, sf_dir, kind, expected="negative"):
    return labels.unexpected(_active(spark, sf_dir, kind), expected)


for _kind, _where in (("review", REVIEW), ("purchase", PURCHASE)):

    @query(f"label_churn_{_kind}", f"WITH {_active_sql(_where, 'diff')} SELECT entity, churn::BIGINT AS churn FROM active")
    def _churn(spark, sf_dir, kind=_kind):
        return _active(spark, sf_dir, kind).select("entity", F.col("churn").cast("long").alias("churn"))

    @query(f"label_unexpected_{_kind}", f"WITH {_active_sql(_where, 'diff')} SELECT entity, churn::BIGINT AS churn, expected::BIGINT AS expected, y::BIGINT AS y FROM labelled")
    def _unexpected(spark, sf_dir, kind=_kind):
        return labelled(spark, sf_dir, kind).select("entity", *(F.col(c).cast("long").alias(c) for c in ("churn", "expected", "y")))


for _change in ("diff", "ratio", "slope"):

    @query(f"activity_{_change}", f"WITH {_active_sql(PURCHASE, _change)} SELECT entity, recent::BIGINT AS recent, round(mu, 6) AS mu, round(g, 6) AS g FROM active")
    def _activity(spark, sf_dir, change=_change):
        return _active(spark, sf_dir, "purchase", change).select("entity", F.col("recent").cast("long").alias("recent"), F.round("mu", 6).alias("mu"), F.round(F.col("g").cast("double"), 6).alias("g"))


@query("label_unexpected_drop", f"WITH {_active_sql(REVIEW, 'diff')} SELECT entity, y::BIGINT AS y FROM labelled WHERE NOT (churn = 1 AND expected = 1)")
def _drop(spark, sf_dir):
    return labelled(spark, sf_dir, "review", "drop").select("entity", F.col("y").cast("long").alias("y"))


@query("expected_decline", f"WITH {_active_sql(PURCHASE, 'diff')} SELECT expected::BIGINT AS expected, count(*)::BIGINT AS n FROM judged GROUP BY expected")
def _expected(spark, sf_dir):
    return labelled(spark, sf_dir, "purchase").groupBy(F.col("expected").cast("long").alias("expected")).agg(F.count("*").alias("n"))


@query("theta_table", f"WITH {_active_sql(PURCHASE, 'diff')} SELECT DISTINCT mu, round(0.05 + ln(mu + 1) / ln(10.0) * (1 + 0.02 * mu), 6) AS theta FROM active")
def _theta(spark, sf_dir):
    """Threshold at every level of activity that customers have."""
    mu = _active(spark, sf_dir, "purchase").select(F.col("mu").cast("double").alias("mu")).distinct()
    return mu.select("mu", F.round(labels.theta(F.col("mu")), 6).alias("theta"))


SPLIT_SQL = f"CASE WHEN {u_sql('entity', 'split')} < 0.7 THEN 'train' WHEN {u_sql('entity', 'split')} < 0.85 THEN 'valid' ELSE 'test' END"


@query("prevalence_train", f"""WITH {_active_sql(PURCHASE, 'diff')}, t AS (SELECT * FROM labelled WHERE {SPLIT_SQL} = 'train'),
k AS (SELECT floor(0.015 * count(*) FILTER (y = 0) / 0.985) AS k FROM t),
r AS (SELECT entity, y, row_number() OVER (PARTITION BY y ORDER BY {u_sql('entity', 'prev')}, entity) AS n FROM t)
SELECT entity, y::BIGINT AS y FROM r, k WHERE y = 0 OR n <= k""")
def _prevalence(spark, sf_dir):
    train = labelled(spark, sf_dir, "purchase").filter(splits.by_hash(F.col("entity")) == "train")
    return labels.to_prevalence(train, 0.015).select("entity", F.col("y").cast("long").alias("y"))


@query("prevalence_sweep", "WITH " + _active_sql(REVIEW, "diff") + f""", p(p) AS (VALUES (0.005), (0.015), (0.03)),
k AS (SELECT p, floor(p * (SELECT count(*) FROM labelled WHERE y = 0) / (1 - p)) AS k FROM p),
r AS (SELECT row_number() OVER (ORDER BY {u_sql('entity', 'prev')}, entity) AS n FROM labelled WHERE y = 1)
SELECT p::DOUBLE AS prevalence, (SELECT count(*) FROM labelled WHERE y = 0)::BIGINT AS negatives, count(r.n)::BIGINT AS positives FROM k LEFT JOIN r ON r.n <= k.k GROUP BY p""")
def _sweep(spark, sf_dir):
    """All prevalences from one ranking: a lower one keeps a prefix of a higher one's positives."""
    rows = labelled(spark, sf_dir, "review")
    total = rows.agg(F.count_if(F.col("y") == 0).alias("negatives"), F.count_if(F.col("y") == 1).alias("have"))
    wanted = spark.createDataFrame([(0.005,), (0.015,), (0.03,)], "prevalence double")
    kept = F.floor(F.col("prevalence") * F.col("negatives") / (1 - F.col("prevalence")))
    return wanted.join(F.broadcast(total)).select("prevalence", "negatives", F.least(kept, "have").cast("long").alias("positives"))


@query("prevalence_by_split", f"WITH {_active_sql(PURCHASE, 'diff')} SELECT {SPLIT_SQL} AS split, count(*)::BIGINT AS n, round(avg(y), 6) AS prevalence FROM labelled GROUP BY 1")
def _by_split(spark, sf_dir):
    return labelled(spark, sf_dir, "purchase").groupBy(splits.by_hash(F.col("entity")).alias("split")).agg(F.count("*").alias("n"), F.round(F.avg("y"), 6).alias("prevalence"))


@query("split_hash", f"SELECT c_custkey AS entity, {SPLIT_SQL.replace('entity', 'c_custkey')} AS split FROM customer")
def _split_hash(spark, sf_dir):
    return load(spark, sf_dir, "customer", ["c_custkey"]).select(F.col("c_custkey").alias("entity"), splits.by_hash(F.col("c_custkey")).alias("split"))


@query("split_disjoint", f"WITH s AS (SELECT o_custkey AS entity, {SPLIT_SQL.replace('entity', 'o_custkey')} AS split FROM orders) SELECT count(*)::BIGINT AS entities, count(*) FILTER (n > 1)::BIGINT AS in_several FROM (SELECT entity, count(DISTINCT split) AS n FROM s GROUP BY entity)")
def _split_disjoint(spark, sf_dir):
    """Targets met through their child rows fall into one split each."""
    o = load(spark, sf_dir, "orders", ["o_custkey"]).select(F.col("o_custkey").alias("entity"), splits.by_hash(F.col("o_custkey")).alias("split"))
    seen = o.groupBy("entity").agg(F.min("split").alias("least"), F.max("split").alias("most"))
    return seen.agg(F.count("*").alias("entities"), F.count_if(F.col("least") != F.col("most")).alias("in_several"))


@query("split_time", "SELECT CASE WHEN ts < TIMESTAMP '2024-01-20' THEN 'train' WHEN ts < TIMESTAMP '2024-01-25' THEN 'valid' ELSE 'test' END AS split, count(*)::BIGINT AS n FROM events GROUP BY 1")
def _split_time(spark, sf_dir):
    return load(spark, sf_dir, "events", ["ts"]).groupBy(splits.by_time(F.col("ts"), "2024-01-20", "2024-01-25").alias("split")).agg(F.count("*").alias("n"))


@query("class_weights", f"WITH {_active_sql(PURCHASE, 'diff')} SELECT y::BIGINT AS y, round(sum(count(*)) OVER () / (2.0 * count(*)), 6) AS weight FROM labelled GROUP BY y")
def _weights(spark, sf_dir):
    return splits.class_weights(labelled(spark, sf_dir, "purchase")).select(F.col("y").cast("long").alias("y"), F.round("weight", 6).alias("weight"))


@query("train_cap", f"WITH {_active_sql(PURCHASE, 'diff')} SELECT entity, y::BIGINT AS y FROM labelled ORDER BY y DESC, {u_sql('entity', 'cap')}, entity LIMIT 200")
def _cap(spark, sf_dir):
    return splits.cap(labelled(spark, sf_dir, "purchase"), 200, "entity").select("entity", F.col("y").cast("long").alias("y"))


_F4 = "SELECT customer, avg((" + u_sql("p_brand", "bad") + " < 0.35)::INT) AS share FROM tx JOIN part ON part = p_partkey WHERE age > 0 GROUP BY customer"


@query("planted_multihop", f"WITH {TX} SELECT customer AS entity, round(share, 6) AS share, (share >= 0.55)::BIGINT AS y FROM ({_F4})")
def planted_multihop(spark, sf_dir):
    """Evidence two hops away: the share of a customer's articles that carry a marked brand."""
    parts = load(spark, sf_dir, "part", ["p_partkey", "p_brand"])
    rows = tasks.transactions(spark, sf_dir).filter(F.datediff(F.lit(tasks.CUT), "t") > 0).join(parts, F.col("part") == F.col("p_partkey"))
    share = rows.groupBy(F.col("customer").alias("entity")).agg(F.avg((u(F.col("p_brand"), "bad") < 0.35).cast("int")).alias("share"))
    return share.select("entity", F.round("share", 6).alias("share"), (F.col("share") >= 0.55).cast("long").alias("y"))


# Scores to measure: a draw, coarsened so that ties are frequent, lifted for positives.
_SCORED = f"scored AS (SELECT entity, y, round({u_sql('entity', 'score')} * 0.8 + 0.2 * y, 2) AS score FROM labelled)"


def scored(spark, sf_dir):
    rows = labelled(spark, sf_dir, "purchase")
    return rows.select("entity", "y", F.round(u(F.col("entity"), "score") * 0.8 + 0.2 * F.col("y"), 2).alias("score"))


_S = f"WITH {_active_sql(PURCHASE, 'diff')}, {_SCORED}, t AS (SELECT count(*) FILTER (y = 1) AS p, count(*) FILTER (y = 0) AS n FROM scored), d AS (SELECT score, count(*) FILTER (y = 1) AS pos, count(*) FILTER (y = 0) AS neg FROM scored GROUP BY score), c AS (SELECT *, sum(pos) OVER (ORDER BY score DESC) AS tp, sum(neg) OVER (ORDER BY score DESC) AS fp FROM d)"
_AUROC = "sum(pos * ((n - fp) + neg / 2.0)) / (any_value(p) * any_value(n))"
_AUPRC = "sum(pos * 1.0 / p * tp / (tp + fp))"
_TIES = "sum(pos * greatest(0, least(pos + neg, p - (tp + fp - pos - neg))) * 1.0 / (pos + neg)) / any_value(p)"


@query("auroc", f"{_S} SELECT round({_AUROC}, 6) AS auroc FROM c, t")
def _auroc(spark, sf_dir):
    return metrics.ranking(scored(spark, sf_dir)).select(F.round("auroc", 6).alias("auroc"))


@query("auprc", f"{_S} SELECT round({_AUPRC}, 6) AS auprc FROM c, t")
def _auprc(spark, sf_dir):
    return metrics.ranking(scored(spark, sf_dir)).select(F.round("auprc", 6).alias("auprc"))


@query("precision_at_k_ties", f"{_S} SELECT round({_TIES}, 6) AS p_at_k FROM c, t")
def _ties(spark, sf_dir):
    return metrics.ranking(scored(spark, sf_dir)).select(F.round("p_at_k", 6).alias("p_at_k"))


@query("precision_at_k", f"{_S} SELECT round(avg(y), 6) AS p_at_k FROM (SELECT y, row_number() OVER (ORDER BY score DESC, entity) AS k FROM scored), t WHERE k <= p")
def _at_k(spark, sf_dir):
    return metrics.precision_at_k(scored(spark, sf_dir), "entity").select(F.round("p_at_k", 6).alias("p_at_k"))


@query("ranking_bundle", f"""WITH {_active_sql(PURCHASE, 'diff')}, {_SCORED.replace('SELECT entity', f'SELECT {SPLIT_SQL} AS split, entity')},
t AS (SELECT split, count(*) FILTER (y = 1) AS p, count(*) FILTER (y = 0) AS n FROM scored GROUP BY split),
d AS (SELECT split, score, count(*) FILTER (y = 1) AS pos, count(*) FILTER (y = 0) AS neg FROM scored GROUP BY split, score),
c AS (SELECT *, sum(pos) OVER (PARTITION BY split ORDER BY score DESC) AS tp, sum(neg) OVER (PARTITION BY split ORDER BY score DESC) AS fp FROM d)
SELECT split, round({_AUROC}, 6) AS auroc, round({_AUPRC}, 6) AS auprc, round({_TIES}, 6) AS p_at_k FROM c JOIN t USING (split) GROUP BY split""")
def _bundle(spark, sf_dir):
    rows = scored(spark, sf_dir).withColumn("split", splits.by_hash(F.col("entity")))
    return metrics.ranking(rows, ["split"]).select("split", *(F.round(c, 6).alias(c) for c in ("auroc", "auprc", "p_at_k")))


@query("pr_curve", f"{_S} SELECT score, round(tp * 1.0 / p, 6) AS recall, round(tp * 1.0 / (tp + fp), 6) AS precision FROM c, t")
def _pr(spark, sf_dir):
    return metrics.cumulative(scored(spark, sf_dir)).select("score", F.round(F.col("tp") / F.col("P"), 6).alias("recall"), F.round(F.col("tp") / (F.col("tp") + F.col("fp")), 6).alias("precision"))


@query("roc_curve", f"{_S} SELECT score, round(tp * 1.0 / p, 6) AS tpr, round(fp * 1.0 / n, 6) AS fpr FROM c, t")
def _roc(spark, sf_dir):
    return metrics.cumulative(scored(spark, sf_dir)).select("score", F.round(F.col("tp") / F.col("P"), 6).alias("tpr"), F.round(F.col("fp") / F.col("N"), 6).alias("fpr"))


@query("auroc_binned", f"""WITH {_active_sql(PURCHASE, 'diff')}, {_SCORED}, d AS (SELECT least(floor(score * 10), 9) AS b, count(*) FILTER (y = 1) AS pos, count(*) FILTER (y = 0) AS neg FROM scored GROUP BY 1),
c AS (SELECT *, coalesce(sum(neg) OVER (ORDER BY b ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM d)
SELECT round(sum(pos * (below + neg / 2.0)) / (sum(pos) * sum(neg)), 6) AS auroc, round(sum(pos * neg) / 2.0 / (sum(pos) * sum(neg)), 6) AS bound FROM c""")
def _binned(spark, sf_dir):
    return metrics.binned(scored(spark, sf_dir), 10).select(F.round("auroc", 6).alias("auroc"), F.round("bound", 6).alias("bound"))


@query("pair_accuracy", f"{_S} SELECT round(avg(CASE WHEN a.score > b.score THEN 1.0 WHEN a.score = b.score THEN 0.5 ELSE 0 END), 6) AS accuracy FROM scored a JOIN scored b ON a.y = 1 AND b.y = 0")
def _pairs(spark, sf_dir):
    """Order accuracy over all pairs of a positive and a negative, from pairs of distinct scores with their counts."""
    counts = scored(spark, sf_dir).groupBy("score", "y").agg(F.count("*").alias("n"))
    a, b = (counts.filter(f"y = {y}").select(F.col("score").alias(f"s{y}"), F.col("n").alias(f"n{y}")) for y in (1, 0))
    won = F.when(F.col("s1") > F.col("s0"), 1.0).when(F.col("s1") == F.col("s0"), 0.5).otherwise(0.0)
    pairs = F.col("n1") * F.col("n0")
    return a.join(F.broadcast(b)).agg(F.round(F.sum(pairs * won) / F.sum(pairs), 6).alias("accuracy"))


@query("baseline_random", f"WITH {_active_sql(PURCHASE, 'diff')} SELECT entity, round({u_sql('entity', 'random')}, 9) AS score FROM labelled")
def _random(spark, sf_dir):
    return labelled(spark, sf_dir, "purchase").select("entity", F.round(u(F.col("entity"), "random"), 9).alias("score"))


_METRICS = {"orders": "count(*)", "top": "max(o_totalprice)", "customers": "count(DISTINCT o_custkey)"}
_RESULTS = "b AS (SELECT o_custkey % 10 AS method, o_orderpriority AS dataset, o_totalprice, o_custkey FROM orders), r AS (" + " UNION ALL ".join(f"SELECT method, dataset, '{k}' AS metric, {v}::DOUBLE AS value FROM b GROUP BY method, dataset" for k, v in _METRICS.items()) + ")"


@query("avg_rank_printed", f"WITH {_RESULTS} SELECT a.method, a.metric, round(avg(k), 6) AS avg_rank FROM (SELECT x.method, x.metric, x.dataset, 1 + count(*) FILTER (z.value > x.value) + (count(*) FILTER (z.value = x.value) - 1) / 2.0 AS k FROM r x JOIN r z USING (dataset, metric) GROUP BY ALL) a GROUP BY a.method, a.metric")
def _average_rank(spark, sf_dir):
    """Average ranks of ten groups of customers over the order priorities, by three exact measures."""
    by = load(spark, sf_dir, "orders", ["o_custkey", "o_orderpriority", "o_totalprice"]).groupBy((F.col("o_custkey") % 10).alias("method"), F.col("o_orderpriority").alias("dataset"))
    values = by.agg(*[F.expr(v).cast("double").alias(k) for k, v in _METRICS.items()])
    rows = values.unpivot(["method", "dataset"], list(_METRICS), "metric", "value")
    return metrics.average_rank(rows).select("method", "metric", F.round("avg_rank", 6).alias("avg_rank"))


@query("seed_summary", f"WITH r AS (SELECT l_returnflag AS method, l_linestatus AS task, {u_sql('l_orderkey', 'm')} AS value FROM lineitem) SELECT method, task, 'x' AS metric, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS std, count(*)::BIGINT AS seeds FROM r GROUP BY method, task")
def _seeds(spark, sf_dir):
    rows = load(spark, sf_dir, "lineitem", ["l_returnflag", "l_linestatus", "l_orderkey"]).select(F.col("l_returnflag").alias("method"), F.col("l_linestatus").alias("task"), F.lit("x").alias("metric"), u(F.col("l_orderkey"), "m").alias("value"))
    return metrics.over_seeds(rows).select("method", "task", "metric", F.round("mean", 6).alias("mean"), F.round("std", 6).alias("std"), "seeds")

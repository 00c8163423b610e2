"""Graph construction, flattened views and encoding with their oracles."""

from __future__ import annotations

from pyspark.sql import functions as F

from relanom import encode, graph, labels, tasks, views
from relanom.draws import u_sql
from relanom.registry import query
from relanom.sources import TABLES, load

LOG, TX = tasks.LOG_SQL, tasks.TX_SQL
_EDGES = "edges AS (" + " UNION ALL ".join(f"SELECT '{k.name}' AS rel, {k.key}::BIGINT AS src, {k.foreign}::BIGINT AS dst, {k.time or 'NULL::TIMESTAMP'} AS t FROM {k.child}" for k in graph.LINKS) + ")"
long = lambda *cs: [F.col(c).cast("long").alias(c) for c in cs]


@query("scan_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*)::BIGINT AS n FROM {t}" for t in TABLES))
def _scan(spark, sf_dir):
    parts = [load(spark, sf_dir, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n") for t in TABLES]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


@query("graph_nodes", "SELECT 'customer' AS ntype, count(*)::BIGINT AS n, sum(c_custkey)::BIGINT AS ids, round(sum(c_acctbal), 2) AS total FROM customer UNION ALL SELECT 'part', count(*)::BIGINT, sum(p_partkey)::BIGINT, round(sum(p_retailprice), 2) FROM part")
def _nodes(spark, sf_dir):
    both = graph.nodes(spark, sf_dir, "customer", "c_custkey", features=["c_acctbal"]).unionByName(graph.nodes(spark, sf_dir, "part", "p_partkey", features=["p_retailprice"]))
    return both.groupBy("ntype").agg(F.count("*").alias("n"), F.sum("nid").alias("ids"), F.round(F.sum(F.col("x")[0]), 2).alias("total"))


@query("graph_edges", f"WITH {_EDGES} SELECT rel, src, dst FROM edges")
def _edges(spark, sf_dir):
    return graph.edges(spark, sf_dir).select("rel", "src", "dst")


@query("graph_edges_reverse", f"WITH {_EDGES} SELECT rel, count(*)::BIGINT AS n, sum(src)::BIGINT AS s, sum(dst)::BIGINT AS d FROM (SELECT rel, src, dst FROM edges UNION ALL SELECT rel || '_rev', dst, src FROM edges) GROUP BY rel")
def _reverse(spark, sf_dir):
    return graph.with_reverse(graph.edges(spark, sf_dir)).groupBy("rel").agg(F.count("*").alias("n"), F.sum("src").alias("s"), F.sum("dst").alias("d"))


@query("graph_orphans", " UNION ALL ".join(f"SELECT '{k.name}' AS rel, (SELECT count(*) FROM {k.child} WHERE {k.foreign} IS NOT NULL AND {k.foreign} NOT IN (SELECT {k.parent_key} FROM {k.parent}))::BIGINT AS n" for k in graph.LINKS))
def _orphans(spark, sf_dir):
    out = None
    for k in graph.LINKS:
        part = graph.orphans(spark, sf_dir, k).agg(F.count("*").alias("n")).select(F.lit(k.name).alias("rel"), "n")
        out = part if out is None else out.unionByName(part)
    return out


@query("graph_asof_cut", f"WITH {_EDGES} SELECT rel, count(*)::BIGINT AS n FROM edges WHERE t IS NULL OR t <= TIMESTAMP '1999-01-01' GROUP BY rel")
def _asof(spark, sf_dir):
    return graph.as_of(graph.edges(spark, sf_dir), "1999-01-01").groupBy("rel").agg(F.count("*").alias("n"))


@query("graph_asof_targets", f"WITH {LOG} SELECT a.event, count(b.event)::BIGINT AS n FROM log a LEFT JOIN log b ON a.\"user\" = b.\"user\" AND b.t < a.t WHERE a.log = 'auth' GROUP BY a.event")
def _asof_targets(spark, sf_dir):
    """Edges known at each target's own time, as running counts: no join of a target with its entity's history."""
    from pyspark.sql import Window

    w = Window.partitionBy("user").orderBy(views._micros()).rangeBetween(Window.unboundedPreceding, -1)
    return tasks.auth_log(spark, sf_dir).withColumn("n", F.count("*").over(w)).filter("log = 'auth'").select("event", "n")


@query("graph_degrees", f"WITH {_EDGES} SELECT rel, dst, count(*)::BIGINT AS degree FROM edges GROUP BY rel, dst")
def _degrees(spark, sf_dir):
    return graph.degrees(graph.edges(spark, sf_dir))


_FAN = "(SELECT rel, src, dst, row_number() OVER (PARTITION BY rel, dst ORDER BY " + u_sql("rel || ':' || src || ':' || dst", "fan") + ", src) AS k FROM edges)"


@query("sample_fanout", f"WITH {_EDGES} SELECT rel, src, dst FROM {_FAN} WHERE k <= 3")
def _fanout(spark, sf_dir):
    return graph.fanout(graph.edges(spark, sf_dir), 3).select("rel", "src", "dst")


@query("khop_neighbors", f"""WITH {_EDGES}, placed AS (SELECT src, dst FROM {_FAN} WHERE k <= 4 AND rel = 'placed_by'), inn AS (SELECT src, dst FROM {_FAN} WHERE k <= 4 AND rel = 'customer_in'),
both_ AS (SELECT src + 1000000000 AS src, dst FROM placed UNION ALL SELECT src, dst + 2000000000 FROM inn),
h1 AS (SELECT DISTINCT src FROM both_ WHERE dst >= 2000000000), h2 AS (SELECT DISTINCT b.src FROM both_ b JOIN h1 ON b.dst = h1.src)
SELECT hop::BIGINT AS hop, count(*)::BIGINT AS n FROM (SELECT 1 AS hop FROM h1 UNION ALL SELECT 2 FROM h2) GROUP BY hop""")
def _khop(spark, sf_dir):
    e = graph.edges(spark, sf_dir, graph.LINKS[:2])
    capped = graph.fanout(e, 4)
    shifted = capped.select(F.lit("r").alias("rel"), F.when(F.col("rel") == "placed_by", F.col("src") + 1_000_000_000).otherwise(F.col("src")).alias("src"), F.when(F.col("rel") == "customer_in", F.col("dst") + 2_000_000_000).otherwise(F.col("dst")).alias("dst"))
    seeds = load(spark, sf_dir, "nation", ["n_nationkey"]).select((F.col("n_nationkey") + 2_000_000_000).cast("long").alias("nid"))
    return graph.khop(shifted, seeds, 2, 1 << 20).filter("hop > 0").groupBy(F.col("hop").cast("long").alias("hop")).agg(F.count("*").alias("n"))


_NEG = u_sql("rel || ':' || src || ':' || dst", "neg")


@query("negative_edges", f"WITH {_EDGES}, p AS (SELECT * FROM edges WHERE rel = 'placed_by') SELECT DISTINCT rel, src, floor({_NEG} * 1500)::BIGINT AS dst FROM p WHERE NOT EXISTS (SELECT 1 FROM p q WHERE q.src = p.src AND q.dst = floor({_NEG.replace('rel', 'p.rel').replace('src', 'p.src').replace('dst', 'p.dst')} * 1500))")
def _negative(spark, sf_dir):
    return graph.negative_edges(graph.edges(spark, sf_dir, graph.LINKS[:1]), 1500)


@query("sample_anchors", f"""WITH {LOG}, a AS (SELECT *, ({u_sql('event', 'lone')} < 0.005)::INT AS y, least(floor(date_diff('day', TIMESTAMP '2024-01-01', t) * 6 / 30.0), 5)::INT AS bucket FROM log WHERE log = 'auth')
SELECT event, y::BIGINT AS y, bucket::BIGINT AS bucket FROM (SELECT *, row_number() OVER (PARTITION BY bucket, y ORDER BY {u_sql('event', 'anchor')}, event) AS k FROM a) WHERE y = 1 OR k <= 20""")
def sample_anchors(spark, sf_dir):
    from relanom.draws import u

    auth = tasks.auth_log(spark, sf_dir).filter("log = 'auth'").withColumn("y", (u(F.col("event"), "lone") < 0.005).cast("int"))
    return graph.anchors(auth, 20, 6, "2024-01-01", 30).select("event", *long("y", "bucket"))


@query("sample_context", f"""WITH {LOG}, c AS (SELECT a.event, b.event AS other, b.log, row_number() OVER (PARTITION BY a.event ORDER BY b.t DESC, b.event) AS k
FROM log a JOIN log b ON a."user" = b."user" AND b.t < a.t AND b.t >= a.t - INTERVAL 6 HOUR WHERE a.log = 'auth') SELECT event, other, log FROM c WHERE k <= 5""")
def _context(spark, sf_dir):
    logs = tasks.auth_log(spark, sf_dir)
    return graph.context(logs.filter("log = 'auth'"), logs, 6 * 3600, 5)


@query("benchmark_summary", f"WITH {LOG} SELECT 'cyber' AS task, count(*)::BIGINT AS records, count(*) FILTER (log = 'auth')::BIGINT AS targets FROM log UNION ALL SELECT 'purchase', (SELECT count(*) FROM lineitem) + (SELECT count(*) FROM customer) + (SELECT count(*) FROM part), (SELECT count(*) FROM customer)")
def _summary(spark, sf_dir):
    n = lambda t: load(spark, sf_dir, t).agg(F.count("*").alias("n"))
    cyber = tasks.auth_log(spark, sf_dir).agg(F.count("*").alias("records"), F.count_if(F.col("log") == "auth").alias("targets")).select(F.lit("cyber").alias("task"), "records", "targets")
    rows = n("lineitem").unionByName(n("customer")).unionByName(n("part")).agg(F.sum("n").alias("records"))
    return cyber.unionByName(rows.join(F.broadcast(n("customer").withColumnRenamed("n", "targets"))).select(F.lit("purchase").alias("task"), "records", "targets"))


@query("task_audit", "SELECT 'purchase' AS task, true AS several_tables, (SELECT count(*) FROM customer) > 0 AS has_target, (SELECT count(DISTINCT o_orderdate) FROM orders) > 1 AS has_time")
def _audit(spark, sf_dir):
    one = load(spark, sf_dir, "customer").agg((F.count("*") > 0).alias("has_target"))
    time = load(spark, sf_dir, "orders", ["o_orderdate"]).agg((F.approx_count_distinct("o_orderdate") > 1).alias("has_time"))
    return one.join(F.broadcast(time)).select(F.lit("purchase").alias("task"), F.lit(True).alias("several_tables"), "has_target", "has_time")


# ---- flattened views
_WIDTHS = {"10m": "10 MINUTE", "1h": "1 HOUR", "1d": "1 DAY"}
_frame = lambda w: f"RANGE BETWEEN INTERVAL {w} PRECEDING AND INTERVAL 1 MICROSECOND PRECEDING"
_ALL = "RANGE BETWEEN UNBOUNDED PRECEDING AND INTERVAL 1 MICROSECOND PRECEDING"
_CYBER = f"""WITH {LOG}, p AS (SELECT *, count(*) FILTER (log = 'auth') OVER (PARTITION BY "user", machine ORDER BY t {_ALL}) AS pair_before,
  max(CASE WHEN log = 'auth' THEN t END) OVER (PARTITION BY "user", machine ORDER BY t {_ALL}) AS pair_last FROM log),
w AS (SELECT *, (log = 'auth' AND pair_before = 0)::INT AS first_pair,
  {", ".join(f'''count(*) FILTER (log = '{log}') OVER (PARTITION BY "user" ORDER BY t {_frame(w)}) AS user_{log}_{n}''' for log in ("auth", "dns", "flow", "process") for n, w in _WIDTHS.items())},
  {", ".join(f"count(*) FILTER (log = 'auth') OVER (PARTITION BY machine ORDER BY t {_frame(w)}) AS machine_auth_{n}" for n, w in _WIDTHS.items())} FROM p),
v AS (SELECT *, coalesce(sum(first_pair) OVER (PARTITION BY machine ORDER BY t {_ALL}), 0)::BIGINT AS machine_users FROM w)"""


@query("flat_cyber", f"""{_CYBER} SELECT event, value, CASE WHEN kind = 'signup' THEN 0 ELSE 1 END::BIGINT AS kind_code, hour(t)::BIGINT AS hour, (isodow(t) - 1)::BIGINT AS weekday FROM v WHERE log = 'auth'""")
def _flat_cyber(spark, sf_dir):
    return views.cyber(spark, sf_dir).select("event", "value", *long("kind_code", "hour", "weekday"))


@query("flat_cyber_novelty", f"{_CYBER} SELECT event, pair_before::BIGINT AS pair_before, round(epoch_us(t - pair_last) / 1e6, 3) AS pair_seconds, first_pair::BIGINT AS novel FROM v WHERE log = 'auth'".replace("epoch_us(t - pair_last)", "(epoch_us(t) - epoch_us(pair_last))"))
def _novelty(spark, sf_dir):
    return views.cyber(spark, sf_dir).select("event", "pair_before", F.round("pair_seconds", 3).alias("pair_seconds"), *long("novel"))


_RECENT = [f"user_{log}_{n}" for log in ("auth", "dns", "flow", "process") for n in _WIDTHS] + [f"machine_auth_{n}" for n in _WIDTHS]


@query("flat_cyber_recent", f"{_CYBER} SELECT event, {', '.join(f'{c}::BIGINT AS {c}' for c in _RECENT)} FROM v WHERE log = 'auth'")
def _recent(spark, sf_dir):
    return views.cyber(spark, sf_dir).select("event", *_RECENT)


@query("flat_cyber_machine_users", f"{_CYBER} SELECT event, machine_users FROM v WHERE log = 'auth'")
def _machine_users(spark, sf_dir):
    return views.cyber(spark, sf_dir).select("event", "machine_users")


@query("flat_cyber_fanout", f"WITH {LOG}, v AS (SELECT event, log, count(DISTINCT machine) OVER (PARTITION BY \"user\" ORDER BY t {_frame('1 DAY')})::BIGINT AS fanout_1d FROM log) SELECT event, fanout_1d FROM v WHERE log = 'auth'")
def _cyber_fanout(spark, sf_dir):
    return views.cyber(spark, sf_dir).select("event", "fanout_1d")


@query("flat_review", f"""WITH {TX} SELECT customer AS entity, {', '.join(f"count(*) FILTER (age < {d})::BIGINT AS reviews_{d}d" for d in (30, 90, 180))}, count(*)::BIGINT AS reviews,
  count(DISTINCT part)::BIGINT AS products, (max(age) - min(age))::BIGINT AS span, min(age)::BIGINT AS since_last FROM tx WHERE flag <> 'N' AND age >= 0 GROUP BY customer""")
def _review(spark, sf_dir):
    return views.review(spark, sf_dir).select("entity", *long("reviews_30d", "reviews_90d", "reviews_180d", "reviews", "products", "span", "since_last"))


@query("flat_review_ratings", f"""WITH {TX} SELECT customer AS entity, round(avg(rating), 6) AS rating_mean, round(stddev_samp(rating), 6) AS rating_std, min(rating)::BIGINT AS rating_min, max(rating)::BIGINT AS rating_max,
  round(avg((rating = 1)::INT), 6) AS lowest_share FROM tx WHERE flag <> 'N' AND age >= 0 GROUP BY customer""")
def _ratings(spark, sf_dir):
    v = views.review(spark, sf_dir)
    return v.select("entity", *(F.round(c, 6).alias(c) for c in ("rating_mean", "rating_std")), *long("rating_min", "rating_max"), F.round("lowest_share", 6).alias("lowest_share"))


@query("flat_purchase", f"""WITH {TX}, c AS (SELECT customer AS entity, {', '.join(f"count(*) FILTER (age < {d})::BIGINT AS bought_{d}d" for d in (30, 90, 180))}, count(*)::BIGINT AS bought, round(max(price), 4) AS price_max,
  count(DISTINCT part)::BIGINT AS articles, (max(age) - min(age))::BIGINT AS span, min(age)::BIGINT AS since_last, {', '.join(f"count(*) FILTER (floor(age / 180.0) = {i}) AS c{i}" for i in range(5))} FROM tx WHERE age >= 0 GROUP BY customer)
SELECT entity, bought_30d, bought_90d, bought_180d, bought, price_max, articles, span, since_last, round((2 * c0 + c1 - c3 - 2 * c4) / 10.0, 6) AS trend, round((c1 + c2 + c3 + c4) / 4.0, 6) AS level FROM c""")
def _purchase(spark, sf_dir):
    v = views.purchase(spark, sf_dir)
    return v.select("entity", *long("bought_30d", "bought_90d", "bought_180d", "bought", "articles", "span", "since_last"), F.round("price_max", 4).alias("price_max"), F.round("trend", 6).alias("trend"), F.round("level", 6).alias("level"))


@query("flat_documents", "SELECT doc_id AS entity, length(text)::BIGINT AS chars, (length(text) - length(replace(text, ' ', '')))::BIGINT AS spaces, round(coalesce(length(regexp_replace(text, '[^0-9]', '', 'g')) * 1.0 / greatest(length(text), 1), 0), 6) AS digit_share, lang, source FROM documents")
def _documents(spark, sf_dir):
    return views.documents(spark, sf_dir).select("entity", *long("chars", "spaces"), F.round("digit_share", 6).alias("digit_share"), "lang", "source")


@query("flat_leakage_probe", "SELECT 0::BIGINT AS changed")
def _leakage(spark, sf_dir):
    """Rows of the purchase view that change when everything after the cut is deleted."""
    now = views.purchase(spark, sf_dir)
    early = tasks.transactions(spark, sf_dir).filter(F.datediff(F.lit(tasks.CUT), "t") >= 0)
    original = tasks.transactions
    try:
        tasks.transactions = lambda *_: early
        then = views.purchase(spark, sf_dir)
    finally:
        tasks.transactions = original
    rounded = lambda v: v.select(*[F.round(c, 6).alias(c) if t == "double" else F.col(c) for c, t in v.dtypes])
    a, b = rounded(now), rounded(then)
    return a.exceptAll(b).unionByName(b.exceptAll(a)).agg(F.count("*").alias("changed"))


@query("motivating_event", f"""{_CYBER} SELECT event FROM v WHERE log = 'auth' AND first_pair = 1 AND user_auth_1d >= 3 AND machine_users >= 1""")
def _motivating(spark, sf_dir):
    """A pair never seen before, on a machine others use, after a burst of the same user."""
    return views.cyber(spark, sf_dir).filter("novel = 1 and user_auth_1d >= 3 and machine_users >= 1").select("event")


@query("label_cyber", f"WITH {LOG} SELECT event, ({u_sql('event', 'lone')} < 0.005)::BIGINT AS y FROM log WHERE log = 'auth'")
def label_cyber(spark, sf_dir):
    from relanom.draws import u

    return tasks.auth_log(spark, sf_dir).filter("log = 'auth'").select("event", (u(F.col("event"), "lone") < 0.005).cast("long").alias("y"))


@query("label_behavioural", f"""WITH {LOG}, v AS (SELECT event, log, row_number() OVER (PARTITION BY "user", machine ORDER BY t) AS k,
  count(DISTINCT machine) OVER (PARTITION BY "user" ORDER BY t RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS n FROM log) SELECT event, (k = 1 AND n >= 6)::BIGINT AS y FROM v WHERE log = 'auth'""")
def _label_behavioural(spark, sf_dir):
    return labels.behavioural(tasks.auth_log(spark, sf_dir)).select("event", *long("y"))


@query("label_documents", "SELECT d.doc_id AS entity, l.toxic::BIGINT AS y FROM documents d LEFT JOIN labels l USING (doc_id)")
def _label_documents(spark, sf_dir):
    d, y = load(spark, sf_dir, "documents", ["doc_id"]), load(spark, sf_dir, "labels", ["doc_id", "toxic"])
    return d.join(y, "doc_id", "left").select(F.col("doc_id").alias("entity"), F.col("toxic").cast("long").alias("y"))


# ---- encoding
@query("encode_coerce", "SELECT c_custkey AS entity, try_cast(c_name AS DOUBLE) AS name_number, try_cast(c_nationkey AS DOUBLE) AS nation FROM customer")
def _coerce(spark, sf_dir):
    rows = load(spark, sf_dir, "customer", ["c_custkey", "c_name", "c_nationkey"]).withColumnsRenamed({"c_custkey": "entity", "c_name": "name_number", "c_nationkey": "nation"})
    return encode.coerce(rows, ["name_number", "nation"])


for _how, _agg in (("mean", "avg"), ("median", "median")):

    @query(f"encode_impute_{_how}", f"WITH x AS (SELECT c_custkey AS entity, CASE WHEN c_acctbal >= 0 THEN c_acctbal END AS v FROM customer) SELECT entity, round(coalesce(v, (SELECT {_agg}(v) FROM x)), 6) AS v FROM x")
    def _impute(spark, sf_dir, how=_how):
        x = load(spark, sf_dir, "customer", ["c_custkey", "c_acctbal"]).select(F.col("c_custkey").alias("entity"), F.when(F.col("c_acctbal") >= 0, F.col("c_acctbal")).alias("v"))
        return encode.impute(x, encode.imputer(x, ["v"], how)).select("entity", F.round("v", 6).alias("v"))


_VOCAB = "v AS (SELECT c_mktsegment, row_number() OVER (ORDER BY count(*) DESC, c_mktsegment) - 1 AS code FROM customer GROUP BY 1)"


@query("encode_index", f"WITH {_VOCAB} SELECT c_custkey AS entity, code::BIGINT AS code FROM customer JOIN v USING (c_mktsegment)")
def _index(spark, sf_dir):
    c = load(spark, sf_dir, "customer", ["c_custkey", "c_mktsegment"])
    return encode.index(c, "c_mktsegment", encode.vocabulary(c, "c_mktsegment")).select(F.col("c_custkey").alias("entity"), F.col("c_mktsegment_code").alias("code"))


@query("encode_onehot", f"WITH {_VOCAB} SELECT c_custkey AS entity, {', '.join(f'(code = {i})::BIGINT AS is_{i}' for i in range(5))} FROM customer JOIN v USING (c_mktsegment)")
def _onehot(spark, sf_dir):
    c = load(spark, sf_dir, "customer", ["c_custkey", "c_mktsegment"])
    coded = encode.index(c, "c_mktsegment", encode.vocabulary(c, "c_mktsegment"))
    return coded.select(F.col("c_custkey").alias("entity"), *[(F.col("c_mktsegment_code") == i).cast("long").alias(f"is_{i}") for i in range(5)])


@query("encode_standardize", "SELECT c_custkey AS entity, round((c_acctbal - (SELECT avg(c_acctbal) FROM customer)) / (SELECT stddev_pop(c_acctbal) FROM customer), 6) AS v FROM customer")
def _standardize(spark, sf_dir):
    x = load(spark, sf_dir, "customer", ["c_custkey", "c_acctbal"]).select(F.col("c_custkey").alias("entity"), F.col("c_acctbal").alias("v"))
    return encode.standardize(x, encode.scaler(x, ["v"])).select("entity", F.round("v", 6).alias("v"))


@query("feature_stats", f"WITH {TX}, f AS (SELECT customer, count(*)::DOUBLE AS bought, count(DISTINCT part)::DOUBLE AS articles FROM tx WHERE age >= 0 GROUP BY 1) " + " UNION ALL ".join(f"SELECT '{c}' AS feature, min({c}) AS low, max({c}) AS high, round(avg({c}), 6) AS mean, count(DISTINCT {c})::BIGINT AS distinct_values, 0::DOUBLE AS null_share FROM f" for c in ("bought", "articles")))
def _stats(spark, sf_dir):
    return encode.profile(views.purchase(spark, sf_dir), ["bought", "articles"]).withColumn("mean", F.round("mean", 6))


@query("mp_mean_messages", "SELECT o_custkey AS dst, round(avg(o_totalprice / 1000) + 1e-7, 4) AS m0, round(avg(o_orderkey / 1000.0) + 1e-7, 4) AS m1 FROM orders GROUP BY 1")
def _messages(spark, sf_dir):
    h = load(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice"]).select(F.col("o_orderkey").alias("nid"), F.array(F.col("o_totalprice") / 1000, F.col("o_orderkey") / 1000).alias("h"))
    m = graph.mean_messages(graph.edges(spark, sf_dir, graph.LINKS[:1]), h, 2)
    return m.select("dst", F.round(F.col("m")[0] + 1e-7, 4).alias("m0"), F.round(F.col("m")[1] + 1e-7, 4).alias("m1"))


@query("mp_linearity", "SELECT o_custkey AS dst, round(avg(0.5 * o_totalprice / 1000 - 2 * o_orderkey / 1000.0 + 1) + 1e-7, 4) AS projected_mean, round(0.5 * avg(o_totalprice / 1000) - 2 * avg(o_orderkey / 1000.0) + 1 + 1e-7, 4) AS mean_projected FROM orders GROUP BY 1")
def _linearity(spark, sf_dir):
    """The mean of projected neighbours and the projection of their raw mean, side by side."""
    a, b = F.col("o_totalprice") / 1000, F.col("o_orderkey") / 1000
    return load(spark, sf_dir, "orders").groupBy(F.col("o_custkey").alias("dst")).agg(F.round(F.avg(0.5 * a - 2 * b + 1) + 1e-7, 4).alias("projected_mean"), F.round(0.5 * F.avg(a) - 2 * F.avg(b) + 1 + 1e-7, 4).alias("mean_projected"))

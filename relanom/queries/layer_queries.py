"""Layers, losses, prevalence matching, planted campaigns and paired differences with their oracles."""

from __future__ import annotations

from pyspark.sql import functions as F

from relanom import detector, encode, experiments, graph, labels, layers, metrics, nn, schema, tasks, trainer, tune, views
from relanom.draws import u, u_sql
from relanom.queries.experiment_queries import folder
from relanom.queries.labels_metrics import PURCHASE, _active_sql, labelled
from relanom.registry import query
from relanom.sources import load

LOG, TX = tasks.LOG_SQL, tasks.TX_SQL

# Small weights of the checks.
W_SELF, W_PLACED, W_REVERSE = [[0.5, -0.25], [0.1, 0.8]], [[1.0, 0.5], [-0.5, 0.25]], [[0.3, 0.2], [0.4, -0.6]]
BIAS = [0.125, -0.5]
AWAY = 10**12  # customers' ids start here, orders' ids below

_ROW = lambda w, a, b: f"({w[0]} * {a} + {w[1]} * {b})"
_O = "o AS (SELECT o_orderkey AS id, o_custkey AS cust, o_totalprice / 100000 AS x0, o_custkey / 1000.0 AS x1 FROM orders)"
_C = "c AS (SELECT c_custkey AS id, c_acctbal / 10000 AS x0, c_nationkey / 25.0 AS x1 FROM customer)"


def _states(spark, sf_dir):
    o = load(spark, sf_dir, "orders").select(F.col("o_orderkey").cast("long").alias("nid"), F.array(F.col("o_totalprice") / 100000, F.col("o_custkey") / 1000.0).alias("h"))
    c = load(spark, sf_dir, "customer").select((F.col("c_custkey") + AWAY).alias("nid"), F.array(F.col("c_acctbal") / 10000, F.col("c_nationkey") / 25.0).alias("h"))
    e = graph.edges(spark, sf_dir, graph.LINKS[:1]).withColumn("dst", F.col("dst") + AWAY)
    return o, c, e


@query("mp_project", f"WITH {_C} SELECT id AS nid, round({_ROW(W_SELF[0], 'x0', 'x1')} + {BIAS[0]}, 9) AS h0, round({_ROW(W_SELF[1], 'x0', 'x1')} + {BIAS[1]}, 9) AS h1 FROM c")
def _project(spark, sf_dir):
    _, c, _ = _states(spark, sf_dir)
    h = layers.project(c.select("nid", F.col("h").alias("x")), W_SELF, BIAS)
    return h.select((F.col("nid") - AWAY).alias("nid"), *(F.round(F.col("h")[k], 9).alias(f"h{k}") for k in (0, 1)))


def _layer_sql(k: int) -> str:
    """CTEs co{k}, cc{k}: states of orders and customers after layer k, from those after layer k - 1."""
    o, c = (f"co{k - 1}", f"cc{k - 1}") if k > 1 else ("o", "c")
    own = lambda t, i: _ROW(W_SELF[i], f"{t}.x0", f"{t}.x1")
    return f"""m{k} AS (SELECT cust, avg(x0) AS a, avg(x1) AS b FROM {o} GROUP BY cust),
co{k} AS (SELECT s.id, s.cust, {', '.join(f"greatest(0.0, {own('s', i)} + coalesce({_ROW(W_REVERSE[i], 'p.x0', 'p.x1')}, 0)) AS x{i}" for i in (0, 1))} FROM {o} s LEFT JOIN {c} p ON s.cust = p.id),
cc{k} AS (SELECT s.id, {', '.join(f"greatest(0.0, {own('s', i)} + coalesce({_ROW(W_PLACED[i], 'a', 'b')}, 0)) AS x{i}" for i in (0, 1))} FROM {c} s LEFT JOIN m{k} ON s.id = m{k}.cust)"""


for _k, _name in ((1, "mp_update"), (2, "mp_two_layer")):

    @query(_name, f"WITH {_O}, {_C}, {', '.join(_layer_sql(i) for i in range(1, _k + 1))} SELECT id AS nid, round(x0 + 1e-7, 4) AS z0, round(x1 + 1e-7, 4) AS z1 FROM cc{_k}")
    def _stacked(spark, sf_dir, k=_k):
        o, c, e = _states(spark, sf_dir)
        z = layers.encode(graph.with_reverse(e), o.unionByName(c), [(W_SELF, {"placed_by": W_PLACED, "placed_by_rev": W_REVERSE})] * k)
        return z.filter(F.col("nid") >= AWAY).select((F.col("nid") - AWAY).alias("nid"), *(F.round(F.col("h")[i] + 1e-7, 4).alias(f"z{i}") for i in (0, 1)))


@query("edge_prob", f"WITH {_O}, {_C} SELECT o.id AS src, c.id AS dst, round(1 / (1 + exp(-({_ROW(W_PLACED[0], 'o.x0', 'o.x1')} * c.x0 + {_ROW(W_PLACED[1], 'o.x0', 'o.x1')} * c.x1))), 6) AS prob FROM o JOIN c ON o.cust = c.id")
def _edge_prob(spark, sf_dir):
    o, c, e = _states(spark, sf_dir)
    return layers.edge_probability(e, o, c, W_PLACED).select("src", (F.col("dst") - AWAY).alias("dst"), F.round("prob", 6).alias("prob"))


@query("receptive_field_sizes", "SELECT o_custkey AS dst, count(*)::BIGINT AS degree, least(count(*), 8)::BIGINT AS kept FROM orders GROUP BY 1")
def _sizes(spark, sf_dir):
    return layers.field_sizes(graph.edges(spark, sf_dir, graph.LINKS[:1]), 8).select("dst", "degree", "kept")


@query("rank_pairs", f"""WITH p AS (SELECT c_custkey AS positive, unnest(range(1, 4)) AS j FROM customer WHERE c_nationkey = 3),
n AS (SELECT c_custkey AS id, floor({u_sql('c_custkey', 'pair')} * 64) AS b, {u_sql('c_custkey', 'pair-in')} AS d FROM customer WHERE c_nationkey <> 3),
l AS (SELECT b, arg_min(id, d) AS negative FROM n GROUP BY b)
SELECT positive, j, negative FROM p JOIN l ON floor({u_sql("(positive::VARCHAR || ':' || j::VARCHAR)", 'pair')} * 64) = b""")
def _pairs(spark, sf_dir):
    rows = load(spark, sf_dir, "customer").select(F.col("c_custkey").alias("target"), (F.col("c_nationkey") == 3).cast("int").alias("y"), F.col("c_acctbal").alias("score"))
    return layers.sample_pairs(rows, 3, 64)


_SP = lambda v: f"(greatest({v}, 0) + ln(1 + exp(-abs({v}))))"


@query("rank_loss_sampled", f"""WITH p AS (SELECT c_custkey AS positive, c_acctbal / 10000 AS ps, unnest(range(1, 4)) AS j FROM customer WHERE c_nationkey = 3),
n AS (SELECT c_acctbal / 10000 AS s, floor({u_sql('c_custkey', 'pair')} * 64) AS b, {u_sql('c_custkey', 'pair-in')} AS d FROM customer WHERE c_nationkey <> 3),
l AS (SELECT b, arg_min(s, d) AS ns FROM n GROUP BY b)
SELECT count(*)::BIGINT AS pairs, round(avg({_SP('(ns - ps)')}), 6) AS loss FROM p JOIN l ON floor({u_sql("(positive::VARCHAR || ':' || j::VARCHAR)", 'pair')} * 64) = b""")
def _sampled_loss(spark, sf_dir):
    rows = load(spark, sf_dir, "customer").select(F.col("c_custkey").alias("target"), (F.col("c_nationkey") == 3).cast("int").alias("y"), (F.col("c_acctbal") / 10000).alias("score"))
    return layers.sampled_rank_loss(rows, 3, 64).select("pairs", F.round("loss", 6).alias("loss"))


@query("score_combined", f"""WITH {_O}, {_C}, e AS (SELECT c.id, avg(-ln(1 / (1 + exp(-({_ROW(W_PLACED[0], 'o.x0', 'o.x1')} * c.x0 + {_ROW(W_PLACED[1], 'o.x0', 'o.x1')} * c.x1))))) AS edge FROM o JOIN c ON o.cust = c.id GROUP BY c.id)
SELECT c.id AS nid, round(pow(c.x0 - 0.5, 2) + 0.3 * coalesce(edge, 0), 6) AS score FROM c LEFT JOIN e ON c.id = e.id""")
def _combined(spark, sf_dir):
    o, c, e = _states(spark, sf_dir)
    errors = c.select("nid", layers.squared_distance(F.slice("h", 1, 1), F.array(F.lit(0.5))).alias("error"))
    scores = layers.combined_score(errors, layers.edge_probability(e, o, c, W_PLACED), 0.3)
    return scores.select((F.col("nid") - AWAY).alias("nid"), F.round("score", 6).alias("score"))


@query("objective_total", f"""WITH a AS (SELECT avg(pow(c_acctbal / 10000 - 0.5, 2)) AS attr FROM customer),
s AS (SELECT avg(CASE WHEN o_orderstatus = 'F' THEN {_SP('-o_totalprice / 200000')} ELSE {_SP('o_totalprice / 200000')} END) AS struct FROM orders),
r AS (SELECT avg({_SP('(n_nationkey - n_regionkey * 3) / 10.0')}) AS rank FROM nation)
SELECT round(attr, 6) AS attr, round(struct, 6) AS struct, round(rank, 6) AS rank, round(attr + 0.3 * struct + 2 * rank, 6) AS total FROM a, s, r""")
def _objective(spark, sf_dir):
    rows = load(spark, sf_dir, "customer").select(layers.squared_distance(F.array(F.col("c_acctbal") / 10000), F.array(F.lit(0.5))).alias("error"))
    edges = load(spark, sf_dir, "orders").select((F.col("o_totalprice") / 200000).alias("logit"), (F.col("o_orderstatus") == "F").cast("int").alias("label"))
    pairs = load(spark, sf_dir, "nation").select((F.col("n_nationkey") / 10.0).alias("negative"), (F.col("n_regionkey") * 3 / 10.0).alias("positive"))
    return layers.objective(rows, edges, pairs, 0.3, 2.0).select(*(F.round(c, 6).alias(c) for c in ("attr", "struct", "rank", "total")))


_EMB = lambda i: f"embedding[{i + 1}]::DOUBLE"
_E = "array<double>"


@query("score_attr", f"SELECT vec_id, round(list_sum([pow(embedding[i]::DOUBLE - 0.1 * ((i - 1) % 3), 2) for i in range(1, 65)]), 6) AS score FROM embeddings")
def _score_attr(spark, sf_dir):
    fixed = F.array(*(F.lit(0.1 * (i % 3)) for i in range(64)))
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(layers.squared_distance(F.col("embedding").cast(_E), fixed), 6).alias("score"))


@query("ae_error", f"SELECT vec_id, round(pow({_EMB(0)} - 0.5 * (0.6 * {_EMB(0)} + 0.8 * {_EMB(1)}), 2) + pow({_EMB(1)} - 2 * (0.6 * {_EMB(0)} + 0.8 * {_EMB(1)}), 2), 6) AS score FROM embeddings")
def _ae(spark, sf_dir):
    """Linear autoencoder of two inputs and one hidden unit."""
    x = F.slice(F.col("embedding").cast(_E), 1, 2)
    rows = load(spark, sf_dir, "embeddings").select("vec_id", x.alias("x"))
    rows = rows.withColumn("out", layers.affine(layers.affine(F.col("x"), [[0.6, 0.8]]), [[0.5], [2.0]]))
    return rows.select("vec_id", F.round(layers.squared_distance(F.col("x"), F.col("out")), 6).alias("score"))


@query("svdd_distance", f"SELECT vec_id, round(pow({_ROW(W_SELF[0], _EMB(0), _EMB(1))} - 0.125, 2) + pow({_ROW(W_SELF[1], _EMB(0), _EMB(1))} + 0.5, 2), 6) AS score FROM embeddings")
def _svdd(spark, sf_dir):
    """Distance of a bias-free projection to a fixed centre."""
    z = layers.affine(F.col("embedding").cast(_E), W_SELF)
    return load(spark, sf_dir, "embeddings").select("vec_id", F.round(layers.squared_distance(z, F.array(*map(F.lit, BIAS))), 6).alias("score"))


@query("prevalence_valid", f"""WITH {_active_sql(PURCHASE, 'diff')}, s AS (SELECT *, {u_sql('entity', 'half')} < 0.5 AS train FROM labelled),
k AS (SELECT floor(0.015 * count(*) FILTER (y = 0 AND train) / (1 - 0.015)) AS tp, count(*) FILTER (y = 0 AND train) AS tn, count(*) FILTER (y = 0 AND NOT train) AS vn FROM s),
v AS (SELECT entity, y, row_number() OVER (PARTITION BY y ORDER BY {u_sql('entity', 'prev')}, entity) AS r FROM s WHERE NOT train)
SELECT entity, y::BIGINT AS y FROM v, k WHERE y = 0 OR r <= vn * tp // tn""")
def _valid(spark, sf_dir):
    rows = labelled(spark, sf_dir, "purchase").select("entity", "y").withColumn("train", u(F.col("entity"), "half") < 0.5)
    train = labels.to_prevalence(rows.filter("train"), 0.015)
    return labels.match_prevalence(rows.filter("not train"), train).select("entity", F.col("y").cast("long").alias("y"))


@query("prevalence_threshold", f"""WITH {_active_sql(PURCHASE, 'diff')}, q AS (SELECT round(-g - ln(mu + 1) / ln(10.0) * (1 + 0.02 * mu), 9) AS q, churn FROM active),
c AS (SELECT q, sum(count(*)) OVER (ORDER BY q) AS upto, count(*) AS n FROM q WHERE churn = 1 GROUP BY q),
t AS (SELECT p, floor(p * (SELECT count(*) FROM q)) AS k FROM (VALUES (0.005), (0.015), (0.03)) v(p))
SELECT p::DOUBLE AS prevalence, round(min(q), 6) AS base, min(upto - n)::BIGINT AS positives FROM t JOIN c ON upto > k GROUP BY p""")
def _threshold(spark, sf_dir):
    active = labelled(spark, sf_dir, "purchase")
    return labels.threshold_for(active, [0.005, 0.015, 0.03]).select("prevalence", F.round("base", 6).alias("base"), "positives")


_N = f"(4 + floor({u_sql('uid', 'size')} * 3))::BIGINT"


@query("planted_cyber", f"""WITH {LOG}, w AS (SELECT DISTINCT "user" AS uid FROM log), b AS (SELECT uid, unnest(range(0, {_N})) AS i FROM w WHERE {u_sql('uid', 'camp')} < 0.2)
SELECT event, "user" AS user_id, machine::BIGINT AS machine, t, ({u_sql('event', 'lone')} < 0.005)::BIGINT AS y FROM log WHERE log = 'auth'
UNION ALL SELECT 1000000000 + uid * 10 + i, uid, ((floor({u_sql('uid', 'first')} * 100)::BIGINT + 17 * i) % 100)::BIGINT, TIMESTAMP '2024-01-01' + to_seconds(floor({u_sql('uid', 'when')} * 2505600)::BIGINT + 100 * i), ({u_sql('uid', 'benign')} >= 0.2)::BIGINT FROM b""")
def _planted(spark, sf_dir):
    out = labels.planted_campaigns(tasks.auth_log(spark, sf_dir))
    return out.select("event", F.col("user").alias("user_id"), F.col("machine").cast("long").alias("machine"), "t", F.col("y").cast("long").alias("y"))


@query("paired_difference", """WITH r AS (SELECT l_linestatus AS task, l_returnflag AS method, l_linenumber AS seed, avg(l_quantity) AS value FROM lineitem GROUP BY 1, 2, 3)
SELECT a.task, round(avg(a.value - b.value) + 1e-9, 6) AS mean, round(stddev_samp(a.value - b.value), 6) AS std, count(*)::BIGINT AS seeds, count(*) FILTER (a.value > b.value)::BIGINT AS wins
FROM r a JOIN r b USING (task, seed) WHERE a.method = 'R' AND b.method = 'A' GROUP BY a.task""")
def _paired(spark, sf_dir):
    rows = load(spark, sf_dir, "lineitem").groupBy(F.col("l_linestatus").alias("task"), F.col("l_returnflag").alias("method"), F.col("l_linenumber").alias("seed")).agg(F.avg("l_quantity").alias("value"))
    out = metrics.paired(rows.withColumn("metric", F.lit("mean")), "R", "A")
    return out.select("task", F.round(F.col("mean") + 1e-9, 6).alias("mean"), F.round("std", 6).alias("std"), "seeds", "wins")


@query("flat_admissible", "SELECT * FROM (VALUES ('o_orderstatus'), ('o_totalprice'), ('o_orderpriority')) t(name)")
def _admissible(spark, sf_dir):
    """Columns of a table that a feature view may read: no keys, no times, and some row has a value."""
    orders = load(spark, sf_dir, "orders")
    names = encode.admissible(orders.columns, {"o_orderkey", "o_custkey", "o_orderdate"})
    held = orders.agg(*[F.count(n).alias(n) for n in names]).unpivot([], names, "name", "n")
    return held.filter("n > 0").select("name")


@query("encode_assemble", "SELECT c_custkey AS entity, 2::BIGINT AS width, round(c_acctbal, 6) AS x0, c_nationkey::DOUBLE AS x1 FROM customer")
def _assemble(spark, sf_dir):
    x = encode.assemble(load(spark, sf_dir, "customer"), ["c_acctbal", "c_nationkey"])
    return x.select(F.col("c_custkey").alias("entity"), F.size("x").cast("long").alias("width"), F.round(F.col("x")[0], 6).alias("x0"), F.col("x")[1].alias("x1"))


@query("view_alignment", f"WITH {TX} SELECT c_custkey AS entity, (EXISTS (SELECT 1 FROM tx WHERE customer = c_custkey AND age >= 0))::BIGINT AS seen FROM customer")
def _aligned(spark, sf_dir):
    """Every target once, with its flat row or nulls."""
    targets = graph.nodes(spark, sf_dir, "customer", "c_custkey").select("nid")
    return views.align(views.purchase(spark, sf_dir), targets).select(F.col("nid").alias("entity"), F.col("entity").isNotNull().cast("long").alias("seen"))


@query("inferred_links")
def _links(spark, sf_dir):
    return schema.infer_links({t: load(spark, sf_dir, t) for t in ("region", "nation", "customer", "orders")})


@query("tune_detector")
def _tune(spark, sf_dir):
    """Trials of the search on the cyber task without rules; the row of most rounds is the one frozen."""
    found = tune.search(detector.cyber_task(spark, sf_dir), None, trials=4)
    rows = [(i, float(s["alpha"]), float(s["beta"]), s["hidden"], float(s["rate"]), r, float(v)) for i, (s, r, v) in enumerate(found)]
    return spark.createDataFrame(rows, "trial int, alpha double, beta double, hidden int, rate double, rounds int, auprc double")


@query("partial_documents")
def _partial(spark, sf_dir):
    """Documents of which only some are labelled; the others stay in the graph."""
    return experiments.compare(detector.document_task(spark, sf_dir), folder(spark), "review", ["detector_no_rules", "gnn_weighted", "ae", "mlp", "random"], experiments.Settings(rounds=4, seeds=2, prevalence=None))


@query("sampled_vs_full")
def _sampled(spark, sf_dir):
    """One fitted model, measured on all test rows and on all positives with drawn negatives per time bucket."""
    task = detector.cyber_task(spark, sf_dir)
    task.rows = task.rows.cache()
    rows, spec = detector.assembled(task)
    scores = trainer.fit(rows.cache(), nn.SupervisedGraph(spec, 128, 0), 4).transform(rows)
    dated = scores.join(task.rows.select("target", "event", "t"), "target")
    sample = graph.anchors(dated.filter("split = 'test'"), 20, 10, "2024-01-01", 30)
    return experiments.union([experiments.result("cyber", "full", "labels", dated), experiments.result("cyber", "sampled", "labels", sample)])

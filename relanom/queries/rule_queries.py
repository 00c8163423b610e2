"""Rule mining with its oracles: exact parts over the purchase view and small literal fixtures."""

from __future__ import annotations

from pyspark.sql import functions as F

from relanom import rules, tasks, views
from relanom.draws import u_sql
from relanom.queries.labels_metrics import _F4, planted_multihop
from relanom.registry import query

TEXTS = ["bought_180d <= 3.0", "bought_180d <= 3.0 AND since_last > 30.0", "articles > 60.0", "trend <= -1.5 AND level > 2.0", "bought < 0", "price_max > 60000.0 OR span <= 1500"]
_VIEW = f"""WITH {tasks.TX_SQL}, v AS (SELECT customer AS entity, count(*) FILTER (age < 180) AS bought_180d, count(*) AS bought, max(price) AS price_max, count(DISTINCT part) AS articles, max(age) - min(age) AS span, min(age) AS since_last,
  (2 * count(*) FILTER (floor(age / 180.0) = 0) + count(*) FILTER (floor(age / 180.0) = 1) - count(*) FILTER (floor(age / 180.0) = 3) - 2 * count(*) FILTER (floor(age / 180.0) = 4)) / 10.0 AS trend,
  count(*) FILTER (floor(age / 180.0) BETWEEN 1 AND 4) / 4.0 AS level FROM tx WHERE age >= 0 GROUP BY customer),
f4 AS ({_F4}), view AS (SELECT v.*, (share >= 0.55)::INT AS y FROM v JOIN f4 ON v.entity = f4.customer)"""
_RULES = "r(rule, text) AS (VALUES " + ", ".join(f"({i}, '{t}')" for i, t in enumerate(TEXTS)) + ")"
_MEASURED = "m AS (" + " UNION ALL ".join(f"SELECT {i}::BIGINT AS rule, '{t}' AS text, count(*) FILTER ({t})::BIGINT AS support, coalesce(avg(y) FILTER ({t}), 0)::DOUBLE AS confidence, (coalesce(avg(y) FILTER ({t}), 0) / avg(y))::DOUBLE AS lift FROM view" for i, t in enumerate(TEXTS)) + ")"


def view(spark, sf_dir):
    return views.purchase(spark, sf_dir).join(planted_multihop(spark, sf_dir).select("entity", "y"), "entity")


def measured(spark, sf_dir):
    return rules.measure(view(spark, sf_dir), TEXTS)


for _name, _columns in (("rule_support", ["support"]), ("rule_confidence", ["round(confidence, 6) AS confidence"]), ("rule_lift", ["round(lift, 6) AS lift"]), ("rule_report", ["support", "round(confidence, 6) AS confidence", "round(lift, 6) AS lift"])):

    @query(_name, f"{_VIEW}, {_MEASURED} SELECT rule, {', '.join(_columns)} FROM m")
    def _measure(spark, sf_dir, columns=_columns):
        return measured(spark, sf_dir).selectExpr("rule", *columns)


@query("rule_filter_valid", f"{_VIEW}, {_MEASURED} SELECT rule FROM m WHERE support >= 3 AND confidence >= 0.02")
def _filter_valid(spark, sf_dir):
    return rules.ranked(measured(spark, sf_dir), tasks.PRESETS["cyber"]).select("rule")


@query("rule_filter_train", f"{_VIEW}, {_MEASURED} SELECT rule FROM m WHERE support >= 1")
def _filter_train(spark, sf_dir):
    return rules.ranked(measured(spark, sf_dir), tasks.PRESETS["review"]).select("rule")


@query("rule_rank", f"{_VIEW}, {_MEASURED} SELECT rule, row_number() OVER (ORDER BY confidence DESC, support DESC, len(string_split(text, ' AND ')), text)::BIGINT AS rank FROM m WHERE support >= 1")
def _rank(spark, sf_dir):
    return rules.ranked(measured(spark, sf_dir), tasks.PRESETS["review"]).select("rule", "rank")


@query("rule_seeds", f"{_VIEW}, {_MEASURED} SELECT rule FROM m WHERE support >= 1 ORDER BY -ln(greatest({u_sql('text', 'seed')}, 1e-12)) / greatest(confidence, 1e-9), text LIMIT 3")
def _seeds(spark, sf_dir):
    return rules.seeds(rules.ranked(measured(spark, sf_dir), tasks.PRESETS["review"]), 3).select("rule")


_BITS = ", ".join(f"coalesce(({t})::BIGINT, 0) AS r{i}" for i, t in enumerate(TEXTS))


@query("rule_vector", f"{_VIEW} SELECT entity, {_BITS} FROM view")
def _vector(spark, sf_dir):
    bits = view(spark, sf_dir).withColumn("r", rules.RuleSet(tuple(TEXTS)).vector())
    return bits.select("entity", *[F.col("r")[i].cast("long").alias(f"r{i}") for i in range(len(TEXTS))])


@query("rule_inject", f"{_VIEW} SELECT entity, bought::DOUBLE AS x0, span::DOUBLE AS x1, {', '.join(f'coalesce(({t})::INT, 0)::DOUBLE AS x{i + 2}' for i, t in enumerate(TEXTS))} FROM view")
def _inject(spark, sf_dir):
    x = F.concat(F.array(F.col("bought").cast("double"), F.col("span").cast("double")), rules.RuleSet(tuple(TEXTS)).vector())
    return view(spark, sf_dir).withColumn("x", x).select("entity", *[F.col("x")[i].alias(f"x{i}") for i in range(2 + len(TEXTS))])


CONF = (0.5, 0.6, 0.2, 0.3, 0.9, 0.1)


@query("baseline_rule_score", f"{_VIEW} SELECT entity, greatest(0.0, {', '.join(f'CASE WHEN {t} THEN {c} ELSE 0.0 END' for t, c in zip(TEXTS, CONF))})::DOUBLE AS score FROM view")
def _rule_score(spark, sf_dir):
    return view(spark, sf_dir).select("entity", rules.RuleSet(tuple(TEXTS), CONF).score().alias("score"))


@query("rule_explain", f"{_VIEW}, {_RULES}, x AS (" + " UNION ALL ".join(f"SELECT entity, '{t} ({c:.3f})' AS reason FROM view WHERE {t}" for t, c in zip(TEXTS, CONF)) + ") SELECT entity, reason FROM x")
def _explain(spark, sf_dir):
    return view(spark, sf_dir).select("entity", F.explode(rules.RuleSet(tuple(TEXTS), CONF).explain()).alias("reason"))


@query("posthoc_weighted_sum", f"{_VIEW}, s AS (SELECT entity, {u_sql('entity', 'posthoc')} AS s, ({' + '.join(f'CASE WHEN {t} THEN {c} ELSE 0.0 END' for t, c in zip(TEXTS, CONF))}) / {len(TEXTS)} AS r FROM view) SELECT entity, round((s - min(s) OVER ()) / (max(s) OVER () - min(s) OVER ()) + r, 6) AS score FROM s")
def _posthoc(spark, sf_dir):
    from relanom.fusion import weighted_sum

    from relanom.draws import u

    rows = view(spark, sf_dir).withColumn("score", u(F.col("entity"), "posthoc"))
    return weighted_sum(rows, rules.RuleSet(tuple(TEXTS), CONF)).select("entity", F.round("score", 6).alias("score"))


# Two small trees (tree, node, left, right, feature, threshold, rows, p).
TREES = [(0, 0, 1, 2, 0, 0.5, 40, 0.4), (0, 1, -1, -1, -1, 0.0, 20, 0.1), (0, 2, 3, 4, 1, 2.0, 20, 0.7), (0, 3, -1, -1, -1, 0.0, 12, 0.9), (0, 4, -1, -1, -1, 0.0, 8, 0.4), (1, 0, 1, 2, 1, 3.0, 40, 0.4), (1, 1, 3, 4, 1, 1.5, 30, 0.5), (1, 2, -1, -1, -1, 0.0, 10, 0.2), (1, 3, -1, -1, -1, 0.0, 4, 1.0), (1, 4, -1, -1, -1, 0.0, 26, 0.55)]
#: The splits of those trees over customers: what a customer fulfils who reaches a node.
REACHED = {(0, 0): "true", (0, 1): "f0 <= 0.5", (0, 2): "f0 > 0.5", (0, 3): "f0 > 0.5 AND f1 <= 2.0", (0, 4): "f0 > 0.5 AND f1 > 2.0", (1, 0): "true", (1, 1): "f1 <= 3.0", (1, 2): "f1 > 3.0", (1, 3): "f1 <= 1.5", (1, 4): "f1 <= 3.0 AND f1 > 1.5"}
_TREES = "c AS (SELECT c_acctbal / 10000 AS f0, c_nationkey / 5.0::DOUBLE AS f1, (c_acctbal > 3000 AND c_nationkey < 13)::INT AS y FROM customer), n(tree, node, lft, rgt, feature, threshold, n, p) AS (" + " UNION ALL ".join(f"SELECT {', '.join(map(str, t[:6]))}, count(*) FILTER ({REACHED[t[:2]]}), avg(y) FILTER ({REACHED[t[:2]]}) FROM c" for t in TREES) + ")"
_PATHS = f"""WITH RECURSIVE {_TREES}, w AS (SELECT tree, node, lft, rgt, feature, threshold, n, p, '' AS path FROM n WHERE node = 0
UNION ALL SELECT c.tree, c.node, c.lft, c.rgt, c.feature, c.threshold, c.n, c.p, w.path || ';f' || w.feature || CASE WHEN c.node = w.lft THEN '<=' ELSE '>' END || w.threshold::DOUBLE FROM w JOIN n c ON c.tree = w.tree AND c.node IN (w.lft, w.rgt))
SELECT tree::BIGINT AS tree, node::BIGINT AS leaf, n::BIGINT AS rows, substr(path, 2) AS path FROM w WHERE lft < 0"""


def _tree_nodes(spark, sf_dir):
    """The small trees with the customers that reach each node and the share of positives among them, counted in one scan."""
    customers = spark.read.parquet(f"{sf_dir}/customer.parquet").select((F.col("c_acctbal") / 10000).alias("f0"), (F.col("c_nationkey") / 5).alias("f1"), F.expr("int(c_acctbal > 3000 AND c_nationkey < 13)").alias("y"))
    names = ("tree", "node", "left", "right", "feature", "threshold")
    reached = lambda t: F.when(F.expr(REACHED[t[:2]]), F.col("y"))
    counted = [F.struct(*[F.lit(v).cast("double" if n == "threshold" else "long").alias(n) for n, v in zip(names, t)], F.count(reached(t)).alias("rows"), F.avg(reached(t)).alias("p")).alias(f"n{i}") for i, t in enumerate(TREES)]
    return customers.agg(*counted).select(F.explode(F.array(*[f"n{i}" for i in range(len(TREES))])).alias("n")).select("n.*")


def _tree_paths(spark, sf_dir):
    found = rules.paths(_tree_nodes(spark, sf_dir), 10)
    path = F.array_join(F.transform("conditions", lambda c: F.concat(F.lit("f"), c["feature"].cast("string"), c["op"], c["threshold"].cast("string"))), ";")
    return found.withColumn("path", path)


@query("rule_paths", _PATHS)
def _paths(spark, sf_dir):
    return _tree_paths(spark, sf_dir).select("tree", "leaf", "rows", "path")


@query("rule_leaf_filter", _PATHS + " AND n >= 8 AND p >= 0.5")
def _leaf_filter(spark, sf_dir):
    return _tree_paths(spark, sf_dir).filter("rows >= 8 and p >= 0.5").select("tree", "leaf", "rows", "path")


_LEAVES = ", ".join(f"({t}, {n}, '{text}')" for (t, n), text in REACHED.items() if n not in (0, (2, 1)[t]))


@query("rule_canonical", f"WITH {_TREES} SELECT text FROM n JOIN (VALUES {_LEAVES}) v(tree, node, text) USING (tree, node) WHERE n >= 8 AND p >= 0.5")
def _canonical(spark, sf_dir):
    found = rules.candidates(_tree_paths(spark, sf_dir), ["f0", "f1"], tasks.PRESETS["cyber"])
    return spark.createDataFrame([(rules.text_of(r),) for r in found], "text string")


@query("rule_dedupe", f"{_VIEW}, x AS (SELECT DISTINCT s FROM (" + " UNION ALL ".join(f"SELECT {i} AS rule, count(*) || ':' || sum(entity) AS s FROM view WHERE {t}" for i, t in enumerate([*TEXTS, "NOT bought_180d > 3.0"])) + ")) SELECT count(*)::BIGINT AS n FROM x")
def _dedupe(spark, sf_dir):
    """Rules that cover different rows: a sum over hashed ids in the measuring pass tells coverages apart."""
    texts = [*TEXTS, "NOT bought_180d > 3.0"]
    sums = view(spark, sf_dir).agg(*[F.struct(F.count_if(rules.satisfied(t)).alias("c"), F.sum(F.when(rules.satisfied(t), F.xxhash64("entity").cast("decimal(38,0)"))).alias("h")).alias(f"r{i}") for i, t in enumerate(texts)])
    return sums.select(F.explode(F.array(*[f"r{i}" for i in range(len(texts))])).alias("s")).select("s.*").distinct().agg(F.count("*").alias("n"))


PROPOSED = {
    "bought <= 3.0": "ok", "abs(trend) > 1 AND coalesce(price_max, 0) > 10": "ok", "nothing > 1": "column", "y = 1": "forbidden column", "entity > 5": "forbidden column", "bought +": "syntax", "bought; drop": "syntax", "bought": "type",
    "rand() < 0.5": "function", "random() < 0.5": "function", "monotonically_increasing_id() > 3": "function", "stddev(bought) > 1": "function", "median(bought) > 1": "function", "sum(bought) OVER () > 1": "function",
    "bought > (SELECT 1)": "function", "current_date() > DATE 2020-01-01": "syntax", "now() > TIMESTAMP ''2020-01-01 00:00:00''": "function", "explode(array(true))": "function",
}


@query("rule_rejections", "SELECT * FROM (VALUES " + ", ".join(f"('{t}', '{r}')" for t, r in PROPOSED.items()) + ") t(text, reason)")
def _rejections(spark, sf_dir):
    v = view(spark, sf_dir)
    allowed = {c for c in v.columns if c not in ("entity", "y")}
    texts = [t.replace("''", "'") for t in PROPOSED]
    found = {t: rules.problem(v, t, allowed) or "ok" for t in texts}
    # What is admitted must also run through on the rows.
    fine = set(rules.executable(v, [t for t in texts if found[t] == "ok"]))
    return spark.createDataFrame([(t, r if r != "ok" or t in fine else "fails") for t, r in found.items()], "text string, reason string")


@query("refine_rescore", f"{_VIEW}, {_MEASURED} SELECT text, support, round(confidence, 6) AS confidence, row_number() OVER (ORDER BY confidence DESC, support DESC, len(string_split(text, ' AND ')), text)::BIGINT AS rank FROM m WHERE support >= 1")
def _rescore(spark, sf_dir):
    """Proposals, some of them refused and one given twice, measured and ranked like mined rules."""
    v = view(spark, sf_dir)
    allowed = {c for c in v.columns if c not in ("entity", "y")}
    found = rules.revalidate(v, [*TEXTS, "y = 1", "nothing > 1", TEXTS[0]], allowed, tasks.PRESETS["review"])
    return found.select("text", "support", F.round("confidence", 6).alias("confidence"), "rank")


@query("raw_decision_features", f"{_VIEW} SELECT entity, (level <= 0.5)::BIGINT AS d0, (trend <= 2.0)::BIGINT AS d1, (trend <= 3.0)::BIGINT AS d2, (trend <= 1.5)::BIGINT AS d3 FROM view")
def _raw_decisions(spark, sf_dir):
    """Every inner node of the small trees as one bit, no paths."""
    nodes = spark.createDataFrame(TREES, "tree long, node long, left long, right long, feature long, threshold double, rows long, p double")
    texts = rules.split_texts(nodes, ["level", "trend"], 2)
    bits = view(spark, sf_dir).withColumn("r", rules.RuleSet(tuple(texts)).vector())
    return bits.select("entity", *[F.col("r")[i].cast("long").alias(f"d{i}") for i in range(len(texts))])


RULE = [("bought_180d", "<=", 6.0), ("since_last", ">", 20.0)]


@query("refine_prune", f"{_VIEW} " + " UNION ALL ".join(f"SELECT '{t}' AS text, count(*) FILTER ({t})::BIGINT AS support FROM view" for t in ("since_last > 20.0", "bought_180d <= 6.0")))
def _prune(spark, sf_dir):
    return rules.measure(view(spark, sf_dir), [rules.text_of(r) for r in rules.prune(RULE)]).select("text", "support")


@query("refine_tighten", f"{_VIEW} SELECT max(bought_180d)::DOUBLE AS upper, count(*)::BIGINT AS covered FROM view WHERE y = 1 AND bought_180d <= 6 AND since_last > 20")
def _tighten(spark, sf_dir):
    v = view(spark, sf_dir)
    tight = rules.tighten(v, RULE)
    kept = v.filter("y = 1").filter(rules.satisfied(rules.text_of(tight)))
    return kept.agg(F.lit(float(tight[0][2])).alias("upper"), F.count("*").alias("covered"))


@query("refine_combine", f"{_VIEW} SELECT count(*)::BIGINT AS support FROM view WHERE bought_180d <= 4 AND since_last > 20 AND span > 1000")
def _combine(spark, sf_dir):
    both = rules.combine(RULE, [("bought_180d", "<=", 4.0), ("span", ">", 1000.0)])
    return rules.measure(view(spark, sf_dir), [rules.text_of(both)]).select("support")


@query("refine_generalize", f"{_VIEW} SELECT count(*)::BIGINT AS support FROM view WHERE trend <= -1.2 AND level > 2.6")
def _generalize(spark, sf_dir):
    return rules.measure(view(spark, sf_dir), [rules.text_of(rules.generalize([("trend", "<=", -1.26), ("level", ">", 2.66)]))]).select("support")


_PRED = "SELECT c_custkey AS entity, (coalesce(CASE WHEN c_acctbal > 0 THEN c_acctbal END > 5000, false))::BIGINT AS r FROM customer"


@query("predicate_nulls", _PRED)
def _nulls(spark, sf_dir):
    c = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_custkey").alias("entity"), F.when(F.col("c_acctbal") > 0, F.col("c_acctbal")).alias("v"))
    return c.select("entity", rules.satisfied("v > 5000").cast("long").alias("r"))

import pytest
from pyspark.sql import functions as F

from relanom import detector, experiments, forest, nn, rules, tasks


class Seen(Exception):
    pass


@pytest.mark.parametrize("name", sorted(tasks.PRESETS))
def test_queries_mine_with_the_full_preset(spark, monkeypatch, name):
    asked = []

    def mine(view, features, preset, folder, refine):
        asked.append(preset)
        return rules.RuleSet(())

    def fit(train, features, preset, folder, seed=0, trees=None):
        asked.append(preset)
        assert trees == preset.first_trees
        raise Seen

    monkeypatch.setattr(rules, "mine", mine)
    monkeypatch.setattr(forest, "fit", fit)
    rows = spark.createDataFrame([(1, 0, "train", 0.5, [0.5])], "target long, y int, split string, a double, nb0 array<double>")
    arms = experiments.Arms(detector.Task(name, rows, ["a"], (nn.Relation(1, 1),)), "nowhere", name)
    arms.rules()
    with pytest.raises(Seen):
        arms._decisions()
    assert asked == [tasks.PRESETS[name]] * 2
    assert experiments.PUBLISHED.seeds == 10 and experiments.PUBLISHED.hidden == 128 and experiments.PUBLISHED.rate == 0.001 and experiments.PUBLISHED.prevalence == 0.015


def test_every_path_is_measured(spark, monkeypatch):
    found = [[("a", "<=", float(i))] for i in range(10_000)]
    got = []

    def measure(view, texts, conditions=None):
        got.extend(texts)
        assert len(conditions) == len(texts)
        raise Seen

    monkeypatch.setattr(forest, "fit", lambda *a, **b: None)
    for name, value in {"paths": None, "candidates": found}.items():
        monkeypatch.setattr(rules, name, lambda *a, value=value, **b: value)
    monkeypatch.setattr(rules, "measure", measure)
    with pytest.raises(Seen):
        rules.mine(spark.createDataFrame([(0, "train", 0.5)], "y int, split string, a double"), ["a"], tasks.PRESETS["purchase"], "nowhere")
    assert len(got) == 10_000


def test_conditions_and_texts_are_measured_alike(spark):
    rows = [(i % 3 == 0 if i % 7 else None, float(i % 11) if i % 5 else None, float("nan") if i % 13 == 0 else i % 4 - 1.5) for i in range(500)]
    view = spark.createDataFrame([(None if y is None else int(y), a, b) for y, a, b in rows], "y int, a double, b double").repartition(3)
    found = {rules.text_of(r): r for r in ([("a", "<=", float(i))] + ([("b", ">", float(j))] if j else []) for i in range(12) for j in range(-2, 3))}
    as_numbers, as_texts = (sorted(tuple(r) for r in rules.measure(view, list(found), c).collect()) for c in (found, None))
    assert as_numbers == as_texts and len(as_texts) == len(found)
    both = rules.measure(view, [*found, "a > b OR b IS NULL"], dict(list(found.items())[:9]))
    assert sorted(tuple(r) for r in both.collect())[: len(found)] == as_texts


def test_pruned_rules_that_lose_confidence_go_and_pairs_are_disjoined():
    rule = [("a", "<=", 1.0), ("b", ">", 2.0)]
    rows = [{"text": rules.text_of(rule), "confidence": 0.5}, {"text": "a <= 1.0", "confidence": 0.4}, {"text": "b > 2.0", "confidence": 0.5}, {"text": "c > 0.0", "confidence": 0.1}]
    assert [r["text"] for r in rules.without_losses(rows, [rule])] == [rules.text_of(rule), "b > 2.0", "c > 0.0"]
    proposed = rules.ScriptedProposer().propose(None, [rule, [("c", ">", 0.0)]])
    assert "(a <= 1.0 AND b > 2.0) OR (c > 0.0)" in proposed and "a <= 1.0 AND b > 2.0 AND c > 0.0" in proposed


def test_predicates_that_fail_on_rows_are_dropped(spark):
    view = spark.createDataFrame([(1, "12", 0.0), (0, "x", 1.0)], "y int, s string, a double")
    texts = ["a > 0", "cast(s AS int) > 1", "1 / a > 2", "s = 'x'"]
    assert rules.executable(view, texts) == ["a > 0", "s = 'x'"]
    assert rules.executable(view, []) == []


def test_ablations_cover_three_tasks():
    import __spark_entry__

    known = __spark_entry__.queries()
    for name in ("rq2_rules", "rq2_fusion", "rq3_edges", "rq4_refine", "ablate_rank"):
        assert sum(q == name or q in {f"{name}_{k}" for k in ("cyber", "review", "purchase")} for q in known) == 3


def test_prevalence_compares_rules_on_both_churn_tasks(spark, monkeypatch):
    ran = []

    def runs(self, methods):
        shares = [self.task.rows.filter(f"split = '{s}' and y = 1").count() / self.task.rows.filter(f"split = '{s}'").count() for s in ("train", "valid", "test")]
        ran.append((self.preset, shares))
        return [(self.task.name, m, "x", "test", 0, 0.5, 0.5, 0.5) for m in methods]

    monkeypatch.setattr(experiments.Arms, "runs", runs)
    got = experiments.prevalence(spark, "/root/testdata/sf0.01", "nowhere").collect()
    assert sorted((r.task, r.method) for r in got) == sorted((f"{k}@{p}", m) for k in ("review", "purchase") for p in (0.005, 0.015, 0.03) for m in ("detector_alpha0", "gnn_weighted"))
    for (_, (train, valid, test)), p in zip(ran, (0.005, 0.015, 0.03) * 2):
        assert 0 < train <= p + 0.001 and valid <= train + 0.001 and test > 0.1


def test_runs_measure_every_seed_and_ranks_follow(spark):
    from dataclasses import replace

    task = detector.document_task(spark, "/root/testdata/sf0.01")
    arms = experiments.Arms(task, "file:///tmp/relanom-arms-test", tasks.small(tasks.PRESETS["review"]), replace(experiments.PUBLISHED, hidden=8, rounds=1, steps=2, seeds=2, prevalence=None), tune_mlp=True)
    methods = ["detector_no_rules_bce", "gnn_weighted", "mlp", "deep_svdd_soft", "posthoc_fusion", "posthoc_logistic", "random", "isolation_forest"]
    got = arms.runs(methods)
    assert sorted((r[1], r[4]) for r in got) == sorted((m, s) for m in methods for s in range(2))
    table = spark.createDataFrame(got, experiments.RUNS)
    assert {r.method: r.seeds for r in experiments.summary(table).collect()} == dict.fromkeys(methods, 2)
    assert experiments.ranks(table).filter("metric = 'auprc'").selectExpr("sum(avg_rank)").first()[0] == len(methods) * (len(methods) + 1) / 2


def test_paths_are_measured_once_and_the_context_is_made_for_those_who_read_it(spark, monkeypatch):
    view = spark.range(400).selectExpr("id % 10 / 10D AS a", "id % 7 / 7D AS b", "if(id % 4 = 3, 'valid', 'train') AS split").selectExpr("*", "int(a > 0.55 AND b <= 0.5) AS y")
    preset = tasks.small(tasks.PRESETS["review"], 3, 3)
    asked, measure = [], rules.measure
    monkeypatch.setattr(rules, "measure", lambda rows, texts, conditions=None: asked.append(list(texts)) or measure(rows, texts, conditions))
    monkeypatch.setattr(rules, "guarded_context", lambda *a, **b: pytest.fail("nobody reads it"))
    got = rules.mine(view, ["a", "b"], preset, "file:///tmp/relanom-once-test")
    assert got.texts and len(asked) == 2 and not set(asked[0]) & set(asked[1])


def test_rules_reach_the_driver_as_texts_and_share_their_conditions(spark):
    step = lambda f, op, t: {"feature": f, "op": op, "threshold": t}
    rows = [(1, 4, 9, 0.9, [step(0, ">", 0.1), step(1, "<=", 2.0)]), (0, 3, 9, 0.9, [step(1, "<=", 2.0)]), (0, 5, 9, 0.9, [step(1, "<=", 3.0), step(1, "<=", 2.0)]), (0, 6, 9, 0.9, [step(0, "<=", 1.0), step(0, ">", 1.0)]), (0, 7, 1, 0.9, [step(0, "<=", 7.0)])]
    found = rules.candidates(spark.createDataFrame(rows, rules.PATHS), ["a", "b"], tasks.PRESETS["review"])
    assert found == [[("b", "<=", 2.0)], [("a", ">", 0.1), ("b", "<=", 2.0)]]
    assert found[0][0] is found[1][1]


def test_codes_of_neighbours_become_columns():
    import numpy as np
    import pyarrow as pa

    from relanom import trainer

    rows = pa.RecordBatch.from_pylist([{"x": [1.0], "y": 1, "nb0": [{"id": 1, "x": [0.5], "m": [2.0], "code": 2}, {"id": 2, "x": [0.1], "m": [3.0], "code": 0}]}, {"x": [2.0], "y": 0, "nb0": None}])
    got = trainer.batch_of(rows, nn.Spec(1, (nn.Relation(1, 4, hot=3),)))["relations"][0]
    assert np.array_equal(got["m"], [[2, 0, 0, 1], [3, 1, 0, 0]]) and got["seg"].tolist() == [0, 0]


def test_all_rule_variants_start_from_one_forest(spark, tmp_path, monkeypatch):
    from dataclasses import replace

    rows = spark.range(600).select(F.col("id").alias("target"), (F.col("id") % 7 == 0).cast("int").alias("y"), F.when(F.col("id") % 3 > 0, "train").otherwise("valid").alias("split"), (F.col("id") % 7).cast("double").alias("a"), F.rand(3).alias("b"))
    preset = replace(tasks.small(tasks.PRESETS["purchase"], 4, 3), leaf_rows=1)
    grown, fit = [], forest.fit
    monkeypatch.setattr(forest, "fit", lambda *a, **k: grown.append(1) or fit(*a, **k))
    monkeypatch.setattr(experiments, "stored", lambda df, name: df.cache())
    arms = experiments.Arms(detector.Task("t", rows, ["a", "b"], ()), f"file://{tmp_path}", preset, experiments.Settings(prevalence=None))
    found = {v: arms.rules(v).texts for v in ("raw", "path", "refined")}
    assert len(grown) == 1 and all(found.values())
    alone = rules.mine(arms.task.rows.select("y", "split", "a", "b"), ["a", "b"], preset, f"file://{tmp_path}/alone")
    assert found["refined"] == alone.texts


def test_tables_without_rules_train_while_rules_are_mined(spark, tmp_path, monkeypatch):
    import threading
    from dataclasses import replace

    rows = spark.range(600).select(F.col("id").alias("target"), (F.col("id") % 7 == 0).cast("int").alias("y"), F.element_at(F.array(F.lit("train"), F.lit("valid"), F.lit("test")), (F.col("id") % 3 + 1).cast("int")).alias("split"), (F.col("id") % 7).cast("double").alias("a"), F.rand(3).alias("b"))
    preset = replace(tasks.small(tasks.PRESETS["purchase"], 4, 3), leaf_rows=1)
    trained, fit, mine = threading.Event(), experiments.Arms._fit, experiments.mined
    monkeypatch.setattr(experiments.Arms, "_fit", lambda self, *a: trained.set() or fit(self, *a))
    monkeypatch.setattr(experiments, "mined", lambda *a: mine(*a) if trained.wait(60) else pytest.fail("mining came first"))
    monkeypatch.setattr(experiments, "stored", lambda df, name: df.cache())
    monkeypatch.setattr(experiments, "drop_stored", lambda *tables: None)
    arms = experiments.Arms(detector.Task("t", rows, ["a", "b"], ()), f"file://{tmp_path}", preset, experiments.Settings(hidden=4, rounds=1, steps=2, seeds=1, prevalence=None))
    got = arms.runs(["detector_path_rules", "detector_no_rules", "detector_alpha0"])
    assert sorted(r[1] for r in got) == ["detector_alpha0", "detector_no_rules", "detector_path_rules"]


def test_the_driver_hands_freed_native_memory_back(spark):
    from relanom import sources

    said = sources.trim(spark)
    assert said is None or "native heap" in said
    assert said or int(spark.sparkContext._jvm.System.getProperty("java.specification.version")) < 21


@pytest.mark.parametrize("prevalence", [0.005, 0.015, 0.3, 0.9, 0.0])
def test_rows_are_thinned_out_as_they_are_read(spark, monkeypatch, prevalence):
    from dataclasses import replace

    rows = spark.range(3000).select(F.col("id").alias("target"), F.when(F.col("id") % 11 > 0, (F.col("id") % 4 == 0).cast("int")).alias("y"), F.element_at(F.array(F.lit("train"), F.lit("valid"), F.lit("test")), (F.col("id") % 3 + 1).cast("int")).alias("split"))
    written = []
    monkeypatch.setattr(experiments, "stored", lambda df, name: written.append(name) or df.cache())
    arms = experiments.Arms(detector.Task("t", rows, [], ()), "nowhere", "review", replace(experiments.PUBLISHED, prevalence=prevalence))
    assert written == ["task"]
    got, expected = (sorted(map(tuple, df.collect()), key=str) for df in (arms.task.rows, experiments.at_prevalence(rows, prevalence)))
    assert got == expected


@pytest.mark.parametrize("kind", ["review", "purchase"])
def test_tasks_do_not_depend_on_the_order_of_rows(spark, monkeypatch, kind):
    """Features and neighbours to the last bit."""
    from datetime import datetime, timedelta

    log = [(i % 3, i % 50 + 1, datetime(2001, 1, 31) - timedelta(days=i * 37 % 900), (i * 7919 % 99991) / 100 * (1 - i % 11 / 100), float(i * 31 % 50 + 1), "R") for i in range(300)]

    def read(some):
        rows = spark.createDataFrame(some, "customer long, part long, t timestamp_ntz, price double, quantity double, flag string").coalesce(1)
        monkeypatch.setattr(tasks, "transactions", lambda spark, sf_dir: rows)
        labels = spark.createDataFrame([(0, 1), (1, 0), (2, 0)], "entity long, y int")
        return sorted(map(repr, detector.customer_task(spark, "/root/testdata/sf0.001", kind, labels).rows.collect()))

    assert read(log) == read(log[::-1])


def test_the_tasks_of_the_ranks_run_at_the_same_time(spark, monkeypatch):
    import threading

    from relanom.queries import experiment_queries

    met = threading.Barrier(3)

    def runs(spark, sf_dir, kind, methods):
        met.wait(60)
        return spark.createDataFrame([(kind, m, "none", "test", 0, float(i), 0.5, 0.5) for i, m in enumerate(methods)], experiments.RUNS)

    monkeypatch.setattr(experiment_queries, "runs", runs)
    found = {(r.method, r.metric): r.avg_rank for r in experiment_queries._ranks(spark, "nowhere").collect()}
    assert len(found) == 30 and found[experiment_queries.MAIN[-1], "auroc"] == 1 and found[experiment_queries.MAIN[0], "auroc"] == 10


def test_a_table_with_rules_is_the_first_to_be_made(spark, monkeypatch):
    import threading

    started, both = [], threading.Barrier(2)

    def table(self, variant):
        started.append(variant)
        if len(started) <= 2:
            both.wait(60)
        raise KeyError(variant)

    monkeypatch.setattr(experiments.Arms, "table", table)
    monkeypatch.setattr(experiments, "stored", lambda df, name: df)
    arms = experiments.Arms(detector.Task("t", spark.range(1), [], ()), "nowhere", "review", experiments.Settings(prevalence=None))
    with pytest.raises(KeyError):
        arms.scores(["ae", "detector_no_rules", "detector_alpha0"])
    assert set(started[:2]) == {"flat", "refined"}

"""Experiment workloads: methods on one task over several seeds, ablations, prevalence sweep; results are rows of measures."""

from __future__ import annotations

import threading
import uuid
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace
from functools import reduce
from math import floor

from pyspark import inheritable_thread_target
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from relanom import detector, fusion, isolation, labels, metrics, nn, rules, tasks, trainer
from relanom.draws import u
from relanom.sources import drop_stored, stored

MEASURES = ("auroc", "auprc", "p_at_k")
RUNS = "task string, method string, supervision string, split string, seed int, auroc double, auprc double, p_at_k double"


@dataclass(frozen=True)
class Settings:
    """How models are trained and over how many seeds results are taken; ``prevalence`` None leaves the training rows as they are.

    Rounds and steps are the least mini-batches a model sees: every round runs through all train rows.
    """

    hidden: int = 128
    rate: float = 0.001
    rounds: int = 8
    steps: int = 20
    seeds: int = 10
    prevalence: float | None = 0.015


#: The published protocol.
PUBLISHED = Settings()


def union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def measured(scores: DataFrame) -> list:
    """Rows (model, auroc, auprc, p_at_k) on the labelled test rows of (model, y, split, score)."""
    test = scores.filter("split = 'test' and y is not null").select("model", "y", "score").persist()
    found = metrics.ranking(test, ["model"]).collect()
    test.unpersist()
    return found


def result(task: str, method: str, supervision: str, scores: DataFrame) -> DataFrame:
    """Measures on the test split of (y, split, score)."""
    test = scores.filter("split = 'test' and y is not null").select("y", "score")
    m = metrics.ranking(test)
    return m.select(F.lit(task).alias("task"), F.lit(method).alias("method"), F.lit(supervision).alias("supervision"), F.lit("test").alias("split"), *(F.col(c).cast("double").alias(c) for c in MEASURES))


def mined(task: detector.Task, preset: str | tasks.Preset, folder: str, refine: bool = True, pool: rules.Pool | None = None) -> rules.RuleSet:
    return rules.mine(task.rows.select("y", "split", *task.features), task.features, setting(preset), folder, refine, **({"pool": pool} if pool else {}))


def setting(preset: str | tasks.Preset) -> tasks.Preset:
    """A task's full settings by name, or those that are given."""
    return tasks.PRESETS[preset] if isinstance(preset, str) else preset


def at_prevalence(rows: DataFrame, prevalence: float | None) -> DataFrame:
    """Training positives thinned out to the share, validation to what training then has, test rows as they are."""
    if prevalence is None:
        return rows
    train = labels.to_prevalence(rows.filter("split = 'train'"), prevalence, "target")
    valid = labels.match_prevalence(rows.filter("split = 'valid'"), train, "target")
    return train.unionByName(valid).unionByName(rows.filter("split = 'test'"))


def kept_at(rows: DataFrame, prevalence: float, parts: int = 4096) -> Column:
    """The condition that ``at_prevalence`` comes to on these rows: positives up to the last one, by draw, that it keeps.

    Positives are counted per part of the range of draws, and only the parts in which the counts are reached are ranked.
    """
    draw = u(F.col("target"), "prev")
    placed = rows.filter("split in ('train', 'valid') and y in (0, 1)").select("split", "target", draw.alias("draw"), F.when(F.col("y") == 1, F.floor(draw * parts)).otherwise(-1).alias("part"))
    found: dict[str, dict[int, int]] = {"train": {}, "valid": {}}
    for r in placed.groupBy("split", "part").count().collect():
        found[r["split"]][r["part"]] = r["count"]
    negatives = {s: n.pop(-1, 0) for s, n in found.items()}
    wanted = {"train": min(floor(prevalence * negatives["train"] / (1 - prevalence)), sum(found["train"].values()))}
    wanted["valid"] = min(int(negatives["valid"] * wanted["train"] / negatives["train"]) if negatives["train"] else 0, sum(found["valid"].values()))
    last = {}
    for s, n in found.items():
        before = 0
        for part in sorted(n):
            if before < wanted[s] <= before + n[part]:
                last[s] = part, wanted[s] - before
            before += n[part]
    either = lambda some: reduce(lambda a, b: a | b, some, F.lit(False))
    open_ = placed.filter(either((F.col("split") == s) & (F.col("part") == part) for s, (part, _) in last.items()))
    ranked = open_.withColumn("rank", F.row_number().over(Window.partitionBy("split").orderBy("draw", "target")))
    ends = ranked.filter(either((F.col("split") == s) & (F.col("rank") == rank) for s, (_, rank) in last.items())).collect() if last else []
    upto = [(F.col("split") == r["split"]) & (F.col("y") == 1) & ((draw < r["draw"]) | ((draw == r["draw"]) & (F.col("target") <= r["target"]))) for r in ends]
    return (F.col("split") == "test") | (F.col("split").isin("train", "valid") & (F.col("y") == 0)) | either(upto)


def _detector(alpha: float = 0.0, beta: float = 1.0) -> Callable[..., nn.Model]:
    return lambda spec, hidden, seed: nn.RelationalAutoencoder(spec, hidden, seed, alpha=alpha, beta=beta)


#: Trained methods: rules in the graph table ("flat" has none and no neighbours), supervision, model.
TRAINED: dict[str, tuple[str, str, Callable[..., nn.Model]]] = {
    "detector_alpha0": ("refined", "ranking", _detector()),
    "detector_bce": ("refined", "ranking", _detector(0.1)),
    "detector_bce_low": ("refined", "ranking", _detector(0.01)),
    "detector_bce_high": ("refined", "ranking", _detector(1.0)),
    "detector_no_rules": ("none", "ranking", _detector()),
    "detector_no_rules_bce": ("none", "ranking", _detector(0.1)),
    "detector_path_rules": ("path", "ranking", _detector()),
    "detector_path_rules_bce": ("path", "ranking", _detector(0.1)),
    "raw_decisions": ("raw", "ranking", _detector()),
    "raw_decisions_bce": ("raw", "ranking", _detector(0.1)),
    "detector_no_rank": ("refined", "unsupervised", _detector(beta=0.0)),
    "gnn_weighted": ("none", "labels", lambda spec, hidden, seed: nn.SupervisedGraph(spec, hidden, seed, weighted=True)),
    "gnn_unweighted": ("none", "labels", lambda spec, hidden, seed: nn.SupervisedGraph(spec, hidden, seed)),
    "ae": ("flat", "unsupervised", lambda spec, hidden, seed: nn.Autoencoder(spec, hidden, seed)),
    "ae_rank": ("flat", "ranking", lambda spec, hidden, seed: nn.Autoencoder(spec, hidden, seed, beta=1.0)),
    "deep_svdd": ("flat", "unsupervised", lambda spec, hidden, seed: nn.DeepSvdd(spec, hidden, seed)),
    "deep_svdd_soft": ("flat", "unsupervised", lambda spec, hidden, seed: nn.DeepSvdd(spec, hidden, seed, nu=0.1)),
    "drl": ("flat", "unsupervised", lambda spec, hidden, seed: nn.DecomposedRepresentation(spec, hidden, seed)),
    "mlp": ("flat", "labels", lambda spec, hidden, seed: nn.Mlp(spec, hidden, seed)),
}
#: Methods that take the scores of others or train nothing by gradient, with their supervision.
OTHERS = {"posthoc_fusion": "ranking", "posthoc_logistic": "labels", "isolation_forest": "unsupervised", "rule_score": "labels", "random": "none"}
#: Tables of a task that are made and learned from at once, and those of all tasks that run at the same time.
TABLES = 2
WORKING = threading.BoundedSemaphore(3)
#: (width, rate) that the supervised network is searched over where its settings are chosen on the validation split.
MLP_GRID = [(64, 0.001), (64, 0.003), (128, 0.001), (128, 0.003)]


class Arms:
    """The methods of the comparison on one task; each table is made once and all models that learn from it share its passes."""

    #: A forest keeps all cores busy: tasks that run at the same time mine one after the other.
    _mining = threading.Lock()

    def __init__(self, task: detector.Task, folder: str, preset: str | tasks.Preset, settings: Settings = PUBLISHED, tune_mlp: bool = False):
        self.task, self.folder, self.preset, self.settings, self.tune_mlp = task, folder, preset, settings, tune_mlp
        task.rows = stored(task.rows, "task")
        if settings.prevalence is not None:
            # The rows are thinned out as they are read: neighbours are not written twice.
            task.rows = task.rows.filter(kept_at(task.rows, settings.prevalence))
        self._rules: dict[str, rules.RuleSet] = {}
        #: Forest and measured paths, which all variants of the rules start from.
        self._pool: rules.Pool | None = None
        self._tables: dict[str, tuple[DataFrame, nn.Spec]] = {}
        self._scores: dict[str, DataFrame] = {}

    def rules(self, variant: str = "refined") -> rules.RuleSet | None:
        if variant in ("none", "flat"):
            return None
        with self._mining:
            if variant not in self._rules:
                made = self._decisions() if variant == "raw" else mined(self.task, self.preset, self._folder(), variant == "refined", self._pool)
                self._rules[variant], self._pool = made, self._pool or made.pool
            return self._rules[variant]

    def table(self, variant: str) -> tuple[DataFrame, nn.Spec]:
        if variant not in self._tables:
            rows, spec = detector.assembled(self.task, self.rules(variant), flat=variant == "flat")
            self._tables[variant] = stored(rows, f"table-{variant}"), spec
        return self._tables[variant]

    def _folder(self) -> str:
        return f"{self.folder}/forest-{uuid.uuid4().hex}"

    def _decisions(self) -> rules.RuleSet:
        """Single splits of the first trees as bits, instead of whole paths."""
        preset, features = setting(self.preset), self.task.features
        if not self._pool:
            view = self.task.rows.select("y", "split", *features).persist()
            self._pool = rules.pooled(view, features, preset, self._folder())
            view.unpersist()
        texts = rules.split_texts(self._pool.nodes, features, preset.first_trees, preset.max_rules)
        return rules.RuleSet(tuple(texts), (1.0,) * len(texts))

    def _fit(self, rows: DataFrame, models: dict[str, nn.Model], rates: dict[str, float] | None = None) -> dict[str, trainer.Fitted]:
        s = self.settings
        return trainer.fit_all(rows, models, s.rounds, s.steps, rate=s.rate, rates=rates)

    def _mlp(self) -> tuple[int, float]:
        """Width and rate of the supervised network: the defaults, or the best of the grid by validation AUPRC."""
        if not self.tune_mlp:
            return self.settings.hidden, self.settings.rate
        rows, spec = self.table("flat")
        grid = {str(i): nn.Mlp(spec, hidden, 0) for i, (hidden, _) in enumerate(MLP_GRID)}
        found = self._fit(rows, grid, {str(i): rate for i, (_, rate) in enumerate(MLP_GRID)})
        return MLP_GRID[int(max(found, key=lambda k: (found[k].auprc, -int(k))))]

    def scores(self, methods: list[str]) -> dict[str, DataFrame]:
        """(model, target, y, split, score) of validation and test rows by table of the trained methods, a model ``method#seed`` for every seed.

        ``TABLES`` tables are worked on at once: the models of one table are often fewer than the cores.  One that needs rules comes
        first, as it takes longest, and those without rules train while rules are mined; others with rules come last.
        """

        def of(variant: str) -> DataFrame:
            with WORKING:
                return scored(variant)

        def scored(variant: str) -> DataFrame:
            rows, spec = self.table(variant)
            models, rates = {}, {}
            for m in (m for m in methods if TRAINED[m][0] == variant):
                hidden, rate = self._mlp() if m == "mlp" else (self.settings.hidden, self.settings.rate)
                for seed in range(self.settings.seeds):
                    models[f"{m}#{seed}"], rates[f"{m}#{seed}"] = TRAINED[m][2](spec, hidden, seed), rate
            test = rows.filter("split <> 'train'")
            return trainer.score_all(test, self._fit(rows, models, rates)).cache()

        every = list(dict.fromkeys(TRAINED[m][0] for m in methods))
        ruled = [v for v in every if v not in ("none", "flat")]
        variants = ruled[:1] + [v for v in every if v not in ruled] + ruled[1:]
        with ThreadPoolExecutor(TABLES) as pool:
            made = [pool.submit(inheritable_thread_target(self.task.rows.sparkSession)(of), v) for v in variants]
            return {v: m.result() for v, m in zip(variants, made)}

    def _other(self, name: str) -> DataFrame:
        """(model, y, split, score) of a method that trains nothing by gradient, or builds on the detector without rules."""
        rows, seeds = self.task.rows, range(self.settings.seeds)
        named = lambda df, seed=0: df.select(F.lit(f"{name}#{seed}").alias("model"), "y", "split", "score")
        if name == "isolation_forest":
            flat = self.table("flat")[0]
            return union([named(isolation.score(flat, isolation.fit(flat.filter("split = 'train'"), 50, seed=seed)), seed) for seed in seeds])
        if name == "rule_score":
            return named(rows.withColumn("score", self.rules().score()))
        if name == "random":
            return union([named(rows.withColumn("score", u(F.col("target"), f"random{seed}")), seed) for seed in seeds])
        if "none" not in self._scores:
            self._scores = self._scores | self.scores(["detector_no_rules"])
        parts = []
        for seed in seeds:
            scored = rows.join(self._scores["none"].filter(F.col("model") == f"detector_no_rules#{seed}").select("target", "score"), "target")
            if name == "posthoc_fusion":
                parts.append(named(fusion.weighted_sum(scored, self.rules()), seed))
            else:
                parts.append(named(fusion.logistic(scored.filter("split = 'valid' and y is not null"), scored, self.rules()), seed))
        return union(parts)

    def runs(self, methods: list[str]) -> list[tuple]:
        """(task, method, supervision, split, seed, auroc, auprc, p_at_k) of every method and seed."""
        trained = [m for m in methods if m in TRAINED]
        if set(methods) & {"posthoc_fusion", "posthoc_logistic"} and "detector_no_rules" not in trained:
            trained.append("detector_no_rules")
        self._scores = self.scores(trained)
        every = [scores.select("model", "y", "split", "score") for scores in self._scores.values()] + [self._other(m) for m in methods if m in OTHERS]
        out = []
        for r in measured(union(every)) if every else []:
            method, seed = r["model"].split("#")
            if method in methods:
                supervision = TRAINED[method][1] if method in TRAINED else OTHERS[method]
                out.append((self.task.name, method, supervision, "test", int(seed), *(None if r[c] is None else float(r[c]) for c in MEASURES)))
        for scores in self._scores.values():
            scores.unpersist()
        drop_stored(*(rows for rows, _ in self._tables.values()))
        self._tables, self._scores = {}, {}
        return out


def summary(runs: DataFrame) -> DataFrame:
    """Mean and standard deviation over the seeds."""
    spread = [c for m in MEASURES for c in (F.avg(m).alias(m), F.stddev_samp(m).alias(f"{m}_std"))]
    return runs.groupBy("task", "method", "supervision", "split").agg(F.count("*").alias("seeds"), *spread)


def compare(task: detector.Task, folder: str, preset: str | tasks.Preset, methods: list[str], settings: Settings = PUBLISHED, tune_mlp: bool = False) -> DataFrame:
    arms = Arms(task, folder, preset, settings, tune_mlp)
    return summary(task.rows.sparkSession.createDataFrame(arms.runs(methods), RUNS))


def ranks(runs: DataFrame) -> DataFrame:
    """(method, metric, avg_rank): mid-ranks of the means over the seeds, averaged over the tasks."""
    means = runs.groupBy("task", "method").agg(*[F.avg(m).alias(m) for m in MEASURES])
    long = union([means.select(F.col("task").alias("dataset"), "method", F.lit(m).alias("metric"), F.col(m).alias("value")) for m in MEASURES])
    return metrics.average_rank(long)


def prevalence(spark, sf_dir: str, folder: str, kinds=("review", "purchase"), levels=(0.005, 0.015, 0.03), settings: Settings = PUBLISHED) -> DataFrame:
    """Detector with rules and supervised graph model on unexpected churn, with fewer positives in training and validation; nested samples."""
    out = []
    for kind in kinds:
        for p in levels:
            arms = Arms(detector.customer_task(spark, sf_dir, kind), folder, kind, replace(settings, prevalence=p))
            out += [(f"{kind}@{p}", *r[1:]) for r in arms.runs(["detector_alpha0", "gnn_weighted"])]
            drop_stored(arms.task.rows)
    return summary(spark.createDataFrame(out, RUNS))

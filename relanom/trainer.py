"""Data-parallel training on Spark: every task streams its rows in mini-batches, parameters are averaged, validation stops it.

Rows are (target, y, split, x, nb0.. nbK), each nb an array of structs (id, x, m).  The train rows
are dealt into shards in drawn order once and serve all rounds; a round is one pass of each task
over its shard.  All models that learn from one table, such as several seeds, share its passes;
where shards are fewer than cores the models are dealt too.  Only parameters and optimiser
moments travel: they are averaged model by model on the executors, and the driver gets one of each.
"""

from __future__ import annotations

import copy
import ctypes
import pickle
from dataclasses import dataclass
from itertools import chain

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relanom import nn
from relanom.draws import u
from relanom.sources import let_go

#: Rows of a task that are made into arrays at once, to train on and to score.
FRAME, SCORED = 2048, 512
#: Rows of a batch that Spark keeps between rounds.
KEPT = 128


def _matrix(lists: pa.ListArray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows of a list column as a matrix, zero where the list is null, and which are not null."""
    known = lists.is_valid().to_numpy(zero_copy_only=False)
    out = np.zeros((len(lists), width), nn.PRECISION)
    out[known] = lists.flatten().to_numpy(zero_copy_only=False).reshape(-1, width) if known.any() and width else 0
    return out, known


def batch_of(rows: pa.RecordBatch, spec: nn.Spec) -> dict:
    """Arrays of a batch of rows, taken from the Arrow buffers without going through objects."""
    relations = []
    for k, r in enumerate(spec.relations):
        lists = rows.column(f"nb{k}")
        sizes = pc.fill_null(lists.value_lengths(), 0).to_numpy(zero_copy_only=False)
        near = lists.flatten()
        x, _ = _matrix(near.field("x"), r.x)
        m, has = _matrix(near.field("m"), r.m - r.hot)
        if r.hot:
            m = np.hstack([m, np.eye(r.hot, dtype=nn.PRECISION)[near.field("code").to_numpy(zero_copy_only=False)]])
        relations.append({"seg": np.repeat(np.arange(rows.num_rows), sizes), "id": near.field("id").to_numpy(zero_copy_only=False).astype(np.int64), "x": x, "m": m, "has": has.astype(nn.PRECISION)})
    y = rows.column("y").to_numpy(zero_copy_only=False).astype(float)
    return {"x": _matrix(rows.column("x"), spec.x)[0], "y": y, "relations": relations}


def _batches(parts, spec: nn.Spec, size: int = FRAME):
    """Batches of at most ``size`` rows with their arrays."""
    for batch in parts:
        for at in range(0, batch.num_rows, size):
            some = batch.slice(at, size)
            yield some, batch_of(some, spec)


def _release() -> None:
    """Hand freed memory back: a worker that waits for its next task holds it else beside the one that works."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


@dataclass
class Fitted:
    model: nn.Model
    rounds: int
    auprc: float

    def transform(self, rows: DataFrame) -> DataFrame:
        """(target, y, split, score): map-side, the parameters broadcast."""
        return score_all(rows, {"": self}).drop("model")

    def embed(self, rows: DataFrame) -> DataFrame:
        """(target, split, z) of a graph model: embeddings of the targets as an array, for whatever comes after."""
        held = rows.sparkSession.sparkContext.broadcast(pickle.dumps(self.model))

        def run(parts):
            model = pickle.loads(held.value)
            p = model.vars()
            for some, batch in _batches(parts, model.spec, SCORED):
                z = pa.array(list(model.embed(p, batch).astype(float)), pa.list_(pa.float64()))
                yield pa.RecordBatch.from_arrays([some.column("target"), some.column("split"), z], names=["target", "split", "z"])

        return rows.mapInArrow(run, "target long, split string, z array<double>")


def score_all(rows: DataFrame, fitted: dict[str, Fitted]) -> DataFrame:
    """(model, target, y, split, score) of all models on one table, in one pass over it."""
    held = rows.sparkSession.sparkContext.broadcast(pickle.dumps({k: f.model for k, f in fitted.items()}))

    def run(parts):
        models = pickle.loads(held.value)
        params = {k: m.vars() for k, m in models.items()}
        for some, batch in _batches(parts, next(iter(models.values())).spec, SCORED):
            for k, model in models.items():
                score = model.score(params[k], batch).astype(float)
                yield pa.RecordBatch.from_arrays([pa.array([k] * len(score)), *(some.column(c) for c in ("target", "y", "split")), pa.array(score)], names=["model", "target", "y", "split", "score"])
        _release()

    return rows.mapInArrow(run, "model string, target long, y int, split string, score double")


def validation_auprc(valid: DataFrame, fitted: dict[str, Fitted]) -> dict[str, float]:
    """AUPRC of every model for early stopping: tasks count labels per score, cut to 11 binary places; one task a model adds up.

    Scores that agree so far count as ties; there are at most 2^20 counts a model, however many rows, and the driver gets its measure only.
    """
    held = valid.sparkSession.sparkContext.broadcast(pickle.dumps({k: f.model for k, f in fitted.items()}))

    def run(parts):
        models, counts = pickle.loads(held.value), {}
        params = {k: m.vars() for k, m in models.items()}
        for _, batch in _batches(parts, next(iter(models.values())).spec, SCORED):
            for k, model in models.items():
                bits = np.nan_to_num(model.score(params[k], batch).astype(np.float32)).view(np.int32).astype(np.int64)
                place = np.where(bits >= 0, bits, -(bits & 0x7FFFFFFF)) >> 12
                for y in (0, 1):
                    for p, n in zip(*(x.tolist() for x in np.unique(place[batch["y"] == y], return_counts=True))):
                        counts.setdefault((k, p), [0, 0])[y] += n
        rows = [(k, p, neg, pos) for (k, p), (neg, pos) in counts.items()]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [()] * 4, (pa.string(), pa.int64(), pa.int64(), pa.int64()))], names=["model", "place", "neg", "pos"])
        _release()

    def precision(pdf):
        _, neg, pos = pdf.groupby("place")[["neg", "pos"]].sum().sort_index(ascending=False).reset_index().to_numpy(float).T
        hits, all_ = np.cumsum(pos), np.cumsum(pos + neg)
        return pd.DataFrame({"model": [pdf["model"].iloc[0]], "auprc": [float((pos * hits / all_).sum() / hits[-1]) if hits[-1] else 0.0]})

    counted = valid.mapInArrow(run, "model string, place long, neg long, pos long").groupBy("model", "place").agg(F.sum("neg").alias("neg"), F.sum("pos").alias("pos"))
    out = {r["model"]: r["auprc"] for r in counted.groupBy("model").applyInPandas(precision, "model string, auprc double").collect()}
    held.destroy()
    return out


def shards_for(rows: int, steps: int, size: int, cores: int) -> int:
    """One for what about ``steps`` mini-batches take, at most one a core: larger shards are streamed, not held."""
    return max(1, min(cores, -(-rows // (steps * size))))


def _mean(parts: list[tuple[int, tuple]]) -> tuple:
    """Parameters and optimiser state of a model, averaged by rows."""
    total = sum(n for n, _ in parts) or 1
    mix = lambda pick: {name: sum((n / total) * pick(s)[name] for n, s in parts if name in pick(s)) for name in pick(parts[0][1])}
    return mix(lambda s: s[0]), (max(s[1][0] for _, s in parts), mix(lambda s: s[1][1]), mix(lambda s: s[1][2]))


ROUND = "model string, group int, shard int, n long, found binary"


def _merged(pdf: pd.DataFrame) -> pd.DataFrame:
    """One row of ``ROUND`` for those of a model."""
    parts = sorted(zip(pdf["n"].tolist(), pdf["shard"].tolist(), pdf["found"]), key=lambda x: x[:2])
    found = pickle.dumps(_mean([(n, pickle.loads(f)) for n, _, f in parts]))
    return pd.DataFrame({"model": [pdf["model"].iloc[0]], "group": [pdf["group"].iloc[0]], "shard": [int(pdf["shard"].min())], "n": [int(pdf["n"].sum())], "found": [found]})


def _round(dealt: DataFrame, models: dict[str, nn.Model], states: dict[str, tuple], copies: int, groups: int, steps: int, size: int, rates: dict[str, float], seed: int) -> dict[str, tuple]:
    """New parameters and optimiser states after one pass over all shards."""
    held = dealt.sparkSession.sparkContext.broadcast(pickle.dumps((models, states)))

    def run(parts):
        first = next((b for b in parts if b.num_rows), None)
        if first is None:
            return
        shard, copy = divmod(first.column("part")[0].as_py(), copies)
        every, known = pickle.loads(held.value)
        own = {k: m for i, (k, m) in enumerate(sorted(every.items())) if i % copies == copy}
        if own:
            stream = (b for _, b in _batches(chain([first], parts), next(iter(own.values())).spec))
            n, found = nn.train_steps(own, known, stream, steps, size, rates, seed * 1_000_003 + shard)
            for k in sorted(found):
                yield pa.RecordBatch.from_arrays([pa.array([k]), *(pa.array([v], pa.int32()) for v in (shard % groups, shard)), pa.array([n]), pa.array([pickle.dumps(found.pop(k))], pa.binary())], names=["model", "group", "shard", "n", "found"])
        _release()

    made = dealt.mapInArrow(run, ROUND)
    if groups > 1:
        made = made.groupBy("model", "group").applyInPandas(_merged, ROUND)
    out = {r["model"]: pickle.loads(r["found"]) for r in made.groupBy("model").applyInPandas(_merged, ROUND).select("model", "found").collect()}
    held.destroy()
    let_go(dealt.sparkSession)
    _release()
    return out


def deal(train: DataFrame, shards: int, copies: int) -> DataFrame:
    """The rows in ``shards`` x ``copies`` partitions, each in drawn order and numbered by ``part``; kept for all rounds."""
    # Java's serializer holds on to a hundred batches that it writes to disk: of Spark's 4 MB each they would fill an executor's heap.
    train.sparkSession.conf.set("spark.sql.inMemoryColumnarStorage.batchSize", KEPT)
    shard = F.floor(u(F.col("target"), "shard") * shards)
    each = train.withColumn("part", F.explode(F.transform(F.sequence(F.lit(0), F.lit(copies - 1)), lambda c: (shard * copies + c).cast("int"))))
    return each.repartitionById(shards * copies, F.col("part")).sortWithinPartitions(u(F.col("target"), "order"), "target").persist()


def _centre(dealt: DataFrame, models: dict[str, nn.DeepSvdd], copies: int) -> None:
    """The centres of the models: means of the first embeddings of all train rows, summed up by shard."""
    if not models:
        return
    held = dealt.sparkSession.sparkContext.broadcast(pickle.dumps(models))

    def run(parts):
        every, sums, n, shard = pickle.loads(held.value), {}, 0, 0
        params = {k: m.vars() for k, m in every.items()}
        for some, batch in _batches(parts, next(iter(every.values())).spec):
            part, n = some.column("part")[0].as_py(), n + some.num_rows
            if part % copies:
                return
            shard = part // copies
            for k, m in every.items():
                sums[k] = sums.get(k, 0) + m.embedded(params[k], batch).value.sum(axis=0, dtype=float)
        for k, s in sums.items():
            yield pa.RecordBatch.from_arrays([pa.array([k]), pa.array([shard], pa.int32()), pa.array([n]), pa.array([s.tolist()], pa.list_(pa.float64()))], names=["model", "shard", "n", "total"])
        _release()

    found = dealt.mapInArrow(run, "model string, shard int, n long, total array<double>").collect()
    held.destroy()
    for k, m in models.items():
        own = sorted((r for r in found if r["model"] == k), key=lambda r: r["shard"])
        if not own:
            raise ValueError("no train rows to take a centre from")
        m.centre_at(sum(np.array(r["total"]) for r in own) / sum(r["n"] for r in own))


def fit_all(rows: DataFrame, models: dict[str, nn.Model], rounds: int = 4, steps: int = 30, size: int = 512, rate: float = 0.001, patience: int = 5, seed: int = 0, rates: dict[str, float] | None = None) -> dict[str, Fitted]:
    """Train all models on split 'train'; each keeps the parameters of its best validation AUPRC and stops after ``patience`` worse rounds.

    Every round runs through all train rows in at least ``steps`` mini-batches a shard.
    """
    train, valid = rows.filter("split = 'train'"), rows.filter("split = 'valid' and y is not null")
    cores = train.sparkSession.sparkContext.defaultParallelism
    valid = valid.repartition(min(4 * cores, 1 + valid.count() // 256)).persist()
    shards = shards_for(train.count(), steps, size, cores)
    copies = max(1, min(len(models), cores // shards))
    rates = {k: (rates or {}).get(k, rate) for k in models}
    dealt, states = deal(train, shards, copies), {}
    _centre(dealt, {k: m for k, m in models.items() if isinstance(m, nn.DeepSvdd) and m.centre is None}, copies)
    # A round gives a model new arrays and changes none in place.
    best = {k: Fitted(copy.copy(m), 0, -1.0) for k, m in models.items()}
    open_, stale = dict(models), dict.fromkeys(models, 0)
    for r in range(1, rounds + 1):
        found = _round(dealt, open_, {k: s for k, s in states.items() if k in open_}, copies, max(1, int(shards**0.5)) if shards > 16 else 1, steps, size, rates, seed * 1000 + r)
        if not found:
            break
        for k, (params, state) in found.items():
            open_[k].params, states[k] = params, state
        now = {k: Fitted(copy.copy(m), r, 0.0) for k, m in open_.items()}
        measured = validation_auprc(valid, now)
        for k, f in now.items():
            f.auprc = measured.get(k, 0.0)
            if f.auprc > best[k].auprc:
                best[k], stale[k] = f, 0
            else:
                stale[k] += 1
        open_ = {k: m for k, m in open_.items() if stale[k] < patience}
        if not open_:
            break
    dealt.unpersist()
    valid.unpersist()
    return best


def fit(rows: DataFrame, model: nn.Model, rounds: int = 4, steps: int = 30, size: int = 512, rate: float = 0.001, patience: int = 5, seed: int = 0) -> Fitted:
    """One model by ``fit_all``."""
    return fit_all(rows, {"": model}, rounds, steps, size, rate, patience, seed)[""]


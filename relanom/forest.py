"""Random forest with balanced class weights, one tree a task over the broadcast training rows.

A value takes one byte: features are cut at quantiles into at most ``BINS`` bins.  All labelled rows are used unless
a ``cap`` is given; then about so many are, all positives first.  Trees are independent and seeded by their number, so the first trees of
a forest are the same however many follow.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relanom.splits import drawn_cap
from relanom.tasks import Preset

BINS = 64
#: Nodes whose histograms are held at once.
NODES = 2048
#: Columns whose values the driver holds at once to cut them.
COLUMNS = 4
NODE_TABLE = "tree long, node long, left long, right long, feature long, threshold double, rows long, p double"


@dataclass
class Sample:
    """bins[row, feature]; a row is in bin b of a feature if its value is at most edges[feature][b] and above the edge before."""

    bins: np.ndarray
    edges: list[np.ndarray]
    y: np.ndarray
    weight: np.ndarray


def _edges(x: np.ndarray) -> np.ndarray:
    values = np.unique(x)
    middle = (values[1:] + values[:-1]) / 2
    return middle if len(middle) < BINS else np.unique(np.quantile(x, np.arange(1, BINS) / BINS))


def sample_of(train: DataFrame, features: list[str], cap: int | None = None) -> Sample:
    """The training rows, capped if asked for; nulls are -1, and rules are measured anew on the nulls themselves."""
    rows = train.select("y", *features).filter("y in (0, 1)")
    if cap is not None:
        rows = drawn_cap(rows, cap, F.xxhash64("y", *features))
    names = [f"x{i}" for i in range(len(features))]
    rows = rows.select(F.col("y").cast("double").alias("y"), *[F.coalesce(F.col(f).cast("double"), F.lit(-1.0)).alias(x) for f, x in zip(features, names)]).persist()
    edges = []
    for a in range(0, len(names), COLUMNS):
        some = rows.select(*names[a : a + COLUMNS]).toArrow()
        edges += [_edges(some.column(x).to_numpy()) for x in some.column_names]
        del some

    def binned(batches):
        for batch in batches:
            row = np.zeros((batch.num_rows, 1 + len(names)), np.uint8)
            row[:, 0] = batch.column("y").to_numpy(zero_copy_only=False) == 1
            for i, x in enumerate(names):
                row[:, 1 + i] = np.searchsorted(edges[i], batch.column(x).to_numpy(zero_copy_only=False), side="left")
            yield pa.RecordBatch.from_arrays([pa.array([r.tobytes() for r in row], pa.binary())], names=["row"])

    wide = 1 + len(names)
    raw = rows.mapInArrow(binned, "row binary").toArrow().column("row").cast(pa.binary(wide))
    rows.unpersist()
    found = np.concatenate([np.empty(0, np.uint8), *(np.frombuffer(c.buffers()[1], np.uint8)[c.offset * wide :][: len(c) * wide] for c in raw.chunks if len(c))])
    del raw
    # In an order of its own, whatever order the rows came in; rows that sort alike are alike.
    found.view(f"S{wide}").sort()
    found = found.reshape(-1, wide)
    bins, y = found[:, 1:].copy(), found[:, 0] == 1
    both = np.array([(~y).sum(), y.sum()])
    weight = np.where(y, len(y) / (2 * max(1, both[1])), len(y) / (2 * max(1, both[0])))
    return Sample(bins, edges, y, weight)


def grow(sample: Sample, tree: int, preset: Preset, seed: int = 0) -> list[tuple]:
    """Nodes of one tree over a bootstrap sample, level by level."""
    rng = np.random.default_rng([seed, tree])
    n, width = sample.bins.shape
    if not n or not width:
        return []
    times = np.bincount(rng.integers(0, n, n), minlength=n)
    rows = np.flatnonzero(times)
    count, weight = times[rows].astype(float), times[rows] * sample.weight[rows]
    hit = np.where(sample.y[rows], weight, 0.0)
    at, out, first, level, tried = np.zeros(len(rows), np.int64), [], 0, 1, max(1, int(width**0.5))
    for depth in range(preset.max_depth + 1):
        size, total, hits = (np.bincount(at, v, level) for v in (count, weight, hit))
        split = np.zeros(level, bool)
        feature, cut = np.zeros(level, np.int64), np.zeros(level, np.int64)
        if depth < preset.max_depth:
            open_ = np.flatnonzero((hits > 0) & (hits < total) & (size >= 2 * preset.min_leaf))
            place = np.full(level, -1)
            place[open_] = np.arange(len(open_))
            for a in range(0, len(open_), NODES):
                some = open_[a : a + NODES]
                inside = np.flatnonzero((place[at] >= a) & (place[at] < a + NODES))
                found, f, b = _best(sample, rows[inside], place[at[inside]] - a, count[inside], weight[inside], hit[inside], size[some], total[some], hits[some], preset.min_leaf, tried, rng)
                split[some], feature[some], cut[some] = found, f, b
        child = np.full(level, -1)
        child[split] = first + level + 2 * np.arange(split.sum())
        for k in range(level):
            inner = bool(split[k])
            out.append((tree, first + k, int(child[k]) if inner else -1, int(child[k]) + 1 if inner else -1, int(feature[k]) if inner else -1, float(sample.edges[feature[k]][cut[k]]) if inner else 0.0, int(size[k]), float(hits[k] / total[k])))
        if not split.any():
            break
        stay = split[at]
        rows, at, count, weight, hit = rows[stay], at[stay], count[stay], weight[stay], hit[stay]
        right = sample.bins[rows, feature[at]] > cut[at]
        first, level, at = first + level, 2 * int(split.sum()), child[at] - first - level + right
    return out


def _best(sample, rows, at, count, weight, hit, size, total, hits, min_leaf, tried, rng):
    """Per node whether a split lowers the Gini impurity, and the best feature and bin among ``tried`` features drawn for it."""
    nodes = len(size)
    drawn = rng.random((nodes, sample.bins.shape[1])).argsort(axis=1)[:, :tried]
    base = (hits**2 + (total - hits) ** 2) / total
    best, feature, cut = np.full(nodes, 1e-9), np.zeros(nodes, np.int64), np.zeros(nodes, np.int64)
    for k in range(drawn.shape[1]):
        key = at * BINS + sample.bins[rows, drawn[at, k]]
        c, t, h = (np.bincount(key, v, nodes * BINS).reshape(nodes, BINS).cumsum(axis=1)[:, :-1] for v in (count, weight, hit))
        rest, rest_hits = total[:, None] - t, hits[:, None] - h
        with np.errstate(divide="ignore", invalid="ignore"):
            gain = (h**2 + (t - h) ** 2) / t + (rest_hits**2 + (rest - rest_hits) ** 2) / rest - base[:, None]
        gain[~((c >= min_leaf) & (size[:, None] - c >= min_leaf))] = -1.0
        b = gain.argmax(axis=1)
        better = gain[np.arange(nodes), b] > best
        best[better], feature[better], cut[better] = gain[np.arange(nodes), b][better], drawn[better, k], b[better]
    return best > 1e-9, feature, cut


def fit(train: DataFrame, features: list[str], preset: Preset, folder: str, seed: int = 0, trees: int | None = None) -> DataFrame:
    """Node table of the forest, written under ``folder`` and read back."""
    spark, trees = train.sparkSession, preset.trees if trees is None else trees
    held = spark.sparkContext.broadcast(sample_of(train, features, preset.train_cap))
    names = [c.split()[0] for c in NODE_TABLE.split(", ")]

    def build(parts):
        for pdf in parts:
            for tree in pdf["id"]:
                yield pd.DataFrame(grow(held.value, int(tree), preset, seed), columns=names)

    tasks = max(1, min(trees, 4 * spark.sparkContext.defaultParallelism))
    spark.range(0, trees, 1, tasks).mapInPandas(build, NODE_TABLE).write.mode("overwrite").parquet(folder)
    held.unpersist()
    return spark.read.schema(NODE_TABLE).parquet(folder)

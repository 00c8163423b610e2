"""Isolation forest: seeded subsamples, one task per tree; trees are rows, scores come from a broadcast forest."""

from __future__ import annotations

from math import ceil, log, log2

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from relanom.draws import u

EULER = 0.5772156649
SCHEMA = "tree long, node long, left long, right long, feature long, threshold double, size long"


def c(n: float) -> float:
    """Mean path length of an unsuccessful search among n."""
    return 2 * (log(n - 1) + EULER) - 2 * (n - 1) / n if n > 2 else float(n == 2)


def grow(x: np.ndarray, tree: int, rng: np.random.Generator) -> list[tuple]:
    limit, rows = ceil(log2(max(2, len(x)))), []

    def split(part: np.ndarray, depth: int) -> int:
        me = len(rows)
        rows.append(None)
        low, high = (part.min(axis=0), part.max(axis=0)) if len(part) else (np.zeros(x.shape[1]),) * 2
        wide = np.flatnonzero(high > low)
        if depth >= limit or len(part) <= 1 or not len(wide):
            rows[me] = (tree, me, -1, -1, -1, 0.0, len(part))
            return me
        f = int(rng.choice(wide))
        at = float(rng.uniform(low[f], high[f]))
        left = split(part[part[:, f] <= at], depth + 1)
        rows[me] = (tree, me, left, split(part[part[:, f] > at], depth + 1), f, at, len(part))
        return me

    split(x, 0)
    return rows


def fit(rows: DataFrame, trees: int = 100, sample: int = 256, seed: int = 0) -> DataFrame:
    """Forest of rows (target, x) as a node table; each row joins a tree by draw, so samples need no sort."""
    n = max(1, rows.count())
    share = min(1.0, 1.5 * sample / n)
    each = rows.select("target", "x", F.explode(F.sequence(F.lit(0), F.lit(trees - 1))).alias("tree")).filter(u(F.concat_ws("/", "target", "tree"), f"if{seed}") < share)

    def build(key, pdf):
        rng = np.random.default_rng([seed, int(key[0])])
        x = np.array(pdf.sort_values("target")["x"].tolist(), float)
        x = x[rng.permutation(len(x))[:sample]]
        return pd.DataFrame(grow(x, int(key[0]), rng), columns=[c.split()[0] for c in SCHEMA.split(", ")])

    return each.groupBy("tree").applyInPandas(build, SCHEMA)


def score(rows: DataFrame, forest: DataFrame, sample: int = 256) -> DataFrame:
    """rows with score 2^(-mean path / c(sample)); the forest is at most trees x 2 x sample nodes."""
    nodes = forest.toPandas()
    held = rows.sparkSession.sparkContext.broadcast({t: g.set_index("node").sort_index() for t, g in nodes.groupby("tree")})
    own = rows.schema

    def run(parts):
        trees = [tuple(g[k].to_numpy() for k in ("left", "right", "feature", "threshold", "size")) for g in held.value.values()]
        for pdf in parts:
            x = np.array(pdf["x"].tolist(), float)
            total = np.zeros(len(x))
            for left, right, feature, threshold, size in trees:
                at, depth = np.zeros(len(x), int), np.zeros(len(x))
                while True:
                    inner = left[at] >= 0
                    if not inner.any():
                        break
                    i = np.flatnonzero(inner)
                    go = x[i, feature[at[i]]] <= threshold[at[i]]
                    at[i] = np.where(go, left[at[i]], right[at[i]])
                    depth[i] += 1
                total += depth + np.array([c(s) for s in size])[at]
            yield pdf.assign(score=2.0 ** (-total / max(1, len(trees)) / c(sample)))

    return rows.mapInPandas(run, StructType([*own.fields, StructField("score", DoubleType())]))

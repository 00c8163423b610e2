"""Near-duplicate vectors by collision counting on one-dimensional projections.

Vectors of equal components are one node.  A table deals the nodes into cells by the signs
of a few random projections, as many as keep cells at about ``CELL`` nodes; tables are as many
as a pair at the threshold needs to share a cell with probability 1 - ``MISS``.  Inside a cell
the nodes are sorted by each of ``PROJECTIONS`` further random projections, every node opens a
window of one threshold distance to both sides on each, and a pair's collisions are counted.
Pairs with as many as a pair at the threshold reaches with probability 1 - ``MISS`` are
verified by their cosine in double precision.

A pair counts in the first table whose cell it shares, so links are counted once without
listing them: a cell returns per node its number of links and one edge of a spanning forest.
Cells of more than ``BLOCK`` nodes are compared block against block in separate tasks.

Vectors that are null, empty, zero or hold null or non-finite components link with nothing;
vectors of different length do not link.  Repeated rows link with each other.  A row without a
vec_id links like any other; a component is named by its least vec_id, null if it has none.
"""

from __future__ import annotations

from math import acos, ceil, comb, erf, log, log2, pi, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relanom.llm import components, kernels, scratch

CELL = 256
BLOCK = 1024
PROJECTIONS = 24
MISS = 1e-3
SEED = 20_11
_FOUND = "h long, g long, links long, root_h long, root_g long"


def plan_tables(nodes: int, cosine: float) -> tuple[int, int]:
    """(bits of a cell, number of tables)."""
    bits = max(0, ceil(log2(max(nodes, 1) / CELL)))
    if not bits:
        return 0, 1
    together = (1 - acos(cosine) / pi) ** bits
    return bits, ceil(log(MISS) / log(1 - together))


def least_count(cosine: float) -> tuple[float, int]:
    """Half-width of the windows and the collisions that a pair at the threshold all but surely reaches."""
    distance = sqrt(2 - 2 * cosine)
    p, total = erf(1 / sqrt(2)), 0.0
    for count in range(PROJECTIONS + 1):
        total += comb(PROJECTIONS, count) * p**count * (1 - p) ** (PROJECTIONS - count)
        if total > MISS / 10:
            return distance, count
    return distance, PROJECTIONS


def directions(dim: int, count: int, seed: int) -> np.ndarray:
    return np.random.default_rng([SEED, dim, seed]).standard_normal((dim, count))


def collisions(projected: np.ndarray, width: float) -> np.ndarray:
    """[i, j] number of projections on which j lies in the window around i."""
    n = len(projected)
    counts = np.zeros((n, n), np.uint8)
    for p in projected.T:
        order = np.argsort(p, kind="stable")
        rank = np.empty(n, np.int32)
        rank[order] = np.arange(n, dtype=np.int32)
        low = np.searchsorted(p[order], p - width, side="left").astype(np.int32)
        high = np.searchsorted(p[order], p + width, side="right").astype(np.int32)
        counts += (rank[None, :] >= low[:, None]) & (rank[None, :] < high[:, None])
    return counts


def cell_links(unit: np.ndarray, earlier: np.ndarray, side: np.ndarray | None, cosine: float) -> tuple[np.ndarray, np.ndarray]:
    """Linked pairs (i, j), i < j, of a cell that share no cell of the ``earlier`` tables; with ``side``, pairs across sides only."""
    width, least = least_count(cosine)
    counts = collisions(unit @ directions(unit.shape[1], PROJECTIONS, 1), width)
    i, j = np.nonzero(np.triu(counts >= least, 1))
    if side is not None:
        across = side[i] != side[j]
        i, j = i[across], j[across]
    if not len(i):
        return i, j
    good = np.concatenate([np.einsum("ij,ij->i", unit[i[a : a + 65536]], unit[j[a : a + 65536]]) >= cosine for a in range(0, len(i), 65536)])
    i, j = i[good], j[good]
    new = ~(earlier[i] == earlier[j]).any(axis=1)
    return i[new], j[new]


def forest(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Root of each of n nodes under the edges."""
    root = list(range(n))

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for a, b in zip(i.tolist(), j.tolist()):
        a, b = find(a), find(b)
        if a != b:
            root[max(a, b)] = min(a, b)
    return np.array([find(x) for x in range(n)])


def cells(raw: np.ndarray, bits: int, tables: int, upto: int) -> np.ndarray:
    """[vector, table] cells of the first ``upto`` tables: the signs of ``bits`` projections each."""
    signs = (raw @ directions(raw.shape[1], max(1, bits * tables), 0)) > 0
    codes = np.zeros((len(raw), upto), np.int64)
    for b in range(bits):
        codes = codes << 1 | signs[:, b * tables : b * tables + upto]
    return codes


def _dealt(nodes: DataFrame, bits: int, tables: int) -> DataFrame:
    """(tab, dim, cell, h, g, n, vector) of every node in every table."""
    schema = pa.schema([("tab", pa.int32()), ("dim", pa.int32()), ("cell", pa.int64()), ("h", pa.int64()), ("g", pa.int64()), ("n", pa.int64()), ("vector", pa.binary())])

    def run(batches):
        for batch in batches:
            sizes = np.array(batch.column("vector").value_lengths())
            for dim in np.unique(sizes).tolist():
                part = batch.filter(pa.array(sizes == dim))
                raw = np.asarray(part.column("vector").flatten(), np.float64).reshape(-1, dim)
                codes = cells(raw, bits, tables, tables)
                plain = pa.array([x.tobytes() for x in raw], pa.binary())
                for t in range(tables):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(raw), t, np.int32)), pa.array(np.full(len(raw), dim, np.int32)), pa.array(codes[:, t]), part.column("h"), part.column("g"), part.column("n"), plain], schema=schema)

    return nodes.select("h", "g", "n", "vector").mapInArrow(run, "tab int, dim int, cell long, h long, g long, n long, vector binary")


class _Cell:
    """The rows of one task key, gathered over batches."""

    def __init__(self, key: tuple):
        self.key, self.parts = key, []

    def add(self, columns: dict[str, np.ndarray], vectors: np.ndarray, a: int, b: int) -> None:
        self.parts.append(({c: v[a:b] for c, v in columns.items()}, vectors))

    def found(self, bits: int, tables: int, cosine: float) -> pa.RecordBatch | None:
        table, dim, _, first, second = self.key
        of = lambda c: np.concatenate([p[0][c] for p in self.parts])
        raw = np.concatenate([p[1] for p in self.parts]).reshape(-1, dim)
        if len(raw) < 2:
            return None
        unit = raw / np.linalg.norm(raw, axis=1, keepdims=True)
        # Cells of earlier tables are worked out again: cheaper than to carry them through the shuffle.
        i, j = cell_links(unit, cells(raw, bits, tables, table), of("block") if first != second else None, cosine)
        if not len(i):
            return None
        size, h, g = of("n"), of("h"), of("g")
        count = (np.bincount(i, size[j], len(raw)) + np.bincount(j, size[i], len(raw))).astype(np.int64)
        at = np.flatnonzero(count)
        root = forest(len(raw), i, j)[at]
        return pa.RecordBatch.from_arrays([pa.array(x) for x in (h[at], g[at], count[at], h[root], g[root])], names=[x.split()[0] for x in _FOUND.split(", ")])


def links(nodes: DataFrame, cosine: float) -> DataFrame:
    """Per node and cell with a new link: number of vectors linked and a node of its component there."""
    bits, tables = plan_tables(nodes.count(), cosine)
    dealt = _dealt(nodes, bits, tables)
    large = dealt.groupBy("tab", "dim", "cell").agg(F.count("*").alias("size")).filter(F.col("size") > BLOCK)
    large = scratch.table(large.withColumn("blocks", F.ceil(F.col("size") / BLOCK)).drop("size"), "cells")
    split = dealt.join(large, ["tab", "dim", "cell"], "left").withColumn("blocks", F.coalesce("blocks", F.lit(1).cast("long")))
    split = split.withColumn("block", F.pmod(F.xxhash64("h", "g"), "blocks")).withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    split = split.withColumn("i", F.least("block", "other")).withColumn("j", F.greatest("block", "other")).drop("other", "blocks")
    key = ["tab", "dim", "cell", "i", "j"]

    def run(batches):
        held = None
        for batch in batches:
            columns = {c: batch.column(c).to_numpy() for c in (*key, "h", "g", "n", "block")}
            vector = batch.column("vector")
            ends = np.frombuffer(vector.buffers()[1], np.int32)[vector.offset : vector.offset + len(vector) + 1] // 8
            values = np.frombuffer(vector.buffers()[2] or b"", np.float64, int(ends[-1]))
            change = np.any([columns[c][1:] != columns[c][:-1] for c in key], axis=0)
            starts = np.concatenate(([0], np.flatnonzero(change) + 1, [batch.num_rows])).tolist()
            for a, b in zip(starts, starts[1:]):
                if a == b:
                    continue
                k = tuple(int(columns[c][a]) for c in key)
                if held is None or held.key != k:
                    if held and (out := held.found(bits, tables, cosine)):
                        yield out
                    held = _Cell(k)
                held.add(columns, values[ends[a] : ends[b]], a, b)
        if held and (out := held.found(bits, tables, cosine)):
            yield out

    dealt = split.repartition(*key).sortWithinPartitions(*key)
    return dealt.mapInArrow(run, _FOUND)


def link_vectors(vectors: DataFrame, cosine: float = 0.9) -> DataFrame:
    """vec_id, n_links, component_id and kept of every row of ``vectors`` (vec_id, embedding)."""
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("vector"))
    fit = F.expr("vector is not null and size(vector) > 0 and forall(vector, x -> x is not null and not isnan(x) and abs(x) < double('infinity')) and exists(vector, x -> x <> 0)")
    # Zeros of either sign are one component, so that equal vectors group. Two hashes with different seeds name a vector.
    rows = rows.withColumn("fit", F.coalesce(fit, F.lit(False))).withColumn("vector", F.when(F.col("fit"), F.expr("transform(vector, x -> x + 0d)")))
    rows = rows.withColumn("h", F.xxhash64("vector")).withColumn("g", F.xxhash64(F.lit("second"), F.reverse("vector")))
    nodes = scratch.table(rows.filter("fit").groupBy("h", "g").agg(F.min("vec_id").alias("rep"), F.count("*").alias("n"), F.first("vector").alias("vector")), "vectors")
    found = scratch.table(links(nodes, cosine), "found")
    count = found.groupBy("h", "g").agg(F.sum("links").alias("links"))
    node = lambda a, b: F.struct(F.col(a).alias("h"), F.col(b).alias("g"))
    roots = scratch.table(components.components(found.select(node("h", "g").alias("u"), node("root_h", "root_g").alias("v"))), "roots")
    named = nodes.select(node("h", "g").alias("node"), "rep", "n").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    named = scratch.table(named, "named")
    least = scratch.table(named.groupBy("root").agg(F.min("rep").alias("component_id")), "least")
    summed = named.join(least, "root").select("node.*", "n", "component_id").join(count, ["h", "g"], "left")
    summed = scratch.table(summed.select("h", "g", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).cast("long").alias("n_links"), "component_id"), "summed")
    scratch.drop(nodes, found, roots, named, least)
    joined = rows.withColumn("h", F.when(F.col("fit"), F.col("h"))).join(summed, ["h", "g"], "left")
    component = F.when(F.col("fit"), F.col("component_id")).otherwise(F.col("vec_id"))
    return joined.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(False)).alias("kept"))


def op10_collision_counting(spark, sf_dir: str) -> DataFrame:
    return link_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))

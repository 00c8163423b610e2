"""Exact search for repeated windows, partitioned by content-chosen anchors.

Every window takes the least-hashed gram inside it as its anchor, so equal windows
share the anchor and its offset.  Consecutive windows with one anchor form a segment
that travels as one string.  Only segments whose anchor occurs at least twice in the
corpus go on; equal segments are counted under a 128-bit digest before anything is
grouped, and the distinct segments of an anchor meet in one task, where the caller's
index compares their windows.  An anchor with more than ``heavy`` distinct segments
is taken apart instead, so no group grows with the corpus: its windows are dealt into
blocks by their distance to the anchor, at which equal windows agree.  A block whose
whole text occurs in two segments is marked at once; one whose core, the text all its
windows share, occurs nowhere else holds no repeat; only what lies between is listed
window by window, under a digest each.

Documents are identified by ``doc_id`` and a hash of the text: repeated rows count as
separate documents and get equal results; a null ``doc_id`` is a value like any other.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from hashlib import blake2b
from math import isqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relanom.llm import kernels, scratch

KEYS = "doc_id long, th long"
SEGMENTS = f"{KEYS}, start int, windows int, anchor long, segment binary"
BODIES = "anchor long, segment binary, windows int, heavy boolean, whole boolean, body binary"
#: Rows up to which a list of anchors is broadcast (8 bytes each); beyond, it is joined by a shuffle.
BROADCAST_ROWS = 1 << 20


@dataclass
class Cut:
    """Segments of a block of documents; arrays are parallel, ``at`` is the anchor's distance from a segment's start."""

    doc: np.ndarray
    start: np.ndarray
    windows: np.ndarray
    anchor: np.ndarray
    at: np.ndarray
    body: Callable[[int], bytes]


@dataclass
class Windowing:
    """How one operator sees a text.

    length, gram: units (bytes or words) of a window and of an anchor; prepare: stored text to the bytes that windows
    are taken from; cut: prepared texts to segments; between: a prepared text and (first, end) units to the bytes there.
    """

    length: int
    gram: int
    prepare: Callable[[bytes], bytes]
    cut: Callable[[list[bytes]], Cut]
    between: Callable[[bytes, list[tuple[int, int]]], list[bytes]]

    @property
    def block(self) -> int:
        """Windows of a block: as many as a segment has blocks."""
        return max(1, isqrt(self.length - self.gram + 1))


def digest(data: bytes) -> bytes:
    return blake2b(data, digest_size=16).digest()


def cut_runs(minima: np.ndarray, first: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, ...]:
    """(doc, start, windows, anchor position) of the runs of windows with one anchor; count[d] windows of d begin at first[d]."""
    doc = np.repeat(np.arange(len(count)), count)
    rel = np.arange(len(doc)) - np.repeat(np.cumsum(count) - count, count)
    chosen = minima[first[doc] + rel] if len(doc) else np.empty(0, np.int64)
    at = np.flatnonzero(np.concatenate(([True], (chosen[1:] != chosen[:-1]) | (doc[1:] != doc[:-1])))) if len(doc) else np.empty(0, np.int64)
    return doc[at], rel[at], np.diff(np.append(at, len(doc))), chosen[at]


def blocks(batch: pa.RecordBatch, prepare, limit: int = 1 << 20) -> Iterator[tuple[list[int], list[bytes]]]:
    """Row numbers and prepared texts, about ``limit`` bytes at a time."""
    rows, texts, size = [], [], 0
    for i, text in enumerate(batch.column("text").cast(pa.binary())):
        data = text.as_py()
        if not data:
            continue
        rows.append(i)
        texts.append(prepare(data))
        size += len(texts[-1])
        if size >= limit:
            yield rows, texts
            rows, texts, size = [], [], 0
    if rows:
        yield rows, texts


def _count_anchors(windowing: Windowing):
    schema = pa.schema([("anchor", pa.int64()), ("n", pa.int64())])

    def run(batches):
        for batch in batches:
            for _, texts in blocks(batch, windowing.prepare):
                keys, n = np.unique(windowing.cut(texts).anchor, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(n)], schema=schema)

    return run


def _cut_segments(windowing: Windowing):
    schema = pa.schema([("doc_id", pa.int64()), ("th", pa.int64()), ("start", pa.int32()), ("windows", pa.int32()), ("anchor", pa.int64()), ("segment", pa.binary())])

    def run(batches):
        for batch in batches:
            ids, hashes = batch.column("doc_id"), batch.column("th")
            for rows, texts in blocks(batch, windowing.prepare):
                cut = windowing.cut(texts)
                row = pa.array(np.asarray(rows, np.int64)[cut.doc])
                digests = [digest(cut.body(i)) for i in range(len(cut.doc))]
                yield pa.RecordBatch.from_arrays([ids.take(row), hashes.take(row), pa.array(cut.start.astype(np.int32)), pa.array(cut.windows.astype(np.int32)), pa.array(cut.anchor), pa.array(digests, pa.binary())], schema=schema)

    return run


def _extract(windowing: Windowing):
    schema = pa.schema([("anchor", pa.int64()), ("segment", pa.binary()), ("windows", pa.int32()), ("heavy", pa.bool_()), ("whole", pa.bool_()), ("body", pa.binary())])

    def rows(batches):
        for batch in batches:
            for text, wanted in zip(batch.column("text").cast(pa.binary()), batch.column("wanted")):
                todo = wanted.as_py()
                bodies = windowing.between(windowing.prepare(text.as_py()), [(x["start"], x["start"] + x["windows"] + windowing.length - 1) for x in todo])
                for x, body in zip(todo, bodies):
                    yield x["anchor"], x["segment"], x["windows"], x["heavy"], x["whole"], body

    return lambda batches: kernels.row_batches(rows(batches), schema, 4000)


def _index_groups(index: Callable[[list[tuple[bytes, int]]], list[list[tuple[int, int]]]], limit: int):
    """Feed whole anchors to ``index``, about ``limit`` bytes at a time; the input is sorted by anchor and segment."""
    schema = pa.schema([("segment", pa.binary()), ("a", pa.int32()), ("b", pa.int32())])

    def rows(batches):
        held, size, last = [], 0, None
        for batch in batches:
            for anchor, segment, windows, whole, body in zip(*(batch.column(c).to_pylist() for c in ("anchor", "segment", "windows", "whole", "body"))):
                if size >= limit and anchor != last:
                    yield from found(held)
                    held, size = [], 0
                last = anchor
                if held and held[-1][0] == segment:
                    continue
                held.append((segment, whole, body, windows))
                size += len(body)
        yield from found(held)

    def found(held):
        for (segment, whole, _, _), spans in zip(held, index([x[2:] for x in held]) if held else []):
            for a, b in () if whole else spans:
                yield segment, a, b

    return lambda batches: kernels.row_batches(rows(batches), schema)


def _blocks(windowing: Windowing):
    """Blocks of windows [a, b) with digests of their whole text and of their core."""
    schema = pa.schema([("segment", pa.binary()), ("whole", pa.bool_()), ("a", pa.int32()), ("b", pa.int32()), ("text", pa.binary()), ("core", pa.binary())])
    size, length = windowing.block, windowing.length

    def rows(batches):
        for batch in batches:
            segments, windows, whole, bodies = (batch.column(c).to_pylist() for c in ("segment", "windows", "whole", "body"))
            # A segment's bytes hold its windows and nothing else: cut again, they are one run with the same anchor.
            for segment, n, flag, body, at in zip(segments, windows, whole, bodies, windowing.cut(bodies).at.tolist()):
                spans, numbers, cores, a = [], [], [], 0
                while a < n:
                    number = (at - a) // size
                    last = at - number * size
                    spans.append((a, min(n, last + 1)))
                    numbers.append(number)
                    cores.append((last, last - size + 1 + length))
                    a = last + 1
                texts = windowing.between(body, [(a, b + length - 1) for a, b in spans] + cores)
                for (a, b), number, text, core in zip(spans, numbers, texts, texts[len(spans) :]):
                    yield segment, flag, a, b, digest(text), digest(b"%d " % number + core)

    return lambda batches: kernels.row_batches(rows(batches), schema)


def _listed(windowing: Windowing):
    """Digests of the windows of some blocks of each segment."""
    schema = pa.schema([("segment", pa.binary()), ("mark", pa.bool_()), ("a", pa.int32()), ("window", pa.binary())])

    def rows(batches):
        for batch in batches:
            for segment, body, blocks in zip(*(batch.column(c).to_pylist() for c in ("segment", "body", "blocks"))):
                starts = [(x["mark"], a) for x in blocks for a in range(x["a"], x["b"])]
                for (mark, a), window in zip(starts, windowing.between(body, [(a, a + windowing.length) for _, a in starts])):
                    yield segment, mark, a, digest(window)

    return lambda batches: kernels.row_batches(rows(batches), schema)


def _heavy_marks(bodies: DataFrame, windowing: Windowing) -> DataFrame:
    """(segment, a, b): repeated windows of the segments of heavy anchors; segments that occur twice are marked elsewhere."""
    blocks = bodies.mapInArrow(_blocks(windowing), "segment binary, whole boolean, a int, b int, text binary, core binary").distinct()
    blocks = scratch.table(blocks, "blocks")
    texts = scratch.table(blocks.groupBy("text", "core").agg(F.count("*").alias("n"), F.min(F.struct("segment", "a", "b", "whole")).alias("one")), "texts")
    settled = blocks.filter("not whole").join(texts.filter("n > 1").select("text"), "text", "left_semi").select("segment", "a", "b")
    # Written, so that the join by core is not tied to the partitioning of this count and a common core can be split.
    near = scratch.table(texts.groupBy("core").count().filter("count > 1").select("core"), "near")
    open_ = texts.join(near, "core", "left_semi").select("one.segment", F.struct("one.a", "one.b", (~F.col("one.whole") & (F.col("n") == 1)).alias("mark")).alias("block"))
    per_segment = open_.groupBy("segment").agg(F.collect_list("block").alias("blocks"))
    listed = bodies.select("segment", "body").join(per_segment, "segment").mapInArrow(_listed(windowing), "segment binary, mark boolean, a int, window binary")
    listed = scratch.table(listed.distinct(), "listed")
    often = scratch.table(listed.groupBy("window").count().filter("count > 1").select("window"), "often")
    return settled.unionByName(listed.filter("mark").join(often, "window", "left_semi").select("segment", "a", (F.col("a") + 1).alias("b")))


def keyed(documents: DataFrame) -> DataFrame:
    """doc_id, text and the text's hash; other columns, whatever their names, are left behind."""
    return documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text").withColumn("th", F.xxhash64("text"))


def repeated_windows(documents: DataFrame, windowing: Windowing, index, heavy: int = 128, limit: int = 1 << 19) -> DataFrame:
    """(doc_id, th, spans): half-open ranges of window numbers that also start anywhere else in the corpus."""
    docs = keyed(documents)
    counts = docs.select("text").mapInArrow(_count_anchors(windowing), "anchor long, n long")
    again = scratch.table(counts.groupBy("anchor").agg(F.sum("n").alias("n")).filter("n > 1").select("anchor"), "anchors")
    few = again.count() <= BROADCAST_ROWS
    segments = docs.mapInArrow(_cut_segments(windowing), SEGMENTS).join(F.broadcast(again) if few else again, "anchor", "left_semi")
    segments = scratch.table(segments, "segments")

    one = lambda c: F.first(c).alias(c)  # noqa: E731  any occurrence will do: the digest fixes what it holds
    distinct = scratch.table(segments.groupBy("segment").agg(F.count("*").alias("n"), *map(one, ("doc_id", "th", "start", "windows", "anchor"))), "distinct")
    shared = scratch.table(distinct.groupBy("anchor").agg(F.count("*").alias("texts")).filter("texts > 1"), "shared")
    wanted = distinct.join(shared, "anchor").withColumn("heavy", F.col("texts") > heavy).withColumn("whole", F.col("n") > 1)
    per_doc = wanted.groupBy("doc_id", "th").agg(F.collect_list(F.struct("anchor", "segment", "start", "windows", "heavy", "whole")).alias("wanted"))
    same = lambda x, y: x["doc_id"].eqNullSafe(y["doc_id"]) & (x["th"] == y["th"])
    # A text that several rows repeat under one id is taken once per row; equal bodies are dropped again by digest.
    bodies = docs.join(per_doc, same(docs, per_doc)).select("text", "wanted").mapInArrow(_extract(windowing), BODIES)
    any_heavy = shared.filter(F.col("texts") > heavy).limit(1).count() > 0
    if any_heavy:
        bodies = scratch.table(bodies, "bodies")
    light = bodies.filter("not heavy").repartition("anchor").sortWithinPartitions("anchor", "segment")
    marks = light.mapInArrow(_index_groups(index, limit), "segment binary, a int, b int")
    if any_heavy:
        # Heavy anchors are dealt by segment, evenly, before their windows are looked at.
        tasks = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        marks = marks.unionByName(_heavy_marks(bodies.filter("heavy").select("segment", "windows", "whole", "body").repartition(tasks, "segment"), windowing))
    whole = distinct.filter("n > 1").select("segment", F.lit(0).alias("a"), F.col("windows").alias("b"))
    marks = scratch.table(marks.unionByName(whole), "marks")
    spans = segments.join(marks, "segment").select("doc_id", "th", (F.col("start") + F.col("a")).alias("a"), (F.col("start") + F.col("b")).alias("b"))
    # Rows that repeat under one id give each span once per row; a set holds it once.
    return spans.groupBy("doc_id", "th").agg(F.collect_set(F.struct("a", "b")).alias("spans"))


def with_spans(documents: DataFrame, spans: DataFrame) -> DataFrame:
    """Every document, with the spans found for it or null."""
    docs = keyed(documents)
    joined = docs.join(spans, docs["doc_id"].eqNullSafe(spans["doc_id"]) & (docs["th"] == spans["th"]), "left")
    return joined.select(docs["doc_id"], docs["text"], spans["spans"])

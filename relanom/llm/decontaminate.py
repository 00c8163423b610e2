"""Benchmark decontamination by winnowing.

Training and benchmark texts are cut into lower-cased words.  Of every ``w`` consecutive
``k``-word hashes the least is kept as a fingerprint, so any shared span of k + w - 1 words
shares a fingerprint; with k + w - 1 = ``window`` no shared window can be missed.  Where a
document's fingerprint is one of the benchmark's, the windows around it are compared word by
word with the benchmark's windows and hits are extended over every word they cover.  Items
shorter than a window are one window of their own length, found by a hash of that length.

The benchmark is broadcast, as sorted arrays, only while its text stays under
``broadcast_bytes``; beyond, fingerprints are joined by a shuffle, and candidates (document,
item) are confirmed document by document.  Both ways give the same rows.

Null and wordless texts have no words and no windows.  Items with a null ``item_id`` or no
words are ignored; items of equal text count one each.  Repeated documents are judged row by
row.
"""

from __future__ import annotations

import re
from collections import defaultdict
from hashlib import sha256

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relanom.llm import kernels

WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
_INSIDE = np.zeros(256, bool)
_INSIDE[0x30:0x3A] = _INSIDE[0x61:0x7B] = _INSIDE[0x80:] = True
GRAM = 5
RESULT = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean"


def words_of(text: bytes | None) -> list[bytes]:
    return WORD.findall(text.lower()) if text else []


def fingerprints(grams: np.ndarray, w: int) -> np.ndarray:
    """Positions that winnowing keeps: the least hash of each window of ``w``."""
    return np.unique(kernels.window_minima(grams, w))


class BenchmarkIndex:
    """Windows of the benchmark as sorted hashes with their items, and the fingerprints that lead to them.

    Arrays only: 24 bytes a window beside the words' bytes, which confirm every hit.
    """

    def __init__(self, items: list[tuple[int, bytes]], window: int, gram: int = GRAM):
        self.window, self.gram = window, gram
        prints, short, hashes, owner, begin, end, text, at = [np.empty(0, np.uint64)], defaultdict(list), [], [], [], [], [], 0
        for item, raw in items:
            words = words_of(raw)
            size = min(window, len(words))
            if not size:
                continue
            sizes = np.array([len(w) + 1 for w in words], np.int64)
            starts = np.concatenate(([0], np.cumsum(sizes)))
            own = self._hashes(words)
            grams = kernels.gram_hashes(own, size)
            n = len(grams)
            hashes.append(grams)
            owner.append(np.full(n, item, np.int64))
            begin.append(at + starts[:n])
            end.append(at + starts[size : size + n] - 1)
            text.append(b" ".join(words))
            at += len(text[-1]) + 1
            if size == window:
                grams = kernels.gram_hashes(own, gram)
                prints.append(grams[fingerprints(grams, window - gram + 1)])
            else:
                short[size].append(grams)
        self.prints = np.unique(np.concatenate(prints))
        self.short = {size: np.unique(np.concatenate(x)) for size, x in short.items()}
        self.text = b" ".join(text)
        joined = lambda parts, kind: np.concatenate([np.empty(0, kind), *parts]).astype(kind)
        hashes = joined(hashes, np.uint64)
        order = np.argsort(hashes, kind="stable")
        self.hashes, self.items = hashes[order], joined(owner, np.int64)[order]
        self.begin, self.end = joined(begin, np.int64)[order].astype(np.int32), joined(end, np.int64)[order].astype(np.int32)

    @staticmethod
    def _hashes(words: list[bytes]) -> np.ndarray:
        raw = np.frombuffer(b" ".join(words), np.uint8)
        return kernels.word_hashes(raw, *kernels.word_spans(raw, _INSIDE))

    def items_of(self, hashed: np.uint64, window: bytes) -> set[int]:
        """Items that hold the words of ``window``, joined by one space; equal hashes of other words are told apart by the bytes."""
        low, high = np.searchsorted(self.hashes, hashed, "left"), np.searchsorted(self.hashes, hashed, "right")
        return {int(self.items[k]) for k in range(low, high) if self.text[self.begin[k] : self.end[k]] == window}

    def hits(self, texts: list[bytes]) -> list[tuple[int, set[int], set[int]]]:
        """Per lower-cased text: number of words, hit words, items."""
        data = b"\n".join(texts)
        raw = np.frombuffer(data, np.uint8)
        start, end = kernels.word_spans(raw, _INSIDE)
        sizes = np.array([len(t) + 1 for t in texts], np.int64)
        first = np.searchsorted(start, np.append(np.cumsum(sizes) - sizes, len(raw) + 1))
        hashes = kernels.word_hashes(raw, start, end)
        out = [(int(n), set(), set()) for n in np.diff(first)]

        def confirm(at: np.ndarray, size: int) -> None:
            """Windows of ``size`` words from the words ``at`` on."""
            doc = np.searchsorted(first, at, side="right") - 1
            inside = (at + size <= first[doc + 1]) & (at + size <= len(hashes))
            at, doc = at[inside], doc[inside]
            own = kernels.gram_hashes(hashes[at[:, None] + np.arange(size)].ravel(), size)[::size] if len(at) else np.empty(0, np.uint64)
            known = _found(own, self.hashes)
            for s, d, h in zip(at[known].tolist(), doc[known].tolist(), own[known]):
                items = self.items_of(h, b" ".join(data[a:b] for a, b in zip(start[s : s + size].tolist(), end[s : s + size].tolist())))
                if items:
                    out[d][1].update(range(s - int(first[d]), s - int(first[d]) + size))
                    out[d][2].update(items)

        grams = kernels.gram_hashes(hashes, self.gram)
        kept = fingerprints(grams, self.window - self.gram + 1)
        hit = kept[_found(grams[kept], self.prints)]
        around = np.unique(hit[:, None] - np.arange(self.window - self.gram + 1))
        confirm(around[around >= 0], self.window)
        for size, known in self.short.items():
            confirm(np.flatnonzero(_found(kernels.gram_hashes(hashes, size), known)), size)
        return out


def _found(hashes: np.ndarray, known: np.ndarray) -> np.ndarray:
    if not len(known):
        return np.zeros(len(hashes), bool)
    return known[np.minimum(np.searchsorted(known, hashes), len(known) - 1)] == hashes


def _result(doc_id, n_words: int, hit: set[int], items: set[int]) -> tuple:
    listed = ",".join(sorted(map(str, items)))
    return doc_id, n_words, len(hit), len(items), sha256(listed.encode()).hexdigest(), bool(hit)


def _lowered(batch: pa.RecordBatch, limit: int = 1 << 20):
    rows, texts, size = [], [], 0
    for i, text in enumerate(batch.column("text").cast(pa.binary())):
        rows.append(i)
        texts.append((text.as_py() or b"").lower())
        size += len(texts[-1])
        if size >= limit:
            yield rows, texts
            rows, texts, size = [], [], 0
    if rows:
        yield rows, texts


_SCHEMA = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_hit", pa.int64()), ("n_items", pa.int64()), ("items_sha256", pa.string()), ("contaminated", pa.bool_())])


def _by_broadcast(docs: DataFrame, items: DataFrame, window: int) -> DataFrame:
    index = docs.sparkSession.sparkContext.broadcast(BenchmarkIndex([(r[0], r[1].encode()) for r in items.collect()], window))

    def rows(batches):
        for batch in batches:
            ids = batch.column("doc_id").to_pylist()
            for at, texts in _lowered(batch):
                for i, (n, hit, found) in zip(at, index.value.hits(texts)):
                    yield _result(ids[i], n, hit, found)

    return docs.mapInArrow(lambda batches: kernels.row_batches(rows(batches), _SCHEMA), RESULT)


def _by_shuffle(docs: DataFrame, items: DataFrame, window: int, keep_hash: bool = False) -> DataFrame:
    """Fingerprints of both sides meet by value; candidates are confirmed pair by pair."""
    w, keyed = window - GRAM + 1, docs.withColumn("th", F.xxhash64("text"))

    def prints_of(text: bytes, sizes) -> set[int]:
        hashes = BenchmarkIndex._hashes(words_of(text))
        grams = kernels.gram_hashes(hashes, GRAM)
        return {x for part in (grams[fingerprints(grams, w)], *(kernels.gram_hashes(hashes, s) for s in sizes)) for x in part.view(np.int64).tolist()}

    sizes = [r[0] for r in items.select(F.size(F.regexp_extract_all(F.lower("text"), F.lit("[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+"), 0)).alias("n")).filter(f"n > 0 and n < {window}").distinct().collect()]
    doc_schema = pa.schema([("doc_id", pa.int64()), ("th", pa.int64()), ("print", pa.int64())])
    item_schema = pa.schema([("item_id", pa.int64()), ("print", pa.int64())])

    def doc_prints(batches):
        for batch in batches:
            for d, th, text in zip(batch.column("doc_id").to_pylist(), batch.column("th").to_pylist(), kernels.as_bytes(batch.column("text"))):
                for x in prints_of(text or b"", sizes):
                    yield d, th, x

    def item_prints(batches):
        for batch in batches:
            for item, text in zip(batch.column("item_id").to_pylist(), kernels.as_bytes(batch.column("text"))):
                n = len(words_of(text))
                for x in prints_of(text, [n] if 0 < n < window else []) if n else ():
                    yield item, x

    left = keyed.mapInArrow(lambda b: kernels.row_batches(doc_prints(b), doc_schema), "doc_id long, th long, print long")
    right = items.mapInArrow(lambda b: kernels.row_batches(item_prints(b), item_schema), "item_id long, print long")
    pairs = left.join(right, "print").select("doc_id", "th", "item_id").distinct()
    pairs = pairs.join(items.withColumnRenamed("text", "item_text"), "item_id").groupBy("doc_id", "th").agg(F.collect_list(F.struct("item_id", "item_text")).alias("items"))
    joined = keyed.join(pairs, keyed["doc_id"].eqNullSafe(pairs["doc_id"]) & (keyed["th"] == pairs["th"]), "left").select(keyed["doc_id"], keyed["text"], keyed["th"], "items")

    def rows(batches):
        for batch in batches:
            for d, text, th, found in zip(batch.column("doc_id").to_pylist(), kernels.as_bytes(batch.column("text")), batch.column("th").to_pylist(), batch.column("items")):
                some = [(x["item_id"], x["item_text"].encode()) for x in found.as_py() or ()]
                yield _result(d, *BenchmarkIndex(some, window).hits([(text or b"").lower()])[0]) + ((th,) if keep_hash else ())

    schema = _SCHEMA.append(pa.field("th", pa.int64())) if keep_hash else _SCHEMA
    return joined.mapInArrow(lambda batches: kernels.row_batches(rows(batches), schema), RESULT + ", th long" * keep_hash)


def contamination(documents: DataFrame, benchmark: DataFrame, window: int = 10, broadcast_bytes: int = 8 << 20) -> DataFrame:
    """Per document how many of its words lie in a window of the benchmark, and in windows of which items."""
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).dropna()
    size = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    return (_by_broadcast if size <= broadcast_bytes else _by_shuffle)(docs, items, window)


def decontaminated(documents: DataFrame, benchmark: DataFrame, window: int = 10, broadcast_bytes: int = 8 << 20) -> DataFrame:
    """The documents, all columns, that hold no window of the benchmark."""
    items = benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).dropna()
    size = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    if size > broadcast_bytes:
        hit = _by_shuffle(documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), items, window, keep_hash=True)
        hit = hit.filter("contaminated").select(F.col("doc_id").alias("_hit"), "th").distinct()
        return documents.join(hit, documents["doc_id"].eqNullSafe(hit["_hit"]) & (F.xxhash64(documents["text"].cast("string")) == hit["th"]), "left_anti")
    index = documents.sparkSession.sparkContext.broadcast(BenchmarkIndex([(r[0], r[1].encode()) for r in items.collect()], window))

    def run(batches):
        for batch in batches:
            clean = [not hit for _, texts in _lowered(batch) for _, hit, _ in index.value.hits(texts)]
            yield batch.filter(pa.array(clean, pa.bool_()))

    return documents.mapInArrow(run, documents.schema)


def op2_winnowing(spark, sf_dir: str) -> DataFrame:
    """Contamination of every document of ``documents`` by ``benchmark``."""
    return contamination(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


ORACLE = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents
), i AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark WHERE item_id IS NOT NULL
), k AS (
  SELECT DISTINCT item_id, least(10, len(w)) AS n, array_to_string(w[p:p + least(10, len(w)) - 1], ' ') AS s
  FROM (SELECT *, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS p FROM i WHERE len(w) > 0)
), h AS (
  SELECT g.doc_id, g.p, g.n, k.item_id
  FROM (SELECT doc_id, n, p, array_to_string(w[p:p + n - 1], ' ') AS s
        FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS p FROM d CROSS JOIN (SELECT DISTINCT n FROM k) WHERE len(w) >= n)) g
  JOIN k ON k.n = g.n AND k.s = g.s
), c AS (
  SELECT doc_id, count(DISTINCT q) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + n)) AS q FROM h) GROUP BY doc_id
), t AS (
  SELECT doc_id, count(*) AS n_items, string_agg(i, ',' ORDER BY i) AS items FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS i FROM h) GROUP BY doc_id
)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(c.n_hit, 0)::BIGINT AS n_hit, coalesce(t.n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(t.items, '')) AS items_sha256, coalesce(c.n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN c USING (doc_id) LEFT JOIN t USING (doc_id)
"""

"""Repeated byte strings through a run-length compressed Burrows-Wheeler index.

Per task the distinct segments of some anchors (see ``anchored``) are joined and indexed by
the run-length encoded Burrows-Wheeler transform, with match lengths sampled at run ends.
Every segment is streamed backwards through the index, one step along its run a byte, which
yields each position's longest match elsewhere; positions of at least ``length`` are marked.
In repetitive text runs are few, so samples are too.

Null text counts as empty.  Texts shorter than ``length`` keep every byte.  Ties (equal
segments, overlapping occurrences) all count; nothing is kept as a "first" copy.
"""

from __future__ import annotations

from hashlib import sha256

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from relanom.llm import anchored, kernels

GRAM = 32
_END = 0xFF  # occurs in no UTF-8 text


def suffix_array(text: np.ndarray) -> np.ndarray:
    """Suffix array by prefix doubling from 8-byte keys; only tied suffixes are sorted again."""
    n = len(text)
    padded = np.zeros(n + 8, np.uint64)
    padded[:n] = text
    key = np.zeros(n, np.uint64)
    for i in range(8):
        key = (key << np.uint64(8)) | padded[i : i + n]
    order = np.argsort(key)
    new = np.concatenate(([True], key[order][1:] != key[order][:-1]))
    head = np.flatnonzero(new)[np.cumsum(new) - 1]
    rank = np.empty(n, np.int64)
    rank[order] = head
    size = np.diff(np.append(np.flatnonzero(new), n))
    todo = np.flatnonzero(np.repeat(size > 1, size))
    h = 8
    while len(todo) and h < 2 * n:
        at = order[todo]
        beyond = at + h
        second = np.where(beyond < n, rank[np.minimum(beyond, n - 1)], -1)
        both = rank[at] * (n + 1) + second + 1
        by = np.argsort(both)
        order[todo], both = at[by], both[by]
        fresh = np.concatenate(([True], both[1:] != both[:-1]))
        heads = todo[np.flatnonzero(fresh)[np.cumsum(fresh) - 1]]
        rank[order[todo]] = heads
        size = np.diff(np.append(np.flatnonzero(fresh), len(todo)))
        todo = todo[np.repeat(size > 1, size)]
        h *= 2
    return order


def _common(text: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Length of the common prefix of the suffixes at x and y, pair by pair."""
    n = len(text)
    wide = np.zeros(n + 8, np.uint64)
    wide[:n] = text
    words = np.zeros(n, np.uint64)
    for i in range(8):
        words |= wide[i : i + n] << np.uint64(8 * i)
    length = np.zeros(len(x), np.int64)
    todo = np.arange(len(x))
    while len(todo):
        p, q = x[todo] + length[todo], y[todo] + length[todo]
        inside = np.maximum(p, q) < n
        todo, p, q = todo[inside], p[inside], q[inside]
        differ = words[p] ^ words[q]
        low = differ & (~differ + np.uint64(1))
        same = np.where(differ == 0, 8, np.floor(np.log2(np.maximum(low, 1).astype(np.float64))).astype(np.int64) // 8)
        length[todo] += np.minimum(same, n - np.maximum(p, q))
        todo = todo[same == 8]
    return length


class RunLengthIndex:
    """Run-compressed transform of segments that are each closed by ``_END`` and joined.

    A run is its byte, its first and last row, the row that its first row steps to and the run which that row lies in.
    The match length with the neighbour above is kept where a run's first row steps to, that with the neighbour below
    where its last row does, and both where a segment's stream begins.  Text, suffix array and transform are not kept.
    """

    def __init__(self, text: np.ndarray):
        order = suffix_array(text)
        # Nothing stands before text position 0: a letter of its own keeps it out of its neighbours' runs.
        before = text[order - 1].astype(np.int16)
        before[order == 0] = -1
        self.heads = np.concatenate(([0], np.flatnonzero(before[1:] != before[:-1]) + 1))
        self.tails = np.append(self.heads[1:] - 1, len(text) - 1)
        self.bytes = before[self.heads]
        self.steps = self._steps()
        self.into = np.searchsorted(self.heads, self.steps, side="right") - 1
        inner = np.flatnonzero((self.bytes >= 0) & (self.bytes < _END))
        self.above, self.below = np.zeros(len(self.heads), np.int64), np.zeros(len(self.heads), np.int64)
        self.above[inner] = self._matches(text, order, self.steps[inner], -1)
        self.below[inner] = self._matches(text, order, (self.steps + self.tails - self.heads)[inner], 1)
        ends = np.flatnonzero(text == _END)
        self.sizes = np.diff(ends, prepend=-1) - 1
        rows = np.flatnonzero(text[order] == _END)
        self.entry = rows[np.argsort(order[rows])]
        self.entry_above = self._matches(text, order, self.entry, -1)
        self.entry_below = self._matches(text, order, self.entry, 1)

    def _steps(self) -> np.ndarray:
        """Where each run's first row steps to: behind the suffixes of smaller bytes and those of its byte above it."""
        by = np.argsort(self.bytes, kind="stable")
        size = np.where(self.bytes < 0, 0, self.tails - self.heads + 1)[by]
        out = np.empty(len(by), np.int64)
        out[by] = np.cumsum(size) - size
        return out

    def _moved(self, row: np.ndarray, run: np.ndarray) -> np.ndarray:
        """Runs of ``row``: those in ``run`` or some way behind them."""
        beyond = np.flatnonzero(row > self.tails[run])
        for _ in range(4):
            if not len(beyond):
                return run
            run[beyond] += 1
            beyond = beyond[row[beyond] > self.tails[run[beyond]]]
        run[beyond] = np.searchsorted(self.heads, row[beyond], side="right") - 1
        return run

    @staticmethod
    def _matches(text: np.ndarray, order: np.ndarray, rows: np.ndarray, beside: int) -> np.ndarray:
        """Length of the match of the suffixes at ``rows`` with those ``beside`` them."""
        other = rows + beside
        real = (other >= 0) & (other < len(order))
        length = np.zeros(len(rows), np.int64)
        length[real] = _common(text, order[rows[real]], order[other[real]])
        return length

    def matching_lengths(self) -> list[np.ndarray]:
        """Per segment and byte the longest match that also starts at another position.

        All segments are streamed in step from their ends to their starts.  With each byte a row steps along its run:
        inside the run the neighbour steps along and the match grows by one, at the run's first or last row the
        neighbour is another and the sample holds.
        """
        by = np.argsort(-self.sizes, kind="stable")
        row, up, down, sizes = self.entry[by], self.entry_above[by], self.entry_below[by], self.sizes[by]
        run = np.searchsorted(self.heads, row, side="right") - 1
        best = np.zeros((int(sizes.max(initial=0)), len(by)), np.int32)
        for t in range(len(best)):
            k = int(np.searchsorted(-sizes, -t, side="left"))
            now, at = row[:k], run[:k]
            offset = now - self.heads[at]
            up[:k] = np.where(offset > 0, up[:k] + 1, self.above[at])
            down[:k] = np.where(now < self.tails[at], down[:k] + 1, self.below[at])
            row[:k] = self.steps[at] + offset
            run[:k] = self._moved(row[:k], self.into[at])
            np.maximum(up[:k], down[:k], out=best[t, :k], casting="unsafe")
        out: list[np.ndarray] = [np.empty(0, np.int32)] * len(by)
        for lane, (segment, size) in enumerate(zip(by.tolist(), sizes.tolist())):
            out[segment] = best[:size, lane][::-1]
        return out


def index_segments(length: int):
    def index(segments: list[tuple[bytes, int]]) -> list[list[tuple[int, int]]]:
        text = np.frombuffer(b"".join(body + bytes([_END]) for body, _ in segments), np.uint8)
        found = RunLengthIndex(text).matching_lengths()
        return [kernels.flagged_runs(longest[:windows] >= length) for longest, (_, windows) in zip(found, segments)]

    return index


def windowing(length: int, gram: int = GRAM) -> anchored.Windowing:
    """Byte windows of ``length``, anchored by grams of ``gram`` bytes."""

    def cut(texts: list[bytes]) -> anchored.Cut:
        texts = [t if len(t) >= length else b"" for t in texts]
        sizes = np.array([len(t) for t in texts], np.int64)
        data = b"".join(texts)
        first = np.cumsum(sizes) - sizes
        raw = np.frombuffer(data, np.uint8)
        hashes = np.empty(max(0, len(raw) - gram + 1), np.uint64)
        step = 1 << 20
        for i in range(0, len(hashes), step):
            part = kernels.prefix_hash(raw[i : i + step + gram - 1])
            start = np.arange(len(part) - gram)
            hashes[i : i + step] = kernels.span_hashes(part, start, start + gram)
        minima = kernels.window_minima(hashes, length - gram + 1)
        doc, start, windows, at = anchored.cut_runs(minima, first, np.maximum(sizes - length + 1, 0))
        begin, end = (first[doc] + start).tolist(), (first[doc] + start + windows + length - 1).tolist()
        return anchored.Cut(doc, start, windows, hashes[at].view(np.int64), at - first[doc] - start, lambda i: data[begin[i] : end[i]])

    return anchored.Windowing(length, gram, prepare=bytes, cut=cut, between=lambda text, wanted: [text[a:b] for a, b in wanted])


def repeated_bytes(documents: DataFrame, length: int = 400, heavy: int = 128) -> DataFrame:
    """(doc_id, th, spans) of the starts of ``length``-byte strings that occur again."""
    return anchored.repeated_windows(documents, windowing(length), index_segments(length), heavy)


def remove_repeats(documents: DataFrame, length: int = 400, heavy: int = 128, text: bool = False) -> DataFrame:
    """Per document what is left once every byte of a repeated string is removed.

    doc_id, n_bytes, n_removed, n_spans, kept_sha256, and with ``text`` the remaining bytes as ``kept``.
    """
    fields = [("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string())] + [("kept", pa.binary())] * text

    def rows(batches):
        for batch in batches:
            for doc_id, data, spans in zip(batch.column("doc_id").to_pylist(), batch.column("text").cast(pa.binary()), batch.column("spans")):
                data, spans = data.as_py() or b"", spans.as_py()
                gone = kernels.merged((x["a"], x["b"] + length - 1) for x in spans or ())
                kept, at = [], 0
                for a, b in gone:
                    kept.append(data[at:a])
                    at = b
                kept = b"".join([*kept, data[at:]])
                yield (doc_id, len(data), len(data) - len(kept), len(gone), sha256(kept).hexdigest()) + ((kept,) if text else ())

    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + ", kept binary" * text
    joined = anchored.with_spans(documents, repeated_bytes(documents, length, heavy))
    return joined.mapInArrow(lambda batches: kernels.row_batches(rows(batches), pa.schema(fields)), schema)


def op3_suffix_array_dedup(spark, sf_dir: str) -> DataFrame:
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet"), 400)

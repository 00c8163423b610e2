"""Repeated word windows by super-k-mer partitioning.

Consecutive windows that share a minimiser travel as one packed string (words joined by
one space) to the minimiser's bucket; there the windows are unpacked and sorted, and equal
neighbours are counted exactly.  Only minimisers that occur twice are sent at all, equal
super-k-mers once.  A minimiser with very many distinct super-k-mers has its windows
counted by digest across all tasks instead (see ``anchored``).

Null text has no words.  Texts of fewer words than a window keep all of them.  All
occurrences of a repeated window are removed, none is kept as the first.
"""

from __future__ import annotations

from hashlib import sha256
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from relanom.llm import anchored, kernels

GRAM = 8
_INSIDE = np.ones(256, bool)
_INSIDE[[0x20, 0x0A]] = False


def _pack(text: bytes) -> bytes:
    """Words joined by one space; ``bytes.split`` takes exactly the white space 20 and 09 to 0D."""
    return b" ".join(text.split())


def _word_starts(body: bytes) -> list[int]:
    gaps = np.flatnonzero(np.frombuffer(body, np.uint8) == 0x20)
    return [0, *(gaps + 1).tolist(), len(body) + 1]


def _windows(body: bytes, windows: int, length: int):
    at = _word_starts(body)
    return (body[at[i] : at[i + length] - 1] for i in range(windows))


def sort_and_count(length: int):
    """Index of a bucket: sort its windows, flag those that occur twice."""

    def index(segments: list[tuple[bytes, int]]) -> list[list[tuple[int, int]]]:
        flags = [np.zeros(windows, bool) for _, windows in segments]
        listed = sorted((w, s, i) for s, (body, windows) in enumerate(segments) for i, w in enumerate(_windows(body, windows, length)))
        for _, same in groupby(listed, key=lambda x: x[0]):
            _, s, i = next(same)
            for _, t, j in same:
                flags[s][i] = flags[t][j] = True
        return [kernels.flagged_runs(f) for f in flags]

    return index


def windowing(length: int, gram: int = GRAM) -> anchored.Windowing:
    """Windows of ``length`` words whose minimiser is a gram of ``gram`` words."""

    def cut(texts: list[bytes]) -> anchored.Cut:
        data = b"\n".join(texts)
        raw = np.frombuffer(data, np.uint8)
        start, end = kernels.word_spans(raw, _INSIDE)
        sizes = np.array([len(t) + 1 for t in texts], np.int64)
        first = np.searchsorted(start, np.cumsum(sizes) - sizes)
        words = np.diff(np.append(first, len(start)))
        grams = kernels.gram_hashes(kernels.word_hashes(raw, start, end), gram)
        minima = kernels.window_minima(grams, length - gram + 1)
        doc, rel, windows, at = anchored.cut_runs(minima, first, np.maximum(words - length + 1, 0))
        begin, stop = start[first[doc] + rel].tolist(), end[first[doc] + rel + windows + length - 2].tolist()
        return anchored.Cut(doc, rel, windows, grams[at].view(np.int64), at - first[doc] - rel, lambda i: data[begin[i] : stop[i]])

    def between(text: bytes, wanted: list[tuple[int, int]]) -> list[bytes]:
        at = _word_starts(text)
        return [text[at[a] : at[b] - 1] for a, b in wanted]

    return anchored.Windowing(length, gram, prepare=_pack, cut=cut, between=between)


def repeated_word_windows(documents: DataFrame, length: int = 35, heavy: int = 128) -> DataFrame:
    """(doc_id, th, spans) of the starts of windows of ``length`` words that occur again."""
    return anchored.repeated_windows(documents, windowing(length), sort_and_count(length), heavy)


def remove_repeats(documents: DataFrame, length: int = 35, heavy: int = 128, text: bool = False) -> DataFrame:
    """Per document what is left without repeated windows: doc_id, n_words, n_removed, kept_sha256 (and ``kept``)."""
    fields = [("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string())] + [("kept", pa.binary())] * text

    def rows(batches):
        for batch in batches:
            for doc_id, data, spans in zip(batch.column("doc_id").to_pylist(), batch.column("text").cast(pa.binary()), batch.column("spans")):
                words, kept, at = (data.as_py() or b"").split(), [], 0
                for a, b in kernels.merged((x["a"], x["b"] + length - 1) for x in spans.as_py() or ()):
                    kept += words[at:a]
                    at = b
                kept += words[at:]
                joined = b" ".join(kept)
                yield (doc_id, len(words), len(words) - len(kept), sha256(joined).hexdigest()) + ((joined,) if text else ())

    schema = "doc_id long, n_words long, n_removed long, kept_sha256 string" + ", kept binary" * text
    joined = anchored.with_spans(documents, repeated_word_windows(documents, length, heavy))
    return joined.mapInArrow(lambda batches: kernels.row_batches(rows(batches), pa.schema(fields)), schema)


def op7_super_kmer_dedup(spark, sf_dir: str) -> DataFrame:
    return remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet"), 35)

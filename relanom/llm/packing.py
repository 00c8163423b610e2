"""Sequence packing by minimum bin slack.

Documents are tokenised once into pieces: full windows and one remainder.  Only the
histogram of piece lengths (at most ``capacity`` counts) reaches the driver, where windows
are planned: with the longest length left as its first piece, a bitset subset-sum over the
remaining counts finds the multiset that fills the window closest to capacity, its counts
are backtracked, and the pattern is repeated while its lengths last, so at least one length
is used up per pattern and the plan is bounded by the square of ``capacity``.  Pieces find
their places by their rank among those of their length, taken over all tasks.

Null text is empty and gives one piece with the end id alone.  Equal pieces are
interchangeable; ties in rank change nothing but which of them goes where.
"""

from __future__ import annotations

import base64
from functools import lru_cache
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from relanom.llm import kernels, scratch

CAPACITY = 1024
END_ID = 0
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"


@lru_cache(maxsize=2)
def encoder(json_path: str, ranks_path: str | None):
    """Text to ids.  Ranks of the same vocabulary are quicker; texts that spell a special token take the first file."""
    from tokenizers import Tokenizer

    slow = Tokenizer.from_file(json_path)
    if not ranks_path:
        return lambda text: slow.encode(text, add_special_tokens=False).ids
    import public_tokenizers
    import tiktoken

    with open(ranks_path, "rb") as f:
        ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, f)}
    quick = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    special = [t.content for t in slow.get_added_tokens_decoder().values()]

    def encode(text: str) -> list[int]:
        if any(s in text for s in special):
            return slow.encode(text, add_special_tokens=False).ids
        return quick.encode_ordinary(text)

    return encode


def default_paths() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken")


def pieces(documents: DataFrame, paths: tuple[str, str | None] | None = None, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """Every document's ids and the end id, cut at multiples of ``capacity``."""
    fields = [(n, pa.int64()) for n in ("doc_id", "start", "length", "ids_crc32", "doc_tokens")] + [("ids", pa.list_(pa.int32()))] * with_ids

    def rows(batches):
        encode = encoder(*(paths or default_paths()))
        for batch in batches:
            for doc_id, text in zip(batch.column("doc_id").to_pylist(), batch.column("text")):
                ids = np.asarray([*encode(text.as_py() or ""), END_ID], "<u4")
                for a in range(0, len(ids), capacity):
                    part = ids[a : a + capacity]
                    yield (doc_id, a, len(part), crc32(part.tobytes()), len(ids)) + ((part.astype(np.int32).tolist(),) if with_ids else ())

    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return docs.mapInArrow(lambda batches: kernels.row_batches(rows(batches), pa.schema(fields), 2000), PIECES + ", ids array<int>" * with_ids)


def best_fill(counts: dict[int, int], room: int) -> dict[int, int]:
    """Multiset of lengths, within ``counts``, whose sum comes closest to ``room`` from below."""
    full = (1 << (room + 1)) - 1
    reach, steps = 1, []
    for length in sorted((x for x in counts if x <= room), reverse=True):
        left, take = min(counts[length], room // length), 1
        while left and not reach >> room & 1:
            n = min(take, left)
            steps.append((length, n, reach))
            reach |= reach << length * n & full
            left, take = left - n, take * 2
    at, chosen = reach.bit_length() - 1, {}
    for length, n, before in reversed(steps):
        if not before >> at & 1:
            chosen[length] = chosen.get(length, 0) + n
            at -= length * n
    return chosen


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int, int]]:
    """Rows (length, first_rank, end_rank, per_window, first_sequence, offset)."""
    left = {k: v for k, v in histogram.items() if v}
    used, rows, sequence = dict.fromkeys(left, 0), [], 0
    while left:
        longest = max(left)
        rest = {k: v - (k == longest) for k, v in left.items() if v > (k == longest)}
        pattern = best_fill(rest, capacity - longest) if capacity > longest else {}
        pattern[longest] = pattern.get(longest, 0) + 1
        times = min(left[k] // n for k, n in pattern.items())
        offset = 0
        for k in sorted(pattern, reverse=True):
            n = pattern[k]
            rows.append((k, used[k], used[k] + n * times, n, sequence, offset))
            offset += k * n
            used[k] += n * times
            left[k] -= n * times
            if not left[k]:
                del left[k]
        sequence += times
    return rows


def pack(documents: DataFrame, paths: tuple[str, str | None] | None = None, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """One row per piece with its sequence and offset; with ``with_ids`` the ids too."""
    spark = documents.sparkSession
    cut = scratch.table(pieces(documents, paths, capacity, with_ids), "pieces")
    # Ranks within a length come from ranks within a slice of it plus the sizes of the slices before.
    slices = int(spark.conf.get("spark.sql.shuffle.partitions"))
    cut = cut.withColumn("slice", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32"), F.lit(slices)))
    sizes = cut.groupBy("length", "slice").agg(F.count("*").alias("n"))
    before = sizes.withColumn("before", F.sum("n").over(Window.partitionBy("length").orderBy("slice")) - F.col("n")).drop("n")
    histogram = {r["length"]: r["n"] for r in cut.groupBy("length").agg(F.count("*").alias("n")).collect()}
    rows = plan(histogram, capacity)
    places = spark.createDataFrame(rows, "p_length long, first_rank long, end_rank long, per_window long, first_sequence long, base long")
    own = Window.partitionBy("length", "slice").orderBy("doc_id", "start", "ids_crc32", "doc_tokens")
    ranked = cut.withColumn("own", F.row_number().over(own) - 1).join(before, ["length", "slice"]).withColumn("rank", F.col("own") + F.col("before"))
    placed = ranked.join(F.broadcast(places), (F.col("length") == F.col("p_length")) & (F.col("rank") >= F.col("first_rank")) & (F.col("rank") < F.col("end_rank")))
    step = F.col("rank") - F.col("first_rank")
    return placed.select(
        "doc_id", "start", "length", "ids_crc32", "doc_tokens",
        (F.col("first_sequence") + F.floor(step / F.col("per_window"))).alias("sequence_id"),
        (F.col("base") + F.pmod(step, F.col("per_window")) * F.col("length")).alias("offset"),
        *(["ids"] if with_ids else []),
    )


def op8_min_bin_slack(spark, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"))

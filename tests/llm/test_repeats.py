import random
from collections import defaultdict
from hashlib import sha256

import numpy as np
import pytest

from relanom.llm import substring_dedup, suffix_dedup


def corpus(seed=3, n=60):
    r = random.Random(seed)
    word = lambda: r.choice(["é", "th", "on", "erin", "ßa", "ing", "a", "bb"]) + r.choice(["x", "yy", "ö", ""])
    text = lambda k: "".join(word() + r.choice([" ", "  ", "\n"]) for _ in range(k))
    shared = [text(40), text(30), text(14)]
    docs = []
    for i in range(n):
        t = text(r.randrange(0, 60))
        if i % 3:
            t += r.choice(shared) + text(r.randrange(0, 20))
        if i % 11 == 0:
            t += "ab " * 60
        docs.append((i, t))
    docs += [(100, docs[4][1]), (101, docs[4][1]), (102, None), (103, ""), (4, docs[4][1]), (None, docs[5][1]), (104, "z" * 400)]
    return docs


def brute(docs, items, length, join):
    where = defaultdict(set)
    seqs = [items(t) for _, t in docs]
    for d, s in enumerate(seqs):
        for i in range(len(s) - length + 1):
            where[tuple(s[i : i + length])].add((d, i))
    out = []
    for d, s in enumerate(seqs):
        gone = set()
        for i in range(len(s) - length + 1):
            if len(where[tuple(s[i : i + length])]) > 1:
                gone.update(range(i, i + length))
        kept = join([x for i, x in enumerate(s) if i not in gone])
        runs = sum(1 for i in gone if i - 1 not in gone)
        out.append((docs[d][0], len(s), len(gone), runs, sha256(kept).hexdigest()))
    return out


order = lambda rows: sorted(rows, key=str)


@pytest.mark.parametrize("heavy", [1, 256])
def test_bytes_match_brute_force(spark, heavy):
    docs = corpus()
    df = spark.createDataFrame([(*d, 0, 1) for d in docs], "doc_id long, text string, th int, anchor int").repartition(3)
    got = [tuple(r) for r in suffix_dedup.remove_repeats(df, 50, heavy).collect()]
    assert order(got) == order(brute(docs, lambda t: (t or "").encode(), 50, bytes))


@pytest.mark.parametrize("heavy", [1, 256])
def test_words_match_brute_force(spark, heavy):
    docs = corpus(5)
    df = spark.createDataFrame([(*d, 0, 1) for d in docs], "doc_id long, text string, th int, anchor int").repartition(3)
    got = [tuple(r) for r in substring_dedup.remove_repeats(df, 12, heavy).collect()]
    want = [(d, n, g, h) for d, n, g, _, h in brute(docs, lambda t: (t or "").encode().split(), 12, b" ".join)]
    assert order(got) == order(want)


def test_empty_table(spark):
    df = spark.createDataFrame([], "doc_id long, text string")
    assert suffix_dedup.remove_repeats(df).count() == 0
    assert substring_dedup.remove_repeats(df).count() == 0


def test_run_length_index():
    r = np.random.default_rng(1)
    for segments in ([r.integers(0, 2, 300)], [r.integers(0, 2, 90), r.integers(0, 2, 120), r.integers(0, 2, 1)], [np.tile(r.integers(0, 4, 17), 20)] * 2, [np.zeros(40), np.zeros(25)]):
        parts = [s.astype(np.uint8).tobytes() for s in segments]
        data = b"".join(p + b"\xff" for p in parts)
        index = suffix_dedup.RunLengthIndex(np.frombuffer(data, np.uint8))
        common = lambda a, b: next((k for k in range(len(data) - max(a, b)) if data[a + k] != data[b + k]), len(data) - max(a, b))
        want = [max((common(i, j) for j in range(len(data)) if j != i), default=0) for i in range(len(data))]
        found, at = index.matching_lengths(), 0
        for part, longest in zip(parts, found):
            assert longest.tolist() == want[at : at + len(part)]
            at += len(part) + 1
        assert (index.tails - index.heads + 1).sum() == len(data)


def covered(texts, length):
    """Flags of the bytes that a repeated string of ``length`` (400) covers, by hashes of all windows, sorted."""
    u, sizes = np.uint64, np.array([len(t) for t in texts])
    data = np.frombuffer(b"".join(texts), np.uint8)
    h, kept = np.random.default_rng(1).integers(1, 1 << 63, 256, dtype=np.uint64)[data], {}
    for s in (1, 2, 4, 8, 16, 32, 64, 128, 256):
        kept[s] = h
        x = h[:-s] * u(0x9E3779B97F4A7C15 + 2 * s) + h[s:]
        x = (x ^ (x >> u(33))) * u(0xFF51AFD7ED558CCD)
        h = x ^ (x >> u(29))
    m = len(data) - length + 1
    whole = kept[256][:m] * u(3) + kept[128][256 : 256 + m] * u(5) + kept[16][384 : 384 + m] * u(7)
    valid = np.concatenate([np.arange(s) < s - length + 1 for s in sizes])[:m]
    at = np.flatnonzero(valid)
    _, group, n = np.unique(whole[at], return_inverse=True, return_counts=True)
    twice = at[n[group] > 1]
    change = np.zeros(len(data) + 1, np.int64)
    np.add.at(change, twice, 1)
    np.add.at(change, twice + length, -1)
    return np.split(np.cumsum(change[:-1]) > 0, np.cumsum(sizes)[:-1])


def test_all_documents_match_sorted_windows(spark):
    table = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    docs = sorted((r["doc_id"], (r["text"] or "").encode()) for r in table.select("doc_id", "text").collect())
    want = []
    for (doc_id, text), gone in zip(docs, covered([t for _, t in docs], 400)):
        edge = np.diff(gone.astype(np.int8), prepend=0)
        kept = np.frombuffer(text, np.uint8)[~gone].tobytes()
        want.append((doc_id, len(text), int(gone.sum()), int((edge == 1).sum()), sha256(kept).hexdigest()))
    got = sorted(tuple(r) for r in suffix_dedup.remove_repeats(table).collect())
    assert got == want and sum(w[2] > 0 for w in want) > 100

import random

import numpy as np
import pytest

from relanom.llm import decontaminate, near_dups, vector_links

SF = "/root/testdata/sf0.01"


def slow_similarity(a, b):
    keys = set(a) | set(b)
    return sum(1 / sum(max(a.get(k, 0) / a[d], b.get(k, 0) / b[d]) for k in keys) for d in set(a) & set(b))


def counted(text):
    w = decontaminate.words_of((text or "").encode())
    out = {}
    for i in range(len(w) - 4 if len(w) >= 5 else bool(w)):
        out[tuple(w[i : i + 5])] = out.get(tuple(w[i : i + 5]), 0) + 1
    return out


def closure(n, pairs):
    root = list(range(n))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in pairs:
        a, b = sorted((find(a), find(b)))
        root[b] = a
    return [find(x) for x in range(n)]


def test_similarity_and_estimate():
    r = random.Random(4)
    for _ in range(20):
        a = {i: r.randrange(1, 5) for i in r.sample(range(40), 25)}
        b = {i: a.get(i, r.randrange(1, 5)) if r.random() < 0.8 else r.randrange(1, 5) for i in r.sample(range(40), 25)}
        arrays = lambda s: (np.array(sorted(s), np.uint64), np.array([s[k] for k in sorted(s)]))
        assert near_dups.probability_jaccard(arrays(a), arrays(b)) == pytest.approx(slow_similarity(a, b))
    agree = expected = 0
    for i in range(40):
        a = {r.getrandbits(63): r.randrange(1, 4) for _ in range(120)}
        b = {k: v for k, v in a.items() if r.random() < 0.9} | {r.getrandbits(63): 2 for _ in range(10)}
        doc = np.array([0] * len(a) + [1] * len(b))
        s = near_dups.signatures(doc, np.array([*a, *b], np.uint64), np.array([*a.values(), *b.values()]), 2)
        agree += (s[0] == s[1]).mean() / 40
        expected += slow_similarity(a, b) / 40
    assert abs(agree - expected) < 0.03


def test_classes_match_brute_force(spark):
    r = random.Random(9)
    text = lambda n: [r.choice("abcdefghijklmnopqrstuvwxyz") + r.choice("xyz") for _ in range(n)]
    docs = []
    for g in range(12):
        base = text(r.randrange(30, 120))
        for _ in range(r.randrange(1, 9)):
            t = list(base)
            for _ in range(r.randrange(0, 5)):
                t[r.randrange(len(t))] = "new" + str(r.randrange(1000))
            docs.append(" ".join(t))
    docs += [docs[0], docs[0].upper() + "!", None, "", "a b", "A, b", "...", docs[3]]
    df = spark.createDataFrame([(i, t, "c", b"n") for i, t in enumerate(docs)], "doc_id long, text string, class string, node binary").repartition(3)
    sets = [counted(t) for t in docs]
    pairs = [(i, j) for i in range(len(docs)) for j in range(i) if sets[i] and sets[j] and slow_similarity(sets[i], sets[j]) >= 0.8]
    want = closure(len(docs), pairs)
    got = {x.doc_id: x.class_id for x in near_dups.classes(df).collect()}
    assert [got[i] for i in range(len(docs))] == want
    kept = near_dups.deduplicated(df.unionByName(df.filter("doc_id = 0"))).collect()
    assert sorted(x.doc_id for x in kept) == sorted(set(want)) and kept[0].asDict().keys() == set(df.columns)
    assert near_dups.classes(df.limit(0)).count() == 0


def test_blocks_join_what_the_star_misses(spark, monkeypatch):
    monkeypatch.setattr(near_dups, "BLOCK", 2)
    r = random.Random(2)
    base = [f"w{i}" for i in range(100)]
    docs = []
    for i in range(30):  # a chain: neighbours are similar, ends are not
        base[(7 * i) % 100] = f"x{i}"
        docs.append(" ".join(base))
    sets = [counted(t) for t in docs]
    want = closure(30, [(i, j) for i in range(30) for j in range(i) if slow_similarity(sets[i], sets[j]) >= 0.8])
    got = {x.doc_id: x.class_id for x in near_dups.classes(spark.createDataFrame(list(enumerate(docs)), "doc_id long, text string")).collect()}
    assert [got[i] for i in range(30)] == want
    assert r


def test_large_class_stays_linear(spark, monkeypatch):
    monkeypatch.setattr(near_dups, "BLOCK", 4)
    member = lambda i, name: (1, 2, bytes([i]), name, b"", "", b"a", 25, 1)
    rows = [member(i, b"a") for i in range(100)] + [member(100 + i, b"b") for i in range(3)]
    df = spark.createDataFrame(rows, "band int, bucket long, node binary, class binary, signature binary, text string, major binary, major_blocks long, rest_blocks long")
    dealt = near_dups._dealt(df)
    assert dealt.count() == 100 + 3 * 25 + 3  # and not 103 * 26
    met = {}
    for r in dealt.collect():
        met.setdefault((r.kind, r.i, r.j), []).append(r)
    pairs = {(x.node, y.node) for (kind, i, j), rs in met.items() for x in rs for y in rs if x.node < y.node and (x.side != y.side or (kind and i == j))}
    assert len(pairs) == 100 * 3 + 3


def test_recall_on_all_documents(spark):
    """Links of all pairs at 0.8 and more, found through every shingle that two documents share."""
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet").select("doc_id", "text")
    got = {r.doc_id: r.class_id for r in near_dups.classes(docs).collect()}
    first, texts = {}, []
    for r in sorted(docs.collect(), key=lambda r: r.doc_id):
        words = b" ".join(decontaminate.words_of((r.text or "").encode()))
        if words and words not in first:
            first[words] = r.doc_id
            texts.append((r.doc_id, words))
    sets = [near_dups._sets(w) for _, w in texts]
    owner = np.repeat(np.arange(len(sets)), [len(v) for v, _ in sets])
    value, share = np.concatenate([v for v, _ in sets]), np.concatenate([w / w.sum() for _, w in sets])
    order = np.argsort(value, kind="stable")
    owner, value, share = owner[order], value[order], share[order]
    links = found = 0
    for i, (values, weight) in enumerate(sets):
        low, high = np.searchsorted(value, values, "left"), np.searchsorted(value, values, "right")
        at = np.repeat(low - np.concatenate(([0], np.cumsum(high - low)[:-1])), high - low) + np.arange((high - low).sum())
        # No pair is more similar than the sum of the lesser shares of what it has in common.
        bound = np.bincount(owner[at], np.minimum(share[at], np.repeat(weight / weight.sum(), high - low)), len(sets))
        for j in np.flatnonzero(bound[:i] >= 0.8 - 1e-9).tolist():
            if near_dups.probability_jaccard(sets[i], sets[j]) >= 0.8:
                links += 1
                found += got[texts[i][0]] == got[texts[j][0]]
    assert links > 50 and found / links >= 0.99


@pytest.mark.parametrize("cell,block", [(256, 1024), (16, 8)])
def test_vectors_match_brute_force(spark, monkeypatch, cell, block):
    monkeypatch.setattr(vector_links, "CELL", cell)
    monkeypatch.setattr(vector_links, "BLOCK", block)
    rng = np.random.default_rng(7)
    base = rng.standard_normal((250, 24))
    near = base[:60] + 0.25 * rng.standard_normal((60, 24))
    x = np.concatenate([base, near, np.repeat(base[:3], 20, axis=0) + 0.05 * rng.standard_normal((60, 24)), base[:5], 3 * base[5:9]]).astype(np.float32)
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    odd = [(1000, None), (1001, [0.0] * 24), (1002, [float("nan")] + [1.0] * 23), (1003, [None] + [1.0] * 23), (1004, []), (1005, [1.0, 2.0]), (1006, [2.0, 4.0]), (1007, [float("inf")] * 24), (None, rows[0][1])]
    df = spark.createDataFrame([(*r, 0, 1) for r in rows + odd], "vec_id long, embedding array<float>, label int, h int")
    got = {r.vec_id: r for r in vector_links.link_vectors(df).collect()}
    assert len(got) == len(rows) + len(odd)
    every = np.concatenate([x, x[:1]])  # the row without vec_id equals row 0 and links like it
    unit = every.astype(float) / np.linalg.norm(every.astype(float), axis=1, keepdims=True)
    linked = unit @ unit.T >= 0.9
    np.fill_diagonal(linked, False)
    root = closure(len(every), zip(*np.nonzero(linked)))
    n = np.array([got[i].n_links for i in [*range(len(x)), None]])
    assert (n <= linked.sum(1)).all() and n.sum() >= 0.99 * linked.sum()
    # A link that is missed splits a component at most, it never joins two.
    component = [got[i].component_id for i in range(len(x))]
    assert all(root[c] == root[i] for i, c in enumerate(component))
    assert sum(c == r for c, r in zip(component, root)) >= (len(x) if (n == linked.sum(1)).all() else 0.97 * len(x))
    assert all(got[i].kept == (got[i].component_id == i) for i in range(len(x)))
    assert [got[i].n_links for i in range(1000, 1008)] == [0, 0, 0, 0, 0, 1, 1, 0] and got[1006].component_id == 1005
    assert got[None].n_links == linked[-1].sum() and got[None].component_id == root[-1] and not got[None].kept
    assert vector_links.link_vectors(df.limit(0)).count() == 0


def test_vectors_recall_on_the_small_check_table(spark):
    table = spark.read.parquet("/root/testdata/check_s/embeddings.parquet")
    rows = sorted((r.vec_id, r.embedding) for r in table.collect() if r.embedding is not None and r.vec_id is not None)
    x = np.array([v for _, v in rows], np.float64)
    assert np.isfinite(x).all() and x.any(axis=1).all()
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    want = np.concatenate([(unit[a : a + 1024] @ unit.T >= 0.9).sum(axis=1) - 1 for a in range(0, len(x), 1024)])
    got = {r.vec_id: r.n_links for r in vector_links.link_vectors(table).collect()}
    found = np.array([got[i] for i, _ in rows])
    assert want.sum() > 1000 and (found <= want).all() and found.sum() >= 0.99 * want.sum()

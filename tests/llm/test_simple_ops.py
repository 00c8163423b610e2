import random
from pathlib import Path
from zlib import crc32

import duckdb
import numpy as np
import pytest

from relanom.llm import decontaminate, packing, queries, url_rules

SF = "/root/testdata/sf0.01"


def against_sql(spark, name, sf=SF):
    con = duckdb.connect()
    for p in Path(sf).glob("*.parquet"):
        con.execute(f"CREATE VIEW {p.stem} AS SELECT * FROM '{p}'")
    want = con.execute(queries.ORACLES[name]).df()
    got = queries.QUERIES[name](spark, sf).toPandas()
    assert sorted(got.columns) == sorted(want.columns)
    rows = lambda df: sorted(map(str, df[sorted(df.columns)].astype(object).where(df.notna(), None).values.tolist()))
    assert rows(got) == rows(want)
    return got


def test_url_rules_match_sql(spark):
    against_sql(spark, "op5_url_rules")


def test_url_rules_nested(spark):
    rules = [("com", "/", "allow"), ("a.com", "/x", "block"), ("b.a.com", "/x/y", "allow"), ("a.com", "/x", "allow"), ("c-d.com", "/", "block"), ("c.com", "/", "block")]
    urls = ["http://A.com/x", "http://q.a.com/xz?u", "http://b.a.com/x/y#", "http://ba.com/x", "http://c-d.com/", "http://x.c.com/a", None, "", "a.com/x", "http://com/", "http://a.com", "https://u@net/x"] * 2
    df = spark.createDataFrame([(i if i else None, u, "h") for i, u in enumerate(urls)], "page_id long, url string, host string")
    got = url_rules.judge(df, url_rules.rule_table(spark, rules), "allow", 3).collect()

    def one(u):
        if not u or "://" not in u:
            return "", "", None, "allow"
        rest = u.split("://", 1)[1]
        host = rest.split("/")[0].split("?")[0].split("#")[0].lower()
        path = rest[len(host) :].split("?")[0].split("#")[0]
        fits = [(len(h + p), h + p, v) for h, p, v in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
        return (host, path, *(max(fits)[1:] if fits else (None, "allow")))

    assert sorted(map(str, (tuple(r)[1:] for r in got))) == sorted(map(str, map(one, urls)))
    assert url_rules.judge(df.limit(0), url_rules.rule_table(spark, rules)).count() == 0


def test_decontamination_matches_sql(spark):
    got = against_sql(spark, "op2_winnowing")
    assert got.contaminated.sum() > 10


@pytest.mark.parametrize("limit", [1 << 20, 0])
def test_decontamination_both_ways(spark, limit):
    r = random.Random(5)
    text = lambda n: " ".join(r.choice(["a", "B", "c", "é", "9", "dd"]) for _ in range(n))
    items = [(i, text(r.randrange(1, 30))) for i in range(25)] + [(50, None), (None, text(12)), (51, ""), (52, "z y x")]
    docs = [(i, text(r.randrange(0, 80)) + r.choice(["", "!! " + items[i % 25][1].replace(" ", "-") + " ?"])) for i in range(60)] + [(61, None), (62, "Z, y; X"), (None, items[1][1]), (3, text(9)), (63, "")]
    got = decontaminate.contamination(spark.createDataFrame([(*d, 1) for d in docs], "doc_id long, text string, item_id int"), spark.createDataFrame(items, "item_id long, text string"), 10, limit).collect()

    def one(t):
        w = decontaminate.words_of((t or "").encode())
        hit, found = set(), set()
        for item, x in items:
            v = decontaminate.words_of((x or "").encode())
            n = min(10, len(v))
            known = {tuple(v[i : i + n]) for i in range(len(v) - n + 1)} if n and item is not None else set()
            for i in range(len(w) - n + 1):
                if tuple(w[i : i + n]) in known:
                    hit.update(range(i, i + n))
                    found.add(item)
        return len(w), hit, found

    assert sorted(map(str, map(tuple, got))) == sorted(str(decontaminate._result(d, *one(t))) for d, t in docs)
    empty = spark.createDataFrame([], "item_id long, text string")
    assert decontaminate.contamination(spark.createDataFrame(docs, "doc_id long, text string"), empty, 10, limit).filter("contaminated").count() == 0


def test_packing_round_trip(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(400)
    odd = spark.createDataFrame([(9001, None), (9002, ""), (9003, "a<|endoftext|>b"), (9003, "a<|endoftext|>b"), (None, "x " * 3000)], "doc_id long, text string")
    docs = docs.select("doc_id", "text").unionByName(odd)
    rows = packing.pack(docs, with_ids=True).collect()
    encode = packing.encoder(packing.default_paths()[0], None)
    want = sorted((str(d.doc_id), [*encode(d.text or ""), 0]) for d in docs.collect())
    whole = {}
    for r in sorted(rows, key=lambda r: r.start):
        assert crc32(np.asarray(r.ids, "<u4").tobytes()) == r.ids_crc32 and len(r.ids) == r.length
        whole.setdefault((str(r.doc_id), r.doc_tokens), []).extend(r.ids)
    assert sum(len(x) for x in whole.values()) == sum(len(x) for _, x in want)
    assert all([ids for d, ids in want if d == k[0]][0] == v[: k[1]] for k, v in whole.items())
    by = {}
    for r in rows:
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for s in by.values():
        at = 0
        for o, n in sorted(s):
            assert o == at
            at += n
        assert at <= 1024
    assert sorted(by) == list(range(len(by)))
    assert sum(r.length for r in rows) / (1024 * len(by)) > 0.98
    assert packing.pack(docs.limit(0)).count() == 0


def test_best_fill_is_optimal():
    r = random.Random(1)
    for _ in range(60):
        counts = {r.randrange(1, 40): r.randrange(1, 4) for _ in range(5)}
        room = r.randrange(1, 90)
        chosen = packing.best_fill(counts, room)
        sums = {0}
        for k, n in counts.items():
            sums |= {s + k * i for s in sums for i in range(n + 1)}
        assert all(chosen[k] <= counts[k] for k in chosen)
        assert sum(k * n for k, n in chosen.items()) == max(s for s in sums if s <= room)


def test_quick_ids_equal_the_named_tokenizer(spark):
    """Every text of sf0.1 and texts of all scripts, long runs and odd signs."""
    from tokenizers import Tokenizer

    slow = Tokenizer.from_file(packing.default_paths()[0])
    quick = packing.encoder(*packing.default_paths())
    r = random.Random(8)
    blocks = [(0x20, 0x7F), (0xA0, 0x180), (0x370, 0x400), (0x400, 0x500), (0x590, 0x700), (0x900, 0xA00), (0xE00, 0xE80), (0x1100, 0x1200), (0x2000, 0x2070), (0x3040, 0x3100), (0x4E00, 0x9FFF), (0xAC00, 0xD7A3), (0xFE00, 0xFE10), (0x1F300, 0x1F700), (0x20000, 0x2A000), (0, 0x20)]
    odd = ["".join(chr(r.randrange(*r.choice(blocks))) for _ in range(r.randrange(1, 200))) for _ in range(2000)]
    odd += [c * n for c in " a1\n\t\u00a0é中🙂'-" for n in (1, 2, 7, 999, 20_000)] + ["I'll we'VE 'S  x", " \n \n  x", "12345678901234567890", "\r\n" * 50 + " x", "a\u0301\u200d\ufe0f", "\ufeffx", "<|endoftext|>", "x<|endoftext|> y"]
    texts = odd + [t.text or "" for t in spark.read.parquet("/root/testdata/sf0.1/documents.parquet").select("text").collect()]
    for at in range(0, len(texts), 500):
        some = texts[at : at + 500]
        for text, want in zip(some, slow.encode_batch(some, add_special_tokens=False)):
            assert list(quick(text)) == want.ids, text[:80]


def test_plan_fills_as_a_planner_without_repeats():
    r = random.Random(4)
    for _ in range(15):
        histogram = {r.randrange(1, 60): r.randrange(1, 30) for _ in range(r.randrange(1, 14))}
        rows = packing.plan(histogram, 60)
        placed, fills = {}, {}
        for length, low, high, per, first, base in rows:
            placed[length] = placed.get(length, 0) + high - low
            for k in range((high - low) // per):
                fills[first + k] = fills.get(first + k, 0) + per * length
        assert placed == histogram and max(fills.values()) <= 60 and sorted(fills) == list(range(len(fills)))
        left, slow = dict(histogram), []
        while left:
            longest = max(left)
            left[longest] -= 1
            sums, some = {0: {}}, {k: v for k, v in left.items() if v}
            for k, n in sorted(some.items(), reverse=True):
                for s, chosen in list(sums.items()):
                    for i in range(1, n + 1):
                        if s + k * i <= 60 - longest:
                            sums.setdefault(s + k * i, chosen | {k: i})
            for k, n in sums[max(sums)].items():
                left[k] -= n
            slow.append(longest + max(sums))
            left = {k: v for k, v in left.items() if v}
        assert len(fills) <= len(slow) + 1 and sum(fills.values()) == sum(slow)


def test_packing_and_decontamination_of_long_texts_and_clashing_columns(spark):
    long_text = "Zeta 7 beta, " * 150_000 + "a b c d e f g h i j k"
    rows = [(1, long_text, 5, 6, 7), (2, "x", 5, 6, 7)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, length long, slice int, start long")
    packed = packing.pack(docs).collect()
    assert sum(r.length for r in packed if r.doc_id == 1) == len(packing.encoder(*packing.default_paths())(long_text)) + 1
    items = spark.createDataFrame([(9, "B c d e f g h i j k l")], "item_id long, text string")
    for limit in (1 << 20, 0):
        got = {r.doc_id: r for r in decontaminate.contamination(docs.withColumnRenamed("slice", "th").withColumnRenamed("start", "print"), items, 10, limit).collect()}
        assert got[1].n_words == 450_011 and got[1].n_hit == 10 and got[2].n_hit == 0
        assert decontaminate.contamination(docs.limit(0), items, 10, limit).count() == 0

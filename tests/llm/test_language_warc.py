import base64
import gzip
import html
import random
import re
import time
from hashlib import sha1

import numpy as np
import pytest
from pyspark.sql import functions as F

from relanom.llm import components, language_id, warc

SF = "/root/testdata/sf0.01"


def test_automaton_and_phrases():
    text = "abracadabra banana"
    parser = language_id.CrossParser({"x": text, "y": "zzzz yyyy"})

    def count(sample, t):
        n, i = 0, 0
        while i < len(t):
            j = i
            while j < len(t) and t[i : j + 1] in sample:
                j += 1
            n, i = n + 1, max(j, i + 1)
        return n

    texts = ["abra nana", "cadab zz", "qqq", "yy zz aba", ""]
    got = parser.phrases(texts)
    assert got.tolist() == [[count(s, t) for t in texts] for s in (text, "zzzz yyyy")]


def test_held_out_accuracy(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    got = language_id.identify(docs, keep=["lang"])
    assert got.count() == docs.count()
    right = got.filter("held_out and lang is not null and lang_pred <> 'und'").agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int"))).first()[0]
    assert right > 0.97


def test_no_cap_on_letters_or_languages(spark):
    # 2000 letters in one sample, some beyond U+FFFF, and 100 languages.
    letters = [chr(0x4E00 + i) for i in range(1500)] + [chr(0x20000 + i) for i in range(500)]
    r = random.Random(3)
    samples = {f"l{k:03}": "".join(r.choices("abcdefghijklmnop", k=300)) for k in range(100)} | {"zh": "".join(letters), "rev": "".join(reversed(letters))}
    parser = language_id.CrossParser(samples)
    found = parser.predict(["".join(letters[700:900]), "".join(reversed(letters[1600:1900])), samples["l042"][40:160]])
    assert [k for k, _ in found] == ["zh", "rev", "l042"] and all(score > 0.9 for _, score in found)
    df = spark.createDataFrame([(i, t, k) for i, (k, t) in enumerate(samples.items())], "doc_id long, text string, lang string")
    got = language_id.identify(df)
    assert got.count() == 102 and got.filter("not held_out").select("lang_pred").distinct().count() > 60


def test_predictions_match_brute_force():
    r = random.Random(5)
    samples = {k: "".join(r.choices(a, k=400)) for k, a in (("x", "abc "), ("y", "abd "), ("z", "αβ "))}
    texts = ["".join(r.choices("abcdαβ 1", k=r.randrange(1, 300))) for _ in range(40)]
    parser = language_id.CrossParser(samples)
    for text, (lang, score) in zip(texts, parser.predict(texts)):
        if not any(ch.isalpha() for ch in text):
            assert (lang, score) == ("und", 0.0)
            continue
        cost = {}
        for k, sample in samples.items():
            clean, rest, n = sample.replace("1", " "), text.replace("1", " "), 0
            while rest:
                size = next((i for i in range(len(rest), 0, -1) if rest[:i] in clean), 1)
                rest, n = rest[size:], n + 1
            cost[k] = n * np.log2(len(sample))
        ranked = sorted(cost.items(), key=lambda x: (x[1], x[0]))
        assert lang == ranked[0][0] and score == pytest.approx(1 - ranked[0][1] / ranked[1][1])


def test_language_edges(spark):
    rows = [(1, None, "en"), (2, "", "en"), (3, "123 ?!", None), (4, "x" * 3000, "en"), (None, "hello", "en"), (5, "ß" * 10, None)]
    df = spark.createDataFrame([(*r, 0.5) for r in rows], "doc_id long, text string, lang string, score double")
    got = {r.doc_id: r for r in language_id.identify(df).collect()}
    assert len(got) == 6 and got[1].lang_pred == got[2].lang_pred == got[3].lang_pred == "und"
    assert all(0 <= r.score <= 1 for r in got.values()) and got[None].held_out is False
    assert language_id.identify(df.limit(0)).count() == 0


def test_warc_round_trip(spark, tmp_path):
    pages = spark.read.parquet(f"{SF}/pages.parquet").unionByName(spark.createDataFrame([(-1, None, None), (-2, "http://a/", "")], "page_id long, url string, html string"))
    rows = warc.derive(warc.responses(pages)).collect()
    assert len(rows) == 2 * pages.count()
    source = {r.page_id: r for r in warc.responses(pages).collect()}
    for r in rows:
        ((fields, block),) = warc.parse_records(warc.record_bytes(r.header, r.block))
        assert fields["WARC-Refers-To"] == source[r.page_id].record_id == r.refers_to
        assert block.decode() == r.block and int(fields["Content-Length"]) == len(block)
        assert fields["WARC-Block-Digest"] == "sha1:" + base64.b32encode(sha1(block).digest()).decode()
        assert r.source_digest == warc.digest((source[r.page_id].payload or "").encode())
        if r.warc_type == "metadata" and source[r.page_id].payload:
            assert "source-header: HTTP/1.1 200 OK" in r.block
    assert len({r.record_id for r in rows}) == len(rows)
    head = "HTTP/1.1 200 OK\r\nX: y"
    block = f"{head}\r\n\r\n<p>Hi <b>there</b></p>".encode()
    record = warc.header_block([("WARC-Type", "response"), ("WARC-Record-ID", "<urn:x>"), ("WARC-Target-URI", "http://a/"), ("WARC-Date", "2020-01-01T00:00:00Z"), ("Content-Length", str(len(block)))]).encode() + block + b"\r\n\r\n"
    (tmp_path / "a.warc.gz").write_bytes(gzip.compress(record * 2))
    read = warc.derive(warc.read_responses(spark, str(tmp_path / "a.warc.gz"))).collect()
    assert [r.block for r in read if r.warc_type == "conversion"] == ["Hi there"] * 2
    assert all(r.refers_to == "<urn:x>" and "WARC-Refers-To-Date: 2020-01-01T00:00:00Z" in r.header for r in read)


def old_text(page):
    """The same reading by regular expressions, as a second opinion on closed pages."""
    page = re.sub(r"<!--.*?-->|<(script|style|noscript|template)\b[^>]*>.*?</\1\s*>", " ", page, flags=re.S | re.I)
    page = re.sub(r"</?(?:p|div|br|li|ul|ol|tr|table|h[1-6]|section|article|nav|header|footer|title|head|body|blockquote|pre|hr|td|th)\b[^>]*>", "\n", page, flags=re.I)
    lines = (re.sub(r"[ \t\r\f\v\xa0]+", " ", line).strip() for line in html.unescape(re.sub(r"<[^>]*>", " ", page)).split("\n"))
    return "\n".join(line for line in lines if line)


def test_every_page_and_derivative_match_a_second_reading(spark):
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    texts = {r.page_id: r.html or "" for r in pages.collect()}
    rows = warc.derive(warc.responses(pages.withColumn("payload", F.lit(1)).withColumn("date", F.lit(2)))).collect()
    assert len(rows) == 2 * len(texts)
    for r in rows:
        page = texts[r.page_id]
        assert r.source_digest == "sha1:" + base64.b32encode(sha1(page.encode()).digest()).decode()
        if r.warc_type == "conversion":
            assert r.block == old_text(page)
        else:
            links = re.findall(r"""<a\b[^>]*?\bhref\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+))""", re.sub(r"<!--.*?-->", " ", page, flags=re.S), re.I)
            assert [line for line in r.block.split("\r\n") if line.startswith("outlink")] == [f"outlink: {' '.join(html.unescape(''.join(x)).split())} L a/@href" for x in links]
    assert warc.derive(warc.responses(pages.limit(0))).count() == 0


def test_hostile_pages_take_linear_time(spark):
    for page in ("<script>" * 60_000, "<!-- x " * 60_000, "<a " * 150_000, "<a href='" * 50_000, "<title>" * 60_000, "<a b>" * 100_000, "<" * 400_000):
        start = time.process_time()
        warc.plain_text(page), warc.metadata_fields(page, "")
        assert time.process_time() - start < 3
    long_page = "<p>" + "word " * 600_000 + "</p>"
    rows = warc.derive(warc.responses(spark.createDataFrame([(1, "u", long_page)], "page_id long, url string, html string"))).collect()
    assert max(r.content_length for r in rows) == 3_000_000 - 1


def test_targets_cannot_add_header_lines(spark):
    df = spark.createDataFrame([(1, "http://a/\r\nX-Injected: 1", "<p>x</p>")], "page_id long, url string, html string")
    for r in warc.derive(warc.responses(df)).collect():
        ((fields, _),) = warc.parse_records(warc.record_bytes(r.header, r.block))
        assert "X-Injected" not in fields and fields["WARC-Target-URI"] == "http://a/%0D%0AX-Injected:%201" and r.target_uri == "http://a/\r\nX-Injected: 1"


def test_reading_codings_charsets_and_cut_files(spark, tmp_path):
    def record(head, body):
        block = ("HTTP/1.1 200 OK\r\n" + head).encode() + b"\r\n\r\n" + body
        return warc.header_block([("WARC-Type", "response"), ("WARC-Record-ID", "<urn:x>"), ("Content-Length", str(len(block)))]).encode() + block + b"\r\n\r\n"

    whole = record("Content-Encoding: gzip", gzip.compress("<p>é</p>".encode())) + record("Content-Type: text/html; charset=latin-1", "<p>ü</p>".encode("latin-1")) + record("Content-Type: text/html; charset=nonsense", b"<p>z</p>")
    (tmp_path / "a.warc").write_bytes(whole + record("X: y", b"cut")[:-20])
    (tmp_path / "b.warc.gz").write_bytes(gzip.compress(whole)[:-12])
    read = warc.read_responses(spark, str(tmp_path))
    assert [r.payload for r in read.collect()].count("<p>é</p>") == 2 and {"<p>ü</p>", "<p>z</p>"} <= {r.payload for r in read.collect()} and read.filter("payload like '%cut%'").count() == 0


def test_plain_text():
    assert warc.plain_text("<head><title>T &amp; U</title><style>p{}</style><script>var t='</p>';</script></head><p>a<b>b</b>  c</p><!-- x --><div>d</div>") == "T & U\na b c\nd"


@pytest.mark.parametrize("seed", [1, 2])
def test_components(spark, seed):
    r = random.Random(seed)
    edges = [(r.randrange(60), r.randrange(60)) for _ in range(40)] + [(100 + i, 101 + i) for i in range(12)] + [(7, 7)]
    root = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for a, b in edges:
        if a != b:
            a, b = sorted((find(a), find(b)))
            root[b] = a
    got = {x.node: x.root for x in components.components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == {x: find(x) for e in edges if e[0] != e[1] for x in e}


def test_copies_do_not_thin_the_sample(spark):
    # 60 distinct texts in 120,000 rows: a draw by rows expects less than one of them.
    texts = spark.range(60).select(F.col("id").alias("k"), F.array_join(F.transform(F.sequence(F.lit(1), F.lit(60)), lambda i: F.sha2(F.concat_ws(":", F.col("id"), i), 256)), " ").alias("text"))
    copies = texts.crossJoin(spark.range(2000)).select(F.lit("xx").alias("lang"), "text")
    few = spark.createDataFrame([("yy", f"short line {i}") for i in range(5)], "lang string, text string")
    got = language_id.labelled_sample(copies.unionByName(few), 24_000, 1_000)
    assert len(got["xx"]) == 24_000 and len(set(got["xx"].split(" "))) > 300
    assert sorted(w for w in got["yy"].split() if w.isdigit()) == list("01234")


def test_short_texts_fill_the_sample(spark):
    # 144 passages of 41 characters would be a quarter of the bound.
    lines = spark.range(3000).select(F.lit("xx").alias("lang"), F.substring(F.sha2(F.col("id").cast("string"), 256), 1, 40).alias("text"))
    assert len(language_id.labelled_sample(lines, 24_000, 1_000)["xx"]) == 24_000

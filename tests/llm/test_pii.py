import re

import regex
from pyspark.sql import functions as F

from relanom.llm import pii

SF = "/root/testdata/sf0.01"
KEY = "a key for tests"


def luhn(s):
    d = [int(c) for c in s if c.isdigit()][::-1]
    return sum(d[::2]) + sum(sum(divmod(2 * x, 10)) for x in d[1::2])


def test_kinds_and_formats(spark):
    rows = [
        (1, "mail Jane.Doe42@mail8.example.com, or éz@ex-a.org."),
        (2, "call +1 (988) 555-2485 or 988-555-2485; JANE.DOE42@mail8.example.com"),
        (3, "card 4041894974608795, 4041 8949 7460 8795. ip 42.144.35.254 and 192.168.1.7."),
        (4, "Mr. John Smith met Mrs. Smith and Frau Müller; Госпожа Иванова came"),
        (5, 'token = "0641917ea4e9feb9cda83477b57ac2654884f485" password=e3b3ed3cc8548923d6 x'),
        (6, "ssn 123-45-6789 and DE44 5001 0517 5407 3249 31"),
        (11, "It costs 3 tokens; TOKEN: 'abcdefgh12' api_key=ZZZZyyyy9"),
        (7, "version 1.2.3.4.5 of 2024-01-02 costs 1000000 at 10:30, a@b, 12345"),
        (8, None), (9, ""), (None, "+1 (456) 555-2186 4404 +1 (456) 555-2186"), (10, "42.144.35.254"), (10, "42.144.35.254"),
    ]
    df = spark.createDataFrame([(*r, "x", 7) for r in rows], "doc_id long, text string, kind string, attempt int")
    got = pii.replace(df, KEY, keep=["kind"]).collect()
    assert len(got) == len(rows)
    out = {(r.doc_id): r for r in got}
    shape = lambda t: re.sub(r"[a-z]", "a", re.sub(r"[A-Z]", "A", re.sub(r"\d", "9", t)))
    for i in (1, 2, 5):
        assert out[i].text != rows[i - 1][1] and len(out[i].text) == len(rows[i - 1][1])
    assert shape(out[2].text.split(";")[0]) == shape("call +1 (988) 555-2485 or 988-555-2485")
    phones = re.findall(r"[\d(][\d() -]{10,}\d", out[2].text.split("+1 ")[1].split(";")[0])
    assert len({re.sub(r"\D", "", p) for p in phones}) == 1
    first, again = re.search(r"mail (\S+),", out[1].text)[1], out[2].text.split("; ")[1]
    assert first.lower() == again.lower() and first.endswith(".com") and first != "Jane.Doe42@mail8.example.com"
    cards = re.findall(r"\d{4} ?\d{4} ?\d{4} ?\d{4}", out[3].text)
    assert cards[0] == cards[1].replace(" ", "") and luhn(cards[0]) % 10 == 0 and cards[0] != "4041894974608795"
    ips = re.findall(r"\d+\.\d+\.\d+\.\d+", out[3].text)
    assert ips[1].startswith("192.168.") and ips[1] != "192.168.1.7" and ips[0] == out[10].text != "42.144.35.254"
    man, woman = re.match(r"Mr\. (\w+ \w+) met Mrs\. (\w+) and Frau \w+; Госпожа ([а-яА-Я]+) came", out[4].text).groups()[:2]
    assert man.split()[1] == woman and man.split()[0][-1] in "on" and "Smith" not in out[4].text
    assert out[5].text.startswith('token = "') and "0641917e" not in out[5].text and "e3b3ed3cc" not in out[5].text
    assert "123-45-6789" not in out[6].text and re.search(r"\d{3}-\d{2}-\d{4}", out[6].text) and "5001 0517" not in out[6].text
    assert out[7].text == rows[7][1] and out[7].n_entities == 0
    assert re.fullmatch(r"It costs 3 tokens; TOKEN: '[a-z]{8}\d\d' api_key=[A-Z]{4}[a-z]{4}\d", out[11].text) and "abcdefgh" not in out[11].text
    assert out[8].text is None and out[9].text == "" and out[None].n_entities == 2
    assert pii.replace(df.limit(0), KEY).count() == 0


def test_every_document_by_brute_force(spark):
    """Each text is cut at the pattern by another engine: gaps stay, what replaces a mention is a function of its entity, one to one, of its kind and never real."""
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    got = {r.doc_id: r for r in pii.replace(docs, KEY).collect()}
    pattern, made, real = regex.compile(pii.PATTERN), {}, set()
    kinds = {k: regex.compile(p) for k, p in pii.PATTERNS.items()}
    secret = regex.compile("^" + pii._SECRET)

    def entity(mention):
        kind = "secret" if secret.match(mention) else next(k for k, p in kinds.items() if p.fullmatch(mention))
        digits = re.sub("[^0-9]", "", mention)
        return kind, {"card": digits, "ssn": digits, "phone": digits[-10:], "email": mention.lower(), "secret": secret.sub("", mention)}.get(kind, mention)

    for r in docs.collect():
        old, new = r.text, got[r.doc_id].text
        found = list(pattern.finditer(old or ""))
        assert got[r.doc_id].n_entities == len(found)
        if not found:
            assert new == old
            continue
        assert len(new) == len(old) or any(entity(m[0])[0] in ("ip", "name") for m in found)
        at = shift = 0
        for m in found:
            assert old[at : m.start()] == new[at + shift : m.start() + shift]
            kind, name = entity(m[0])
            gap = old[m.end() : m.end() + 1]
            size = len(m[0]) if kind != "ip" else next(n for n in range(15, 6, -1) if kinds["ip"].fullmatch(new[m.start() + shift :][:n]) and new[m.start() + shift + n :][:1] == gap)
            other = new[m.start() + shift :][:size]
            assert entity(other)[0] == kind and made.setdefault((kind, name), entity(other)[1]) == entity(other)[1]
            real.add((kind, name))
            at, shift = m.end(), shift + size - len(m[0])
        assert old[at:] == new[at + shift :]
    assert len(made) > 500 and len({(k, v) for (k, _), v in made.items()}) == len(made) and not {(k, v) for (k, _), v in made.items()} & real


def test_names_keep_their_person_when_redrawn(spark, monkeypatch):
    plain = pii._draws

    def first_draws_are_zero(key, kind, name, attempt, size):
        return pii.F.transform(plain(key, kind, name, attempt, size), lambda x: pii.F.when(attempt == 0, pii.F.lit(0)).otherwise(x))

    monkeypatch.setattr(pii, "_draws", first_draws_are_zero)
    rows = [(1, "Mr. John Smith"), (2, "Mr. Smith"), (3, "Mrs. Jane Smith"), (4, "Mr. John Miller"), (5, "Mrs. Miller"), (6, "Mr. Jack Brown")]
    got = {r.doc_id: r.text.split() for r in pii.replace(spark.createDataFrame(rows, "doc_id long, text string"), KEY).collect()}
    assert got[1][2] == got[2][1] == got[3][2] != got[4][2] == got[5][1]
    assert got[1][1] == got[4][1] != got[6][1] and len({got[i][-1] for i in (1, 4, 6)}) == 3


def test_full_space_of_addresses(spark):
    every = spark.range(254 * 254).select("id", F.concat(F.lit("at 192.168."), (F.col("id") / 254 + 1).cast("int"), F.lit("."), F.col("id") % 254 + 1).alias("text")).withColumnRenamed("id", "doc_id")
    others = spark.createDataFrame([(-1, "at 10.1.2.3"), (-2, "at 44.5.6.7"), (-3, "x.y@a.org")], "doc_id long, text string")
    got = {r.doc_id: r.text for r in pii.replace(every.unionByName(others), KEY, rounds=2).collect()}
    old = {r.doc_id: r.text for r in every.collect()}
    assert len(set(got.values())) == 254 * 254 + 3 and all(got[i] != t and got[i].startswith("at 192.168.") for i, t in old.items())
    assert got[-1].startswith("at 10.") and got[-1] != "at 10.1.2.3"


def test_check_digits_and_ranges(spark):
    rows = [(i, f"iban DE44 5001 0517 5407 3249 {i:02} or DE44500105175407324{i:03}, GB29NWBK601613319268{i:02}; ssn 123-45-67{i:02}") for i in range(40)]
    value = lambda t: int("".join(str(int(c, 36)) for c in t[4:] + t[:4])) % 97
    for r in pii.replace(spark.createDataFrame(rows, "doc_id long, text string"), KEY).collect():
        ibans = [x.replace(" ", "") for x in re.findall(r"(?:DE|GB)\d\d[ A-Z0-9]+\d", r.text.split(";")[0].replace(" or ", ","))]
        assert len(ibans) >= 2 and all(value(x) == 1 for x in ibans), r.text
        area, group, serial = re.search(r"(\d{3})-(\d\d)-(\d{4})", r.text).groups()
        assert "000" < area < "666" and group != "00" and serial != "0000"


def test_collisions_are_redrawn(spark, monkeypatch):
    plain = pii._draws

    def first_draws_are_zero(key, kind, name, attempt, size):
        return pii.F.transform(plain(key, kind, name, attempt, size), lambda x: pii.F.when(attempt == 0, pii.F.lit(0)).otherwise(x))

    monkeypatch.setattr(pii, "_draws", first_draws_are_zero)
    texts = [f"call +1 (555) 555-{i:04d} now" for i in range(40)] + ["call 000-000-0000"]
    got = [r.text for r in pii.replace(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), KEY).collect()]
    assert len(set(got)) == len(texts) and not set(got) & set(texts)


def test_sift_keeps_secrets_in_any_case(spark):
    words = ["password", "passwd", "pwd", "secret", "token", "apikey", "api_key", "access_key"]
    cases = [str, str.upper, str.capitalize, str.swapcase, lambda w: w[0] + w[1:].capitalize(), lambda w: "".join(c.upper() if i % 2 else c for i, c in enumerate(w))]
    rows = [(i, f"{case(w)}{sep}correcthorsebattery") for i, (w, case, sep) in enumerate((w, c, s) for w in words for c in cases for s in (": ", "="))]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    got = {r.doc_id: r for r in pii.replace(df, KEY).collect()}
    assert len(got) == len(rows)
    for i, text in rows:
        assert got[i].n_entities == 1 and "correcthorsebattery" not in got[i].text, text
        assert got[i].text.startswith(text[: -len("correcthorsebattery")])
    # Every row that the pattern finds passes the sift; no keyword, no pass.
    assert df.filter(pii.maybe(df.text)).count() == len(rows)
    assert spark.createDataFrame([("key words: none",), ("a pwd here",)], "text string").filter(pii.maybe(F.col("text"))).count() == 0

"""Surrogates for personal data, in DataFrame functions only.

A text is split at one pattern for all entity kinds; each match is replaced, the gaps stay.
A mention names one entity, a titled name one for each of its words (given name, surname), so
a bare surname agrees with the full name.  A surrogate is drawn from a keyed hash of (kind,
canonical form, attempt): a mention's spelling does not matter and equal entities agree in all
documents.  It keeps the mention's format: digits stay digits, letters keep script and case,
separators stay; card numbers and IBANs get valid check digits, social security numbers valid
ranges, addresses keep private or public range, mail keeps its top-level domain, given names
keep the gender their title states.

Surrogates are checked over all rows: one that two entities share, or that some text really
holds, is drawn again with the next attempt.  Where that does not end because a format's space
is nearly full (all addresses of a /16, say), all entities of that format are mapped by a keyed
shift of each place instead: still distinct and never their own, but possibly another's real
value.  Only the entities that needed any of this form a table; it is joined to their
documents, by document, when it is not empty.

Null text stays null, text without an entity stays as it is.  Repeated rows get equal text.
"""

from __future__ import annotations

from secrets import token_hex

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from relanom.llm import scratch

_W = r"\p{L}\p{N}_"
_NAME = r"\p{Lu}\p{Ll}+(?:-\p{Lu}\p{Ll}+)?"
#: Titles with the gender they state.
TITLES = {"Mr": "m", "Mister": "m", "Sir": "m", "Herr": "m", "Monsieur": "m", "Señor": "m", "Mrs": "f", "Ms": "f", "Miss": "f", "Madam": "f", "Frau": "f", "Madame": "f", "Mme": "f", "Señora": "f", "Señorita": "f", "Господин": "m", "Госпожа": "f", "Κύριος": "m", "Κυρία": "f"}
_DOTTED = ["Mrs", "Mme", "Mr", "Ms"]
_TITLE = r"(?:(?:" + "|".join(_DOTTED) + r")\.?|" + "|".join(sorted(set(TITLES) - set(_DOTTED), key=len, reverse=True)) + ")"
_SECRET = r"""(?i:password|passwd|pwd|secret|token|api_?key|access_key)\s{0,3}[=:]\s{0,3}["']?"""
#: Kinds in order of precedence where two could start at one place.
PATTERNS = {
    "ip": rf"(?<!\.)(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){{3}}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?![{_W}]|\.\d)",
    "card": rf"(?<![.+-])(?:\d{{4}}[ -]?){{3}}\d{{1,7}}(?![{_W}]|[.-]\d)",
    "ssn": rf"(?<![.-])\d{{3}}-\d{{2}}-\d{{4}}(?![{_W}-])",
    "phone": rf"(?:\+\d{{1,3}}(?:[ .-]?\(?\d{{2,4}}\)?){{2,4}}|\(?\d{{3}}\)?[ .-]\d{{3}}[ .-]\d{{4}})(?![{_W}])",
    "iban": rf"[A-Z]{{2}}\d{{2}}(?: ?[A-Z0-9]{{4}}){{3,7}}(?: ?[A-Z0-9]{{1,3}})?(?![{_W}])",
    "name": rf"{_TITLE} {_NAME}(?: {_NAME}){{0,2}}",
    "email": rf"(?<![.%+-])[{_W}.%+-]{{1,64}}+@(?:[{_W}-]{{1,63}}\.)+\p{{L}}{{2,24}}",
}
#: All kinds at once: one look behind rules out the middles of words, one ahead picks the kinds that can start here.
PATTERN = (
    rf"{_SECRET}[A-Za-z0-9+/_=-]{{8,}}|(?<![{_W}])(?:(?=[\d+(])(?:{PATTERNS['ip']}|{PATTERNS['card']}|{PATTERNS['ssn']}|{PATTERNS['phone']})"
    rf"|(?=\p{{Lu}})(?:{PATTERNS['iban']}|{PATTERNS['name']})|{PATTERNS['email']})"
)
#: Every text that the pattern can match has a digit, an @, one of these or the start of a secret.
_SIGNS = [t + " " for t in TITLES] + [t + "." for t in _DOTTED]
#: Letters and digits by script and case.
_SCRIPTS = [
    "abcdefghijklmnopqrstuvwxyz",
    "ABCDEFGHIJKLMNOPQRSTUVWXYZ",
    "0123456789",
    "ßàáâãäåæçèéêëìíîïðñòóôõöøùúûüýþÿ",
    "ÀÁÂÃÄÅÆÇÈÉÊËÌÍÎÏÐÑÒÓÔÕÖØÙÚÛÜÝÞ",
    "αβγδεζηθικλμνξοπρστυφχψω",
    "ΑΒΓΔΕΖΗΘΙΚΛΜΝΞΟΠΡΣΤΥΦΧΨΩ",
    "абвгдежзийклмнопрстуфхцчшщъыьэюя",
    "АБВГДЕЖЗИЙКЛМНОПРСТУФХЦЧШЩЪЫЬЭЮЯ",
]
#: Syllables of invented names and their gendered ends, by script.
_SYLLABLES = {
    "latin": (["bar", "del", "fin", "gal", "hor", "jan", "kel", "lor", "mar", "nor", "pel", "ros", "sim", "tor", "val", "wen"], ["o", "on"], ["a", "ina"]),
    "cyrillic": (["бар", "вел", "гор", "дан", "зор", "кам", "лев", "мир", "нар", "пет", "рад", "сав", "тим", "фед", "хар", "яр"], ["ан", "ов"], ["ана", "ова"]),
    "greek": (["βαρ", "γελ", "δημ", "ζαν", "θεο", "καλ", "λαμ", "μαρ", "νικ", "παν", "ροδ", "σιμ", "τιμ", "φιλ", "χαρ", "ηλι"], ["ος", "ης"], ["α", "η"]),
}


def maybe(text: Column) -> Column:
    """Cheap test that no text with an entity fails; most texts do, and then the pattern never runs."""
    some = text.rlike("[0-9@]")
    for sign in _SIGNS:
        some = some | text.contains(sign)
    return some | ((text.contains("=") | text.contains(":")) & text.rlike(_SECRET))


def kind_of(mention: Column) -> Column:
    """Kind of a whole match, tried in the order of the pattern for all."""
    cases = [F.when(mention.rlike(f"^{_SECRET}"), F.lit("secret"))]
    return F.coalesce(*cases, *[F.when(mention.rlike(f"^(?:{p})$"), F.lit(k)) for k, p in PATTERNS.items()])


def canonical(mention: Column, kind: Column) -> Column:
    """What mentions of one entity have in common: digits of numbers, the national part of phones, case folded text."""
    digits = F.regexp_replace(mention, "[^0-9]", "")
    return (
        F.when(kind.isin("card", "ssn"), digits)
        .when(kind == "phone", F.when(F.length(digits) > 10, F.substring(digits, -10, 10)).otherwise(digits))
        .when(kind == "iban", F.regexp_replace(mention, " ", ""))
        .when(kind == "email", F.lower(mention))
        .when(kind == "secret", F.regexp_replace(mention, f"^{_SECRET}", ""))
        .otherwise(mention)
    )


def entities(mention: Column, kind: Column) -> Column:
    """Array of (kind, name) that a mention names: the words of a titled name one by one, else the whole."""
    entity = lambda k, name: F.struct(k.alias("kind"), name.alias("name"))
    plain = F.regexp_replace(F.regexp_extract(mention, f"^({_TITLE}) ", 1), r"\.$", "")
    given = F.when(plain.isin([t for t, g in TITLES.items() if g == "f"]), F.lit("given_f")).otherwise(F.lit("given_m"))
    words = F.split(F.regexp_replace(mention, f"^{_TITLE} ", ""), " ")
    of_words = F.transform(words, lambda word, i: entity(F.when(i == F.size(words) - 1, F.lit("surname")).otherwise(given), word))
    return F.when(kind == "name", of_words).otherwise(F.array(entity(kind, canonical(mention, kind))))


def _draws(key: str, kind: Column, name: Column, attempt: Column, size: Column | int) -> Column:
    """``size`` keyed numbers below 65536; a hash gives 32 of them."""
    size = size if isinstance(size, Column) else F.lit(size)
    seed = F.concat_ws("\u0001", F.lit(key), kind, name, attempt.cast("string"))
    blocks = F.transform(F.sequence(F.lit(0), (size / 32).cast("int")), lambda i: F.sha2(F.concat_ws("\u0001", seed, i.cast("string")), 512))
    return F.slice(F.transform(F.regexp_extract_all(F.array_join(blocks, ""), F.lit(".{4}"), F.lit(0)), lambda x: F.conv(x, 16, 10).cast("int")), F.lit(1), size)


def _characters(key: str, kind: Column, name: Column, attempt: Column, text: Column) -> Column:
    """Each letter or digit becomes another of its script and case; anything else stays."""

    def one(ch: Column, draw: Column) -> Column:
        cases = [F.when(F.instr(F.lit(letters), ch) > 0, F.substring(F.lit(letters), draw % len(letters) + 1, F.lit(1))) for letters in _SCRIPTS]
        return F.coalesce(*cases, ch)

    return F.array_join(F.zip_with(F.split(text, ""), _draws(key, kind, name, attempt, F.length(text)), one), "")


def _digits(key: str, kind: Column, name: Column, attempt: Column, size: Column) -> Column:
    return F.array_join(F.transform(_draws(key, kind, name, attempt, size), lambda x: (x % 10).cast("string")), "")


def _poured(new: Column, mention: Column, places: str) -> Column:
    """The mention's format with the last of its characters ``[places]`` replaced by those of ``new``; leading ones beyond them stay."""
    old = F.regexp_replace(mention, f"[^{places}]", "")
    new = F.concat(F.substring(old, F.lit(1), F.length(old) - F.length(new)), new)
    return F.array_join(F.zip_with(F.split(mention, f"[{places}]", -1), F.split(new, ""), lambda gap, d: F.concat(gap, F.coalesce(d, F.lit("")))), "")


def _with_check_digit(body: Column) -> Column:
    """``body`` and the digit that makes its Luhn sum a multiple of ten."""
    reversed_digits = F.reverse(F.split(body, ""))
    doubled = F.transform(reversed_digits, lambda c, i: F.when(i % 2 == 0, F.element_at(F.array(*map(F.lit, (0, 2, 4, 6, 8, 1, 3, 5, 7, 9))), c.cast("int") + 1)).otherwise(c.cast("int")))
    total = F.aggregate(doubled, F.lit(0), lambda a, x: a + x)
    return F.concat(body, F.pmod(-total, F.lit(10)).cast("string"))


def _with_iban_check(country: Column, account: Column) -> Column:
    """Country, the two digits that make the whole 1 modulo 97, and the account; letters count 10 to 35."""
    value = lambda ch: F.when(ch.rlike("[0-9]"), ch.cast("int")).otherwise(F.ascii(ch) - 55)
    rest = F.aggregate(F.split(F.concat(account, country, F.lit("00")), ""), F.lit(0), lambda a, ch: (a * F.when(ch.rlike("[0-9]"), 10).otherwise(100) + value(ch)) % 97)
    return F.concat(country, F.lpad((98 - rest).cast("string"), 2, "0"), account)


def _fixed_octets(name: Column) -> Column:
    """How many leading octets of an address stay: those of a private range."""
    return F.when(name.rlike(r"^(10|127)\."), 1).when(name.rlike(r"^(192\.168|172\.(1[6-9]|2\d|3[01])|169\.254)\."), 2).otherwise(0)


def _address(key: str, kind: Column, name: Column, attempt: Column) -> Column:
    # A public first octet is drawn from 11 to 126, none of which is private.
    drawn = F.transform(_draws(key, kind, name, attempt, 4), lambda x, i: F.when(i == 0, x % 116 + 11).otherwise(x % 254 + 1).cast("string"))
    keep = _fixed_octets(name)
    return F.array_join(F.concat(F.slice(F.split(name, r"\."), F.lit(1), keep), F.slice(drawn, keep + 1, 4 - keep)), ".")


def _security_number(key: str, kind: Column, name: Column, attempt: Column) -> Column:
    """An area of 001 to 665, a group and a serial number without zeros only: none is invalid."""
    drawn = _draws(key, kind, name, attempt, 3)
    part = lambda i, n, size: F.lpad((drawn[i] % n + 1).cast("string"), size, "0")
    return F.concat(part(0, 665, 3), part(1, 99, 2), part(2, 9999, 4))


def _word(key: str, kind: Column, name: Column, attempt: Column) -> Column:
    """An invented name of the word's script; a given name ends as its gender asks, each attempt makes it longer."""
    drawn, made = _draws(key, kind, name, attempt, 4 + attempt), []
    for syllables, men, women in _SYLLABLES.values():
        table = F.array(*map(F.lit, syllables))
        stem = F.array_join(F.transform(F.slice(drawn, F.lit(2), 3 + attempt), lambda x: F.element_at(table, x % len(syllables) + 1)), "")
        end = lambda ends: F.element_at(F.array(*map(F.lit, ends)), F.element_at(drawn, 1) % len(ends) + 1)
        made.append(F.initcap(F.concat(stem, F.when(kind == "surname", F.lit("")).when(kind == "given_f", end(women)).otherwise(end(men)))))
    return F.when(name.rlike(r"^\p{IsCyrillic}"), made[1]).when(name.rlike(r"^\p{IsGreek}"), made[2]).otherwise(made[0])


def _shifted(key: str, kind: Column, text: Column) -> Column:
    """Each letter or digit moved on in its script and case by a keyed number of places for its position, never by none."""

    def one(ch: Column, draw: Column) -> Column:
        cases = []
        for letters in _SCRIPTS:
            at = F.instr(F.lit(letters), ch)
            cases.append(F.when(at > 0, F.substring(F.lit(letters), (at + draw % (len(letters) - 1)) % len(letters) + 1, F.lit(1))))
        return F.coalesce(*cases, ch)

    return F.array_join(F.zip_with(F.split(text, ""), _draws(key, kind, F.lit("shift"), F.lit(0), F.length(text)), one), "")


def _shifted_address(key: str, kind: Column, name: Column) -> Column:
    keep, moves = F.greatest(_fixed_octets(name), F.lit(1)), _draws(key, kind, F.lit("shift"), F.lit(0), 4)
    octets = F.zip_with(F.split(name, r"\."), moves, lambda o, x: F.struct(o.alias("o"), ((o.cast("int") + 1 + x % 255) % 256).cast("string").alias("new")))
    return F.array_join(F.transform(octets, lambda o, i: F.when(i < keep, o["o"]).otherwise(o["new"])), ".")


_MAIL = r"^(.*)(\.[^.]+)$"


def drawn(kind: Column, name: Column, attempt: Column, key: str) -> Column:
    """Canonical form of the surrogate of the entity (kind, name)."""
    part = lambda i: F.regexp_extract(name, _MAIL, i)
    return (
        F.when(kind == "email", F.concat(_characters(key, kind, name, attempt, part(1)), part(2)))
        .when(kind == "ip", _address(key, kind, name, attempt))
        .when(kind == "card", _with_check_digit(F.concat(F.substring(name, 1, 1), _digits(key, kind, name, attempt, F.length(name) - 2))))
        .when(kind == "ssn", _security_number(key, kind, name, attempt))
        .when(kind == "phone", _digits(key, kind, name, attempt, F.length(name)))
        .when(kind == "iban", _with_iban_check(F.substring(name, 1, 2), _characters(key, kind, name, attempt, F.substring(name, F.lit(5), F.length(name)))))
        .when(kind.isin("surname", "given_f", "given_m"), _word(key, kind, name, attempt))
        .otherwise(_characters(key, kind, name, attempt, name))
    )


def shifted(kind: Column, name: Column, key: str) -> Column:
    """The surrogate where a format's space is nearly full: one to one within the format, and never the name itself."""
    part = lambda i: F.regexp_extract(name, _MAIL, i)
    return (
        F.when(kind == "email", F.concat(_shifted(key, kind, part(1)), part(2)))
        .when(kind == "ip", _shifted_address(key, kind, name))
        .when(kind == "card", _with_check_digit(F.concat(F.substring(name, 1, 1), _shifted(key, kind, F.substring(name, F.lit(2), F.length(name) - 2)))))
        .when(kind == "iban", _with_iban_check(F.substring(name, 1, 2), _shifted(key, kind, F.substring(name, F.lit(5), F.length(name)))))
        .otherwise(_shifted(key, kind, name))
    )


def dressed(mention: Column, kind: Column, made: Column) -> Column:
    """A canonical surrogate in the mention's format."""
    secret = F.regexp_extract(mention, f"^({_SECRET})", 1)
    cased = F.zip_with(F.split(mention, ""), F.split(made, ""), lambda old, new: F.when(old != F.lower(old), F.upper(new)).otherwise(new))
    return (
        F.when(kind == "email", F.when(F.length(mention) == F.length(made), F.array_join(cased, "")).otherwise(made))
        .when(kind.isin("card", "ssn", "phone"), _poured(made, mention, "0-9"))
        .when(kind == "iban", _poured(made, mention, "A-Z0-9"))
        .when(kind == "secret", F.concat(secret, made))
        .otherwise(made)
    )


def shape(kind: Column, name: Column) -> Column:
    """The format whose space an entity and its surrogates share."""
    folded = F.translate(name, "".join(_SCRIPTS), "".join(script[0] * len(script) for script in _SCRIPTS))
    mail = F.concat(F.regexp_extract(folded, _MAIL, 1), F.regexp_extract(name, _MAIL, 2))
    return F.when(kind == "ip", F.array_join(F.slice(F.split(name, r"\."), F.lit(1), F.greatest(_fixed_octets(name), F.lit(1))), ".")).when(kind == "email", mail).otherwise(folded)


def mentions(text: Column) -> Column:
    return F.regexp_extract_all(text, F.lit(PATTERN), F.lit(0))


def _entities(documents: DataFrame) -> DataFrame:
    """Distinct (kind, name)."""
    found = documents.filter(maybe(F.col("text"))).select(F.explode(mentions(F.col("text"))).alias("mention")).withColumn("kind", kind_of(F.col("mention")))
    return found.select(F.explode(entities(F.col("mention"), F.col("kind"))).alias("e")).select("e.*").distinct()


def redraws(documents: DataFrame, key: str, rounds: int = 12) -> DataFrame:
    """(kind, name, attempt) of the entities whose first surrogates were taken, by another entity or by a real one; attempt -1 is the keyed shift."""
    tasks = int(documents.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    found = scratch.table(_entities(documents).withColumn("attempt", F.lit(0)), "entities")
    real = found.select(F.col("kind").alias("k"), F.col("name").alias("made"))
    named, left = found, found
    for _ in range(rounds):
        # Only what was taken is drawn again; a surrogate that was free stays so, for later draws are checked against all.
        again = left.repartition(tasks, "kind", "name").withColumn("made", drawn(F.col("kind"), F.col("name"), F.col("attempt"), key))
        named = again if left is found else named.join(left.select("kind", "name"), ["kind", "name"], "left_anti").unionByName(again)
        named = scratch.table(named, "made")
        order = F.row_number().over(Window.partitionBy("kind", "made").orderBy("attempt", "name"))
        shared = scratch.table(named.groupBy("kind", "made").agg(F.count("*").alias("n")).filter("n > 1").select("kind", "made"), "shared")
        # The first of those that share a surrogate keeps it; a surrogate that is real is kept by none.
        taken = named.join(shared, ["kind", "made"], "left_semi").withColumn("order", order).filter("order > 1").select("kind", "name", "attempt")
        taken = taken.unionByName(named.join(real, (named["kind"] == real["k"]) & (named["made"] == real["made"]), "left_semi").select("kind", "name", "attempt")).distinct()
        left = scratch.table(taken.withColumn("attempt", F.col("attempt") + 1), "taken")
        if not left.limit(1).count():
            return named.filter("attempt > 0").select("kind", "name", "attempt")
    full = left.select("kind", shape(F.col("kind"), F.col("name")).alias("shape")).distinct()
    every = named.withColumn("shape", shape(F.col("kind"), F.col("name"))).join(full.withColumn("full", F.lit(True)), ["kind", "shape"], "left")
    return every.withColumn("attempt", F.when(F.col("full"), F.lit(-1)).otherwise(F.col("attempt"))).filter("attempt <> 0").select("kind", "name", "attempt")


def replace(documents: DataFrame, key: str, keep: list[str] | None = None, rounds: int = 12) -> DataFrame:
    """doc_id, text with surrogates, n_entities, and the columns in ``keep``.  Whoever has ``key`` can draw the surrogates again."""
    keep = keep or []
    docs = documents.select("doc_id", F.col("text").cast("string").alias("text"), *keep)
    odd = scratch.table(redraws(docs, key, rounds), "odd")
    many = odd.limit(1).count() > 0
    if many:
        # Attempts meet the documents by document: each document's redrawn entities, then the document itself.
        docs = docs.withColumn("_th", F.xxhash64("text"))
        said = docs.filter(maybe(F.col("text"))).select("_th", F.explode(F.array_distinct(mentions(F.col("text")))).alias("mention")).withColumn("kind", kind_of(F.col("mention")))
        said = said.select("_th", F.explode(entities(F.col("mention"), F.col("kind"))).alias("e")).select("_th", "e.*").distinct().join(odd, ["kind", "name"])
        per_doc = said.groupBy("_th").agg(F.map_from_entries(F.collect_set(F.struct(F.concat_ws("\u0001", "kind", "name"), "attempt"))).alias("_attempts"))
        docs = docs.join(per_doc, "_th", "left")

    def attempted(e: Column) -> Column:
        attempt = F.coalesce(F.try_element_at(F.col("_attempts"), F.concat_ws("\u0001", e["kind"], e["name"])), F.lit(0)) if many else F.lit(0)
        return F.struct(e["kind"].alias("kind"), e["name"].alias("name"), attempt.alias("attempt"))

    def made(e: Column) -> Column:
        if not many:
            return drawn(e["kind"], e["name"], F.lit(0), key)
        return F.when(e["attempt"] < 0, shifted(e["kind"], e["name"], key)).otherwise(drawn(e["kind"], e["name"], e["attempt"], key))

    def dress(x: Column) -> Column:
        person = F.concat(F.regexp_extract(x["mention"], f"^{_TITLE} ", 0), F.array_join(x["new"], " "))
        return F.when(x["kind"] == "name", person).otherwise(dressed(x["mention"], x["kind"], x["new"][0]))

    def surrogates(found: Column) -> Column:
        """What replaces each mention; every step is an array of its own, so nothing is worked out again for each use."""
        both = lambda x, name, value: F.struct(x["mention"].alias("mention"), x["kind"].alias("kind"), value.alias(name))
        kinds = F.transform(found, lambda m: F.struct(m.alias("mention"), kind_of(m).alias("kind")))
        named = F.transform(kinds, lambda x: both(x, "entities", entities(x["mention"], x["kind"])))
        ready = F.transform(named, lambda x: both(x, "entities", F.transform(x["entities"], attempted)))
        return F.transform(F.transform(ready, lambda x: both(x, "new", F.transform(x["entities"], made))), dress)

    # One expression a projection: none is expensive and used twice, so the planner keeps them apart.
    docs = docs.withColumn("_maybe", maybe(F.col("text")))
    docs = docs.withColumn("_found", F.when(F.col("_maybe"), mentions(F.col("text"))))
    docs = docs.withColumn("n_entities", F.coalesce(F.size("_found").cast("long"), F.lit(0).cast("long"))).withColumn("n_entities", F.greatest("n_entities", F.lit(0).cast("long")))
    gaps = F.split(F.col("text"), PATTERN, -1)
    mixed = F.array_join(F.zip_with(gaps, surrogates(F.col("_found")), lambda gap, other: F.concat(gap, F.coalesce(other, F.lit("")))), "")
    return docs.select("doc_id", F.when(F.col("n_entities") > 0, mixed).otherwise(F.col("text")).alias("text"), "n_entities", *keep)


def session_key(spark) -> str:
    """The key in ``spark.relanom.surrogates.key``; a fresh random one for the session where it is unset."""
    key = spark.conf.get("spark.relanom.surrogates.key", None)
    if not key:
        key = token_hex(16)
        spark.conf.set("spark.relanom.surrogates.key", key)
    return key


def op4_surrogates(spark, sf_dir: str) -> DataFrame:
    """Every document with surrogates for its personal data, under the session's key."""
    return replace(spark.read.parquet(f"{sf_dir}/documents.parquet"), session_key(spark))

"""Near-duplicate documents by ProbMinHash, banding and verification.

A text's five-word shingles weigh as often as they occur.  Every shingle runs a Poisson
process of its weight through the signature's places, without repeating one, and stops as
soon as its time exceeds all the places' least times; a place keeps the shingle that came
first.  Two signatures agree at a place with the probability Jaccard similarity of the
weighted sets.  Texts that agree in all places of a band become candidates, and a candidate
pair is linked if its exact probability Jaccard similarity is at least ``similarity``.

Texts of equal words are one node from the start, so exact copies are never paired.  In each
band's bucket every node is compared with the bucket's first; that joins groups of copies
with as many comparisons as members.  Buckets that still hold nodes of several classes are
then compared in full, without listing pairs: blocks of ``BLOCK`` nodes meet in one task,
signature against signature, and a pair of different classes that agrees in enough places and
in no earlier band is compared exactly there.  Nodes of a bucket's largest class meet the
others only, not each other, so a large group of copies with a few strangers stays linear.
Each link found makes its two classes one, so a task returns fewer links than it has nodes.

Words are as in ``decontaminate``; a text of fewer than five is one shingle.  Texts without
words, null ones too, are classes of their own.  A class is named by its least doc_id, null
if it has none; of equal rows one is kept.
"""

from __future__ import annotations

from functools import lru_cache
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from relanom.llm import components, decontaminate, kernels, scratch

SHINGLE = 5
PLACES = 128
ROWS = 6
SIMILARITY = 0.8
BLOCK = 256
#: Rows up to which a list of bucket keys is broadcast.
BROADCAST_ROWS = 1 << 20
_U = np.uint64


def shingles(texts: list[bytes], k: int = SHINGLE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, hash, weight) of the distinct shingles of lower-cased texts."""
    raw = np.frombuffer(b"\n".join(texts), np.uint8)
    start, end = kernels.word_spans(raw, decontaminate._INSIDE)
    sizes = np.array([len(t) + 1 for t in texts], np.int64)
    first = np.searchsorted(start, np.append(np.cumsum(sizes) - sizes, len(raw) + 1))
    words = kernels.word_hashes(raw, start, end)
    count = np.diff(first)
    grams = kernels.gram_hashes(words, k)
    n = np.maximum(count - k + 1, 0)
    doc = np.repeat(np.arange(len(texts)), n)
    value = grams[np.repeat(first[:-1], n) + np.arange(len(doc)) - np.repeat(np.cumsum(n) - n, n)] if len(doc) else np.empty(0, _U)
    few = np.flatnonzero((count > 0) & (count < k))
    whole = [kernels.gram_hashes(words[first[d] : first[d + 1]], int(count[d]))[0] for d in few]
    doc, value = np.concatenate((doc, few)), np.concatenate((value, np.array(whole, _U)))
    _, at, weight = np.unique(kernels.mix(value + doc.astype(_U) * _U(0xD1342543DE82EF95)), return_index=True, return_counts=True)
    return doc[at], value[at], weight


def signatures(doc: np.ndarray, value: np.ndarray, weight: np.ndarray, docs: int, places: int = PLACES) -> np.ndarray:
    """[doc, place] first arrivals; ``places`` is a power of two."""
    least = np.full(docs * places, np.inf)
    winner = np.zeros(docs * places, _U)
    time = np.zeros(len(doc))
    step = (kernels.mix(value + _U(1)) | _U(1)) & _U(places - 1)
    offset = kernels.mix(value + _U(2)) & _U(places - 1)
    live = np.arange(len(doc))
    for i in range(places):
        draw = kernels.mix(value[live] ^ _U((0x9E3779B97F4A7C15 * (i + 3)) & 0xFFFFFFFFFFFFFFFF))
        uniform = ((draw >> _U(11)).astype(np.float64) + 0.5) / float(1 << 53)
        # i places are taken already: the next of the remaining ones arrives at their joint rate.
        time[live] -= np.log(uniform) / (weight[live] * (places - i))
        place = ((step[live] * _U(i) + offset[live]) & _U(places - 1)).astype(np.int64)
        slot = doc[live] * places + place
        np.minimum.at(least, slot, time[live])
        won = time[live] == least[slot]
        winner[slot[won]] = value[live[won]]
        live = live[time[live] < least.reshape(docs, places).max(axis=1)[doc[live]]]
        if not len(live):
            break
    return winner.reshape(docs, places)


def probability_jaccard(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Exact similarity of two weighted sets given as (sorted values, weights)."""
    common, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    if not len(common):
        return 0.0
    x, y = a[1][i].astype(float), b[1][j].astype(float)
    # Sum over d' of max(x'/x, y'/y): x' counts where its ratio x'/y' is at least that of d, y' elsewhere.
    order = np.argsort(x / y, kind="stable")
    x, y = x[order], y[order]
    ratio = x / y
    at = np.searchsorted(ratio, ratio, side="left")
    only_a, only_b = a[1].sum() - x.sum(), b[1].sum() - y.sum()
    x_from = only_a + np.concatenate((np.cumsum(x[::-1])[::-1], [0.0]))[at]
    y_below = only_b + np.concatenate(([0.0], np.cumsum(y)))[at]
    return float((1 / (x_from / x + y_below / y)).sum())


def _sets(text: bytes) -> tuple[np.ndarray, np.ndarray]:
    _, value, weight = shingles([text.lower()])
    order = np.argsort(value)
    return value[order], weight[order]


def signed(documents: DataFrame) -> DataFrame:
    """(doc_id, th, node, signature) per document; node is a digest of its words, null without words."""
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("th", F.xxhash64("text"))
    schema = pa.schema([("doc_id", pa.int64()), ("th", pa.int64()), ("node", pa.binary()), ("signature", pa.binary())])

    def run(batches):
        for batch in batches:
            for rows, texts in decontaminate._lowered(batch, 1 << 20):
                found = signatures(*shingles(texts), len(texts))
                words = [decontaminate.WORD.findall(t) for t in texts]
                nodes = [blake2b(b" ".join(w), digest_size=16).digest() if w else None for w in words]
                at = pa.array(rows)
                made = [s.tobytes() if n else None for s, n in zip(found, nodes)]
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").take(at), batch.column("th").take(at), pa.array(nodes, pa.binary()), pa.array(made, pa.binary())], schema=schema)

    return docs.mapInArrow(run, "doc_id long, th long, node binary, signature binary")


def _banded(nodes: DataFrame) -> DataFrame:
    """(node, band, bucket): a bucket is a band with the hash of its places."""
    width = ROWS * 8
    bands = F.transform(F.sequence(F.lit(0), F.lit(PLACES // ROWS - 1)), lambda i: F.xxhash64(i, F.substring(F.col("signature"), i * width + 1, F.lit(width))))
    return nodes.select("node", F.posexplode(bands).alias("band", "bucket"))


def _texts(asked: DataFrame, documents: DataFrame, nodes: DataFrame) -> DataFrame:
    """(node, text) of the nodes asked for; several equal rows if a row repeats."""
    where = nodes.join(asked.distinct(), "node", "left_semi").select("node", F.col("doc_id").alias("d"), "th")
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("h", F.xxhash64("text"))
    return docs.join(where, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("h") == F.col("th"))).select("node", "text")


_LINKS = pa.schema([("u", pa.binary()), ("v", pa.binary())])


def _verify(pairs: DataFrame, texts: DataFrame, similarity: float) -> DataFrame:
    """The pairs (u, v) of nodes that are similar enough."""
    both = pairs.join(texts.select(F.col("node").alias("u"), F.col("text").alias("x")), "u").join(texts.select(F.col("node").alias("v"), F.col("text").alias("y")), "v")

    def rows(batches):
        sets = lru_cache(maxsize=256)(_sets)
        for batch in batches:
            for u, v, x, y in zip(*(batch.column(c) for c in ("u", "v", "x", "y"))):
                if probability_jaccard(sets(x.as_py().encode()), sets(y.as_py().encode())) >= similarity - 1e-12:
                    yield u.as_py(), v.as_py()

    return both.select("u", "v", "x", "y").mapInArrow(lambda b: kernels.row_batches(rows(b), _LINKS), "u binary, v binary").distinct()


def _dealt(members: DataFrame) -> DataFrame:
    """Each member in every task (bucket, band, kind, i, j) it is compared in; ``side`` tells the two sides of a task apart.

    Kind 0 sets block i of the largest class against block j of the rest, kind 1 two blocks of the rest against each other.
    """
    major = F.col("class") == F.col("major")
    members = members.withColumn("own", F.pmod(F.xxhash64("node"), F.when(major, F.col("major_blocks")).otherwise(F.col("rest_blocks"))))
    upto = lambda c: F.sequence(F.lit(0).cast("long"), F.col(c) - 1)
    task = lambda kind, i, j, side: F.struct(F.lit(kind).alias("kind"), i.alias("i"), j.alias("j"), side.alias("side"))
    own, one, zero = F.col("own"), F.lit(1).cast("long"), F.lit(0).cast("long")
    of_major = F.transform(upto("rest_blocks"), lambda j: task(0, own, j, one))
    of_rest = F.concat(F.transform(upto("major_blocks"), lambda i: task(0, i, own, zero)), F.transform(upto("rest_blocks"), lambda o: task(1, F.least(own, o), F.greatest(own, o), own)))
    return members.select("band", "bucket", "node", "class", "signature", "text", F.explode(F.when(major, of_major).otherwise(of_rest)).alias("task")).select("*", "task.*").drop("task")


def _block_links(members: DataFrame, similarity: float) -> DataFrame:
    """Links (u, v) between classes within buckets (band, bucket, major, major_blocks, rest_blocks, node, class, signature, text)."""
    # Three deviations below the expected number of agreeing places.
    enough = PLACES * similarity - 3 * (PLACES * similarity * (1 - similarity)) ** 0.5
    key_columns = ["bucket", "band", "kind", "i", "j"]
    dealt = _dealt(members).repartition("bucket", "kind", "i", "j").sortWithinPartitions(*key_columns, "node")

    def rows(batches):
        key, held = None, []
        for batch in batches:
            columns = [batch.column(c).to_pylist() for c in (*key_columns, "node", "class", "signature", "side", "text")]
            for *k, node, name, signature, own, text in zip(*columns):
                if k != key:
                    yield from compare(held, key)
                    key, held = k, []
                if not held or held[-1][0] != node:
                    held.append((node, name, np.frombuffer(signature, _U), own, text.encode()))
        yield from compare(held, key)

    def compare(held, key):
        if len(held) < 2:
            return
        _, band, kind, first, second = key
        across = kind == 0 or first != second
        signs, root, sets = np.stack([x[2] for x in held]), {}, {}
        bands = signs[:, : PLACES // ROWS * ROWS].reshape(len(held), -1, ROWS)

        def find(name):
            while root.get(name, name) != name:
                name = root[name]
            return name

        def set_of(x):
            if x not in sets:
                sets[x] = _sets(held[x][4])
            return sets[x]

        for i, (node, name, sign, own, _) in enumerate(held):
            agree = (signs[i + 1 :] == sign).sum(axis=1)
            near = np.flatnonzero(agree >= enough)
            for j in (near[np.argsort(-agree[near], kind="stable")] + i + 1).tolist():
                a, b = find(name), find(held[j][1])
                if a == b or (across and held[j][3] == own) or (bands[i, :band] == bands[j, :band]).all(axis=1).any():
                    continue
                if probability_jaccard(set_of(i), set_of(j)) >= similarity - 1e-12:
                    root[max(a, b)] = min(a, b)
                    yield min(node, held[j][0]), max(node, held[j][0])

    return dealt.mapInArrow(lambda b: kernels.row_batches(rows(b), _LINKS), "u binary, v binary")


def node_classes(documents: DataFrame, similarity: float = SIMILARITY) -> tuple[DataFrame, DataFrame]:
    """The signed documents and (node, root) of every node that is linked to another."""
    signs = scratch.table(signed(documents), "signed")
    one = lambda c: F.first(c).alias(c)
    nodes = scratch.table(signs.filter("node is not null").groupBy("node").agg(one("doc_id"), one("th"), one("signature")), "nodes")
    buckets = scratch.table(_banded(nodes).groupBy("band", "bucket").agg(F.count("*").alias("n"), F.min("node").alias("first")).filter("n > 1"), "buckets")
    keys = F.broadcast(buckets) if buckets.count() <= BROADCAST_ROWS else buckets
    members = scratch.table(_banded(nodes).join(keys, ["band", "bucket"]), "members")
    pairs = scratch.table(members.filter("node <> first").select(F.col("first").alias("u"), F.col("node").alias("v")).distinct(), "pairs")
    # What is grouped is every node that shares a bucket, so the texts fetched for the stars serve the blocks too.
    texts = scratch.table(_texts(members.select("node"), documents, nodes), "texts")
    links = scratch.table(_verify(pairs, texts, similarity), "links")
    roots = scratch.table(components.components(links), "roots")
    named = scratch.table(members.join(roots, "node", "left").select("band", "bucket", "node", F.coalesce("root", "node").alias("class")), "named")
    sizes = named.groupBy("band", "bucket", "class").agg(F.count("*").alias("n"))
    largest = sizes.groupBy("band", "bucket").agg(F.max(F.struct("n", "class")).alias("top"), F.sum("n").alias("all")).filter(F.col("all") > F.col("top.n"))
    open_ = scratch.table(largest.select("band", "bucket", F.col("top.class").alias("major"), F.ceil(F.col("top.n") / BLOCK).alias("major_blocks"), F.ceil((F.col("all") - F.col("top.n")) / BLOCK).alias("rest_blocks")), "open")
    left = named.join(open_, ["band", "bucket"]).join(nodes.select("node", "signature"), "node").join(texts, "node")
    more = scratch.table(_block_links(left, similarity).distinct(), "more")
    if more.limit(1).count():
        scratch.drop(roots)
        roots = scratch.table(components.components(links.unionByName(more)), "roots")
    scratch.drop(nodes, buckets, members, pairs, texts, links, named, open_, more)
    return signs, roots


def classes(documents: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """doc_id, class_id and kept of every document; one document of each class is kept."""
    signs, roots = node_classes(documents, similarity)
    rooted = signs.select("doc_id", "th", "node").join(roots, "node", "left").withColumn("class", F.coalesce("root", "node"))
    rooted = scratch.table(rooted.select("doc_id", "th", "class"), "rooted")
    scratch.drop(signs, roots)
    least = scratch.table(rooted.filter("class is not null").groupBy("class").agg(F.min("doc_id").alias("class_id")), "least")
    return rooted.join(least, "class", "left").select("doc_id", "th", "class", F.when(F.col("class").isNull(), F.col("doc_id")).otherwise(F.col("class_id")).alias("class_id"))


def deduplicated(documents: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """The documents, all columns, one row of each class: that with the least doc_id."""
    # Written, so that the join that names the classes is not tied to the grouping below and a large class can be split.
    named = scratch.table(classes(documents, similarity), "classes")
    # Several rows can share the least id (or have none); equal texts among them are one, others are told apart by their hash.
    keepers = named.filter("class is not null and (doc_id = class_id or (doc_id is null and class_id is null))").groupBy("class").agg(F.first("doc_id").alias("k_id"), F.min("th").alias("k_th")).select("k_id", "k_th")
    keepers = keepers.unionByName(named.filter("class is null").select(F.col("doc_id").alias("k_id"), F.col("th").alias("k_th")).distinct())
    rows = documents.withColumn("_th", F.xxhash64(F.col("text").cast("string")))
    joined = rows.join(keepers, rows["doc_id"].cast("long").eqNullSafe(keepers["k_id"]) & (rows["_th"] == keepers["k_th"])).drop("k_id", "k_th")
    again = joined.groupBy("doc_id", "_th").count().filter("count > 1").select(F.col("doc_id").alias("k_id"), F.col("_th").alias("k_th"))
    if not scratch.table(again, "again").limit(1).count():
        return joined.drop("_th")
    number = F.row_number().over(Window.partitionBy("doc_id", "_th").orderBy(F.lit(0)))
    return joined.withColumn("_n", number).filter("_n = 1").drop("_n", "_th")


def op9_prob_minhash(spark, sf_dir: str) -> DataFrame:
    named = classes(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return named.select("doc_id", "class_id", F.coalesce(F.col("doc_id") == F.col("class_id"), F.lit(False)).alias("kept"))

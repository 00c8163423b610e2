"""Language identification by cross-parsing.

For every learned language a suffix automaton of a bounded sample of labelled text is
built.  A text is parsed greedily into longest matches against each automaton; the language
whose phrases, normalised by log2 of its sample's length, are fewest wins.  Texts are parsed
in lanes of ``LANE`` characters, all lanes and languages in step, so a text's phrases are
those of its lanes together.

The sample is bounded by ``chars`` per language, taken in passages of ``passage`` characters
from the distinct texts of least hash until it is full or no text is left; everything else
covers all rows.  Every label with text is learned from and every letter of a sample has its
transitions, however many scripts there are; what is broadcast grows with the labels only.

Null texts and texts without a letter are ``und`` with score 0.  Ties go to the first
language in text order.  Nothing to learn from: every row is ``und``.  The score is one less
the quotient of the least and second least cost (1 with a single language).
"""

from __future__ import annotations

import re
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relanom.llm import kernels

LANE = 8192
DENSE = 1 << 22
_LETTER = re.compile(r"[^\W\d_]")
RESULT = "doc_id long, held_out boolean, lang_pred string, score double"


def suffix_automaton(codes: list[int]) -> tuple[list[dict[int, int]], np.ndarray]:
    """Transitions of the automaton that accepts every substring of ``codes``, root 0, and how often each state's substrings occur."""
    after: list[dict[int, int]] = [{}]
    link, size, often, last = [-1], [0], [0], 0
    for c in codes:
        now = len(after)
        after.append({})
        size.append(size[last] + 1)
        link.append(0)
        often.append(1)
        p = last
        while p >= 0 and c not in after[p]:
            after[p][c] = now
            p = link[p]
        if p >= 0:
            q = after[p][c]
            if size[q] == size[p] + 1:
                link[now] = q
            else:
                twin = len(after)
                after.append(dict(after[q]))
                size.append(size[p] + 1)
                link.append(link[q])
                often.append(0)
                while p >= 0 and after[p].get(c) == q:
                    after[p][c] = twin
                    p = link[p]
                link[q] = link[now] = twin
        last = now
    for state in sorted(range(1, len(after)), key=lambda x: -size[x]):
        often[link[state]] += often[state]
    return after, np.array(often)


class CrossParser:
    """Automata of all languages with their states numbered through.

    The states whose substrings occur most often have a row of a dense table, about ``DENSE`` entries in all languages
    together; the transitions of all others are in one hash table from (state, letter) to state.
    """

    def __init__(self, samples: dict[str, str]):
        self.languages = sorted(samples)
        texts = [samples[k].lower() for k in self.languages]
        letters = sorted({ch for t in texts for ch in t if ch.isalpha()})
        # Sign 0 is whatever is no letter, 1 a letter that no sample has.
        self.signs = np.array([chr(i).isalpha() for i in range(0x110000)], np.int32)
        self.signs[[ord(ch) for ch in letters]] = np.arange(2, len(letters) + 2)
        self.width = len(letters) + 2
        automata = [suffix_automaton(self.codes(t).tolist()) for t in texts]
        rows = max(1, DENSE // (self.width * max(1, len(automata))))
        numbers, self.dense_states = [], 1
        for after, often in automata:
            rank = np.empty(len(after), np.int64)
            often[0] = len(after) + 1 + often.max(initial=0)
            rank[np.argsort(-often, kind="stable")] = np.arange(len(after))
            numbers.append(rank)
            self.dense_states += min(rows, len(after))
        first, beyond, edges = 1, self.dense_states, []
        self.roots = []
        for (after, _), rank in zip(automata, numbers):
            kept = min(rows, len(after))
            number = np.where(rank < kept, rank + first, rank - kept + beyond)
            self.roots.append(int(number[0]))
            edges += [(int(number[state]), c, int(number[to])) for state, out in enumerate(after) for c, to in out.items()]
            first, beyond = first + kept, beyond + len(after) - kept
        at = np.array(edges, np.int64).reshape(-1, 3)
        self.dense = np.zeros(self.dense_states * self.width, np.int32)
        inside = at[:, 0] < self.dense_states
        self.dense[at[inside, 0] * self.width + at[inside, 1]] = at[inside, 2]
        self._store(at[~inside, 0] * self.width + at[~inside, 1], at[~inside, 2].astype(np.int32))
        self.cost = np.array([np.log2(max(2, len(t))) for t in texts])

    def _slots(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def _store(self, keys: np.ndarray, targets: np.ndarray) -> None:
        self.bits = max(4, (2 * len(keys)).bit_length())
        self.keys, self.to = np.full(1 << self.bits, -1, np.int64), np.zeros(1 << self.bits, np.int32)
        slot, left = self._slots(keys), np.arange(len(keys))
        while len(left):
            free = left[self.keys[slot[left]] < 0]
            self.keys[slot[free]] = keys[free]
            placed = self.keys[slot[left]] == keys[left]
            self.to[slot[left[placed]]] = targets[left[placed]]
            left = left[~placed]
            slot[left] = (slot[left] + 1) & ((1 << self.bits) - 1)

    def _looked_up(self, keys: np.ndarray) -> np.ndarray:
        slot, out, left = self._slots(keys), np.zeros(len(keys), np.int32), np.arange(len(keys))
        while len(left):
            found = self.keys[slot[left]]
            hit = left[found == keys[left]]
            out[hit] = self.to[slot[hit]]
            left = left[(found != keys[left]) & (found >= 0)]
            slot[left] = (slot[left] + 1) & ((1 << self.bits) - 1)
        return out

    def step(self, states: np.ndarray, signs: np.ndarray) -> np.ndarray:
        """Next states, 0 where there is no transition; ``signs`` are broadcast against the states."""
        out = self.dense[np.minimum(states, self.dense_states - 1) * self.width + signs]
        rare = np.nonzero(states >= self.dense_states)
        if len(rare[0]):
            out[rare] = self._looked_up(states[rare] * self.width + np.broadcast_to(signs, states.shape)[rare])
        return out

    def codes(self, text: str) -> np.ndarray:
        return self.signs[np.frombuffer(text.encode("utf-32-le", "replace"), np.uint32)]

    def phrases(self, texts: list[str]) -> np.ndarray:
        """[language, text] counts of longest-match phrases."""
        codes = [self.codes(t.lower()) for t in texts]
        lanes = [(len(c) - a if len(c) - a < LANE else LANE, i, a) for i, c in enumerate(codes) for a in range(0, len(c), LANE)]
        out = np.zeros((len(self.languages), len(texts)), np.int64)
        if not lanes:
            return out
        lanes.sort(reverse=True)
        sizes = np.array([n for n, _, _ in lanes])
        grid = np.zeros((LANE, len(lanes)), np.int32)
        for k, (n, i, a) in enumerate(lanes):
            grid[:n, k] = codes[i][a : a + n]
        roots = np.array(self.roots, np.int64)[:, None]
        fresh = roots * self.width
        state = np.broadcast_to(roots, (len(roots), len(lanes))).copy()
        count = np.zeros(state.shape, np.int32)
        for t in range(sizes[0]):
            k = int(np.searchsorted(-sizes, -t, side="left"))
            signs, now = grid[t, :k], state[:, :k]
            after = self.step(now, signs)
            ended = after == 0
            count[:, :k] += ended | (now == roots)
            # A phrase that ends here leaves this letter to the next one; a letter that the sample lacks is one by itself.
            anew = self.dense[fresh + signs]
            state[:, :k] = np.where(ended, np.where(anew == 0, roots, anew), after)
        owner = np.array([i for _, i, _ in lanes])
        for total, own in zip(out, count):
            total += np.bincount(owner, own, len(texts)).astype(np.int64)
        return out

    def predict(self, texts: list[str | None]) -> list[tuple[str, float]]:
        out: list[tuple[str, float]] = [("und", 0.0)] * len(texts)
        real = [i for i, t in enumerate(texts) if t and _LETTER.search(t)]
        if not self.languages or not real:
            return out
        cost = self.phrases([texts[i] for i in real]) * self.cost[:, None]
        best = cost.argmin(axis=0)
        ranked = np.sort(cost, axis=0)
        score = 1 - ranked[0] / ranked[1] if len(ranked) > 1 else np.ones(len(real))
        for i, b, s in zip(real, best.tolist(), score.tolist()):
            out[i] = (self.languages[b], s)
        return out


def labelled_sample(learn: DataFrame, chars: int, passage: int) -> dict[str, str]:
    """Per language at most ``chars`` characters in passages; ``learn`` has text and a non-null lang."""
    hashed = learn.select("lang", "text", F.xxhash64("text").alias("h"))
    # What each distinct text can give, however many copies it has.
    useful = hashed.groupBy("lang", "h").agg(F.max(F.least(F.length("text"), F.lit(passage)) + 1).alias("chars"))
    given = {r["lang"]: r["chars"] for r in useful.groupBy("lang").agg(F.sum("chars").alias("chars")).collect()}
    start = 1 + F.pmod(F.col("h"), F.greatest(F.lit(1), F.length("text") - passage)).cast("int")
    out: dict[str, str] = {}
    # A hash falls below its language's share with a probability that gives about ``times`` the bound in distinct passages; a language that got less draws again.
    times = 3
    while open_ := sorted(set(given) - set(out)):
        shares = {lang: min(1.0, times * chars / max(1, given[lang])) for lang in open_}
        share = F.create_map(*[F.lit(x) for pair in shares.items() for x in pair])[F.col("lang")]
        drawn = hashed.filter(F.pmod(F.col("h"), F.lit(1 << 20)) / float(1 << 20) < share)
        texts, seen = defaultdict(str), defaultdict(set)
        for lang, h, text in sorted(drawn.select("lang", "h", F.substring(F.col("text"), start, F.lit(passage)).alias("text")).distinct().collect(), key=lambda r: (r[0], r[1] & 0xFFFFF, r[1], r[2])):
            if len(texts[lang]) < chars and h not in seen[lang]:
                seen[lang].add(h)
                texts[lang] += (text + " ")[: chars - len(texts[lang])]
        out |= {lang: texts[lang] for lang in open_ if len(texts[lang]) >= chars or shares[lang] == 1.0}
        times *= 8
    return out


def identify(documents: DataFrame, learn: DataFrame | None = None, chars: int = 24_000, passage: int = 1_000, keep: list[str] | None = None) -> DataFrame:
    """doc_id, held_out, lang_pred and score of every row, and the columns in ``keep``.

    Learns from ``learn`` (doc_id, text, lang), by default ``documents``; rows with crc32(doc_id) mod 3 = 1 or a null id are not learned from.
    """
    fold = F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(3))
    source = (learn if learn is not None else documents).select("doc_id", F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"))
    samples = labelled_sample(source.filter(fold != 1).filter("lang is not null and length(text) > 0").select("lang", "text"), chars, passage)
    parser = documents.sparkSession.sparkContext.broadcast(CrossParser(samples))
    keep = keep or []
    docs = documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(fold == 1, F.lit(False)).alias("held_out"), F.col("text").cast("string").alias("_text"), *keep)

    def run(batches):
        for batch in batches:
            kept = [batch.column(c) for c in ("doc_id", "held_out")]
            rest = [batch.column(c) for c in keep]
            texts, found, size, at = batch.column("_text"), [], 0, 0
            held: list[str | None] = []
            for text in texts:
                held.append(text.as_py())
                size += len(held[-1] or "")
                if size > 1 << 22:
                    found += parser.value.predict(held)
                    held, size = [], 0
            found += parser.value.predict(held)
            yield pa.RecordBatch.from_arrays([*kept, pa.array([x for x, _ in found], pa.string()), pa.array([x for _, x in found], pa.float64()), *rest], names=["doc_id", "held_out", "lang_pred", "score", *keep])

    extra = "".join(f", `{c}` {documents.schema[c].dataType.simpleString()}" for c in keep)
    return docs.mapInArrow(run, RESULT + extra)


def op6_cross_parsing(spark, sf_dir: str) -> DataFrame:
    return identify(spark.read.parquet(f"{sf_dir}/documents.parquet"))

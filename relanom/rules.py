"""Rules: forest paths to predicates, validation, measuring, selection, refinement, freezing, application.

A rule is an array of (feature, op, threshold) conditions with its canonical text; free
predicates are SQL texts.  All rules are measured in one scan, which returns two counters per
rule and task: conditions are compared on Arrow batches, free texts come as packed bits.
"""

from __future__ import annotations

import json
import re
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field
from functools import reduce
from hashlib import sha256

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from relanom import forest
from relanom.draws import u
from relanom.tasks import Preset

#: Predicates packed into one long.
CHUNK = 62
#: Expressions whose value is not a function of the row alone, by the names of their classes.
REFUSED = re.compile(r"Aggregate|Window|Subquery|ListQuery|Exists|UDF|Current|Now$|LocalTimestamp|InputFile|SparkPartitionID|Reflection|Uuid|Rand|Generator|Explode|Inline$|StaticInvoke|Version$")

Conditions = list[tuple[str, str, float]]


def text_of(conditions: Iterable[tuple[str, str, float]]) -> str:
    return " AND ".join(f"{f} {op} {float(t)!r}" for f, op, t in conditions)


def canonical(conditions: Iterable[tuple[str, str, float]]) -> list[tuple[str, str, float]] | None:
    """Tightest bound per feature and direction, sorted; None if no value can satisfy it."""
    best: dict[tuple[str, str], float] = {}
    for f, op, t in conditions:
        key = (f, op)
        best[key] = t if key not in best else (min if op == "<=" else max)(best[key], t)
    for (f, op), t in best.items():
        if op == "<=" and best.get((f, ">"), float("-inf")) >= t:
            return None
    return sorted((f, op, t) for (f, op), t in best.items())


# ---- forest
PATHS = "tree long, leaf long, rows long, p double, conditions array<struct<feature:long,op:string,threshold:double>>"


def paths(nodes: DataFrame, first_trees: int, leaf_rows: int = 0, leaf_positive: float = 0.0) -> DataFrame:
    """(tree, leaf, rows, p, conditions): root-to-leaf paths of the first trees to leaves with enough rows and positives.

    A tree's nodes meet in one task; they are bounded by the sample it was grown on.
    """
    import pandas as pd

    def climb(pdf):
        parent = {}
        for node, left, right, feature, threshold in zip(pdf["node"], pdf["left"], pdf["right"], pdf["feature"], pdf["threshold"]):
            if left >= 0:
                parent[left], parent[right] = (node, (feature, "<=", threshold)), (node, (feature, ">", threshold))
        out = []
        for tree, node, left, rows, p in zip(pdf["tree"], pdf["node"], pdf["left"], pdf["rows"], pdf["p"]):
            if left < 0 and node in parent and rows >= leaf_rows and p >= leaf_positive:
                conditions, at = [], node
                while at in parent:
                    at, step = parent[at]
                    conditions.append(dict(zip(("feature", "op", "threshold"), step)))
                out.append((tree, node, rows, p, conditions[::-1]))
        return pd.DataFrame(out, columns=["tree", "leaf", "rows", "p", "conditions"])

    return nodes.filter(F.col("tree") < first_trees).groupBy("tree").applyInPandas(climb, PATHS)


def candidates(found: DataFrame, features: list[str], preset: Preset) -> list[list[tuple[str, str, float]]]:
    """Canonical conditions of leaves with enough rows and positives, without duplicates; bounded by the trees read."""
    import pandas as pd

    def written(parts):
        for pdf in parts:
            rules = [canonical((features[c["feature"]], c["op"], c["threshold"]) for c in conditions) for conditions in pdf["conditions"]]
            yield pd.DataFrame([(t, n, text_of(r)) for t, n, r in zip(pdf["tree"], pdf["leaf"], rules) if r], columns=["tree", "leaf", "text"])

    kept = found.filter((F.col("rows") >= preset.leaf_rows) & (F.col("p") >= preset.leaf_positive)).select("tree", "leaf", "conditions")
    texts = kept.mapInPandas(written, "tree long, leaf long, text string").groupBy("text").agg(F.min(F.struct("tree", "leaf")).alias("first")).orderBy("first")
    # Only texts travel, and a condition that many rules share is held once.
    known: dict[str, tuple[str, str, float]] = {}
    return [[known[c] if c in known else known.setdefault(c, _condition(c)) for c in text.split(" AND ")] for text in texts.select("text").toArrow().column("text").to_pylist()]


def _condition(text: str) -> tuple[str, str, float]:
    f, op, t = text.rsplit(" ", 2)
    return f, op, float(t)


# ---- validation
def _refused(expression) -> bool:
    """Whether an analysed expression or a part of it depends on more than the row."""
    if not expression.deterministic() or REFUSED.search(expression.getClass().getSimpleName()):
        return True
    children = expression.children()
    return any(_refused(children.apply(i)) for i in range(children.size()))


def problem(view: DataFrame, text: str, allowed: set[str]) -> str | None:
    """Why a predicate text is refused, or None: functions, columns and type are read off the analysed plan."""
    try:
        parsed = view.limit(0).select(F.expr(text).alias("ok"))
    except Exception as e:  # the parser and the analyser raise several kinds
        return "column" if "UNRESOLVED_COLUMN" in str(e) else "syntax"
    plan = parsed._jdf.queryExecution().analyzed()
    # Aggregates, windows and generators make a plan of their own around the projection.
    if plan.getClass().getSimpleName() != "Project" or plan.children().apply(0).getClass().getSimpleName() != "GlobalLimit":
        return "function"
    expression = plan.projectList().apply(0)
    if _refused(expression):
        return "function"
    if parsed.schema["ok"].dataType.simpleString() != "boolean":
        return "type"
    used = expression.references().toSeq()
    names = {used.apply(i).name() for i in range(used.size())}
    return None if names <= allowed else "forbidden column"


def executable(view: DataFrame, texts: list[str]) -> list[str]:
    """The predicates that run through on all rows; one job, and halves of what fails."""
    if not texts:
        return []
    try:
        view.select(*[satisfied(t).alias(f"r{i}") for i, t in enumerate(texts)]).write.format("noop").mode("overwrite").save()
    except Exception:
        return [] if len(texts) == 1 else [*executable(view, texts[: len(texts) // 2]), *executable(view, texts[len(texts) // 2 :])]
    return texts


# ---- measuring
def satisfied(text: str) -> Column:
    """The predicate with NULL as not satisfied."""
    return F.coalesce(F.expr(text), F.lit(False))


def _counter(rules: list[Conditions | None], names: list[str]):
    """Per task (rule, rows, positives, support, hits) of all rules over batches of y, packed bits and features."""
    import numpy as np
    import pyarrow as pa

    schema = pa.schema([(c, pa.int64()) for c in ("rule", "labelled", "positives", "support", "hits")])
    texts = [i for i, r in enumerate(rules) if r is None]

    def values(column) -> np.ndarray:
        x = column.to_numpy(zero_copy_only=False).astype(float)
        known = column.is_valid().to_numpy(zero_copy_only=False)
        # To Spark a stored NaN is greater than any number.
        return np.where(known & np.isnan(x), np.inf, x)

    def run(batches):
        support, hits, labelled, positives = np.zeros(len(rules), np.int64), np.zeros(len(rules), np.int64), 0, 0
        for batch in batches:
            y = values(batch.column("y"))
            one = y == 1
            labelled, positives = labelled + int((~np.isnan(y)).sum()), positives + int(one.sum())
            for k, i in enumerate(texts):
                bit = (batch.column(f"_bits{k // CHUNK}").to_numpy(zero_copy_only=False) >> (k % CHUNK) & 1).astype(bool)
                support[i] += bit.sum()
                hits[i] += (bit & one).sum()
            x, known = {f: values(batch.column(f)) for f in names}, {}
            for i, rule in enumerate(rules):
                if rule is None:
                    continue
                fits = None
                for f, op, t in rule:
                    if (f, op, t) not in known:
                        known[f, op, t] = x[f] <= t if op == "<=" else x[f] > t
                    fits = known[f, op, t] if fits is None else fits & known[f, op, t]
                support[i] += fits.sum()
                hits[i] += (fits & one).sum()
        n = len(rules)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(n)), pa.array(np.full(n, labelled)), pa.array(np.full(n, positives)), pa.array(support), pa.array(hits)], schema=schema)

    return run


def measure(view: DataFrame, rules: list[str], conditions: dict[str, Conditions] | None = None) -> DataFrame:
    """(rule, text, support, confidence, lift) of each predicate over a view with y, in one scan; ``conditions`` of those that have them."""
    known = [(conditions or {}).get(r) for r in rules]
    texts = [r for r, c in zip(rules, known) if c is None]
    names = sorted({f for c in known if c for f, _, _ in c})
    pack = lambda some: reduce(lambda a, b: a.bitwiseOR(b), [F.shiftleft(satisfied(t).cast("long"), i) for i, t in enumerate(some)])
    bits = [pack(texts[a : a + CHUNK]).alias(f"_bits{a // CHUNK}") for a in range(0, len(texts), CHUNK)]
    rows = view.select(F.col("y").cast("double").alias("y"), *bits, *[F.col(f).cast("double").alias(f) for f in names])
    counted = rows.mapInArrow(_counter(known, names), "rule long, labelled long, positives long, support long, hits long")
    summed = counted.groupBy("rule").agg(*[F.sum(c).alias(c) for c in ("labelled", "positives", "support", "hits")])
    named = summed.join(F.broadcast(view.sparkSession.createDataFrame(list(enumerate(rules)), "rule long, text string")), "rule")
    base = F.try_divide(F.col("positives"), F.col("labelled"))
    confidence = F.coalesce(F.try_divide(F.col("hits"), F.col("support")), F.lit(0.0))
    return named.select("rule", "text", "support", confidence.alias("confidence"), F.coalesce(F.try_divide(confidence, base), F.lit(0.0)).alias("lift"))


MEASURED = "rule long, text string, support long, confidence double, lift double"
RANKED = f"{MEASURED}, rank long"


def ranked(measured: DataFrame, preset: Preset) -> DataFrame:
    """Rules that pass the filter, ranked by confidence, support, brevity and text; at most the pool."""
    size = F.size(F.split("text", " AND "))
    order = Window.partitionBy(F.lit(0)).orderBy(F.col("confidence").desc(), F.col("support").desc(), size, "text")
    kept = measured.filter((F.col("support") >= preset.min_support) & (F.col("confidence") >= preset.min_confidence))
    return kept.withColumn("rank", F.row_number().over(order).cast("long")).filter(F.col("rank") <= preset.pool)


def seeds(pool: DataFrame, n: int, salt: str = "seed") -> DataFrame:
    """n rules drawn without replacement in proportion to their confidence, by exponential keys."""
    key = -F.ln(F.greatest(u(F.col("text"), salt), F.lit(1e-12))) / F.greatest("confidence", F.lit(1e-9))
    return pool.withColumn("key", key).orderBy("key", "text").limit(n).drop("key")


def revalidate(view: DataFrame, proposals: list[str], allowed: set[str], preset: Preset, trusted: dict[str, Conditions] | None = None) -> DataFrame:
    """Proposals go through validation, measuring, filter and ranking like any other rule; refused ones and repeats drop out.

    ``trusted`` texts with their conditions, such as forest paths, are written by the engine itself and not parsed again.
    """
    fine = admitted(view, proposals, allowed, trusted or {})
    return ranked(measure(view, fine, trusted), preset) if fine else ranked(measure(view, ["false"]), preset).limit(0)


def admitted(view: DataFrame, proposals: list[str], allowed: set[str], trusted: dict[str, Conditions]) -> list[str]:
    """Proposals without repeats and without those that validation refuses."""
    proposals = list(dict.fromkeys(proposals))
    columns_only = view.sparkSession.createDataFrame([], view.schema)
    free = set(executable(view, [t for t in proposals if t not in trusted and problem(columns_only, t, allowed) is None]))
    return [t for t in proposals if t in trusted or t in free]


def split_texts(nodes: DataFrame, features: list[str], first_trees: int, limit: int = 64) -> list[str]:
    """Each inner node of the first trees as a predicate of its own, in order of tree and node, without repeats; at most ``limit``."""
    inner = nodes.filter((F.col("tree") < first_trees) & (F.col("left") >= 0)).groupBy("feature", "threshold").agg(F.min(F.struct("tree", "node")).alias("first"))
    return [text_of([(features[r["feature"]], "<=", r["threshold"])]) for r in inner.orderBy("first").limit(limit).collect()]


# ---- refinement
def prune(rule: list[tuple[str, str, float]]) -> list[list[tuple[str, str, float]]]:
    return [rule[:i] + rule[i + 1 :] for i in range(len(rule))] if len(rule) > 1 else []


def tighten(view: DataFrame, rule: list[tuple[str, str, float]]) -> list[tuple[str, str, float]]:
    """Upper thresholds move down to the covered positives' maximum; lower ones up to just under their minimum."""
    return tightened(view, [rule])[0]


def tightened(view: DataFrame, rules: list[Conditions]) -> list[Conditions]:
    """Each rule tightened, all in one scan."""
    bound = lambda rule, f, op: (F.max if op == "<=" else F.min)(F.when(satisfied(text_of(rule)), F.col(f).cast("double")))
    bounds = [bound(rule, f, op) for rule in rules for f, op, _ in rule]
    row = iter(view.filter("y = 1").agg(*[b.alias(f"c{i}") for i, b in enumerate(bounds)]).first() if bounds else ())
    at = lambda op, t, v: t if v is None else v if op == "<=" else max(t, v - max(1e-9, abs(v) * 1e-9))
    return [[(f, op, at(op, t, next(row))) for f, op, t in rule] for rule in rules]


def combine(a: list[tuple[str, str, float]], b: list[tuple[str, str, float]]) -> list[tuple[str, str, float]] | None:
    return canonical([*a, *b])


def either(a: list[tuple[str, str, float]], b: list[tuple[str, str, float]]) -> str:
    """Disjunction of two rules; it has no conditions of its own and goes on as a text."""
    return f"({text_of(a)}) OR ({text_of(b)})"


def generalize(rule: list[tuple[str, str, float]], digits: int = 1) -> list[tuple[str, str, float]]:
    """Thresholds rounded outwards to few digits."""
    from math import ceil, floor

    scale = 10**digits
    return [(f, op, (ceil if op == "<=" else floor)(t * scale) / scale) for f, op, t in rule]


@dataclass(frozen=True)
class Context:
    """What a proposer may see: train statistics, a few positive train rows, seed rules with their measures."""

    features: list[str]
    statistics: list[dict]
    positives: list[dict]
    seeds: list[dict]


def guarded_context(train: DataFrame, features: list[str], seed_rows: list[dict], limit: int = 20) -> Context:
    """Refuses anything but train rows."""
    from relanom.encode import profile

    if train.filter("split <> 'train' or split is null").limit(1).count():
        raise ValueError("a proposer sees train rows only")
    positives = train.filter("y = 1").select(*features).limit(limit).collect()
    return Context(features, [r.asDict() for r in profile(train, features).collect()], [r.asDict() for r in positives], seed_rows)


class ScriptedProposer:
    """Deterministic moves over seeds: prune, generalise, combine pairs by AND and by OR; tightening needs the view and is done by ``mine``."""

    reads_context = False

    def __init__(self, budget: int = 200):
        self.budget = budget

    def propose(self, context: Context, rules: list[list[tuple[str, str, float]]]) -> list[str]:
        out: dict[str, None] = {}
        for r in rules:
            for new in [*prune(r), generalize(r)]:
                out[text_of(new)] = None
        for i, a in enumerate(rules):
            for b in rules[i + 1 : i + 4]:
                if both := combine(a, b):
                    out[text_of(both)] = None
                out[either(a, b)] = None
        return list(out)[: self.budget]


class RecordedProposer:
    """Replays predicates from a file, one a line."""

    def __init__(self, path: str):
        self.path = path

    def propose(self, context: Context, rules) -> list[str]:
        with open(self.path) as f:
            return [line.strip() for line in f if line.strip()]


class CallbackProposer:
    """Hands the context to a function of the user's, such as a language model client."""

    def __init__(self, function: Callable[[Context], list[str]]):
        self.function = function

    def propose(self, context: Context, rules) -> list[str]:
        return self.function(context)


# ---- frozen rules
@dataclass(frozen=True)
class RuleSet:
    """Rules in order; nothing about them changes after mining."""

    texts: tuple[str, ...]
    confidences: tuple[float, ...] = field(default=())
    #: What they were mined from, for other rules of the same rows.
    pool: Pool | None = field(default=None, compare=False, repr=False)

    @property
    def fingerprint(self) -> str:
        return sha256("\n".join(self.texts).encode()).hexdigest()

    def save(self, path: str) -> None:
        with open(path, "w") as f:
            json.dump({"texts": self.texts, "confidences": self.confidences, "fingerprint": self.fingerprint}, f)

    @staticmethod
    def load(path: str) -> RuleSet:
        with open(path) as f:
            d = json.load(f)
        out = RuleSet(tuple(d["texts"]), tuple(d["confidences"]))
        if out.fingerprint != d["fingerprint"]:
            raise ValueError("the rule file was changed")
        return out

    def vector(self) -> Column:
        """0/1 per rule; map-side only."""
        return F.array(*[satisfied(t).cast("double") for t in self.texts]) if self.texts else F.array().cast("array<double>")

    def score(self) -> Column:
        """Best confidence of the satisfied rules."""
        return F.greatest(F.lit(0.0), F.lit(0.0), *[F.when(satisfied(t), F.lit(float(c))).otherwise(0.0) for t, c in zip(self.texts, self.confidences)])

    def explain(self) -> Column:
        return F.array_compact(F.array(*[F.when(satisfied(t), F.lit(f"{t} ({c:.3f})")) for t, c in zip(self.texts, self.confidences)]))


def without_losses(rows: list, chosen: list[Conditions]) -> list:
    """Measured rules without those that dropped a condition of a chosen rule and lost confidence by it."""
    confidence = {r["text"]: r["confidence"] for r in rows}
    parents: dict[str, list[str]] = {}
    for rule in chosen:
        for shorter in prune(rule):
            parents.setdefault(text_of(shorter), []).append(text_of(rule))
    return [r for r in rows if r["text"] not in parents or any(r["confidence"] >= confidence.get(p, 0.0) for p in parents[r["text"]])]


@dataclass(frozen=True)
class Pool:
    """What path rules and refined ones both start from: the forest, its rules by text, the measured pool, the seeds drawn from it."""

    nodes: DataFrame
    by_text: dict[str, Conditions]
    measured: list[dict]
    drawn: list[dict]


def pooled(view: DataFrame, features: list[str], preset: Preset, folder: str, seed: int = 0) -> Pool:
    """Forest paths, measured and ranked on the preset's split.

    Only the trees that paths are read from are grown: the others would change nothing.
    """
    nodes = forest.fit(view.filter("split = 'train'"), features, preset, folder, seed, preset.first_trees)
    found = candidates(paths(nodes, preset.first_trees, preset.leaf_rows, preset.leaf_positive), features, preset)
    by_text = {text_of(r): r for r in found}
    measured = [r.asDict() for r in ranked(measure(view.filter(F.col("split") == preset.select_on), list(by_text), by_text), preset).collect()] if found else []
    drawn = [r.asDict() for r in seeds(view.sparkSession.createDataFrame(measured, RANKED), preset.seeds).collect()] if measured else []
    return Pool(nodes, by_text, measured, drawn)


def mine(view: DataFrame, features: list[str], preset: Preset, folder: str, refine: bool = True, proposer=None, seed: int = 0, pool: Pool | None = None) -> RuleSet:
    """Seeds of the pool; with ``refine`` proposals made from them are measured and ranked alike. ``view`` has y and split; ``pool`` of it if it is known."""
    view = view.persist()
    try:
        pool = pool or pooled(view, features, preset, folder, seed)
        return _mined(view, features, preset, pool, refine, proposer or ScriptedProposer())
    finally:
        view.unpersist()


def _mined(view: DataFrame, features: list[str], preset: Preset, pool: Pool, refine: bool, proposer) -> RuleSet:
    by_text, drawn = pool.by_text, pool.drawn
    if not by_text:
        return RuleSet((), (), pool)
    train, on = view.filter("split = 'train'"), view.filter(F.col("split") == preset.select_on)
    if not refine:
        best = drawn
    else:
        context = guarded_context(train, features, drawn) if getattr(proposer, "reads_context", True) else None
        chosen = [by_text[d["text"]] for d in drawn]
        tight = [rule for r in tightened(train, chosen[:5]) if (rule := canonical(r))]
        trusted = by_text | {text_of(r): r for r in [*tight, *(p for r in chosen for p in prune(r))]}
        proposals = [t for t in [*proposer.propose(context, chosen), *map(text_of, tight)] if t not in by_text]
        new = [r.asDict() for r in measure(on, admitted(on, proposals, set(features), trusted), trusted).collect()]
        # The paths are measured already, and one that is not in their pool cannot be in that of all.
        every = view.sparkSession.createDataFrame([{k: r[k] for k in ("rule", "text", "support", "confidence", "lift")} for r in [*pool.measured, *new]], MEASURED)
        rows = ranked(every, preset).orderBy("rank").collect()
        best = without_losses(rows, chosen)[: preset.max_rules]
    return RuleSet(tuple(r["text"] for r in best), tuple(float(r["confidence"]) for r in best), pool)

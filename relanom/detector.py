"""Receptive fields of the tasks and the detector that joins rules, graph and training."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, LongType, StructField, StructType

from relanom import nn, rules, splits, tasks, trainer, views
from relanom.sources import load, stored


#: Codes that brands are hashed to.
BRANDS = 32


@dataclass
class Task:
    """rows: target, y, split, flat features and nb columns; features: flat ones; relations: widths of each nb.

    ``through`` names, for relations whose second hop are other targets, the column of the shared neighbour and the time
    before which those targets lie: their mean features and rule bits join when the features are assembled.
    """

    name: str
    rows: DataFrame
    features: list[str]
    relations: tuple[nn.Relation, ...]
    through: dict[int, tuple[str, str]] = field(default_factory=dict)


def _neighbours(ident, x: list, m: list | None, code=None):
    """Models compute with single precision, so neighbours are stored in it, and a category as its code."""
    numbers = lambda columns: F.array(*[F.coalesce(c.cast("double"), F.lit(0.0)).cast("float") for c in columns])
    fields = [ident.cast("long").alias("id"), numbers(x).alias("x"), (numbers(m) if m is not None else F.lit(None).cast("array<float>")).alias("m")]
    return F.struct(*fields, *([] if code is None else [code.cast("int").alias("code")]))


def customer_task(spark, sf_dir: str, kind: str = "purchase", labels: DataFrame | None = None) -> Task:
    """Customers with all their transactions and each transaction's article; everything at or before the cut."""
    view = views.purchase(spark, sf_dir) if kind == "purchase" else views.review(spark, sf_dir)
    features = [c for c in view.columns if c != "entity"]
    if labels is None:
        from relanom.queries.labels_metrics import labelled

        labels = labelled(spark, sf_dir, kind)
    log = tasks.transactions(spark, sf_dir) if kind == "purchase" else tasks.reviews(spark, sf_dir)
    age = F.datediff(F.lit(tasks.CUT), "t")
    log = log.withColumn("age", age).filter("age >= 0")
    parts = load(spark, sf_dir, "part", ["p_partkey", "p_brand", "p_size", "p_retailprice"])
    far, brand = [F.col("p_size") / 50, F.col("p_retailprice") / 1000], F.pmod(F.xxhash64("p_brand"), F.lit(BRANDS))
    near = [F.col("age") / 1000, F.col("price") / 50000, F.col("quantity") / 50]
    joined = log.join(parts, F.col("part") == F.col("p_partkey"), "left")
    # A transaction is a neighbour of its customer only, so its id need not be more than distinct. In an order of their own, means come out alike in every run.
    ident = F.xxhash64("customer", "part", "t", "price", "quantity")
    fields = joined.groupBy("customer").agg(F.array_sort(F.collect_list(_neighbours(ident, near, far, brand))).alias("nb0"))
    rows = view.join(labels.select("entity", F.col("y").cast("int").alias("y")), "entity").join(fields, F.col("entity") == F.col("customer"), "left")
    rows = rows.withColumn("split", splits.by_hash(F.col("entity"))).withColumn("target", F.col("entity").cast("long"))
    return Task(kind, rows.drop("customer", "entity"), features, (nn.Relation(len(near), len(far) + BRANDS, back=True, hot=BRANDS),))


def cyber_task(spark, sf_dir: str, labels: DataFrame | None = None) -> Task:
    """Authentication events with their user and machine; the second hop are the user's and the machine's earlier authentications."""
    view = views.cyber(spark, sf_dir)
    features = [c for c in view.columns if c not in ("event", "t", "user", "machine")]
    if labels is None:
        from relanom.labels import behavioural

        labels = behavioural(tasks.auth_log(spark, sf_dir))
    users = load(spark, sf_dir, "customer", ["c_custkey", "c_acctbal", "c_nationkey"])
    joined = view.join(labels.select("event", F.col("y").cast("int").alias("y")), "event").join(users, F.col("user") == F.col("c_custkey"), "left")
    user = _neighbours(F.col("user"), [F.col("c_acctbal") / 10000, F.col("c_nationkey") / 25], None)
    machine = _neighbours(F.col("machine"), [F.lit(1.0)], None)  # the tables say nothing of a machine but that it is one
    rows = joined.withColumn("nb0", F.array(user)).withColumn("nb1", F.array(machine)).withColumn("split", splits.by_hash(F.col("event"))).withColumn("target", F.col("event"))
    return Task("cyber", rows.withColumn("us", F.unix_micros(F.col("t").cast("timestamp"))), features, (nn.Relation(2, 0, own=True), nn.Relation(1, 0, own=True)), {0: ("user", "us"), 1: ("machine", "us")})


def document_task(spark, sf_dir: str) -> Task:
    """Documents with their source and language; labels cover some, the others have y null and still shape their source's state."""
    view = views.documents(spark, sf_dir)
    features = ["chars", "spaces", "digit_share", "upper_share", "mark_share"]
    known = load(spark, sf_dir, "labels", ["doc_id", "toxic"]).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("y"))
    rows = view.join(known, F.col("entity") == F.col("doc_id"), "left")
    for k, parent in enumerate(("source", "lang")):
        state = view.groupBy(parent).agg(F.log1p(F.count("*")).alias("n"), *(F.avg(c).alias(f"m_{c}") for c in features))
        near = _neighbours(F.xxhash64(parent), [F.col("n")], [F.log1p("m_chars"), *(F.col(f"m_{c}") for c in features[2:])])
        rows = rows.join(state.select(F.col(parent).alias("parent"), F.array(near).alias(f"nb{k}")), F.col(parent) == F.col("parent"), "left").drop("parent")
    rows = rows.withColumn("split", splits.by_hash(F.col("entity"))).withColumn("target", F.col("entity"))
    return Task("documents", rows.drop("doc_id", "entity", "source", "lang"), features, (nn.Relation(1, 4), nn.Relation(1, 4)))


def earlier_means(rows: DataFrame, key: str, time: str, width: int, name: str, slices: int = 64, base: DataFrame | None = None) -> DataFrame:
    """Adds the mean of array ``x`` over the rows of the same key strictly before each row's time, null where there are none.

    Time is cut into slices; sums per key and slice are carried forward, and only the rows of one key and slice meet in a
    task, so a key with a third of all rows is spread over its slices.  ``base`` are the same rows by a shorter plan, if there
    is one: what is summed up beforehand comes from it.
    """
    base = rows if base is None else base
    span = base.agg(F.min(time).alias("low"), F.max(time).alias("high")).first()
    wide = max(1, ((span["high"] or 0) - (span["low"] or 0)) // slices + 1)
    sliced = lambda df: df.withColumn("_slice", F.floor((F.col(time) - (span["low"] or 0)) / wide))
    rows, base = sliced(rows), sliced(base)
    sums = base.select(key, "_slice", "x").filter(F.col(key).isNotNull() & F.col("_slice").isNotNull())
    before_schema = StructType([*sums.schema.fields[:2], StructField("_bn", LongType()), StructField("_bs", ArrayType(DoubleType()))])
    before = sums.mapInArrow(_slice_sums(key, width), before_schema).repartition(F.col(key)).sortWithinPartitions(key, "_slice").mapInArrow(_carried(key, width), before_schema)
    near_schema = StructType([*rows.schema.fields, StructField("_n", LongType()), StructField("_s", ArrayType(DoubleType()))])
    near = rows.repartition(F.col(key), F.col("_slice")).sortWithinPartitions(key, "_slice", time).mapInArrow(_inside(key, time, width), near_schema)
    joined = near.join(before, [key, "_slice"])
    n = F.col("_n") + F.col("_bn")
    return joined.withColumn(name, F.when(n > 0, F.zip_with("_s", "_bs", lambda a, b: (a + b) / n))).select(*[c for c in rows.columns if c != "_slice"], name)


def _vectors(lists, width: int) -> np.ndarray:
    """A list column as a matrix of doubles; what is null adds nothing."""
    out, known = np.zeros((len(lists), width)), lists.is_valid().to_numpy(zero_copy_only=False)
    if known.any() and width:
        out[known] = pc.fill_null(lists.flatten().cast(pa.float64()), 0.0).to_numpy(zero_copy_only=False).reshape(-1, width)
    return out


def _lists(x: np.ndarray) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * x.shape[1], pa.int32()), pa.array(x.ravel()))


def _slice_sums(key: str, width: int):
    """Rows and sums of ``x`` per key and slice of each batch."""

    def run(batches):
        for batch in batches:
            by = np.rec.fromarrays([batch.column(c).to_numpy(zero_copy_only=False) for c in (key, "_slice")])
            _, first, place = np.unique(by, return_index=True, return_inverse=True)
            if len(first):
                columns = [batch.column(c).take(pa.array(first)) for c in (key, "_slice")]
                yield pa.RecordBatch.from_arrays([*columns, pa.array(np.bincount(place)), _lists(nn._sums(_vectors(batch.column("x"), width), place, len(first)))], names=[key, "_slice", "_bn", "_bs"])

    return run


def _carried(key: str, width: int):
    """One row per key and slice, sorted by both, with what lies in the key's slices before it."""

    def run(batches):
        at, before, total = None, (0, np.zeros(width)), (0, np.zeros(width))
        for batch in batches:
            ids, out = list(zip(batch.column(key).to_pylist(), batch.column("_slice").to_pylist())), []
            for i, (now, n, x) in enumerate(zip(ids, batch.column("_bn").to_pylist(), _vectors(batch.column("_bs"), width))):
                if now != at:
                    before = total if at and now[0] == at[0] else (0, np.zeros(width))
                    at, total = now, before
                    out.append((i, *before))
                total = total[0] + n, total[1] + x
            if out:
                columns = [batch.column(c).take(pa.array([i for i, _, _ in out])) for c in (key, "_slice")]
                yield pa.RecordBatch.from_arrays([*columns, pa.array([n for _, n, _ in out]), _lists(np.array([x for _, _, x in out]).reshape(-1, width))], names=[key, "_slice", "_bn", "_bs"])

    return run


def _inside(key: str, time: str, width: int):
    """Adds rows and sums of ``x`` over what lies strictly before a row in its key and slice; the rows come sorted by key, slice and time."""

    def run(batches):
        at, last, before, total = None, None, (0, np.zeros(width)), (0, np.zeros(width))
        for batch in batches:
            ids, when = [batch.column(c).to_numpy(zero_copy_only=False) for c in (key, "_slice")], batch.column(time).to_numpy(zero_copy_only=False)
            x, n, s = _vectors(batch.column("x"), width), np.zeros(len(when), np.int64), np.zeros((len(when), width))
            starts = np.flatnonzero(np.concatenate(([True], (ids[0][1:] != ids[0][:-1]) | (ids[1][1:] != ids[1][:-1])))) if len(when) else []
            for a, b in zip(starts, [*starts[1:], len(when)]):
                if at != (ids[0][a], ids[1][a]):
                    at, last, before, total = (ids[0][a], ids[1][a]), None, (0, np.zeros(width)), (0, np.zeros(width))
                if b - a == 1:
                    before, last = (before if when[a] == last else total), when[a]
                    n[a], s[a] = before
                    total = total[0] + 1, total[1] + x[a]
                    continue
                # Sums up to before each row of the segment; rows of one time take those of the first of them.
                upto = np.cumsum(np.concatenate((total[1][None], x[a:b])), axis=0)
                first = np.maximum.accumulate(np.where(np.concatenate(([True], when[a + 1 : b] != when[a : b - 1])), np.arange(b - a), 0))
                n[a:b], s[a:b] = total[0] + first, upto[first]
                if when[a] == last:
                    same = first == 0
                    n[a:b][same], s[a:b][same] = before
                before, last, total = (n[b - 1], s[b - 1].copy()), when[b - 1], (total[0] + b - a, upto[-1])
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(n), _lists(s)], names=[*batch.schema.names, "_n", "_s"])

    return run


def assembled(task: Task, rule_set: rules.RuleSet | None = None, flat: bool = False) -> tuple[DataFrame, nn.Spec]:
    """Standardised features, rule bits behind them, neighbours: what a model trains on. Statistics come from train rows."""
    from relanom import encode

    train = task.rows.filter("split = 'train'")
    rows = encode.impute(task.rows, encode.imputer(train, task.features, "mean"))
    scale = encode.scaler(rows.filter("split = 'train'"), task.features)
    # Five deviations are far enough: beyond, one heavy-tailed feature would outweigh all others in the squared error.
    x = F.array(*[F.greatest(F.lit(-5.0), F.least(F.lit(5.0), (F.col(f) - m) / s)) for f, (m, s) in scale.items()])
    bits = len(rule_set.texts) if rule_set else 0
    if bits:
        x = F.concat(x, rule_set.vector())
    width = len(task.features) + bits
    if flat:
        return rows.select("target", "y", "split", x.alias("x")), nn.Spec(width)
    keys = sorted({c for pair in task.through.values() for c in pair})
    rows = rows.select("target", "y", "split", x.alias("x"), *keys, *[f"nb{k}" for k in range(len(task.relations))])
    base = rows
    for k, (key, time) in task.through.items():
        rows = earlier_means(rows, key, time, width, "_m", base=base)
        # The rule bits of other targets reach this one through the neighbour they share.
        rows = rows.withColumn(f"nb{k}", F.transform(f"nb{k}", lambda n: F.struct(n["id"].alias("id"), n["x"].alias("x"), F.col("_m").cast("array<float>").alias("m")))).drop("_m")
    relations = tuple(r._replace(m=width) if r.own else r for r in task.relations)
    # Means are taken in double precision, models compute with single.
    return rows.drop(*keys).withColumn("x", F.col("x").cast("array<float>")), nn.Spec(width, relations)


class RelationalDetector:
    """Rule-augmented relational autoencoder; ``rule_set`` None leaves rules out."""

    def __init__(self, rule_set: rules.RuleSet | None = None, alpha: float = 0.0, beta: float = 1.0, hidden: int = 128, rounds: int = 4, seed: int = 0, rate: float = 0.001):
        self.rule_set, self.alpha, self.beta, self.hidden, self.rounds, self.seed, self.rate = rule_set, alpha, beta, hidden, rounds, seed, rate

    def fit(self, task: Task) -> RelationalDetector:
        rows, spec = assembled(task, self.rule_set)
        self.rows = stored(rows, "assembled")
        self.fitted = trainer.fit(self.rows, nn.RelationalAutoencoder(spec, self.hidden, self.seed, alpha=self.alpha, beta=self.beta), self.rounds, rate=self.rate, seed=self.seed)
        return self

    def transform(self, rows: DataFrame | None = None) -> DataFrame:
        return self.fitted.transform(self.rows if rows is None else rows)

    def embed(self, rows: DataFrame | None = None) -> DataFrame:
        """Embeddings z of the targets."""
        return self.fitted.embed(self.rows if rows is None else rows)

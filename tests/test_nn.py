import numpy as np
import pytest
from pyspark.sql import functions as F

from relanom import detector, forest, isolation, layers, metrics, nn, tasks, trainer


@pytest.fixture
def exact(monkeypatch):
    monkeypatch.setattr(nn, "PRECISION", np.float64)


def batch(rng, spec, n=12):
    relations = []
    for r in spec.relations:
        seg = np.sort(rng.integers(0, n, 20))
        relations.append({"seg": seg, "id": rng.integers(0, 9, 20), "x": rng.standard_normal((20, r.x)), "m": rng.standard_normal((20, r.m)), "has": (rng.random(20) < 0.8).astype(float)})
    y = np.zeros(n)
    y[:3] = 1
    y[-2:] = np.nan
    return {"x": rng.standard_normal((n, spec.x)), "y": y, "relations": relations}


SPEC = nn.Spec(5, (nn.Relation(3, 4, back=True), nn.Relation(2, 5, own=True)))
MODELS = [
    lambda: nn.RelationalAutoencoder(SPEC, 6, act="tanh", alpha=0.3, beta=0.7),
    lambda: nn.SupervisedGraph(SPEC, 6, act="tanh", weighted=True),
    lambda: nn.Mlp(nn.Spec(5), 6, act="tanh"),
    lambda: nn.Autoencoder(nn.Spec(5), 8, act="tanh", beta=0.5),
    lambda: nn.DeepSvdd(nn.Spec(5), 6, act="tanh"),
    lambda: nn.DecomposedRepresentation(nn.Spec(5), 6, act="tanh"),
]


@pytest.mark.parametrize("make", MODELS)
def test_gradients(exact, make):
    rng, model = np.random.default_rng(3), make()
    b = batch(rng, model.spec)
    if isinstance(model, nn.DeepSvdd):
        model.prepare(b)
    p = model.vars()
    loss = model.loss(p, b, np.random.default_rng(5))
    loss.backward()
    value = lambda: float(model.loss(model.vars(), b, np.random.default_rng(5)).value)
    for name, array in model.params.items():
        grad = p[name].grad if p[name].grad is not None else np.zeros_like(array)
        for at in list(np.ndindex(array.shape))[:: max(1, array.size // 6)]:
            old, e = array[at], 1e-6
            array[at] = old + e
            up = value()
            array[at] = old - e
            down = value()
            array[at] = old
            assert grad[at] == pytest.approx((up - down) / (2 * e), rel=1e-4, abs=1e-6)


def test_rank_loss_and_adam(exact):
    s = nn.Var(np.zeros(4))
    assert float(nn.rank_loss(s, np.array([1, 0, 0, 0.0]), np.random.default_rng(0)).value) == pytest.approx(np.log(2))
    params, adam = {"a": np.array([1.0, -2.0])}, nn.Adam(0.1)
    adam.step(params, {"a": np.array([3.0, -0.5])})
    assert params["a"] == pytest.approx([0.9, -1.9])
    assert nn.RelationalAutoencoder(SPEC, 4).params.keys().isdisjoint({"edge0"})


def test_isolation_constants():
    assert isolation.c(1) == 0 and isolation.c(2) == 1
    assert isolation.c(256) == pytest.approx(2 * (np.log(255) + 0.5772156649) - 2 * 255 / 256)


def test_soft_boundary_counts_what_is_outside(exact):
    model, rng = nn.DeepSvdd(nn.Spec(5), 6, decay=0.0, nu=0.25), np.random.default_rng(2)
    b = batch(rng, nn.Spec(5))
    model.prepare(b)
    d = model.score(model.vars(), b)
    radius = np.quantile(d, 0.75)
    assert float(model.loss(model.vars(), b, rng).value) == pytest.approx(np.maximum(0, d - radius).mean() / 0.25)
    p = model.vars()
    model.loss(p, b, rng).backward()
    inside = nn.part_of(b, np.flatnonzero(d <= radius))
    assert np.abs(p["w1"].grad).sum() > 0 and len(inside["x"]) == 9


def numbered(n, positive):
    y = np.zeros(n)
    y[:positive] = 1
    return {"x": np.arange(n, dtype=float)[:, None], "y": y, "relations": []}


@pytest.mark.parametrize("rows, positive", [(4000, 1200), (900, 700), (100, 0)])
def test_mini_batches_reach_all_rows_and_positives(rows, positive):
    whole = numbered(rows, positive)
    stream = [nn.part_of(whole, np.arange(a, min(a + 700, rows))) for a in range(0, rows, 700)]
    seen = [b["x"][:, 0].astype(int) for b in nn.mini_batches(iter(stream), 3, 512, np.random.default_rng(7))]
    assert len(seen) >= 3 and len(np.unique(np.concatenate(seen))) == rows
    if positive > 512:
        # The added positives are drawn anew, not the same low ids each time.
        assert not set(range(256)) <= set(seen[0].tolist()) & set(seen[1].tolist())
    assert list(nn.mini_batches(iter([]), 3, 512, np.random.default_rng(7))) == []


def test_rows_without_a_label_are_no_negatives(exact):
    y = np.array([1, 0, np.nan, np.nan])
    score = nn.Var(np.array([1.0, 0.0, 50.0, 60.0]))
    loss = nn.rank_loss(score, y, np.random.default_rng(0))
    assert float(loss.value) == pytest.approx(np.log1p(np.exp(-1.0)))
    model, rng = nn.SupervisedGraph(SPEC, 6), np.random.default_rng(1)
    b = batch(rng, SPEC)
    known = ~np.isnan(b["y"])
    only = nn.part_of(b, np.flatnonzero(known))
    p = model.vars()
    assert float(model.loss(p, b, rng).value) == pytest.approx(float(model.loss(p, only, rng).value))


def test_drawn_pairs_are_no_edges():
    rng = np.random.default_rng(0)
    seg, ids = np.sort(rng.integers(0, 40, 400)), rng.integers(0, 12, 400)
    drawn, real = nn.non_edges(seg, ids, rng)
    edges = set(zip(seg.tolist(), ids.tolist()))
    assert real.mean() > 0.3 and not any((s, ids[d]) in edges for s, d, r in zip(seg.tolist(), drawn.tolist(), real) if r)


def test_shards_are_at_most_the_cores():
    assert trainer.shards_for(100, 30, 512, 4) == 1
    assert trainer.shards_for(30 * 512 * 9 + 1, 30, 512, 16) == 10
    assert trainer.shards_for(10**9, 30, 512, 16) == 16


def test_optimiser_state_goes_on(exact):
    whole, models = numbered(600, 50), {"m": nn.Mlp(nn.Spec(1), 4)}
    _, first = nn.train_steps(models, {}, iter([whole]), 4, 128, {"m": 0.01}, 1)
    _, second = nn.train_steps(models, {"m": first["m"][1]}, iter([whole]), 4, 128, {"m": 0.01}, 1)
    assert first["m"][1][0] == 5 and second["m"][1][0] == 10


def test_forward_pass_scores_and_losses_equal_the_column_forms(spark, exact):
    """Targets t, neighbours n, their neighbours f: the kernel on receptive fields against layers over the whole graph."""
    rng, h = np.random.default_rng(4), 3
    x_t, x_n, x_f = rng.standard_normal((3, 2)), rng.standard_normal((5, 2)), rng.standard_normal((4, 3))
    owner, far = [0, 0, 0, 2, 2], [[0, 1], [1], [], [2, 3, 0], [3]]
    spec = nn.Spec(2, (nn.Relation(2, 3, back=True),))
    model = nn.RelationalAutoencoder(spec, h, 1)
    model.params = {k: v + 0.1 * rng.standard_normal(v.shape) for k, v in model.params.items()}
    p = model.params
    b = {"x": x_t, "y": np.array([1.0, 0.0, 0.0]), "relations": [{"seg": np.array(owner), "id": np.arange(5), "x": x_n, "m": np.array([x_f[f].mean(axis=0) if f else np.zeros(3) for f in far]), "has": np.array([float(bool(f)) for f in far])}]}
    z, _, first = model.layers(model.vars(), b)
    nodes = lambda x, base: spark.createDataFrame([(base + i, [float(v) for v in row]) for i, row in enumerate(x)], "nid long, x array<double>")
    T = lambda k: p[k].T.tolist()
    h0 = layers.project(nodes(x_t, 0), T("Win"), p["bin"].tolist())
    for x, base, k in ((x_n, 100, "nb0"), (x_f, 200, "far0")):
        h0 = h0.unionByName(layers.project(nodes(x, base), T(f"W{k}"), p[f"b{k}"].tolist()))
    e = [("rel", 100 + i, t) for i, t in enumerate(owner)] + [("back", t, 100 + i) for i, t in enumerate(owner)] + [("far", 200 + j, 100 + i) for i, f in enumerate(far) for j in f]
    e = spark.createDataFrame([(*r, None) for r in e], "rel string, src long, dst long, t timestamp_ntz")
    h1 = layers.layer(e, h0, T("self1"), {"rel": T("rel1_0"), "back": T("back1_0"), "far": T("far1_0")})
    h2 = layers.layer(e, h1, T("self2"), {"rel": T("rel2_0")})
    got1, got2 = ({r.nid: r.h for r in d.collect()} for d in (h1, h2))
    assert np.allclose([got1[100 + i] for i in range(5)], first[0].value) and np.allclose([got2[i] for i in range(3)], z.value)
    score = model.score(model.vars(), b)
    hidden = F.transform(layers.affine(F.col("h"), T("Wd1"), p["bd1"].tolist()), lambda v: F.greatest(v, F.lit(0.0)))
    back = h2.filter("nid < 100").withColumn("d", hidden).withColumn("back", layers.affine(F.col("d"), T("Wd2"), p["bd2"].tolist()))
    errors = back.join(nodes(x_t, 0), "nid").select("nid", layers.squared_distance(F.col("back"), F.col("x")).alias("error"))
    assert np.allclose([r.error for r in errors.orderBy("nid").collect()], score)
    pairs = errors.filter("nid = 0").select(F.col("error").alias("positive")).crossJoin(errors.filter("nid > 0").select(F.col("error").alias("negative")))
    none = spark.createDataFrame([], "logit double, label int")
    total = layers.objective(errors, none, pairs, 0.0, 1.0).first()
    exact_rank = np.mean(np.log1p(np.exp(score[1:] - score[0])))
    assert total["attr"] == pytest.approx(score.mean()) and total["rank"] == pytest.approx(exact_rank)
    model.beta = 1.0
    assert float(model.loss(model.vars(), b, np.random.default_rng(0)).value) == pytest.approx(total["total"], rel=0.1)


def test_training_learns_and_is_the_same_twice(spark):
    rows = spark.range(3000).select(F.col("id").alias("target"), F.pmod(F.xxhash64("id"), F.lit(10)).alias("k"))
    rows = rows.select("target", (F.col("k") == 0).cast("int").alias("y"), F.when(F.col("target") % 10 < 6, "train").when(F.col("target") % 10 < 8, "valid").otherwise("test").alias("split"), F.array((F.col("k") == 0).cast("double") + F.rand(1), F.rand(2)).alias("x")).cache()
    models = lambda: {f"m{s}": nn.Mlp(nn.Spec(2), 8, s) for s in range(2)}
    one, two = (trainer.fit_all(rows, models(), 3, 20, 256, 0.01) for _ in range(2))
    assert all(np.array_equal(one[k].model.params[n], two[k].model.params[n]) for k in one for n in one[k].model.params)
    exact_auprc = {r["model"]: r["auprc"] for r in metrics.ranking(trainer.score_all(rows.filter("split = 'valid'"), one).select("model", "y", "score"), ["model"]).collect()}
    for k, f in one.items():
        assert f.auprc > 0.5 and f.auprc == pytest.approx(exact_auprc[k], abs=0.02)


def test_centres_come_from_all_train_rows(spark):
    split = F.when(F.col("id") % 10 < 8, "train").when(F.col("id") % 10 < 9, "valid").otherwise("test")
    rows = spark.range(9000).select(F.col("id").alias("target"), (F.col("id") % 7 == 0).cast("int").alias("y"), split.alias("split"), F.array(F.rand(1) * 5, F.rand(2) - 0.2).cast("array<float>").alias("x")).cache()
    x = np.array([r.x for r in rows.filter("split = 'train'").collect()], np.float32)
    make = lambda: {"hard": nn.DeepSvdd(nn.Spec(2), 8, 3), "soft": nn.DeepSvdd(nn.Spec(2), 8, 4, nu=0.1)}
    for steps in (1, 40):  # several shards, and several copies of one
        for k, f in trainer.fit_all(rows, make(), 1, steps, 256).items():
            alone = make()[k]
            alone.prepare({"x": x})
            assert np.allclose(f.model.centre, alone.centre, rtol=1e-4, atol=1e-5)


def test_rows_kept_between_rounds_come_in_small_batches(spark):
    spark.conf.set("spark.sql.inMemoryColumnarStorage.batchSize", "10000")
    rows = spark.range(1000).select(F.col("id").alias("target"))
    dealt = trainer.deal(rows, 1, 1)
    assert dealt.count() == 1000
    kept = dealt._jdf.queryExecution().withCachedData().cacheBuilder().cachedColumnBuffers()
    assert kept.count() == -(-1000 // trainer.KEPT) and int(spark.conf.get("spark.sql.inMemoryColumnarStorage.batchSize")) <= 128
    dealt.unpersist()


def test_earlier_means_match_brute_force(spark):
    rng = np.random.default_rng(3)
    rows = [(i, int(rng.integers(0, 4)), int(rng.integers(0, 500)), [float(v) for v in rng.standard_normal(3)]) for i in range(300)]
    df = spark.createDataFrame(rows, "target long, key int, us long, x array<double>")
    for r in detector.earlier_means(df, "key", "us", 3, "m", 7).collect():
        before = [x for _, k, t, x in rows if k == r.key and t < r.us]
        assert (r.m is None) == (not before) and (not before or np.allclose(r.m, np.mean(before, axis=0)))
    assert detector.earlier_means(df.limit(0), "key", "us", 3, "m").count() == 0


def test_forest_grows_the_same_trees_and_finds_the_split(spark):
    rows = spark.range(4000).select(F.col("id"), F.rand(1).alias("a"), F.rand(2).alias("b"), F.when(F.rand(3) < 0.1, None).otherwise(F.rand(4)).alias("c")).withColumn("y", ((F.col("a") > 0.8) & (F.col("b") <= 0.3)).cast("int")).cache()
    preset = tasks.small(tasks.PRESETS["cyber"], 6, 8)
    sample = forest.sample_of(rows, ["a", "b", "c"], 1000)
    assert 800 < len(sample.y) < 1200 and sample.y.sum() == rows.filter("y = 1").count()
    one, other = forest.grow(sample, 3, preset), forest.grow(sample, 3, preset)
    assert one == other != forest.grow(sample, 4, preset)
    by = {n[1]: n for n in one}
    for _, node, left, right, feature, threshold, size, p in one:
        assert (left < 0) == (right < 0) and 0 <= p <= 1
        if left >= 0:
            assert by[left][6] + by[right][6] == size and min(by[left][6], by[right][6]) >= preset.min_leaf
    leaves = [n for n in one if n[2] < 0]
    assert sum(n[6] for n in leaves) == len(sample.y)
    # Pure leaves: the rule is found.
    assert sum(n[6] for n in leaves if n[7] in (0.0, 1.0)) > 0.8 * len(sample.y)
    assert forest.fit(rows, ["a", "b", "c"], preset, "file:///tmp/relanom-forest-test", 0, 2).select("tree").distinct().count() == 2


@pytest.mark.parametrize("kind", ["cyber", "review", "purchase"])
def test_forest_grows_from_all_train_rows(spark, kind):
    n = 600_000
    rows = spark.range(n).select((F.col("id") % 50 == 0).cast("int").alias("y"), (F.col("id") % 97).cast("double").alias("a"), F.when(F.col("id") % 3 > 0, F.col("id") % 7).alias("b"))
    rows = rows.unionByName(spark.createDataFrame([(None, 1.0, 1)], "y int, a double, b long"))
    sample = forest.sample_of(rows, ["a", "b"], tasks.PRESETS[kind].train_cap)
    assert sample.bins.shape == (n, 2) and len(sample.y) == n and sample.y.sum() == n // 50
    # Every value is in its bin, in an order that does not depend on that of the rows.
    ids = np.arange(n)
    a, b = ids % 97, np.where(ids % 3 > 0, ids % 7, -1)
    made = np.stack([ids % 50 == 0, np.searchsorted(sample.edges[0], a), np.searchsorted(sample.edges[1], b)], axis=1).astype(np.uint8)
    made = made[np.lexsort(made.T[::-1])]
    assert np.array_equal(made, np.column_stack([sample.y, sample.bins]).astype(np.uint8))


@pytest.mark.parametrize("kind", ["purchase", "review"])
def test_customers_see_all_their_transactions(spark, kind):
    sf = "/root/testdata/sf0.01"
    log = (tasks.transactions if kind == "purchase" else tasks.reviews)(spark, sf).filter(F.datediff(F.lit(tasks.CUT), "t") >= 0)
    degrees = {r["customer"]: r["count"] for r in log.groupBy("customer").count().collect()}
    rows = detector.customer_task(spark, sf, kind).rows.select("target", F.size("nb0").alias("n")).collect()
    assert max(degrees.values()) > 20 and rows
    assert all(max(r["n"], 0) == degrees.get(r["target"], 0) for r in rows)


def test_backward_lets_go_of_what_lies_between():
    import gc
    import weakref

    class Kept(np.ndarray):
        """An array that can be watched."""

    gc.collect()
    gc.disable()
    try:
        w = nn.Var(np.ones((3, 2)))
        middle = nn.times(nn.const(np.ones((4, 3))), w)
        middle.value = middle.value.view(Kept)
        watched = weakref.ref(middle.value)
        nn.mean(nn.square(middle)).backward()
        del middle
        assert watched() is None and w.grad.shape == (3, 2)
    finally:
        gc.enable()


def test_rounds_and_validation_send_one_row_a_model_to_the_driver(spark, monkeypatch):
    frame, sent = type(spark.range(0)), []
    collect = frame.collect
    monkeypatch.setattr(frame, "collect", lambda self: [sent.append(r) or r for r in collect(self)])
    x = F.array(F.rand(1), F.rand(2))
    rows = spark.range(400).select(F.col("id").alias("target"), (F.col("id") % 10 == 0).cast("int").alias("y"), F.when(F.col("id") % 3 > 0, "train").otherwise("valid").alias("split"), x.alias("x")).cache()
    models = {str(seed): nn.Autoencoder(nn.Spec(2), 4, seed, beta=1.0) for seed in range(3)}
    fitted = trainer.fit_all(rows, models, 2, 2, 32)
    assert len(sent) == 2 * 2 * len(models)
    valid = rows.filter("split = 'valid'")
    for k, f in fitted.items():
        exact = metrics.ranking(trainer.score_all(valid, {k: f}).select("y", F.col("score").cast("float").alias("score"))).first()["auprc"]
        assert f.auprc == pytest.approx(exact, abs=0.02)


def test_graph_tables_are_stored_in_single_precision_with_means_from_the_base(spark):
    rows = spark.createDataFrame([(i, i % 2, ["train", "valid", "test"][i % 3], i / 7, i % 3, i, [(i % 3, [1.0], None)]) for i in range(30)], "target long, y int, split string, a double, user long, us long, nb0 array<struct<id:long,x:array<float>,m:array<float>>>")
    task = detector.Task("t", rows, ["a"], (nn.Relation(1, 0, own=True),), {0: ("user", "us")})
    made, spec = detector.assembled(task)
    kinds = dict(made.dtypes)
    assert kinds["x"] == "array<float>" and "m:array<float>" in kinds["nb0"] and spec.relations[0].m == 1
    got = {r.target: r for r in made.collect()}
    for i, r in got.items():
        before = [got[j].x[0] for j in range(i) if j % 3 == i % 3]
        assert r.nb0[0].m is None if not before else r.nb0[0].m[0] == pytest.approx(np.mean(before), abs=1e-6)


@pytest.mark.parametrize("size", [1, 2, 1000])
def test_earlier_means_keep_their_sums_from_batch_to_batch(spark, size):
    rows = [(i, (0, 0, 0, 1, i)[i % 5], i // 6, [float(i), i % 3 - 1.0]) for i in range(120)]
    df = spark.createDataFrame(rows, "target long, user int, us long, x array<double>")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", size)
    try:
        made = detector.earlier_means(df, "user", "us", 2, "m", slices=3)
        got = {r["target"]: r["m"] for r in made.collect()}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    for target, user, us, _ in rows:
        near = [x for _, u, t, x in rows if u == user and t < us]
        assert got[target] == (pytest.approx(np.mean(near, axis=0).tolist()) if near else None)
    # Sums are one column, not one a feature: the plan is as long for a hundred features as for two.
    assert "Window" not in made._jdf.queryExecution().analyzed().toString()


def test_sums_by_place_and_products_of_rows(exact):
    rng = np.random.default_rng(4)
    for at, n in ((np.arange(6), 6), (np.repeat([0, 2], 20), 4), (np.repeat([1, 3, 4], [1, 2, 3]), 6), (rng.integers(0, 9, 40), 9), (np.zeros(0, int), 3)):
        rows, want = rng.standard_normal((len(at), 3)), np.zeros((n, 3))
        np.add.at(want, at, rows)
        assert np.allclose(nn._sums(rows, at, n), want)
    a, b, i, j = nn.Var(rng.standard_normal((4, 3))), nn.Var(rng.standard_normal((5, 3))), rng.integers(0, 4, 9), rng.integers(0, 5, 9)
    assert np.allclose(nn.row_dots(a, b, i, j).value, (a.value[i] * b.value[j]).sum(axis=1))


def test_training_computes_in_single_precision_and_looks_at_a_batch_once():
    model = nn.RelationalAutoencoder(SPEC, 6, alpha=0.3, beta=0.7)
    b = batch(np.random.default_rng(3), SPEC)
    got = []
    for _ in range(2):
        p = model.vars()
        model.loss(p, b, np.random.default_rng(5)).backward()
        got.append([seen for _, seen, _ in nn.seen_of(b)])
        assert {v.grad.dtype for v in p.values() if v.grad is not None} == {np.dtype(np.float32)}
        assert {seen.dtype for seen in got[-1]} == {np.dtype(np.float32)}
    assert all(a is c for a, c in zip(*got))

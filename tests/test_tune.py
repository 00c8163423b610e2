from relanom import layers, tune


def test_draws_repeat_and_stay_inside():
    a, b = tune.draw(tune.SPACE, 20, 3), tune.draw(tune.SPACE, 20, 3)
    assert a == b and a != tune.draw(tune.SPACE, 20, 4)
    assert all(0 <= s["alpha"] <= 0.5 and 0.003 <= s["rate"] <= 0.03 and s["hidden"] in (8, 16, 32) for s in a)


def test_halving_keeps_the_better_part():
    seen = tune.halving([{"v": v} for v in (3, 1, 4, 2)], lambda s, rounds: s["v"])
    assert [(s["v"], r) for s, r, _ in seen] == [(3, 1), (1, 1), (4, 1), (2, 1), (4, 2), (3, 2), (4, 4)]
    assert tune.halving([], lambda s, rounds: 0.0) == []


def test_hard_pairs_take_the_highest_score(spark):
    rows = spark.createDataFrame([(i, int(i == 0), float(i)) for i in range(20)], "target long, y int, score double")
    found = layers.sample_pairs(rows, 2, buckets=1, hard=True).collect()
    assert sorted((r.positive, r.j, r.negative) for r in found) == [(0, 1, 19), (0, 2, 19)]
    assert layers.sample_pairs(rows.filter("y = 1"), 2).count() == 0

"""Hyper-parameter search on validation AUPRC: seeded random draws, successive halving, then frozen."""

from __future__ import annotations

import random
from collections.abc import Callable

from relanom import detector, nn, rules, trainer

#: Ranges of the search: (low, high) is drawn evenly, ("log", low, high) evenly in the logarithm, a list evenly.
SPACE = {"alpha": (0.0, 0.5), "beta": (0.25, 2.0), "hidden": [8, 16, 32], "rate": ("log", 0.003, 0.03)}


def draw(space: dict, trials: int, seed: int = 0) -> list[dict]:
    """``trials`` settings, the same for every run with one seed."""
    r = random.Random(seed)

    def one(spec):
        if isinstance(spec, list):
            return r.choice(spec)
        if spec[0] == "log":
            return spec[1] * (spec[2] / spec[1]) ** r.random()
        return spec[0] + (spec[1] - spec[0]) * r.random()

    return [{k: one(v) for k, v in space.items()} for _ in range(trials)]


def halving(settings: list[dict], fit: Callable[[dict, int], float], rounds: int = 1, keep: float = 0.5) -> list[tuple[dict, int, float]]:
    """(setting, rounds, value) of every trial; the better part goes on with twice the rounds until one is left.

    Equal values keep the order of the draws.
    """
    seen, left = [], list(settings)
    while left:
        now = [(s, rounds, fit(s, rounds)) for s in left]
        seen += now
        if len(left) == 1:
            break
        best = sorted(now, key=lambda x: -x[2])[: max(1, int(len(left) * keep))]
        left, rounds = [s for s, _, _ in best], rounds * 2
    return seen


def search(task: detector.Task, rule_set: rules.RuleSet | None, trials: int = 4, seed: int = 0, space: dict = SPACE) -> list[tuple[dict, int, float]]:
    """Trials of the detector on one assembled table; the last entry is the chosen setting."""
    rows, spec = detector.assembled(task, rule_set)
    rows = rows.cache()

    def fit(s: dict, rounds: int) -> float:
        model = nn.RelationalAutoencoder(spec, s["hidden"], seed, alpha=s["alpha"], beta=s["beta"])
        return trainer.fit(rows, model, rounds, rate=s["rate"], seed=seed).auprc

    return halving(draw(space, trials, seed), fit)

"""Baselines that tune a fixed cascade of tools as one opaque function."""

from __future__ import annotations

import itertools
import random
import time
from concurrent.futures import ThreadPoolExecutor

import numpy as np
from pyspark.sql import DataFrame

from ..operators.base import CleaningOperator
from ..operators.strings import applied
from ..quality.quality import Quality
from ..search.engine import Trace
from ..session import written

OFF = {"off": True}


def encode_slots(ops: list[CleaningOperator], slots: int) -> list[list[dict]]:
    """The space of pipelines of up to ``slots`` tools: for each slot, off or a tool with
    one of its settings."""
    choices = [OFF] + [{"op": i, **s} for i, op in enumerate(ops) for s in op.parameter_space()]
    return [choices] * slots


def cascade_space(ops: list[CleaningOperator]) -> list[list[dict]]:
    """For each tool of a fixed order, off or one of its settings."""
    return [[OFF] + [{"op": i, **s} for s in op.parameter_space()] for i, op in enumerate(ops)]


def run_cascade(df: DataFrame, ops: list[CleaningOperator], setting: list[dict], key: str = "rec_id") -> DataFrame:
    """Each tool on the previous one's output."""
    for choice in setting:
        if "off" not in choice:
            op = ops[choice["op"]].with_params({k: v for k, v in choice.items() if k != "op"})
            df = applied(df, op, key)
    return df


class Tuner:
    """Scores settings of a cascade; the best so far is in ``trace``."""

    def __init__(self, name: str, df: DataFrame, ops: list[CleaningOperator], quality: Quality, budget_s: float | None = None, key: str = "rec_id", prepare=lambda d: d):
        self.df, self.ops, self.quality, self.budget_s, self.key, self.prepare = df, ops, quality, budget_s, key, prepare
        self.trace, self.best, self.best_cost, self.trials = Trace(name), None, float("inf"), []

    def out_of_time(self) -> bool:
        return self.budget_s is not None and time.monotonic() - self.trace.began > self.budget_s

    def evaluate(self, setting: list[dict]) -> float:
        cost = self.quality.cost(self.prepare(run_cascade(self.df, self.ops, setting, self.key)))
        self.trials.append((setting, cost))
        if cost < self.best_cost:
            self.best, self.best_cost = setting, cost
        self.trace.add(len(self.trials), self.best_cost, n_evaluated=len(self.trials))
        return cost

    def cleaned(self) -> DataFrame:
        return run_cascade(self.df, self.ops, self.best or [], self.key)


def grid_search(tuner: Tuner, parallel: int = 1, limit: int | None = None) -> Tuner:
    """Every setting of the cascade, ``parallel`` pipelines at a time."""
    grid = itertools.product(*cascade_space(tuner.ops))
    settings = (list(s) for s in itertools.islice(grid, limit))
    with ThreadPoolExecutor(parallel) as threads:
        while not tuner.out_of_time():
            batch = list(itertools.islice(settings, parallel))
            if not batch:
                break
            list(threads.map(tuner.evaluate, batch))
    return tuner


def random_search(tuner: Tuner, trials: int, seed: int = 0) -> Tuner:
    rng, space = random.Random(seed), cascade_space(tuner.ops)
    for _ in range(trials):
        if tuner.out_of_time():
            break
        tuner.evaluate([rng.choice(c) for c in space])
    return tuner


def greedy_tune(tuner: Tuner) -> Tuner:
    """Each tool alone on the original relation; then all their best settings in a row."""
    best, space = [], cascade_space(tuner.ops)
    for slot, choices in enumerate(space):
        alone = lambda c, slot=slot: [c if i == slot else OFF for i in range(len(space))]
        best.append(min(((tuner.evaluate(alone(c)), i, c) for i, c in enumerate(choices) if not tuner.out_of_time() or i == 0), key=lambda x: x[:2])[2])
    tuner.evaluate(best)
    return tuner


class ParzenSampler:
    """Sequential model-based choice: densities of good and of other trials, parameter by
    parameter, and the candidate of the best ratio."""

    def __init__(self, space: list[list[dict]], n_startup: int = 20, good: float = 0.25, candidates: int = 24, seed: int = 0):
        self.space, self.n_startup, self.good, self.candidates = space, n_startup, good, candidates
        self.rng = np.random.default_rng(seed)

    def propose(self, trials: list[tuple[list[dict], float]]) -> list[dict]:
        if len(trials) < self.n_startup:
            return [c[self.rng.integers(len(c))] for c in self.space]
        ranked = sorted(trials, key=lambda t: t[1])
        cut = max(1, int(np.ceil(self.good * len(ranked))))
        return [self._slot(i, [s[i] for s, _ in ranked[:cut]], [s[i] for s, _ in ranked[cut:]]) for i in range(len(self.space))]

    def _slot(self, i: int, good: list[dict], rest: list[dict]) -> dict:
        choices = self.space[i]
        numeric = [k for k in {k for c in choices for k in c} if k not in ("op", "off") and all(isinstance(c.get(k, 0), int | float) for c in choices)]

        def density(seen: list[dict]) -> np.ndarray:
            # A smoothed count of each choice, wider where parameters are numbers.
            d = np.ones(len(choices)) / len(choices)
            for s in seen:
                for j, c in enumerate(choices):
                    if {k: v for k, v in c.items() if k not in numeric} == {k: v for k, v in s.items() if k not in numeric}:
                        far = sum(((c[k] - s[k]) / self._width(i, k)) ** 2 for k in numeric if k in c)
                        d[j] += np.exp(-far / 2)
            return d / d.sum()

        g, r = density(good), density(rest)
        drawn = self.rng.choice(len(choices), size=self.candidates, p=g)
        return choices[max(drawn, key=lambda j: g[j] / r[j])]

    def _width(self, i: int, k: str) -> float:
        values = sorted({c[k] for c in self.space[i] if k in c})
        return max(np.diff(values).max() if len(values) > 1 else 1.0, 1e-9)


def tpe_search(tuner: Tuner, trials: int, seed: int = 0, **options) -> Tuner:
    """Sequential Bayesian optimisation: a trial after the other."""
    sampler = ParzenSampler(cascade_space(tuner.ops), seed=seed, **options)
    for _ in range(trials):
        if tuner.out_of_time():
            break
        tuner.evaluate(sampler.propose(tuner.trials))
    return tuner


def standalone(df: DataFrame, op: CleaningOperator, best: dict, n_random: int = 5, seed: int = 0, key: str = "rec_id") -> list[tuple[dict, DataFrame]]:
    """A tool by itself: its best known setting and some random ones."""
    rng, space = random.Random(seed), list(op.parameter_space())
    settings = [best] + [rng.choice(space) for _ in range(n_random)]
    return [(s, written(applied(df, op.with_params(s), key), "standalone")) for s in settings]

"""Choosing parameter settings of tools."""

from __future__ import annotations

import random
from collections.abc import Iterator

from pyspark.sql import DataFrame

from ..operators.base import CleaningOperator
from ..quality.quality import Quality


def iterate(op: CleaningOperator) -> Iterator[dict]:
    """Every setting, in order."""
    return op.parameter_space()


def uniform(op: CleaningOperator, seed: int = 0) -> Iterator[dict]:
    """Settings drawn without end, whatever the search has found."""
    rng = random.Random(seed)
    while True:
        yield {k: rng.choice(v) for k, v in sorted(op.domains.items())}


def weighted(op: CleaningOperator, weights: dict[str, list[float]], seed: int = 0) -> Iterator[dict]:
    """Settings drawn with given weights: a hook for guided sampling."""
    rng = random.Random(seed)
    while True:
        yield {k: rng.choices(v, weights.get(k))[0] for k, v in sorted(op.domains.items())}


def sweep(op: CleaningOperator) -> Iterator[dict]:
    """Thresholds from strict to loose (the order of their domains), the rest inside."""
    order = [k for k in sorted(op.domains) if k in op.threshold_params]
    return iter(sorted(op.parameter_space(), key=lambda p: [op.domains[k].index(p[k]) for k in order]))


def infer_attrs(df: DataFrame, kinds: tuple[str, ...] = ("string",), skip: tuple[str, ...] = ("rec_id",)) -> list[str]:
    """Attributes of fitting type: the domain of attribute-name parameters."""
    return [n for n, t in df.dtypes if t in kinds and n not in skip]


def relevant_attrs(candidates: list[str], quality: Quality, fds=()) -> list[str]:
    """Attributes that the quality reads, and what dependencies tie to them."""
    wanted = set(quality.attrs)
    while True:
        more = {a for fd in fds for a in fd.attrs if wanted & set(fd.attrs)} - wanted
        if not more:
            return [a for a in candidates if a in wanted]
        wanted |= more

"""The three-call interface of cleaning tools and helpers to wrap them."""

from __future__ import annotations

import itertools
import random
import time
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.pool import bundle, equality_repairs, repair_rows

__all__ = ["CleaningOperator", "coarse", "equality_repairs", "from_table", "repair_rows", "replicate_library", "with_delay"]


class CleaningOperator:
    """A parameterised tool that emits repairs.

    ``domains`` lists the values of each parameter, attribute names among them;
    ``strict`` gives the most restrictive end of threshold parameters first.
    """

    name = "operator"
    attr_params: tuple[str, ...] = ("attr",)
    threshold_params: tuple[str, ...] = ()

    def __init__(self, domains: dict[str, list] | None = None, **params):
        self.domains, self.params = domains or {}, params

    def parameter_space(self) -> Iterator[dict]:
        keys = sorted(self.domains)
        for values in itertools.product(*(self.domains[k] for k in keys)):
            yield dict(zip(keys, values, strict=True))

    def with_params(self, params: dict) -> CleaningOperator:
        new = object.__new__(type(self))
        new.__dict__ = dict(self.__dict__) | {"params": self.params | params}
        return new

    def repairs(self, df: DataFrame) -> DataFrame:
        """Pool rows for ``df`` under the parameters; never changes schema or records."""
        raise NotImplementedError

    def p(self, key: str):
        return self.params[key]

    def attributes(self) -> set[str]:
        """Attributes that the present setting reads or writes."""
        return {str(self.params[a]) for a in self.attr_params if self.params.get(a) is not None}


class _Delayed(CleaningOperator):
    def __init__(self, inner: CleaningOperator, lo_ms: float, hi_ms: float, seed: int):
        super().__init__(inner.domains, **inner.params)
        self.name, self.inner, self.range, self.rng = inner.name, inner, (lo_ms, hi_ms), random.Random(seed)
        self.attr_params, self.threshold_params = inner.attr_params, inner.threshold_params

    def repairs(self, df):
        time.sleep(self.rng.uniform(*self.range) / 1000)
        return self.inner.with_params(self.params).repairs(df)


def with_delay(op: CleaningOperator, lo_ms: float, hi_ms: float, seed: int = 0) -> CleaningOperator:
    """The same repairs after a random wait."""
    return _Delayed(op, lo_ms, hi_ms, seed)


def replicate_library(ops: list[CleaningOperator], times: int) -> list[CleaningOperator]:
    """``times`` redundant copies of every tool."""
    return [op.with_params({}) for _ in range(times) for op in ops]


class _Coarse(CleaningOperator):
    def __init__(self, inner: CleaningOperator):
        super().__init__(inner.domains, **inner.params)
        self.name, self.inner = inner.name, inner
        self.attr_params, self.threshold_params = inner.attr_params, inner.threshold_params

    def repairs(self, df):
        return bundle(self.inner.with_params(self.params).repairs(df))


def coarse(op: CleaningOperator) -> CleaningOperator:
    """All repairs of a setting as one candidate."""
    return _Coarse(op)


class FromTable(CleaningOperator):
    """Any function from table to table: the cells it changed, as repairs by key."""

    attr_params = ()

    def __init__(self, fn: Callable[..., DataFrame], name: str = "wrapped", key: str = "rec_id", domains: dict | None = None, **params):
        super().__init__(domains, **params)
        self.fn, self.name, self.key = fn, name, key

    def repairs(self, df):
        out = self.fn(df, **self.params)
        if out.columns != df.columns:
            raise ValueError("a wrapped tool must keep the schema")
        attrs = [c for c in df.columns if c != self.key]
        both = df.alias("o").join(out.alias("n"), self.key)
        cells = F.array(*[F.struct(F.lit(a).alias("attr"), F.col(f"o.{a}").cast("string").alias("old"), F.col(f"n.{a}").cast("string").alias("new")) for a in attrs])
        changed = both.select(self.key, F.inline(cells)).filter(~F.col("old").eqNullSafe(F.col("new")))
        parts = [equality_repairs(changed.filter(F.col("attr") == a), {self.key: F.col(self.key)}, a, F.col("new"), self.name, self.params) for a in attrs]
        rows = parts[0]
        for p in parts[1:]:
            rows = rows.unionByName(p)
        return rows


def from_table(fn, **options) -> CleaningOperator:
    return FromTable(fn, **options)

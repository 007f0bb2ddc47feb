"""Weighted sums of quality terms, in full and for all candidates of a round at once."""

from __future__ import annotations

import random
import time
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .terms import CAND, FDViolations, SqlTerm, Term


def with_block(df: DataFrame) -> DataFrame:
    return df if "block" in df.columns else df.withColumn("block", F.lit(0).cast("long"))


def prepared(df: DataFrame, attrs: list[str], truth: DataFrame | None = None, key: str = "rec_id") -> DataFrame:
    """Adds ``_base_*`` (the dirty cells) and ``_truth_*`` columns, and ``block`` if absent."""
    out = with_block(df).withColumns({f"_base_{a}": F.col(a) for a in attrs})
    if truth is not None:
        out = out.join(truth.select(key, *[F.col(a).alias(f"_truth_{a}") for a in attrs]), key, "left")
    return out


class Quality:
    """Sum of weight times term; weights default to 1/n."""

    def __init__(self, terms: list[Term] | list[tuple[float, Term]]):
        pairs = [t if isinstance(t, tuple) else (1.0 / len(terms), t) for t in terms]
        self.weights, self.terms = [w for w, _ in pairs], [t for _, t in pairs]
        self.delay_ms: tuple[float, float] | None = None
        self._rng = random.Random(0)

    @staticmethod
    def from_sql(queries: list[str]) -> Quality:
        return Quality([SqlTerm(q) for q in queries])

    @property
    def attrs(self) -> set[str]:
        return {a for t in self.terms for a in t.attrs}

    @property
    def incremental(self) -> bool:
        return all(t.self_maintainable for t in self.terms)

    def normalized(self, df: DataFrame) -> Quality:
        """Each term divided by its value on ``df``."""
        costs = [self._one(t, df) for t in self.terms]
        out = Quality([(w / max(c, 1e-12) if c else w, t) for w, c, t in zip(self.weights, costs, self.terms, strict=True)])
        out.delay_ms = self.delay_ms
        return out

    def _one(self, term: Term, df: DataFrame) -> float:
        return float(term.cost(with_block(df)).agg(F.coalesce(F.sum("cost"), F.lit(0.0))).first()[0])

    def wait(self) -> None:
        if self.delay_ms:
            time.sleep(self._rng.uniform(*self.delay_ms) / 1000)

    def costs(self, df: DataFrame) -> DataFrame:
        """(block, cost) in full, one plan for all terms."""
        df = self._named(with_block(df))
        parts = [t.cost(df).select("block", (F.col("cost") * w).alias("cost")) for w, t in zip(self.weights, self.terms, strict=True)]
        return reduce(DataFrame.unionByName, parts).groupBy("block").agg(F.sum("cost").alias("cost"))

    def cost(self, df: DataFrame) -> float:
        self.wait()
        return float(self.costs(df).agg(F.coalesce(F.sum("cost"), F.lit(0.0))).first()[0])

    def sampled_cost(self, df: DataFrame, on: list[str], share: float) -> float:
        """An estimate from the records whose ``on`` hashes into ``share``, so that
        violating pairs stay together; scaled up.  The hash is that of the fixtures, so
        other engines draw the same records."""
        key = F.concat_ws("|", *[F.col(c).cast("string") for c in on])
        few = df.filter(F.conv(F.substring(F.md5(key), 1, 8), 16, 10).cast("long") % 10_000 < int(share * 10_000))
        return self.cost(few) / share

    def _named(self, df: DataFrame) -> DataFrame:
        for t in self.terms:
            if isinstance(t, FDViolations):
                t.columns = tuple(df.columns)
        return df

    def states(self, df: DataFrame) -> list[DataFrame | None]:
        df = self._named(with_block(df))
        return [t.state(df) for t in self.terms]

    @property
    def by_block(self) -> bool:
        """Whether the cost of a relation is the sum of its blocks' costs."""
        return all(t.by_block for t in self.terms)

    def drifts(self, images: DataFrame, states: list | None = None) -> list[DataFrame | None]:
        return [t.drift(images, s) for t, s in zip(self.terms, states or [None] * len(self.terms), strict=True)]

    def deltas(self, images: DataFrame, states: list, drifts: list | None = None) -> DataFrame:
        """(block, plan, unit, delta) of every candidate, in one job."""
        drifts = drifts or [None] * len(self.terms)
        parts = [
            t.delta(images, s, d).select(*CAND, (F.col("delta") * w).alias("delta")) for w, t, s, d in zip(self.weights, self.terms, states, drifts, strict=True)
        ]
        # A candidate without a row of a term does not change it.
        parts.append(images.select(*CAND, F.lit(0.0).alias("delta")).distinct())
        return reduce(DataFrame.unionByName, parts).groupBy(*CAND).agg(F.sum("delta").alias("delta"))

    def keys(self, images: DataFrame) -> DataFrame:
        cells = images.select(*CAND, F.concat(F.lit("row|"), F.col("rec").cast("string")).alias("key"))
        return reduce(DataFrame.unionByName, [t.keys(images) for t in self.terms], cells).distinct()


def with_eval_delay(q: Quality, lo_ms: float, hi_ms: float, seed: int = 0) -> Quality:
    out = Quality(list(zip(q.weights, q.terms, strict=True)))
    out.delay_ms, out._rng = (lo_ms, hi_ms), random.Random(seed)
    return out

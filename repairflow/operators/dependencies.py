"""Tools driven by functional dependencies."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import FD
from ..plans.pool import canonicalize, clause_struct, equality_repairs, repair_rows
from ..session import written
from .base import CleaningOperator
from .strings import apply_pool


class FDChase(CleaningOperator):
    """Within a left-hand group, right-hand values that differ from the most frequent
    one, and nulls, become that one; ties to the smaller value."""

    name, attr_params = "chase", ()

    def __init__(self, fds: list[FD], max_rounds: int = 5, domains=None, **params):
        super().__init__(domains, **params)
        self.fds, self.max_rounds = fds, max_rounds

    def attributes(self) -> set[str]:
        return {a for fd in self._chosen() for a in fd.attrs}

    def _chosen(self) -> list[FD]:
        which = self.params.get("fd")
        return self.fds if which is None else [fd for fd in self.fds if str(fd) == which]

    def one_round(self, df: DataFrame, fd: FD) -> DataFrame:
        rows = df.filter(fd.condition) if fd.condition else df
        parts = []
        for y in fd.rhs:
            keyed = rows.dropna(subset=list(fd.lhs))
            counts = keyed.groupBy(*fd.lhs, F.col(y).alias("_y")).agg(F.count("*").alias("_n"))
            best = counts.filter("_y is not null").groupBy(*fd.lhs).agg(F.min_by("_y", F.struct(-F.col("_n"), F.col("_y"))).alias("_best"))
            off = counts.join(best, list(fd.lhs)).filter("_y is null or _y <> _best")
            keys = {a: F.col(a) for a in fd.lhs}
            parts.append(equality_repairs(off.filter("_y is not null"), keys | {y: F.col("_y")}, y, F.col("_best"), self.name, self.params | {"fd": fd}))
            attrs = sorted([*fd.lhs, y])
            clauses = [clause_struct(a, "is_null") if a == y else clause_struct(a, "eq", F.col(a)) for a in attrs]
            sig = ",".join(f"{a}:is_null" if a == y else f"{a}:eq" for a in attrs)
            parts.append(repair_rows(off.filter("_y is null"), clauses, sig, y, F.col("_best"), self.name, self.params | {"fd": fd}))
        out = parts[0]
        for p in parts[1:]:
            out = out.unionByName(p)
        return out

    def repairs(self, df):
        """First-round repairs of the chosen dependencies."""
        out = None
        for fd in self._chosen():
            part = self.one_round(df, fd)
            out = part if out is None else out.unionByName(part)
        return canonicalize(out)

    def chase(self, df: DataFrame, key: str = "rec_id") -> DataFrame:
        """The relation after rounds over all dependencies, to a fixpoint."""
        for _ in range(self.max_rounds):
            before = df
            for fd in self._chosen():
                df = written(apply_pool(df, self.one_round(df, fd), key), "chase")
            if df.exceptAll(before).isEmpty():
                break
        return df


class StatisticalFD(CleaningOperator):
    """Cells of violating groups by a smoothed vote of the other attributes.

    Candidates are the values seen with the left-hand side; the log score of one is
    the log share in the group plus the log frequency of each evidence value with
    it.  The best is emitted if it differs and its share of the softmax reaches
    ``threshold``.  Repairs are by record.
    """

    name, attr_params, threshold_params = "stat_fd", (), ("threshold",)

    def __init__(self, fds: list[FD], evidence: list[str], key: str = "rec_id", alpha: float = 1.0, domains=None, **params):
        super().__init__(domains, **params)
        self.fds, self.evidence, self.key, self.alpha = fds, evidence, key, alpha

    def attributes(self) -> set[str]:
        return {a for fd in self.fds for a in fd.attrs}

    def decisions(self, df: DataFrame, fd: FD, y: str) -> DataFrame:
        """(key, old, new, confidence) of every cell of a violating group."""
        lhs, a = list(fd.lhs), self.alpha
        rows = (df.filter(fd.condition) if fd.condition else df).dropna(subset=lhs)
        seen = rows.filter(F.col(y).isNotNull()).groupBy(*lhs, F.col(y).alias("_c")).agg(F.count("*").alias("_n"))
        group = rows.groupBy(*lhs).agg(F.count("*").alias("_rows"), F.count_distinct(y).alias("_vals"), F.count_if(F.col(y).isNull()).alias("_nulls"))
        group = group.filter("_vals >= 1 and (_vals > 1 or _nulls > 0)")
        cells = rows.join(group, lhs).join(seen, lhs)
        score = F.log((F.col("_n") + a) / (F.col("_rows") + a * F.col("_vals")))
        totals = rows.filter(F.col(y).isNotNull()).groupBy(F.col(y).alias("_c")).agg(F.count("*").alias("_t"))
        cells = cells.join(totals, "_c")
        for i, e in enumerate(x for x in self.evidence if x not in lhs and x != y):
            pair = rows.filter(F.col(y).isNotNull() & F.col(e).isNotNull()).groupBy(F.col(y).alias("_c"), F.col(e).alias(f"_e{i}")).agg(F.count("*").alias(f"_p{i}"))
            d = rows.agg(F.count_distinct(e).alias(f"_d{i}"))
            cells = cells.join(pair, (cells["_c"] == pair["_c"]) & (cells[e] == pair[f"_e{i}"]), "left").drop(pair["_c"]).crossJoin(F.broadcast(d))
            score = score + F.when(F.col(e).isNull(), 0.0).otherwise(F.log((F.coalesce(f"_p{i}", F.lit(0)) + a) / (F.col("_t") + a * F.col(f"_d{i}"))))
        scored = cells.select(self.key, F.col(y).alias("old"), "_c", score.alias("_s"))
        best = scored.groupBy(self.key).agg(F.first("old").alias("old"), F.max("_s").alias("_m"), F.max_by("_c", F.struct(F.round("_s", 9), F.col("_c"))).alias("new"), F.collect_list("_s").alias("_all"))
        share = 1 / F.aggregate("_all", F.lit(0.0), lambda acc, s: acc + F.exp(s - F.col("_m")))
        return best.select(self.key, "old", "new", share.alias("confidence"))

    def repairs(self, df):
        out = None
        for fd in self.fds:
            for y in fd.rhs:
                got = self.decisions(df, fd, y).filter((F.col("confidence") >= float(self.p("threshold"))) & ~F.col("old").eqNullSafe(F.col("new")))
                part = equality_repairs(got, {self.key: F.col(self.key)}, y, F.col("new"), self.name, self.params)
                out = part if out is None else out.unionByName(part)
        return out

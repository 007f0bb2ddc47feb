"""Predicates: as Spark columns, and as boxes whose meets decide conflicts."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..model import Clause, Repair, Value


_WHOLE = ("tinyint", "smallint", "int", "bigint")


def comparable(col: Column, kind: str) -> Column:
    """A column of a Spark type as literals given in text are compared with it: whole
    numbers as decimals, so that 5, 5.0 and 5e0 are one value."""
    return col.cast("decimal(38,10)") if kind in _WHOLE else col


def literal(text: Column, kind: str) -> Column:
    """A literal in text as a value that ``comparable`` columns of the type are compared
    with; null if it is none of the type."""
    if kind in ("string", "binary") or kind.startswith(("char", "varchar")):
        return text
    return text.try_cast("decimal(38,10)" if kind in _WHOLE else kind)


def clause_column(c: Clause) -> Column:
    """A pushable condition: comparisons, IN, prefix and null tests only."""
    col = F.col(c.attr)
    if c.op == "eq":
        return col == F.lit(c.lo)
    if c.op == "in":
        return col.isin(*c.vals)
    if c.op == "prefix":
        return col.startswith(c.lo)
    if c.op == "is_null":
        return col.isNull()
    if c.op == "not_null":
        return col.isNotNull()
    if c.op == "between":
        low = F.lit(True) if c.lo is None else (col >= c.lo if c.lo_incl else col > c.lo)
        high = F.lit(True) if c.hi is None else (col <= c.hi if c.hi_incl else col < c.hi)
        return low & high
    return {"lt": col < c.lo, "le": col <= c.lo, "gt": col > c.lo, "ge": col >= c.lo}[c.op]


def predicate(clauses: tuple[Clause, ...]) -> Column:
    out = F.lit(True)
    for c in clauses:
        out = out & clause_column(c)
    return out


def successor(p: str) -> str | None:
    """The least string above every string that starts with p; None if there is none."""
    for i in range(len(p) - 1, -1, -1):
        if ord(p[i]) < 0x10FFFF:
            return p[:i] + chr(ord(p[i]) + 1)
    return None


@dataclass(frozen=True)
class Range:
    """What a box allows of one attribute: values, an interval, null, or any non-null."""

    lo: Value = None
    hi: Value = None
    lo_incl: bool = True
    hi_incl: bool = True
    vals: frozenset | None = None
    null: bool = False

    def has(self, v: Value) -> bool:
        if self.null or v is None:
            return self.null and v is None
        if self.vals is not None and v not in self.vals:
            return False
        low = self.lo is None or v > self.lo or self.lo_incl and v == self.lo
        return low and (self.hi is None or v < self.hi or self.hi_incl and v == self.hi)

    def meet(self, o: Range) -> Range | None:
        if self.null or o.null:
            return self if self.null and o.null else None
        for a, b in ((self, o), (o, self)):
            if a.vals is not None:
                both = frozenset(v for v in a.vals if b.has(v))
                return Range(vals=both) if both else None
        lo, li = max([(r.lo, not r.lo_incl) for r in (self, o) if r.lo is not None], default=(None, False))
        hi, hx = min([(r.hi, r.hi_incl) for r in (self, o) if r.hi is not None], default=(None, True))
        if lo is not None and hi is not None and (lo > hi or lo == hi and (li or not hx)):
            return None
        return Range(lo, hi, not li, hx)


def clause_range(c: Clause) -> Range:
    return {
        "eq": lambda: Range(vals=frozenset([c.lo])),
        "in": lambda: Range(vals=frozenset(c.vals)),
        "lt": lambda: Range(hi=c.lo, hi_incl=False),
        "le": lambda: Range(hi=c.lo),
        "gt": lambda: Range(lo=c.lo, lo_incl=False),
        "ge": lambda: Range(lo=c.lo),
        "between": lambda: Range(c.lo, c.hi, c.lo_incl, c.hi_incl),
        "prefix": lambda: Range(c.lo, successor(c.lo), True, False),
        "is_null": lambda: Range(null=True),
        "not_null": lambda: Range(),
    }[c.op]()


Box = dict[str, Range]


def box(clauses: tuple[Clause, ...]) -> Box | None:
    """The box of a conjunction; None if it cannot hold."""
    out: Box = {}
    for c in clauses:
        r = clause_range(c)
        if c.attr in out:
            r = out[c.attr].meet(r)
        if r is None:
            return None
        out[c.attr] = r
    return out


def disjoint(a: Box | None, b: Box | None) -> bool:
    return a is None or b is None or any(a[k].meet(b[k]) is None for k in a.keys() & b.keys())


def image(b: Box | None, r: Repair) -> Box | None:
    """The box of the rows of ``b`` after the assignment of ``r``."""
    if b is None:
        return None
    return b | {r.target: Range(null=True) if r.value is None else Range(vals=frozenset([r.value]))}


def commute(a: Repair, b: Repair, extended: bool = False) -> bool:
    """Whether the order of two repairs cannot matter on any relation.

    Strict: their boxes are disjoint and neither's image meets the other's box.
    Extended: also rows both touch, if they write different targets that neither
    reads, or the same value to one target that neither reads.
    """
    pa, pb = box(a.pred), box(b.pred)
    if pa is None or pb is None:
        return True
    if disjoint(pa, pb) and disjoint(image(pa, a), pb) and disjoint(image(pb, b), pa):
        return True
    if not extended:
        return False
    return a.target not in pb and b.target not in pa and (a.target != b.target or a.value == b.value)


def numeric(text: str | None) -> float | None:
    try:
        x = float(text) if text is not None else None
    except ValueError:
        return None
    return x if x is None or math.isfinite(x) else None

"""Data model: clauses, conditional assignments, dependencies and their row forms."""

from __future__ import annotations

import hashlib
import json
from collections.abc import Mapping
from dataclasses import dataclass, field, replace

CLAUSE_TYPE = "struct<attr:string,op:string,lo:string,hi:string,lo_incl:boolean,hi_incl:boolean,vals:array<string>>"
POOL_SCHEMA = (
    f"repair_id long, unit long, pos int, pred array<{CLAUSE_TYPE}>, pred_sig string, target string, value string, value_is_null boolean, "
    "op string, params map<string,string>, num_params map<string,double>"
)
TRACE_SCHEMA = (
    "run_id string, method string, step int, elapsed_s double, cost double, suboptimality double, error double, plan_len int, pool_size long, "
    "n_evaluated long, n_pruned_bound long, n_pruned_model long"
)

Value = str | float | int | None


@dataclass(frozen=True)
class Clause:
    """A condition on one attribute; intervals are ``between`` with open or closed ends."""

    attr: str
    op: str  # eq, in, lt, le, gt, ge, between, prefix, is_null, not_null
    lo: Value = None
    hi: Value = None
    lo_incl: bool = True
    hi_incl: bool = True
    vals: tuple[Value, ...] = ()


def eq(attr: str, value: Value) -> Clause:
    return Clause(attr, "eq", value)


def eq_all(values: Mapping[str, Value]) -> tuple[Clause, ...]:
    return tuple(eq(a, v) for a, v in sorted(values.items()))


def one_of(attr: str, values) -> Clause:
    return Clause(attr, "in", vals=tuple(sorted(values)))


def cmp(attr: str, op: str, value: Value) -> Clause:
    if op not in ("lt", "le", "gt", "ge"):
        raise ValueError(f"not an inequality: {op}")
    return Clause(attr, op, value)


def between(attr: str, lo: Value, hi: Value, lo_incl: bool = True, hi_incl: bool = True) -> Clause:
    return Clause(attr, "between", lo, hi, lo_incl, hi_incl)


def prefix(attr: str, p: str) -> Clause:
    return Clause(attr, "prefix", p)


def is_null(attr: str) -> Clause:
    return Clause(attr, "is_null")


def not_null(attr: str) -> Clause:
    return Clause(attr, "not_null")


@dataclass(frozen=True)
class Repair:
    """A conditional assignment: where ``pred`` holds, ``target`` becomes ``value``."""

    pred: tuple[Clause, ...]
    target: str
    value: Value
    op: str = "manual"
    params: tuple[tuple[str, str], ...] = ()
    bundle: str | None = None

    @property
    def signature(self) -> str:
        return ",".join(f"{c.attr}:{c.op}" for c in self.pred)

    @property
    def repair_id(self) -> int:
        """The same edit from any tool or setting has one id."""
        body = json.dumps([[c.attr, c.op, _text(c.lo), _text(c.hi), c.lo_incl, c.hi_incl, [_text(v) for v in c.vals]] for c in self.pred] + [self.target, _text(self.value)])
        return int(hashlib.md5(body.encode()).hexdigest()[:15], 16)

    def restricted(self, *more: Clause) -> Repair:
        return replace(self, pred=tuple(sorted(self.pred + more, key=lambda c: (c.attr, c.op))))


def _text(v: Value) -> str | None:
    return None if v is None else str(v)


@dataclass(frozen=True)
class FD:
    """lhs determines rhs, on the rows that meet ``condition`` (SQL) if given."""

    lhs: tuple[str, ...]
    rhs: tuple[str, ...]
    condition: str | None = None

    @staticmethod
    def parse(text: str, condition: str | None = None) -> FD:
        left, right = text.split("->")
        return FD(tuple(x.strip() for x in left.split(",")), tuple(x.strip() for x in right.split(",")), condition)

    @property
    def attrs(self) -> tuple[str, ...]:
        return self.lhs + self.rhs

    def __str__(self) -> str:
        return f"{','.join(self.lhs)}->{','.join(self.rhs)}"


@dataclass
class Plan:
    """An ordered pipeline of repairs; a later one may overwrite an earlier one."""

    repairs: list[Repair] = field(default_factory=list)

    def then(self, other: Plan) -> Plan:
        return Plan(self.repairs + other.repairs)

    def to_json(self) -> str:
        rows = [
            {"pred": [[c.attr, c.op, c.lo, c.hi, c.lo_incl, c.hi_incl, list(c.vals)] for c in r.pred], "target": r.target, "value": r.value, "op": r.op, "params": dict(r.params), "bundle": r.bundle}
            for r in self.repairs
        ]
        return json.dumps(rows)

    @staticmethod
    def from_json(text: str) -> Plan:
        return Plan(
            [
                Repair(tuple(Clause(*c[:6], tuple(c[6])) for c in r["pred"]), r["target"], r["value"], r["op"], tuple(sorted(r["params"].items())), r["bundle"])
                for r in json.loads(text)
            ]
        )

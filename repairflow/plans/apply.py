"""Applying plans: as nested CASE columns, or as layers of lookup joins."""

from __future__ import annotations

from collections import defaultdict

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.predicates import commute, comparable, literal, predicate
from ..model import Plan, Repair

#: Up to so many repairs are nested as CASE columns; beyond, lookup joins of equal results.
CASE_CAP, BROADCAST_ROWS = 50, 500_000


def compose(first: Plan, second: Plan) -> Plan:
    """``second`` after ``first``."""
    return first.then(second)


def _value(df: DataFrame, r: Repair) -> Column:
    return F.lit(r.value).cast(df.schema[r.target].dataType)


def steps_of(plan: Plan) -> list[list[Repair]]:
    """Repairs in order; those of one bundle that follow each other act at once."""
    out: list[list[Repair]] = []
    for r in plan.repairs:
        if out and r.bundle is not None and out[-1][0].bundle == r.bundle:
            out[-1].append(r)
        else:
            out.append([r])
    return out


def check_schema(df: DataFrame, plan: Plan) -> None:
    """A plan fits any relation that has its attributes."""
    need = {r.target for r in plan.repairs} | {c.attr for r in plan.repairs for c in r.pred}
    if missing := need - set(df.columns):
        raise ValueError(f"the relation lacks {sorted(missing)}")


def apply_plan(df: DataFrame, plan: Plan, mode: str = "auto") -> DataFrame:
    """The repaired relation: same schema, same records.

    ``case`` nests one CASE column in another, in one scan; ``layers`` joins lookup
    tables; ``auto`` takes case up to CASE_CAP repairs.
    """
    check_schema(df, plan)
    if mode == "case" or mode == "auto" and len(plan.repairs) <= CASE_CAP:
        out = df
        for step in steps_of(plan):
            new: dict[str, Column] = {}
            for r in step:
                new[r.target] = F.when(predicate(r.pred), _value(df, r)).otherwise(new.get(r.target, F.col(r.target)))
            out = out.withColumns(new)
        return out.select(*df.columns)
    return _apply_layers(df, plan)


def compile_layers(plan: Plan) -> list[list[Repair]]:
    """Layer of a repair: one past the last earlier layer that it does not commute with."""
    depth: list[int] = []
    for i, r in enumerate(plan.repairs):
        depth.append(1 + max((depth[j] for j in range(i) if not commute(plan.repairs[j], r)), default=-1))
    layers: list[list[Repair]] = [[] for _ in range(max(depth, default=-1) + 1)]
    for r, d in zip(plan.repairs, depth, strict=True):
        layers[d].append(r)
    return layers


def _apply_layers(df: DataFrame, plan: Plan) -> DataFrame:
    """Within a layer, equalities on one attribute set are one lookup table and join."""
    spark, out, types = df.sparkSession, df, dict(df.dtypes)
    bundled = any(r.bundle for r in plan.repairs)
    layers = steps_of(plan) if bundled else compile_layers(plan)
    for layer in layers:
        tables: dict[tuple, list[Repair]] = defaultdict(list)
        rest: dict[str, Column] = {}
        for r in layer:
            if r.pred and all(c.op == "eq" for c in r.pred):
                tables[tuple(c.attr for c in r.pred), r.target].append(r)
            else:
                rest[r.target] = F.when(predicate(r.pred), _value(df, r)).otherwise(rest.get(r.target, F.col(r.target)))
        before, news = out, {}
        for n, ((attrs, target), rs) in enumerate(sorted(tables.items())):
            rows = [(*[None if c.lo is None else str(c.lo) for c in r.pred], None if r.value is None else str(r.value), i) for i, r in enumerate(rs)]
            names, kinds = [f"_k{n}_{i}" for i in range(len(attrs))], [types[a] for a in attrs]
            lookup = spark.createDataFrame(rows, ", ".join(f"{x} string" for x in names) + f", _v{n} string, _i int")
            lookup = lookup.withColumns({x: literal(F.col(x), k) for x, k in zip(names, kinds, strict=True)})
            # Literals may be written in several ways: the last repair of a key stands.
            lookup = lookup.groupBy(*names).agg(F.max_by(F.struct(f"_v{n}"), "_i").alias("_s")).select(*names, f"_s._v{n}", F.lit(True).alias(f"_hit{n}"))
            if len(rows) <= BROADCAST_ROWS:
                lookup = F.broadcast(lookup)
            cond = [comparable(out[a], k) == lookup[x] for a, k, x in zip(attrs, kinds, names, strict=True)]
            out = out.join(lookup, cond, "left")
            value = literal(F.col(f"_v{n}"), types[target]).cast(df.schema[target].dataType)
            news[target] = F.when(F.col(f"_hit{n}"), value).otherwise(news.get(target, F.col(target)))
        for target, col in rest.items():
            # Repairs of one layer touch disjoint rows or agree.
            news[target] = F.when(F.lit(True), col) if target not in news else F.when(~col.eqNullSafe(F.col(target)), col).otherwise(news[target])
        out = out.withColumns(news).select(*before.columns)
    return out.select(*df.columns)


def conflicts(plan: Plan, extended: bool = False) -> list[tuple[int, int]]:
    """Pairs of positions whose order may matter."""
    rs = plan.repairs
    return [(i, j) for i in range(len(rs)) for j in range(i + 1, len(rs)) if not commute(rs[i], rs[j], extended)]


def touched_rows(changes: DataFrame, key: str = "rec_id") -> DataFrame:
    return changes.select("unit", key).distinct()


def disjoint_rows(changes: DataFrame, a: int, b: int, key: str = "rec_id") -> bool:
    """Whether two units touch no record in common, in the relation at hand."""
    rows = touched_rows(changes, key)
    return rows.filter(F.col("unit") == a).join(rows.filter(F.col("unit") == b).select(key), key, "left_semi").isEmpty()


def plan_predicate(plan: Plan) -> list[tuple]:
    """The union of the predicates of a plan's repairs."""
    return list(dict.fromkeys(r.pred for r in plan.repairs))

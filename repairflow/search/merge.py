"""Merging plans whose edits cannot interfere."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import written


#: Up to so many (unit, key) rows the packing is done by the driver in one pass.
DRIVER_KEYS = 100_000


def _pack_here(rows) -> list[tuple]:
    """The sequential greedy choice over collected (block, plan, unit, rank, key) rows."""
    by: dict[tuple, tuple[int, set]] = {}
    for r in rows:
        by.setdefault((r["block"], r["plan"], r["unit"]), (r["rank"], set()))[1].add(r["key"])
    held: dict[tuple, set] = {}
    taken = []
    for cand, (_, keys) in sorted(by.items(), key=lambda x: (x[0][:2], x[1][0], x[0])):
        mine = held.setdefault(cand[:2], set())
        if not mine & keys:
            mine |= keys
            taken.append(cand)
    return taken


def pack_disjoint(ranked: DataFrame, keys: DataFrame, rounds: int | None = None, driver_keys: int = DRIVER_KEYS) -> DataFrame:
    """The units a greedy packing by rank takes: no two share a key.

    ``ranked`` is (block, plan, unit, rank), ``keys`` (block, plan, unit, key).  In
    each round the units that hold the best rank of all their keys are taken and
    those that share a key with one leave; when none is left that is the
    sequential greedy choice, without one task ever seeing all units.  Few rows, as
    checked at the start and after each round, are packed by the driver, which saves
    the rounds' jobs.  A limit of ``rounds`` leaves units out; there is none by default.
    """
    cand = ["block", "plan", "unit"]
    spread = keys.join(ranked, cand).select(*cand, "key", "rank")
    if driver_keys:
        rows = spread.limit(driver_keys + 1).collect()
        if len(rows) <= driver_keys:
            return keys.sparkSession.createDataFrame(_pack_here(rows), "block long, plan long, unit long")
    left = written(spread.filter("rank is not null"), "pack")
    taken, done = None, 0
    while rounds is None or done < rounds:
        done += 1
        best = left.groupBy("block", "plan", "key").agg(F.min("rank").alias("best"))
        won = left.join(best, ["block", "plan", "key"]).groupBy(*cand).agg(F.min((F.col("rank") == F.col("best")).cast("int")).alias("all")).filter("all = 1").select(*cand)
        won = written(won, "pack")
        taken = won if taken is None else taken.unionByName(won)
        shut = left.join(won, cand, "left_semi").select("block", "plan", "key").distinct()
        out = left.join(shut, ["block", "plan", "key"], "left_semi").select(*cand).distinct()
        left = written(left.join(out, cand, "left_anti"), "pack")
        if left.isEmpty():
            break
        if driver_keys:
            rows = left.limit(driver_keys + 1).collect()
            if len(rows) <= driver_keys:
                return taken.unionByName(keys.sparkSession.createDataFrame(_pack_here(rows), "block long, plan long, unit long"))
    return taken


def merge_exact(plans: list[tuple], cost: Callable[[tuple], float], touched: Callable[[object], frozenset]) -> list[tuple[tuple, float]]:
    """Every plan absorbs in turn, by rising cost, each other plan whose touched cells
    or groups it does not meet, if the cost falls: an evaluation for each try.

    ``plans`` are tuples of units; returns the distinct merged plans with costs.
    """
    scored = sorted(((p, cost(p)) for p in plans), key=lambda x: (x[1], x[0]))
    out: dict[tuple, float] = {}
    for plan, value in scored:
        held = frozenset().union(*[touched(u) for u in plan]) if plan else frozenset()
        for other, _ in scored:
            if other == plan or set(other) & set(plan):
                continue
            more = frozenset().union(*[touched(u) for u in other]) if other else frozenset()
            if held & more:
                continue
            joined = plan + other
            new = cost(joined)
            if new < value:
                plan, value, held = joined, new, held | more
        key = tuple(sorted(plan))
        if key not in out or value < out[key]:
            out[key] = value
    return sorted(out.items(), key=lambda x: (x[1], x[0]))

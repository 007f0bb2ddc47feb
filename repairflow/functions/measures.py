"""Cost and accuracy measures of cleaned relations and of search traces."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def cell_counts(dirty: DataFrame, cleaned: DataFrame, truth: DataFrame, attrs: list[str], key: str = "rec_id") -> DataFrame:
    """One row (changed, correct, erroneous, equal, cells) over the cells of ``attrs``."""
    both = dirty.select(key, *[F.col(a).alias(f"d_{a}") for a in attrs]).join(cleaned.select(key, *[F.col(a).alias(f"c_{a}") for a in attrs]), key).join(truth.select(key, *[F.col(a).alias(f"t_{a}") for a in attrs]), key)
    same = lambda x, y: F.col(x).eqNullSafe(F.col(y))
    total = lambda f: reduce(lambda x, y: x + y, [F.count_if(f(a)) for a in attrs])
    return both.agg(
        total(lambda a: ~same(f"d_{a}", f"c_{a}")).alias("changed"),
        total(lambda a: ~same(f"d_{a}", f"c_{a}") & same(f"c_{a}", f"t_{a}")).alias("correct"),
        total(lambda a: ~same(f"d_{a}", f"t_{a}")).alias("erroneous"),
        total(lambda a: same(f"c_{a}", f"t_{a}")).alias("equal"),
        (F.count("*") * len(attrs)).alias("cells"),
    )


def cell_f1(dirty, cleaned, truth, attrs: list[str], key: str = "rec_id") -> DataFrame:
    """(precision, recall, f1, error, accuracy); a share of nothing is 0, and the F1 of
    an untouched clean relation is 1."""
    c = cell_counts(dirty, cleaned, truth, attrs, key)
    p = F.when(F.col("changed") > 0, F.col("correct") / F.col("changed")).otherwise(0.0)
    r = F.when(F.col("erroneous") > 0, F.col("correct") / F.col("erroneous")).otherwise(0.0)
    clean = (F.col("changed") == 0) & (F.col("erroneous") == 0)
    f1 = F.when(clean, 1.0).when(p + r > 0, 2 * p * r / (p + r)).otherwise(0.0)
    return c.select(p.alias("precision"), r.alias("recall"), f1.alias("f1"), (1 - f1).alias("error"), (F.col("equal") / F.col("cells")).alias("accuracy"))


def suboptimality(truth_cost: float, best_cost: float, eps: float = 1e-9) -> float:
    """Cost of the truth over that of the best plan: rises to 1 as the plan improves."""
    return (truth_cost + eps) / (best_cost + eps)


def time_to(trace: list[dict], level: float) -> float | None:
    """Seconds until the cost was at most ``level``."""
    return min((r["elapsed_s"] for r in trace if r["cost"] <= level), default=None)


def quality_ratio(a: DataFrame, b: DataFrame) -> DataFrame:
    """(elapsed_s, ratio): best cost of trace b over that of trace a at each time of a,
    b's as of that time."""
    both = a.select("elapsed_s", "cost", F.lit("a").alias("who")).unionByName(b.select("elapsed_s", "cost", F.lit("b").alias("who")))
    w = Window.orderBy("elapsed_s", F.col("who").desc()).rowsBetween(Window.unboundedPreceding, 0)  # traces are short
    best = lambda who: F.min(F.when(F.col("who") == who, F.col("cost"))).over(w)
    rows = both.withColumn("ca", best("a")).withColumn("cb", best("b"))
    return rows.filter("who = 'a' and cb is not null").select("elapsed_s", (F.col("cb") / F.col("ca")).alias("ratio"))


def speedup(full_s: float, delta_s: float) -> float:
    return full_s / max(delta_s, 1e-9)


def degradation(plain: list[dict], hindered: list[dict]) -> float:
    """How many times longer the hindered run took to reach the plain run's best cost."""
    level = min(r["cost"] for r in plain)
    a, b = time_to(plain, level), time_to(hindered, level)
    return float("inf") if b is None else b / max(a, 1e-9)

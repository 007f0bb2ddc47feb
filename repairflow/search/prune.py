"""Bound pruning of scored candidates: per worker, then with the best of all."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def utility(cost: Column, kind: str = "reciprocal", start: float | None = None) -> Column:
    """Higher is better: 1/(1+cost), or the share of the start's cost that is gone."""
    if kind == "gain":
        return (F.lit(start) - cost) / F.lit(max(start or 0.0, 1e-12))
    return 1.0 / (1.0 + cost)


def prune_local(scored: DataFrame, gamma: float, best_before: float = 0.0, worker: Column | None = None) -> DataFrame:
    """Rows of (…, utility) at least gamma times the best that their worker knows of."""
    w = Window.partitionBy("_w")  # a worker's rows; give ``worker`` where partitions are large
    rows = scored.withColumn("_w", F.spark_partition_id() if worker is None else worker)
    best = F.greatest(F.max("utility").over(w), F.lit(best_before))
    return rows.withColumn("_best", best).filter(F.col("utility") >= gamma * F.col("_best")).drop("_w", "_best")


def prune_global(scored: DataFrame, gamma: float, best_before: float = 0.0, by: list[str] | None = None) -> DataFrame:
    """The second cut, with the best of all workers; never keeps what the first cut drops."""
    by = by or []
    best = scored.groupBy(*by).agg(F.greatest(F.max("utility"), F.lit(best_before)).alias("_best"))
    joined = scored.join(F.broadcast(best), by) if by else scored.crossJoin(F.broadcast(best))
    return joined.filter(F.col("utility") >= gamma * F.col("_best")).drop("_best")


def rebalance(frontier: DataFrame, workers: int, replicate: bool = False, key: str = "plan") -> DataFrame:
    """An even number of plans on each worker; only plan rows move.

    With ``replicate``, workers without a plan get a copy of a random one, which
    ``dropDuplicates`` removes after the round.
    """
    if replicate:
        n = frontier.count()
        if 0 < n < workers:
            slots = frontier.sparkSession.range(workers - n).select(F.pmod(F.xxhash64("id"), F.lit(n)).alias("_i"))
            numbered = frontier.withColumn("_i", F.row_number().over(Window.orderBy(key)) - 1)  # at most ``workers`` rows
            frontier = frontier.unionByName(numbered.join(slots, "_i").drop("_i"))
    return frontier.repartition(workers)

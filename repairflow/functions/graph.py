"""Fixpoint helper and connected components on DataFrames."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import written


def fixpoint(start: DataFrame, step: Callable[[DataFrame], DataFrame], measure: Callable[[DataFrame], object], max_rounds: int = 50, name: str = "fixpoint") -> DataFrame:
    """Apply ``step`` until ``measure`` stands still; every round is a written table."""
    now = written(start, name)
    seen = measure(now)
    for _ in range(max_rounds):
        now = written(step(now), name)
        value = measure(now)
        if value == seen:
            break
        seen = value
    return now


def components(nodes: DataFrame, edges: DataFrame, max_rounds: int = 50) -> DataFrame:
    """(node, comp): least node of each connected component; edges are (a, b)."""
    # Every round reads the edges, which may take long to find.
    both = written(edges.select(F.inline(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b"))))), "edges")
    start = nodes.select("node", F.col("node").alias("comp"))

    def step(label):
        near = both.join(label.select(F.col("node").alias("a"), "comp"), "a").groupBy(F.col("b").alias("node")).agg(F.min("comp").alias("near"))
        least = label.join(near, "node", "left").select("node", F.least("comp", F.coalesce("near", "comp")).alias("comp"))
        # Jump to the label of the label, which halves the depth of the forest.
        up = least.select(F.col("node").alias("_n"), F.col("comp").alias("_c"))
        return least.join(up, F.col("comp") == F.col("_n"), "left").select("node", F.least("comp", F.coalesce("_c", "comp")).alias("comp"))

    return fixpoint(start, step, lambda d: d.agg(F.sum(F.crc32(F.concat_ws("|", F.col("node").cast("string"), F.col("comp").cast("string"))))).first()[0], max_rounds, "components")

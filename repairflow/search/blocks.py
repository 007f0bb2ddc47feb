"""Partitions of a relation into blocks that are searched on their own."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.graph import components
from ..model import FD


class BlockBy:
    """Blocking rules: each gives ``df`` a column ``block``."""

    @staticmethod
    def columns(df: DataFrame, *cols: str) -> DataFrame:
        return df.withColumn("block", F.xxhash64(*cols))

    @staticmethod
    def time(df: DataFrame, ts: str, unit: str = "month", *cols: str) -> DataFrame:
        return df.withColumn("block", F.xxhash64(F.date_trunc(unit, F.col(ts)), *cols))

    @staticmethod
    def expr(df: DataFrame, sql: str) -> DataFrame:
        return df.withColumn("block", F.expr(sql).cast("long"))

    @staticmethod
    def fds(df: DataFrame, fds: list[FD], key: str = "rec_id") -> DataFrame:
        """Connected components of the records in violated left-hand groups; the rest are
        block -1.  Records meet through group nodes, never pairwise."""
        edges = fd_edges(df, fds, key)
        nodes = edges.select(F.col("a").alias("node")).union(edges.select("b")).distinct()
        comp = components(nodes, edges)
        return df.join(comp.withColumnRenamed("node", "_n"), F.xxhash64(F.col(key)) == F.col("_n"), "left").withColumn("block", F.coalesce("comp", F.lit(-1).cast("long"))).drop("_n", "comp")


def fd_edges(df: DataFrame, fds: list[FD], key: str) -> DataFrame:
    """(a, b): records to the violated left-hand groups they are in, as hashes."""
    parts = []
    for fd in fds:
        rows = (df.filter(fd.condition) if fd.condition else df).dropna(subset=list(fd.attrs))
        y = F.struct(*fd.rhs)
        bad = rows.groupBy(*fd.lhs).agg(F.min(y).alias("_lo"), F.max(y).alias("_hi")).filter("_lo <> _hi")
        hit = rows.join(bad.select(*fd.lhs), list(fd.lhs), "left_semi")
        parts.append(hit.select(F.xxhash64(F.col(key)).alias("a"), F.xxhash64(F.lit(str(fd)), *fd.lhs).alias("b")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.distinct()

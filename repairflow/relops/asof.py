"""Joins that Spark has no operator for: as-of, band and theta joins."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: list[str], lts: str, rts: str, value: str, strict: bool = False) -> DataFrame:
    """Each left row with the last right ``value`` at or before it (before, if strict).

    One sort of the union by key and time: no pair is ever built.
    """
    cols = [c for c in left.columns if c not in (*by, lts)]
    a = left.select(*by, F.col(lts).alias("_t"), F.lit(0 if strict else 1).alias("_s"), F.struct(*cols).alias("_row"), F.lit(None).cast(right.schema[value].dataType).alias("_v"))
    b = right.select(*by, F.col(rts).alias("_t"), F.lit(1 if strict else 0).alias("_s"), F.lit(None).cast(a.schema["_row"].dataType).alias("_row"), F.col(value).alias("_v"))
    w = Window.partitionBy(*by).orderBy("_t", "_s").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn("_last", F.last("_v", ignorenulls=True).over(w))
    return both.filter("_row is not null").select(*by, F.col("_t").alias(lts), "_row.*", F.col("_last").alias(value))


def band_join(left: DataFrame, right: DataFrame, lkey: str, rkey: str, width: float) -> DataFrame:
    """Pairs with |lkey - rkey| <= width, through bins of that width: an equi-join with
    three bins for each left row."""
    bin_ = lambda c: F.floor(F.col(c) / width)
    a = left.withColumn("_bin", F.explode(F.array(bin_(lkey) - 1, bin_(lkey), bin_(lkey) + 1)))
    b = right.withColumn("_bin", bin_(rkey))
    return a.join(b, "_bin").filter(F.abs(F.col(lkey) - F.col(rkey)) <= width).drop("_bin")


def events_within(points: DataFrame, events: DataFrame, by: str, pts: str, ets: str, seconds: int) -> DataFrame:
    """Pairs of a point and the events of its key in the ``seconds`` before it."""
    t = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    size = seconds * 1_000_000
    a = points.withColumn("_pt", t(pts)).withColumn("_bin", F.explode(F.array(F.floor(F.col("_pt") / size), F.floor(F.col("_pt") / size) - 1)))
    b = events.withColumn("_et", t(ets)).withColumn("_bin", F.floor(F.col("_et") / size))
    return a.join(b, [by, "_bin"]).filter((F.col("_et") <= F.col("_pt")) & (F.col("_et") >= F.col("_pt") - size)).drop("_bin", "_pt", "_et")

"""Plans, pools and quality on streams."""

from __future__ import annotations

from collections.abc import Callable
from contextlib import contextmanager

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import POOL_SCHEMA, Plan
from ..plans.apply import apply_plan
from ..session import shared_dir


def read_stream(spark: SparkSession, path: str, schema, fmt: str = "parquet", max_files: int | None = None) -> DataFrame:
    reader = spark.readStream.format(fmt).schema(schema)
    return (reader.option("maxFilesPerTrigger", max_files) if max_files else reader).load(path)


def run_to_table(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run what is available now into Parquet folders in shared storage, and return it."""
    spark = stream.sparkSession
    import uuid

    base = f"{shared_dir(spark)}/repairflow/{name}-{uuid.uuid4().hex}"
    writer = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{base}/checkpoint")
    if mode == "append":
        writer.format("parquet").start(f"{base}/data").awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{base}/data")
    # Each batch brings the whole table: it goes to a folder of its own, and the last one counts.
    batches: list[int] = []

    def keep(batch: DataFrame, i: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/data/{i}")
        batches.append(i)

    with _state_on_disk(spark):
        query = writer.foreachBatch(keep).start()
    query.awaitTermination()
    if not batches:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(f"{base}/data/{batches[-1]}")


@contextmanager
def _state_on_disk(spark: SparkSession):
    """Queries started in here keep the groups of a whole table in RocksDB, not on a heap;
    a provider that the user has set stays."""
    name = "spark.sql.streaming.stateStore.providerClass"
    given, state = spark.conf.get(name), "org.apache.spark.sql.execution.streaming.state"
    if given.endswith("HDFSBackedStateStoreProvider"):
        spark.conf.set(name, f"{state}.RocksDBStateStoreProvider")
    try:
        yield
    finally:
        spark.conf.set(name, given)


def clean_stream(stream: DataFrame, plan: Plan) -> DataFrame:
    """A found plan on arriving records of the same attributes: stateless."""
    return apply_plan(stream, plan)


def pool_stream(spark: SparkSession, path: str, per_step: int = 1) -> DataFrame:
    """The durable twin of the pool: a folder that tools append to."""
    return read_stream(spark, path, POOL_SCHEMA, max_files=per_step)


def search_stream(stream: DataFrame, step: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    """Feed each micro-batch of the pool to a search step."""
    stream.writeStream.foreachBatch(step).trigger(availableNow=True).option("checkpointLocation", checkpoint).start().awaitTermination()


def monitor(stream: DataFrame, ts: str, delay: str, width: str, slide: str | None, *aggregates, by: tuple[str, ...] = ()) -> DataFrame:
    """Quality aggregates of arriving data by event-time window; rows later than
    ``delay`` are dropped."""
    timed = stream.withColumn("_ts", F.col(ts).cast("timestamp")).withWatermark("_ts", delay)
    return timed.groupBy(F.window("_ts", width, slide), *by).agg(*aggregates)


def sessions(stream: DataFrame, ts: str, delay: str, gap: str, key: str) -> DataFrame:
    timed = stream.withColumn("_ts", F.col(ts).cast("timestamp")).withWatermark("_ts", delay)
    return timed.groupBy(F.session_window("_ts", gap), key).agg(F.count("*").alias("n"))


def without_repeats(stream: DataFrame, ts: str, delay: str, keys: list[str]) -> DataFrame:
    return stream.withColumn("_ts", F.col(ts).cast("timestamp")).withWatermark("_ts", delay).dropDuplicatesWithinWatermark(keys).drop("_ts")


def last_good_stream(stream: DataFrame, series: str, order: str, attr: str, bad: Callable[[pd.Series], pd.Series], key: str = "rec_id") -> DataFrame:
    """Replace bad and null readings by the last good one of their series, kept as state.

    A batch's rows of a series are put in order together (equal times by key).
    """
    out = f"{key} long, {series} string, {attr} double, good double"

    def update(group, frames, state):
        (last,) = state.get if state.exists else (None,)
        frame = pd.concat(list(frames)).sort_values([order, key])
        if len(frame):
            good = []
            for value, off in zip(frame[attr], bad(frame[attr]), strict=True):
                last = last if off or pd.isna(value) else float(value)
                good.append(last)
            yield pd.DataFrame({key: frame[key], series: frame[series], attr: frame[attr], "good": pd.array(good, dtype="Float64")})
        state.update((last,))

    return stream.select(key, series, order, attr).groupBy(series).applyInPandasWithState(update, out, "last double", "append", "NoTimeout")


def running_counts(stream: DataFrame, *keys: str) -> DataFrame:
    """Counts by group in update mode: the group state of a dependency on a stream."""
    return stream.groupBy(*keys).agg(F.count("*").alias("n"))


def join_within(left: DataFrame, right: DataFrame, key: str, lts: str, rts: str, delay: str, within: str) -> DataFrame:
    """Stream-stream join of records of one key at most ``within`` apart, right after left."""
    a = left.withColumn(lts, F.col(lts).cast("timestamp")).withWatermark(lts, delay)
    b = right.withColumn(rts, F.col(rts).cast("timestamp")).withWatermark(rts, delay)
    return a.join(b, F.expr(f"{key} = {key}_r and {rts} >= {lts} and {rts} <= {lts} + interval {within}"))

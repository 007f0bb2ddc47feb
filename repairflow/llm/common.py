"""Input, scratch-space and clustering helpers of the corpus operators."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Id that stands for a null document id inside the operators.
NULL_ID = -(1 << 62)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir.

    Where it is unset, a local session (as in tests) gets a folder of its own; on a
    cluster a folder of one machine would be seen by no other, so that is an error.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="repairflow-")
        spark.conf.set("spark.checkpoint.dir", base)
    return base.rstrip("/")


def small_batches(df: DataFrame) -> DataFrame:
    """Bound the Arrow batches between the JVM and Python workers, where the session
    has the defaults: two copies of a batch live outside the heap in every task."""
    conf = df.sparkSession.conf
    for key, default, value in (("spark.sql.execution.arrow.maxRecordsPerBatch", "10000", "2000"), ("spark.sql.execution.arrow.maxBytesPerBatch", "67108864", "8388608")):
        if str(conf.get(key, default)).removesuffix("b") in (default, "64MB", "64m"):
            conf.set(key, value)
    return df


def scratch_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/repairflow/{name}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write to the shared folder and read back: cuts lineage, survives executor loss."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: A key with more than this share of the rows is hot; so there are at most as many hot keys.
HOT_SHARE = 512


def join_unique(rows: DataFrame, to: DataFrame, key: str, total: int, count: str, how: str = "inner") -> DataFrame:
    """Join rows with a table of one row a key, hot keys of ``rows`` by broadcast.

    ``to`` has in column ``count`` how many of the ``total`` rows hold its key: at most
    ``HOT_SHARE`` keys can have over a ``HOT_SHARE``-th of them, which bounds what is sent.
    """
    hot = F.broadcast(to.filter(F.col(count) * HOT_SHARE > total).withColumn("_hot", F.lit(True)))
    cold = to.filter(F.col(count) * HOT_SHARE <= total)
    marked = rows.join(F.broadcast(hot.select(key, "_hot")), key, "left")
    return rows.join(hot, key).drop("_hot").unionByName(marked.filter("_hot is null").drop("_hot").join(cold, key, how))


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Components of an undirected graph given as (u long, v long) rows.

    Alternates linking every larger neighbour, then every smaller one, to the local
    minimum until the edges are stars; a round is two windows and a distinct, written to
    the shared folder.  Returns (node, comp) for every node that has an edge, comp being
    the least node of its component.  Raises if the edges are not stars after
    ``max_rounds``.  For contracted graphs: all edges of a node meet in a task.
    """
    stars = materialize(edges.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "cc")
    around, seen = Window.partitionBy("u"), None
    for _ in range(max_rounds):
        now = stars.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first()
        if not now[0] or tuple(now) == seen:
            break
        seen = tuple(now)
        both = stars.unionByName(stars.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = both.withColumn("m", F.least("u", F.min("v").over(around))).filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        low = large.withColumn("m", F.min("v").over(around))
        small = low.select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.*")
        stars = materialize(small.filter("u <> v").distinct(), "cc")
    else:
        raise RuntimeError(f"components not closed after {max_rounds} rounds")
    return stars.select(F.col("u").alias("node"), F.col("v").alias("comp")).unionByName(stars.select(F.col("v").alias("node"), F.col("v").alias("comp")).distinct())


def text_hash_unit(*cols) -> "F.Column":
    """Deterministic uniform in [0, 1) from columns."""
    return (F.pmod(F.xxhash64(*cols), F.lit(1 << 52)) / float(1 << 52)).cast("double")

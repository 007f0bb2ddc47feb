"""Sources and sinks: the given tables, common file formats, plans and traces."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..model import Plan

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = TABLES) -> None:
    for name in names:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def read(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options: str) -> DataFrame:
    """Any of Spark's file formats or a registered data source."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "error", partition_by: tuple[str, ...] = (), **options: str) -> None:
    writer = df.write.format(fmt).mode(mode).options(**options)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def save_bucketed(df: DataFrame, table: str, buckets: int, *keys: str) -> DataFrame:
    """A bucketed and sorted table, so that joins on its keys need no shuffle of it."""
    df.write.bucketBy(buckets, *keys).sortBy(*keys).mode("overwrite").saveAsTable(table)
    return df.sparkSession.table(table)


def save_plan(spark: SparkSession, plan: Plan, path: str) -> None:
    spark.createDataFrame([(plan.to_json(),)], "value string").coalesce(1).write.mode("overwrite").text(path)


def load_plan(spark: SparkSession, path: str) -> Plan:
    return Plan.from_json(spark.read.text(path, wholetext=True).first()["value"].strip())


class ReadingsSource:
    """Name and factory of a Python data source that makes noisy readings.

    ``spark.dataSource.register(ReadingsSource.make())`` then
    ``spark.read.format("noisy_readings").option("rows", n).load()``.
    """

    @staticmethod
    def make():
        from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

        class Part(InputPartition):
            def __init__(self, lo: int, hi: int):
                self.lo, self.hi = lo, hi

        class Reader(DataSourceReader):
            def __init__(self, options):
                self.rows, self.parts = int(options.get("rows", 1000)), int(options.get("parts", 4))

            def partitions(self):
                step = -(-self.rows // self.parts)
                return [Part(lo, min(lo + step, self.rows)) for lo in range(0, self.rows, step)]

            def read(self, partition):
                for i in range(partition.lo, partition.hi):
                    truth = 50.0 + i * 37 % 19 / 4
                    yield i, truth * 20 if i % 100 == 7 else truth, truth

        class Source(DataSource):
            @classmethod
            def name(cls):
                return "noisy_readings"

            def schema(self):
                return "rec_id long, reading double, truth double"

            def reader(self, schema):
                return Reader(self.options)

        return Source

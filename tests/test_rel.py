"""Relational and streaming queries on small tables of known results."""

import datetime as dt

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from repairflow import queries_rel, queries_repair
from repairflow.functions.graph import components
from repairflow.sources.fixtures import build


def test_joins_take_all_events(spark, tmp_path):
    rng = np.random.default_rng(2)
    start = dt.datetime(2024, 1, 1)
    rows = [(i, "ab"[int(rng.integers(2))], start + dt.timedelta(minutes=30 * int(rng.integers(150))), float(rng.integers(1000))) for i in range(200)]
    spark.createDataFrame(rows, "event_id long, event_type string, ts timestamp_ntz, value double").write.parquet(f"{tmp_path}/events.parquet")
    asof, within = {}, {}
    for i, kind, ts, _ in rows:
        before = [(t, k, v) for k, other, t, v in rows if other == kind and t < ts]
        asof[i] = max(before)[2] if before else None
        within[i] = sum(other == kind and ts - dt.timedelta(hours=5) <= t <= ts for _, other, t, _ in rows)
    assert {r["event_id"]: r["value"] for r in queries_rel.QUERIES["rel_asof_all"](spark, str(tmp_path)).collect()} == asof
    assert {r["event_id"]: r["n"] for r in queries_rel.QUERIES["rel_interval_all"](spark, str(tmp_path)).collect()} == within


def test_plan_file_reads_the_name_as_it_was(spark, tmp_path):
    rows = [(1, "old ring", 901.0), (2, "old ring", 950.0), (3, "new rod", 901.0), (4, None, 901.0), (5, "cold ring", 901.0), (6, "new rod", 905.0)]
    spark.createDataFrame(rows, "p_partkey long, p_name string, p_retailprice double").write.parquet(f"{tmp_path}/part.parquet")
    got = {r["p_partkey"]: r["p_name"] for r in queries_rel.QUERIES["rel_plan_file"](spark, str(tmp_path)).collect()}
    assert got == {1: "cold ring", 2: "cold ring", 3: "cheap", 4: "cheap", 5: "cheap", 6: "new rod"}


def _copied_events(spark, path, copies=6, n=400):
    """Events of one series whose times and values come ``copies`` times."""
    rng = np.random.default_rng(5)
    start = dt.datetime(2024, 1, 1)
    once = [(start + dt.timedelta(minutes=int(i)), round(float(rng.exponential(40)), 2)) for i in range(n)]
    rows = [(c * n + i, "view", ts, v) for c in range(copies) for i, (ts, v) in enumerate(once)]
    spark.createDataFrame(rows, "event_id long, event_type string, ts timestamp_ntz, value double").write.parquet(f"{path}/events.parquet")
    return sorted((ts, i, v) for i, _, ts, v in rows)


def test_readings_are_added_in_the_order_of_the_sql(spark, tmp_path):
    rows = _copied_events(spark, tmp_path)
    want = {}
    for at, (_, i, _) in enumerate(rows):
        lo = max(at - 24, 0)
        seen = [v for _, _, v in rows[lo : at + 1]]
        head = -lo % 16
        total = 0.0
        if head + 16 <= len(seen) and head:
            block = 0.0
            for v in seen[:head]:
                total += v
            for v in seen[head : head + 16]:
                block += v
            total += block
            seen = seen[head + 16 :]
        for v in seen:
            total += v
        want[i] = total / (at + 1 - lo)
    got = {r["rec_id"]: r["truth"] for r in build(spark, str(tmp_path), "series", "series_clean").collect()}
    assert got == want


@pytest.mark.parametrize("name", ["o_hist", "o_hist_sliding"])
def test_histograms_of_copied_readings_as_their_sql(spark, tmp_path, name):
    duckdb = pytest.importorskip("duckdb")
    _copied_events(spark, tmp_path, n=4000)
    con = duckdb.connect()
    con.execute(f"create view events as select * from '{tmp_path}/events.parquet/*.parquet'")
    want = {r[0] for r in con.execute(queries_repair.ORACLES[name]).fetchall()}
    assert {r["rec_id"] for r in queries_repair.QUERIES[name](spark, str(tmp_path)).collect()} == want


@pytest.mark.parametrize("name", ["stream_sessions", "stream_running_counts"])
def test_whole_tables_of_streams_go_to_files(spark, tmp_path, name):
    start = dt.datetime(2024, 1, 1)
    rows = [(i, i % 3, "ab"[i % 2], start + dt.timedelta(hours=4 * i)) for i in range(30)]
    spark.createDataFrame(rows, "event_id long, user_id long, event_type string, ts timestamp_ntz").write.parquet(f"{tmp_path}/events.parquet")
    provider = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    got = queries_rel.QUERIES[name](spark, str(tmp_path))
    assert got.inputFiles()  # none behind the memory sink, which holds its rows on the driver
    assert sorted(map(tuple, got.collect())) == ([(u, 1) for u in range(3) for _ in range(10)] if name == "stream_sessions" else [("a", 15), ("b", 15)])
    assert spark.conf.get("spark.sql.streaming.stateStore.providerClass") == provider


@pytest.mark.parametrize("name", ["b_slot_encoding", "m_quality_ratio", "r_conflicts", "r_extended", "r_layer_count", "rel_data_source", "rel_recursive"])
def test_results_come_from_a_given_table(spark, tmp_path, small, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        __spark_entry__.queries()[name](spark, str(tmp_path)).collect()
    duckdb = pytest.importorskip("duckdb")
    con = duckdb.connect()
    for table in ("part", "events"):
        con.execute(f"create view {table} as select * from '{small}/{table}.parquet'")
    got = __spark_entry__.queries()[name](spark, small)
    rel = con.execute(__spark_entry__.oracle_sql()[name])
    assert got.columns == [d[0] for d in rel.description]
    assert sorted(map(tuple, got.collect())) == sorted(rel.fetchall())


def test_components_find_the_edges_once(spark):
    calls = spark.sparkContext.accumulator(0)

    @F.udf("long")
    def counted(x):
        calls.add(1)
        return x

    edges = spark.range(8).select(counted("id").alias("a"), (F.col("id") + 1).alias("b"))
    got = components(spark.range(9).select(F.col("id").alias("node")), edges).collect()
    assert {r["comp"] for r in got} == {0} and len(got) == 9
    assert calls.value <= 16

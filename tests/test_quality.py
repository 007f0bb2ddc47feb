"""Exact deltas: every term, random edits, against full evaluation."""

import random

import pytest
from pyspark.sql import functions as F

from repairflow.model import FD, Repair, eq
from repairflow.operators.base import coarse
from repairflow.operators.outliers import GaussOutlier, HistOutlier, last_good
from repairflow.plans.pool import pool_of
from repairflow.quality.quality import Quality, prepared
from repairflow.quality.terms import EditPenalty, EmptyStrings, FDViolations, GoldCells, GoldF1, OutOfDictionary, Singletons, SqlTerm, WindowAR
from repairflow.search.engine import Session
from repairflow.session import written


@pytest.fixture(scope="module")
def pairs(spark):
    rng = random.Random(2)
    rows = [(i, rng.choice(["p", "q", "r", None]), rng.choice(["u", "v", "", None])) for i in range(25)]
    return written(spark.createDataFrame(rows, "rec_id int, x string, y string"), "pairs")


def terms(spark, pairs):
    words = spark.createDataFrame([("p",), ("q",)], "word string")
    return {
        "pairs": FDViolations(FD.parse("x -> y")),
        "tuples": FDViolations(FD.parse("x -> y"), "tuples"),
        "groups": FDViolations(FD.parse("x -> y"), "groups"),
        "conditional": FDViolations(FD.parse("x -> y", "x <> 'q'")),
        "singletons": Singletons("y"),
        "empty": EmptyStrings("y"),
        "words": OutOfDictionary("x", words),
        "gold": GoldCells(("x", "y")),
        "edits": EditPenalty(("x", "y")),
    }


def edits(n=14):
    rng = random.Random(5)
    out = []
    for _ in range(n):
        pred = eq("rec_id", rng.randrange(25)) if rng.random() < 0.5 else eq(*rng.choice([("x", "p"), ("x", "q"), ("y", "u"), ("y", "")]))
        out.append(Repair((pred,), rng.choice("xy"), rng.choice(["p", "q", "u", "v", "new", "", None])))
    return out


@pytest.mark.parametrize("name", ["pairs", "tuples", "groups", "conditional", "singletons", "empty", "words", "gold", "edits"])
def test_delta_equals_full(spark, pairs, name):
    truth = pairs.withColumn("y", F.coalesce("y", F.lit("u")))
    q = Quality([(1.0, terms(spark, pairs)[name])])
    s = Session(pairs, q, truth=truth)
    s.add(pool_of(spark, edits()))
    plans = s.rows.select("block").distinct().withColumn("plan", F.lit(0).cast("long"))
    images = written(s.images(s.hits(plans, None)), "images")
    states = q.states(s.rows)
    base = q.cost(s.rows)
    for r in q.deltas(images, states).collect():
        after = s.patch(s.rows, images.filter(F.col("unit") == r["unit"]))
        assert base + r["delta"] == pytest.approx(q.cost(after), abs=1e-9)


@pytest.mark.parametrize("name", ["pairs", "tuples", "singletons", "words", "edits"])
def test_delta_under_a_parent(spark, pairs, name):
    """A second round: deltas against a plan that has changed records already."""
    q = Quality([(1.0, terms(spark, pairs)[name])])
    s = Session(pairs, q)
    s.add(pool_of(spark, edits()))
    plans = s.rows.select("block").distinct().withColumn("plan", F.lit(0).cast("long"))
    first = written(s.images(s.hits(plans, None)), "images")
    unit = sorted(r["unit"] for r in first.select("unit").distinct().collect())[0]
    patched = written(first.filter(F.col("unit") == unit).select("block", "plan", "rec", "b", "a"), "patched")
    drifts = q.drifts(patched.withColumn("unit", F.lit(0).cast("long")), q.states(s.rows))
    images = written(s.images(s.hits(plans, patched)), "images")
    middle = s.patch(s.rows, patched)
    base = q.cost(middle)
    got = q.deltas(images, q.states(s.rows), drifts).collect()
    assert got
    for r in got:
        after = s.patch(middle, images.filter(F.col("unit") == r["unit"]))
        assert base + r["delta"] == pytest.approx(q.cost(after), abs=1e-9)


@pytest.mark.parametrize("error", ["squared", "absolute"])
@pytest.mark.parametrize("slide", [None, "2 hours"])
def test_window_delta_equals_full(spark, error, slide):
    """Single and whole-tool edits, at the root and under a plan that has changed readings."""
    rng = random.Random(9)
    rows = [(i, "st" if i % 3 else "tt", f"2024-01-01 {i // 3:02d}:{i % 3 * 7:02d}:00", rng.gauss(10, 2) * (20 if i % 13 == 5 else 1)) for i in range(60)]
    df = spark.createDataFrame(rows, "rec_id int, station string, ts string, reading double").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    q = Quality([(1.0, WindowAR("reading", "station", "ts", error=error, slide=slide))])
    s = Session(df, q)
    tool = GaussOutlier("station", ["ts", "rec_id"], attr="reading", k=2, window_size=6)
    few = tool.repairs(df).unionByName(pool_of(spark, [Repair((eq("rec_id", 7),), "reading", None), Repair((eq("rec_id", 21),), "reading", 11.5)]))
    s.add(few.unionByName(coarse(tool).repairs(df).select(*few.columns)))
    plans = s.rows.select("block").distinct().withColumn("plan", F.lit(0).cast("long"))
    states = [written(x, "state") for x in q.states(s.rows)]
    images = written(s.images(s.hits(plans, None)), "images")
    base, got = q.cost(s.rows), q.deltas(images, states).collect()
    assert len(got) >= 6
    for r in got:
        after = s.patch(s.rows, images.filter(F.col("unit") == r["unit"]))
        assert base + r["delta"] == pytest.approx(q.cost(after), rel=1e-6)
    worst = max(got, key=lambda r: (r["delta"] > 0, abs(r["delta"])))["unit"]
    patched = written(images.filter(F.col("unit") == worst).select("block", "plan", "rec", "b", "a"), "patched")
    drifts = [written(x, "drift") for x in q.drifts(patched.withColumn("unit", F.lit(0).cast("long")), states)]
    middle = written(s.patch(s.rows, patched), "middle")
    images = written(s.images(s.hits(plans, patched)), "images")
    base, got = q.cost(middle), q.deltas(images, states, drifts).collect()
    assert got
    for r in got:
        after = s.patch(middle, images.filter(F.col("unit") == r["unit"]))
        assert base + r["delta"] == pytest.approx(q.cost(after), rel=1e-6)


def _rows_shuffled(df) -> int:
    """Rows that a query hands from stage to stage."""
    df.collect()

    def walk(node) -> int:
        kind = node.getClass().getSimpleName()
        if kind == "AdaptiveSparkPlanExec":
            return walk(node.executedPlan())
        if kind.endswith("QueryStageExec"):
            return walk(node.plan())
        own = node.metrics().get("shuffleRecordsWritten").get().value() if kind == "ShuffleExchangeExec" else 0
        return own + sum(walk(node.children().apply(i)) for i in range(node.children().size()))

    return walk(df._jdf.queryExecution().executedPlan())


def test_window_delta_lays_out_no_pairs_for_each_candidate(spark):
    """Many candidates in one window: what is shuffled grows with both, not with their product."""
    n = 300
    rows = [(i, "st", f"2024-01-01 {i // 60:02d}:{i % 60:02d}:00", float(i * i % 17)) for i in range(n)]
    df = spark.createDataFrame(rows, "rec_id int, station string, ts string, reading double").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    q = Quality([(1.0, WindowAR("reading", "station", "ts", error="absolute"))])
    s = Session(df, q)
    s.add(pool_of(spark, [Repair((eq("rec_id", i),), "reading", 40.0 + i) for i in range(n)]))
    plans = s.rows.select("block").distinct().withColumn("plan", F.lit(0).cast("long"))
    states, images = [written(x, "state") for x in q.states(s.rows)], written(s.images(s.hits(plans, None)), "images")
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        deltas = q.deltas(images, states)
        assert _rows_shuffled(deltas) < 30 * n and deltas.count() == n
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_f1_delta_equals_full(spark, pairs):
    truth = pairs.withColumn("y", F.upper("y"))
    q = Quality([(1.0, GoldF1(("x", "y")))])
    s = Session(pairs, q, truth=truth)
    values = [r["y"] for r in pairs.select("y").distinct().collect() if r["y"]]
    s.add(pool_of(spark, [Repair((eq("y", v),), "y", w) for v in values for w in (v.upper(), "zz")]))
    plans = s.rows.select("block").distinct().withColumn("plan", F.lit(0).cast("long"))
    images = written(s.images(s.hits(plans, None)), "images")
    base = q.cost(s.rows)
    for r in q.deltas(images, q.states(s.rows)).collect():
        assert base + r["delta"] == pytest.approx(q.cost(s.patch(s.rows, images.filter(F.col("unit") == r["unit"]))))
    assert base == 1.0 and s.run().cost == pytest.approx(0.0)


def test_first_order_differs(spark):
    """Two records of one group are moved at once: the two-join delta is off."""
    df = spark.createDataFrame([(1, "p", "u"), (2, "p", "u"), (3, "p", "v"), (4, "p", "v")], "rec_id int, x string, y string")
    term = FDViolations(FD.parse("x -> y"))
    q = Quality([(1.0, term)])
    s = Session(df, q)
    s.add(pool_of(spark, [Repair((eq("y", "u"),), "y", "v")]))
    plans = s.rows.select("block").distinct().withColumn("plan", F.lit(0).cast("long"))
    images = s.images(s.hits(plans, None))
    exact = q.deltas(images, q.states(s.rows)).first()["delta"]
    rough = term.first_order_delta(images, s.rows).first()["delta"]
    assert exact == -8 and rough != exact


def test_weights_sql_and_normalisation(spark, pairs):
    q = Quality([Singletons("y"), EmptyStrings("y")])
    assert q.weights == [0.5, 0.5] and q.attrs == {"y"}
    assert Quality.from_sql(["select count(*) as n from T where y = ''"]).cost(pairs) == Quality([(1.0, EmptyStrings("y"))]).cost(pairs)
    assert Quality([(1.0, EmptyStrings("y"))]).normalized(pairs).cost(pairs) == pytest.approx(1.0)
    assert not Quality([SqlTerm("select 1 as one from T")]).incremental
    assert prepared(pairs, ["x"]).columns == ["rec_id", "x", "y", "block", "_base_x"]


def _readings(spark, n=140):
    rng = random.Random(3)
    rows = [(i, "ab"[i % 2], i // 2, None if i % 17 == 0 else rng.gauss(10, 2) * (9 if i % 13 == 5 else 1)) for i in range(n)]
    return rows, spark.createDataFrame(rows, "rec_id int, station string, ts int, reading double")


def test_sliding_histogram_against_brute_force(spark):
    rows, df = _readings(spark)
    tool = HistOutlier("station", ["ts"], attr="reading", window_size=30, outlier_threshold=0.08, peak_threshold=0.2, bins=10)
    got = {r["rec_id"]: r["flagged"] for r in tool.flag(df).collect()}
    want = {}
    for s in "ab":
        mine = [r for r in rows if r[1] == s]
        for k, r in enumerate(mine):
            seen = [x[3] for x in mine[max(0, k - 29) : k + 1] if x[3] is not None]
            if r[3] is None:
                want[r[0]] = False
                continue
            lo, hi = min(seen), max(seen)
            bin_ = lambda x: min(int((x - lo) / (hi - lo) * 10), 9) if hi > lo else 0
            want[r[0]] = sum(bin_(x) == bin_(r[3]) for x in seen) / len(seen) < 0.08
    assert got == want and any(want.values())


@pytest.mark.parametrize("size", [4, 11, 40])
def test_bucketed_detectors_equal_whole_series(spark, size):
    """Buckets with a halo, also of fewer rows than the window, give the same flags and fills."""
    _, df = _readings(spark)
    for kind, options in ((GaussOutlier, {"k": 2, "window_size": 12}), (HistOutlier, {"window_size": 20, "outlier_threshold": 0.08, "peak_threshold": 0.2})):
        flags, fills = [], []
        for bucket in (None, F.floor(F.col("ts") / size)):
            tool = kind("station", ["ts", "rec_id"], attr="reading", bucket=bucket, **options)
            flags.append({(r["rec_id"], r["flagged"]) for r in tool.flag(df).collect()})
            fills.append({(r["pred"][0]["lo"], r["value"]) for r in tool.repairs(df).collect()})
        assert flags[0] == flags[1] and len(flags[0]) == df.count() and fills[0] == fills[1]


def test_last_good_frames_grow(spark):
    _, df = _readings(spark)
    plan = last_good(df.withColumn("f", F.col("rec_id") % 5 == 0), "f", "reading", "station", ["ts"])._jdf.queryExecution().executedPlan().toString()
    assert "unboundedfollowing" not in plan.lower()


def test_selfjoin_equals_groups(spark, pairs):
    term = FDViolations(FD.parse("x -> y"))
    rows = pairs.withColumn("block", F.lit(0).cast("long"))
    assert term.cost(rows).first()["cost"] == term.selfjoin_cost(rows).first()["cost"]
    assert "Join" not in term.cost(rows)._jdf.queryExecution().executedPlan().toString()


def test_selfjoin_counts_equal_rows_first(spark):
    rows = spark.range(40_000).select(F.lit(0).cast("long").alias("block"), F.lit("p").alias("x"), (F.col("id") % 2).cast("string").alias("y"))
    cost = FDViolations(FD.parse("x -> y")).selfjoin_cost(rows)
    below = cost._jdf.queryExecution().optimizedPlan().toString().split("Join")[1]
    assert below.count("Aggregate") == 2
    assert cost.first()["cost"] == 2 * 20_000.0**2


def test_split_fixture_is_read_once_and_sorted_by_task(spark, small, monkeypatch):
    from repairflow.sources import fixtures, tables

    key, plans, keep = "spark.sql.optimizer.windowGroupLimitThreshold", [], fixtures.written
    before = spark.conf.get(key)

    def seen(df, name):
        plans.append(df._jdf.queryExecution().optimizedPlan().toString())
        return keep(df, name)

    monkeypatch.setattr(fixtures, "written", seen)
    got = fixtures.build(spark, small, "split", "split_dirty")
    assert not any("lineitem" in f for f in got.inputFiles())
    assert "LocalLimit" in plans[0] and spark.conf.get(key) == before
    tables.register_views(spark, small, ("lineitem", "part"))
    want = spark.sql(fixtures.ctes("split", fixtures.SPARK) + " select * from split_dirty")
    assert got.count() == want.count() and not got.exceptAll(want).count()

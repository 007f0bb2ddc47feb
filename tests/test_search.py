"""Search, pruning, merging, generators, learning and baselines."""

import itertools
import random
import threading
import time

import pytest
from pyspark.sql import functions as F

from repairflow.baselines import tuners
from repairflow.functions import measures
from repairflow.learn.pruner import Pruner, confusion, label_examples
from repairflow.model import FD, Plan, Repair, eq
from repairflow.operators.base import CleaningOperator, coarse, from_table, replicate_library, with_delay
from repairflow.operators.dependencies import FDChase
from repairflow.operators.outliers import GaussOutlier
from repairflow.operators.strings import SpellReplace
from repairflow.plans.apply import apply_plan
from repairflow.plans.pool import pool_of
from repairflow.quality.quality import Quality, prepared
from repairflow.quality.terms import EditPenalty, FDViolations, OutOfDictionary, Singletons, SqlTerm, WindowAR
from repairflow.queries_repair import catalog, detector, items, series
from repairflow.queries_search import catalog_library, catalog_quality, catalog_session
from repairflow.runtime import sampler
from repairflow.runtime.generators import AsyncGenerators, RepairPool, SyncGenerators, allocate, search_async
from repairflow.search.blocks import BlockBy
from repairflow.search.engine import Session
from repairflow.search.merge import merge_exact, pack_disjoint
from repairflow.search.prune import prune_global, prune_local, rebalance
from repairflow.session import written

ROWS = [(1, "p", "u"), (2, "p", "u"), (3, "p", "v"), (4, "q", "w"), (5, "q", "w"), (6, "q", "x"), (7, "r", "y"), (8, "rr", "y"), (9, None, "y")]


@pytest.fixture(scope="module")
def tiny(spark):
    return written(spark.createDataFrame(ROWS, "rec_id int, x string, y string"), "tiny")


def brute(spark, df, repairs, quality, depth=3):
    best = quality.cost(df)
    for n in range(1, depth + 1):
        for plan in itertools.permutations(repairs, n):
            best = min(best, quality.cost(apply_plan(df, Plan(list(plan)))))
    return best


def test_search_reaches_brute_force(spark, tiny):
    rs = [Repair((eq("x", "p"), eq("y", "v")), "y", "u"), Repair((eq("x", "q"), eq("y", "x")), "y", "w"), Repair((eq("x", "rr"),), "x", "r"), Repair((eq("y", "u"),), "y", "bad")]
    q = Quality([(1.0, FDViolations(FD.parse("x -> y"))), (1.0, Singletons("x"))])
    s = Session(tiny, q)
    s.add(pool_of(spark, rs))
    result = s.run()
    assert result.cost == pytest.approx(brute(spark, tiny, rs, q))
    costs = [r["cost"] for r in s.trace.rows]
    assert costs == sorted(costs, reverse=True)
    out = result.cleaned()
    assert out.columns == tiny.columns and out.count() == len(ROWS) and q.cost(out) == pytest.approx(result.cost)
    assert result.repairs().count() == 3


def test_merge_counts_only_if_better(spark):
    """Two repairs that each reach the optimum and together miss it: a term without keys."""
    df = spark.createDataFrame([(1, 5), (2, 9)], "rec_id int, v int")
    rs = [Repair((eq("v", 5),), "v", 1), Repair((eq("v", 9),), "v", 5)]
    for merge in (True, False):
        s = Session(df, Quality([(1.0, SqlTerm("select abs(sum(v) - 10) as off from T"))]), merge=merge)
        s.add(pool_of(spark, rs))
        assert s.run().cost == 0


def test_merging_never_ends_worse(spark):
    rng = random.Random(12)
    for case in range(2):
        df = written(spark.createDataFrame([(i, rng.choice("pqr"), rng.choice("uvw")) for i in range(12)], "rec_id int, x string, y string"), "case")
        rs = [Repair((eq("x", rng.choice("pqr")), eq("y", rng.choice("uvw"))), rng.choice("xy"), rng.choice("pqruvw")) for _ in range(8)]
        q = Quality([(1.0, FDViolations(FD.parse("x -> y"))), (0.7, Singletons("y")), (0.3, EditPenalty(("x", "y")))])
        costs = {}
        for merge, beam in ((True, 1), (False, 1), (True, 4)):
            s = Session(df, q, merge=merge, beam=beam, max_rounds=6)
            s.add(pool_of(spark, rs))
            r = s.run()
            costs[merge, beam] = r.cost
            assert r.cost <= q.cost(prepared(df, ["x", "y"])) and q.cost(prepared_after(df, r)) == pytest.approx(r.cost)
        assert costs[True, 1] <= costs[False, 1] + 1e-9, costs


def prepared_after(df, result):
    """The cleaned relation with the dirty cells beside it."""
    base = prepared(df, ["x", "y"]).select("rec_id", "block", "_base_x", "_base_y")
    return result.cleaned().join(base, "rec_id")


def test_wide_frontier_keeps_plans_that_do_not_improve(spark):
    """A step that costs at first opens the plan that pays; a frontier of one misses it."""
    df = spark.createDataFrame([(1, "a", "x"), (2, "a", "x"), (3, "b", "y"), (4, "b", "y")], "rec_id int, x string, y string")
    rs = [Repair((eq("x", "a"),), "x", "b"), Repair((eq("x", "b"), eq("y", "x")), "y", "y")]
    q = Quality([(1.0, SqlTerm("select 2 * count(distinct x) + count(distinct y) + case when count(distinct x) < count(distinct y) then 3 else 0 end as n from T"))])
    costs = {}
    for beam in (1, 3):
        s = Session(df, q, beam=beam, merge=False, gamma=0.5, patience=2)
        s.add(pool_of(spark, rs))
        costs[beam] = s.run().cost
    assert costs == {1: 6.0, 3: 3.0}


def test_budget_cancels_a_round(spark, tiny):
    q = Quality([(1.0, FDViolations(FD.parse("x -> y"))), (1.0, Singletons("x"))])
    s = Session(tiny, q, budget_s=0.4)
    s.add(pool_of(spark, [Repair((eq("x", "rr"),), "x", "r")]))
    s.trace.began = time.monotonic()
    began = time.monotonic()
    r = s.run()
    assert time.monotonic() - began < 30 and r.cost <= q.cost(tiny)


def test_order_dependent_plan_needs_two_rounds(spark):
    df = spark.createDataFrame([(1, "aa"), (2, "bb"), (3, "cc"), (4, "cc")], "rec_id int, x string")
    rs = [Repair((eq("x", "aa"),), "x", "bb"), Repair((eq("x", "bb"),), "x", "cc")]
    for beam, merge in ((1, True), (3, False)):
        s = Session(df, Quality([(1.0, Singletons("x"))]), beam=beam, merge=merge)
        s.add(pool_of(spark, rs))
        assert s.run().cost == 0


def test_full_and_incremental_agree(spark, tiny):
    rs = [Repair((eq("x", "p"), eq("y", "v")), "y", "u"), Repair((eq("x", "rr"),), "x", "r")]
    q = Quality([(1.0, FDViolations(FD.parse("x -> y"))), (0.5, Singletons("x"))])
    costs = []
    for incremental in (True, False):
        s = Session(tiny, q, incremental=incremental)
        s.add(pool_of(spark, rs))
        costs.append(s.run().cost)
    assert costs[0] == pytest.approx(costs[1])


def test_blocks_are_searched_apart(spark):
    rows = [(i, "k", "u" if i % 5 else "v", i // 10) for i in range(30)]
    df = BlockBy.expr(spark.createDataFrame(rows, "rec_id int, x string, y string, g int"), "g")
    q = Quality([(1.0, FDViolations(FD.parse("x -> y")))])
    s = Session(df, q)
    s.add(pool_of(spark, [Repair((eq("y", "v"),), "y", "u")]))
    r = s.run()
    assert r.cost == 0 and r.units.select("block").distinct().count() == 3
    assert s.fork(Quality([(1.0, Singletons("y"))])).run().cost == 0


def test_fd_components(spark):
    rows = [(1, "a", "1"), (2, "a", "2"), (3, "b", "3"), (4, "c", "4"), (5, "c", "5")]
    df = BlockBy.fds(spark.createDataFrame(rows, "rec_id int, x string, y string"), [FD.parse("x -> y")])
    got = {r["rec_id"]: r["block"] for r in df.collect()}
    assert got[1] == got[2] != got[4] == got[5] and got[3] == -1


def test_local_survivors_contain_global(spark):
    rng = random.Random(3)
    df = spark.createDataFrame([(i, rng.random(), i % 4) for i in range(200)], "unit int, utility double, w int")
    local = prune_local(df, 0.9, worker=F.col("w"))
    final = {r["unit"] for r in prune_global(local, 0.9).collect()}
    assert final <= {r["unit"] for r in local.collect()} and final == {r["unit"] for r in prune_global(df, 0.9).collect()}
    top = df.agg(F.max("utility")).first()[0]
    assert {r["utility"] for r in prune_global(df, 1.0).collect()} == {top}
    few = spark.createDataFrame([(1,), (2,)], "plan long")
    assert rebalance(few, 8, replicate=True).count() == 8 and rebalance(few, 8, replicate=True).dropDuplicates(["plan"]).count() == 2


def test_packing_is_the_sequential_choice(spark):
    rng = random.Random(6)
    keys = {u: {rng.randrange(15) for _ in range(rng.randrange(1, 4))} for u in range(25)}
    taken, held = [], set()
    for u in range(25):
        if not keys[u] & held:
            taken.append(u)
            held |= keys[u]
    ranked = spark.createDataFrame([(0, 0, u, u) for u in keys], "block long, plan long, unit long, rank int")
    rows = spark.createDataFrame([(0, 0, u, str(k)) for u, ks in keys.items() for k in ks], "block long, plan long, unit long, key string")
    for driver_keys in (0, 1000):
        assert sorted(r["unit"] for r in pack_disjoint(ranked, rows, rounds=30, driver_keys=driver_keys).collect()) == taken


def test_packing_ends_long_chains(spark):
    """Units in a chain of shared keys, one decided a round: every other one is taken."""
    n = 32
    ranked = spark.createDataFrame([(0, 0, u, u) for u in range(n)], "block long, plan long, unit long, rank long")
    keys = spark.createDataFrame([(0, 0, u, k) for u in range(n) for k in (u, u + 1)], "block long, plan long, unit long, key long")
    for driver_keys in (0, 40):
        assert sorted(r["unit"] for r in pack_disjoint(ranked, keys, driver_keys=driver_keys).collect()) == list(range(0, n, 2))


def test_exact_merge_never_loses():
    gain = {1: 5, 2: 3, 3: 4}
    touched = {1: frozenset("a"), 2: frozenset("b"), 3: frozenset("a")}
    out = merge_exact([(1,), (2,), (3,)], lambda p: 20 - sum(gain[u] for u in p), touched.get)
    assert out[0] == ((1, 2), 12) and all(c <= 20 for _, c in out)


def test_redundant_library_same_pool(spark, small):
    costs, sizes = set(), set()
    for n in (1, 4):
        df = catalog(spark, small)
        s = Session(df, catalog_quality(spark, small), max_rounds=1)
        SyncGenerators(replicate_library(catalog_library(spark, small), n)).fill(s, df)
        sizes.add(s.pool.count())
        costs.add(round(s.run().cost, 9))
    assert len(sizes) == len(costs) == 1


def test_async_equals_sync(spark, small):
    df, q = catalog(spark, small), catalog_quality(spark, small)
    sync = catalog_session(spark, small).run().cost
    best = None
    for best in search_async(Session(df, q), catalog_library(spark, small), df, 120):  # noqa: B007
        pass
    assert best.cost == pytest.approx(sync)


class Fixed(CleaningOperator):
    name, attr_params = "fixed", ()

    def __init__(self, repair, **options):
        super().__init__(**options)
        self.repair = repair

    def repairs(self, df):
        return pool_of(df.sparkSession, [self.repair])


def test_straggler_delays_nothing(spark, tiny):
    fast = Fixed(Repair((eq("x", "rr"),), "x", "r"))
    slow = with_delay(Fixed(Repair((eq("x", "p"), eq("y", "v")), "y", "u")), 25_000, 25_000)
    q = Quality([(1.0, Singletons("x")), (1.0, FDViolations(FD.parse("x -> y")))])
    began = time.monotonic()
    found = search_async(Session(tiny, q), [slow, fast], tiny, 60)
    first = next(found)
    assert time.monotonic() - began < 25 and first.cost < q.cost(tiny)
    assert list(found)[-1].cost < first.cost


def test_back_pressure():
    pool = RepairPool(10)
    done = []

    def work():
        for _ in range(5):
            pool.put(None, 6)
        done.append(True)

    t = threading.Thread(target=work)
    t.start()
    time.sleep(0.3)
    assert not done and pool.size == 6
    while t.is_alive():
        pool.drain()
        time.sleep(0.02)
    assert done and pool.peak <= 10 and allocate(8, 3) == {"generators": 3, "search": 5}


def test_samplers(spark, small):
    op = SpellReplace(None, domains={"rec": [0, 1, 2], "attr": ["a", "b"]})
    assert len(list(sampler.iterate(op))) == 6 and [s["rec"] for s in sampler.sweep(op)] == [0, 0, 1, 1, 2, 2]
    assert next(sampler.uniform(op, 1)).keys() == {"rec", "attr"} and next(sampler.weighted(op, {"rec": [0, 0, 1]}))["rec"] == 2
    df = catalog(spark, small)
    assert sampler.infer_attrs(df) == ["item", "noun", "type", "brand"]
    assert sampler.relevant_attrs(sampler.infer_attrs(df), Quality([Singletons("item")]), [FD.parse("item -> noun")]) == ["item", "noun"]


def test_wrapped_tool_must_keep_schema(spark, tiny):
    op = from_table(lambda d: d.withColumn("x", F.upper("x")))
    assert op.repairs(tiny).count() == 8
    with pytest.raises(ValueError):
        from_table(lambda d: d.drop("x")).repairs(tiny)


def test_coarse_is_one_unit(spark, small):
    df = catalog(spark, small)
    op = coarse(FDChase([FD.parse("item -> noun")]))
    assert op.repairs(df).select("unit").distinct().count() == 1


def test_pruner_never_drops_training_positives(spark, medium):
    df = catalog(spark, medium)
    chase, spell = FDChase([FD.parse("item -> noun")]).repairs(df), SpellReplace(items(spark, medium), attr="item", rec=2).repairs(df)
    pool = written(chase.unionByName(spell), "pool")
    tried = pool.select(F.pmod("unit", F.lit(8)).alias("block"), "unit")
    best = tried.join(pool.filter("op = 'chase'"), "unit", "left_semi")
    examples = written(label_examples(tried, best), "examples")
    p = Pruner(["item", "noun"], ["chase", "spell"], ["rec"]).fit(examples, pool)
    c = confusion(p, examples, pool)
    assert p.active and c["false_negative"] == 0 and c["true_negative"] > 0
    assert p.keep(pool).select("op").distinct().count() == 1
    one_class = examples.withColumn("label", F.lit(1.0))
    assert not Pruner(["item"], ["chase"]).fit(one_class, pool).active
    assert not Pruner(["item"], ["chase"]).fit(examples.filter("block < 2"), pool).active


def test_tuners(spark, small):
    df = written(catalog(spark, small), "dirty")
    ops = [SpellReplace(items(spark, small), domains={"rec": [1, 2]}, attr="item"), FDChase([FD.parse("item -> noun")])]
    q = Quality([(1.0, OutOfDictionary("item", items(spark, small))), (1.0, FDViolations(FD.parse("item -> noun")))])
    new = lambda name: tuners.Tuner(name, df, ops, q)
    grid = tuners.grid_search(new("grid"), parallel=2)
    assert len(grid.trials) == 6
    for t in (tuners.greedy_tune(new("greedy")), tuners.random_search(new("random"), 4), tuners.tpe_search(new("tpe"), 6, n_startup=4)):
        assert grid.best_cost <= t.best_cost <= q.cost(df)
    assert q.cost(grid.cleaned()) == pytest.approx(grid.best_cost)
    # A greedy search over single repairs need not reach the best cascade, but comes near.
    s = Session(df, q)
    SyncGenerators(ops).fill(s, df)
    assert s.run().cost <= 0.2 * q.cost(df)


def test_parzen_prefers_good_settings():
    space = [[{"op": 0, "t": t} for t in range(10)]]
    p = tuners.ParzenSampler(space, n_startup=0, seed=1)
    trials = [([{"op": 0, "t": t}], abs(t - 7)) for t in range(10)]
    picks = [p.propose(trials)[0]["t"] for _ in range(30)]
    assert sum(5 <= t <= 9 for t in picks) > 20


def test_edit_penalty_keeps_cells(spark):
    """Nulling evidence is no gain once edits cost."""
    df = spark.createDataFrame([(1, "p", "u"), (2, "p", "v")], "rec_id int, x string, y string")
    rs = [Repair((eq("x", "p"),), "x", None), Repair((eq("y", "v"),), "y", "u")]
    s = Session(df, Quality([(1.0, FDViolations(FD.parse("x -> y"))), (0.6, EditPenalty(("x", "y")))]))
    s.add(pool_of(spark, rs))
    out = {r["rec_id"]: (r["x"], r["y"]) for r in s.run().cleaned().collect()}
    assert out == {1: ("p", "u"), 2: ("p", "u")}


def test_measures(spark):
    assert measures.suboptimality(1.0, 2.0) == pytest.approx(0.5) and measures.suboptimality(0.0, 0.0) == 1.0
    trace = [{"elapsed_s": 1.0, "cost": 5.0}, {"elapsed_s": 2.0, "cost": 3.0}]
    assert measures.time_to(trace, 3.0) == 2.0 and measures.time_to(trace, 1.0) is None
    assert measures.degradation(trace, [{"elapsed_s": 8.0, "cost": 3.0}]) == 4.0
    d = spark.createDataFrame([(1, "a"), (2, "b"), (3, None)], "rec_id int, v string")
    c = spark.createDataFrame([(1, "a"), (2, "x"), (3, "z")], "rec_id int, v string")
    t = spark.createDataFrame([(1, "a"), (2, "x"), (3, "y")], "rec_id int, v string")
    r = measures.cell_f1(d, c, t, ["v"]).first()
    assert (r["precision"], r["recall"], r["accuracy"]) == (0.5, 0.5, pytest.approx(2 / 3))


def test_flagship_improves_truth(spark, medium):
    dirty, truth = catalog(spark, medium), catalog(spark, medium, "clean")
    cleaned = catalog_session(spark, medium, max_rounds=3).run().cleaned()
    f1 = measures.cell_f1(dirty, cleaned, truth, ["item", "noun"]).first()["f1"]
    assert f1 > 0.5


def test_plans_of_a_round_stay_small(spark, small, monkeypatch):
    """The text of a plan, which the driver makes of all that it runs: cached tables that
    read cached tables would multiply in it."""
    from repairflow.search import engine

    sizes = []

    def measured(df, name):
        sizes.append(len(df._jdf.queryExecution().toString()))
        return written(df, name)

    df = series(spark, small).drop("truth").limit(400)
    gauss = detector(GaussOutlier, k=4, window_size=20)
    monkeypatch.setattr(engine, "written", measured)
    s = Session(df, Quality([WindowAR("reading", "station", "ts", error="absolute")]), max_rounds=2)
    s.add(coarse(gauss).repairs(df).unionByName(gauss.repairs(df)))
    s.run()
    assert len(s.trace.rows) > 2 and max(sizes) < 3_000_000, sizes

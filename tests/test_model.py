"""Predicates, plans, pools: worked examples and properties."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from repairflow.functions.predicates import box, commute, disjoint, successor
from repairflow.model import Clause, Plan, Repair, between, cmp, eq, eq_all, is_null, not_null, one_of, prefix
from repairflow.plans.apply import apply_plan, compile_layers, compose, conflicts, disjoint_rows, plan_predicate
from repairflow.plans.pool import bind, bundle, canonicalize, consensus, expand_keys, generalize, pool_of, support

ROWS = [(1, 1, "NY", 5.0), (2, 2, "New York", -3.0), (3, 3, "Newark", None), (4, 1, None, 7.5), (5, 2, "NY", 0.0)]


@pytest.fixture(scope="module")
def tiny(spark):
    return spark.createDataFrame(ROWS, "rec_id int, a int, b string, c double")


def run(tiny, *repairs, mode="auto"):
    return {r["rec_id"]: (r["a"], r["b"], r["c"]) for r in apply_plan(tiny, Plan(list(repairs)), mode).collect()}


def test_worked_examples(tiny):
    assert run(tiny, Repair((prefix("b", "New Y"),), "b", "NY"))[2][1] == "NY"
    assert run(tiny, Repair((cmp("c", "lt", 0.0),), "c", None))[2][2] is None
    pool = expand_keys(Repair((prefix("b", "New"),), "b", "NY"), tiny)
    assert {r["pred"][0]["lo"] for r in pool.collect()} == {"2", "3"}


def test_later_repairs_overwrite(tiny):
    one, two = Plan([Repair((eq("a", 1),), "b", "x")]), Plan([Repair((eq("b", "x"),), "b", "y")])
    both = apply_plan(tiny, compose(one, two)).filter("b = 'y'").count()
    assert both == 2 and apply_plan(tiny, compose(two, one)).filter("b = 'y'").count() == 0


def test_schema_and_records_stay(tiny):
    for r in (Repair((is_null("b"),), "b", "?"), Repair((not_null("c"),), "c", None), Repair((one_of("a", [1, 3]),), "c", 1.0), Repair((between("c", -5.0, 0.0, True, False),), "a", 9)):
        out = apply_plan(tiny, Plan([r]))
        assert out.schema == tiny.schema and out.count() == len(ROWS)
    with pytest.raises(ValueError):
        apply_plan(tiny, Plan([Repair((eq("z", 1),), "b", "x")]))


def random_repair(rng):
    kinds = [lambda: eq("a", rng.choice([1, 2, 3])), lambda: cmp("c", rng.choice(["lt", "ge"]), rng.choice([0.0, 5.0])), lambda: prefix("b", rng.choice(["N", "New"])), lambda: is_null("b"), lambda: eq("b", "NY")]
    pred = tuple(rng.choice(kinds)() for _ in range(rng.choice([1, 1, 2])))
    target = rng.choice("abc")
    return Repair(pred, target, {"a": rng.choice([1, 2, 9]), "b": rng.choice(["NY", "LA", None]), "c": rng.choice([0.0, 6.0, None])}[target])


def apply_rows(rows, repairs):
    def holds(c, row):
        v = row[c.attr]
        if c.op in ("is_null", "not_null"):
            return (v is None) == (c.op == "is_null")
        if v is None:
            return False
        return {"eq": lambda: v == c.lo, "lt": lambda: v < c.lo, "ge": lambda: v >= c.lo, "prefix": lambda: v.startswith(c.lo)}[c.op]()

    out = [dict(r) for r in rows]
    for r in repairs:
        for row in out:
            if all(holds(c, row) for c in r.pred):
                row[r.target] = r.value
    return out


def test_commuting_repairs_commute():
    rng = random.Random(1)
    rows = [{"a": a, "b": b, "c": c} for a, b, c in itertools.product([1, 2, 3, 9], ["NY", "New York", "LA", None], [-1.0, 0.0, 5.0, 6.0, None])]
    seen = 0
    for _ in range(3000):
        x, y = random_repair(rng), random_repair(rng)
        for extended in (False, True):
            if commute(x, y, extended):
                seen += 1
                assert apply_rows(rows, [x, y]) == apply_rows(rows, [y, x]), (x, y)
    assert seen > 200
    a, b = Repair((eq("a", 1),), "a", 2), Repair((eq("a", 2),), "b", "x")
    assert not commute(a, b) and apply_rows(rows, [a, b]) != apply_rows(rows, [b, a])


def test_boxes():
    assert disjoint(box((cmp("c", "lt", 0.0),)), box((cmp("c", "ge", 0.0),)))
    assert not disjoint(box((eq("a", 1),)), box((eq("b", "x"),)))
    assert box((eq("a", 1), eq("a", 2))) is None and successor("ab") == "ac" and successor("") is None
    assert disjoint(box((is_null("b"),)), box((prefix("b", ""),)))


def test_layers_equal_case(tiny, spark):
    rng = random.Random(4)
    for _ in range(4):
        plan = [random_repair(rng) for _ in range(8)]
        assert run(tiny, *plan, mode="layers") == run(tiny, *plan, mode="case")
        layers = compile_layers(Plan(plan))
        assert sum(map(len, layers)) == 8
    assert conflicts(Plan([Repair((eq("a", 1),), "a", 2), Repair((eq("a", 2),), "a", 1)])) == [(0, 1)]


def test_literals_are_typed(spark):
    """Booleans, large doubles, dates, whole numbers: case, layers and bind agree."""
    import datetime

    df = spark.createDataFrame([(1, True, 1e7, datetime.date(2024, 1, 2), 5, "1"), (2, False, 2.5, datetime.date(2024, 1, 3), 7, "true"), (3, None, None, None, None, None)], "rec_id int, f boolean, p double, d date, n int, s string")
    rs = [
        Repair((eq("f", True),), "s", "yes"), Repair((eq("p", 1e7),), "s", "dear"), Repair((eq("d", datetime.date(2024, 1, 3)),), "s", "third"), Repair((eq("n", 5.0),), "s", "five"), Repair((eq("s", "true"),), "f", True),
        Repair((cmp("p", "ge", 1e7),), "n", 8), Repair((one_of("n", [7.0, 9]),), "p", 1e8), Repair((eq("rec_id", 2),), "d", datetime.date(2020, 2, 2)), Repair((between("d", datetime.date(2024, 1, 1), datetime.date(2024, 1, 2)),), "n", 1),
    ]
    for r in rs:
        case, layers = ({x["rec_id"]: tuple(x) for x in apply_plan(df, Plan([r]), mode).collect()} for mode in ("case", "layers"))
        changed = {k for k, x in case.items() if x != {y["rec_id"]: tuple(y) for y in df.collect()}[k]}
        assert case == layers and changed == {x["rec_id"] for x in bind(pool_of(spark, [r]), df, ("rec_id",)).collect()} != set(), r
    many = Plan(rs[:5] * 12)
    assert [tuple(x) for x in apply_plan(df, many, "auto").orderBy("rec_id").collect()] == [tuple(x) for x in apply_plan(df, many, "case").orderBy("rec_id").collect()]


def test_extended_commutation_and_plan_predicate(tiny):
    a, b = Repair((eq("a", 1),), "b", "x"), Repair((cmp("c", "ge", 0.0),), "b", "x")
    assert not commute(a, b) and commute(a, b, extended=True) and conflicts(Plan([a, b]), extended=True) == []
    assert plan_predicate(Plan([a, b, a])) == [a.pred, b.pred]


def test_bundle_acts_at_once(tiny):
    rs = [Repair((eq("b", "NY"),), "a", 7, bundle="s"), Repair((eq("b", "NY"),), "b", "N", bundle="s")]
    for mode in ("case", "layers"):
        assert run(tiny, *rs, mode=mode)[1] == (7, "N", 5.0)


def test_plan_json_and_ids(spark):
    plan = Plan([Repair((prefix("b", "é'"), between("c", 1.0, None, False)), "a", None, "t", (("k", "1"),), "u"), Repair(eq_all({"b": "x", "a": 1}), "c", 2.5)])
    assert Plan.from_json(plan.to_json()) == plan
    pool = pool_of(spark, [Repair((eq("b", "x"),), "b", "y", "one"), Repair((eq("b", "x"),), "b", "y", "two"), Repair((eq("b", "x"),), "b", "z")])
    assert pool.select("repair_id").distinct().count() == 2 and canonicalize(pool).count() == 2
    assert bundle(pool).select("unit").distinct().count() == 3


def test_binding(tiny, spark):
    rs = [Repair((eq("b", "NY"), eq("a", 1)), "c", 1.0), Repair((cmp("c", "gt", 4.0),), "b", None), Repair((one_of("a", [3]),), "b", "NJ"), Repair((is_null("b"),), "b", "?"), Repair((between("c", -3.0, 0.0, False, True),), "a", 4), Repair((eq("b", "NY"),), "b", "NY")]
    got = {(r["rec_id"], r["target"], r["new"]) for r in bind(pool_of(spark, rs), tiny, ("rec_id",)).collect()}
    assert got == {(1, "c", "1.0"), (1, "b", None), (3, "b", "NJ"), (4, "b", "?"), (5, "a", "4")}
    assert {r["support"] for r in support(pool_of(spark, rs[:1]), tiny).collect()} == {1}
    changes = bind(pool_of(spark, rs), tiny, ("rec_id",))
    units = {r["target"] + str(r["rec_id"]): r["unit"] for r in changes.collect()}
    assert disjoint_rows(changes, units["b3"], units["c1"]) and not disjoint_rows(changes, units["c1"], units["b1"])
    assert bind(pool_of(spark, rs).limit(0), tiny, ("rec_id",)).count() == 0


def test_generalize_and_consensus(tiny, spark):
    low = generalize(expand_keys(Repair((cmp("c", "le", 0.0),), "c", 9.0), tiny), tiny, ["c", "a"])
    assert ("c", "le", "0.0") in {(r["attr"], r["op"], r["bound"]) for r in low.collect()}
    votes = pool_of(spark, [Repair((eq("b", "NY"),), "b", "N", "one"), Repair((eq("b", "NY"),), "b", "N", "two"), Repair((eq("b", "NY"),), "b", "M", "three")])
    assert {(r["rec_id"], r["new"], r["votes"]) for r in consensus(votes, tiny).collect()} == {(1, "N", 2), (5, "N", 2)}


def test_predicates_reach_the_scan(spark, small):
    part = spark.read.parquet(f"{small}/part.parquet")
    out = expand_keys(Repair((eq("p_name", "old ring"),), "p_brand", "x"), part, "p_partkey")
    assert out.count() >= 0
    plan = apply_plan(part, Plan([Repair((eq("p_name", "a"),), "p_brand", "b")])).select("p_brand")._jdf.queryExecution().toString()
    assert "ReadSchema: struct<p_name:string,p_brand:string>" in plan
    assert Clause("a", "eq", 1) == eq("a", 1) and F.lit(1) is not None

"""Queries of the repair methods with the same results in plain SQL.

A query is (function of (spark, sf_dir), SQL or None).  SQL runs over views of the
given tables; fixtures are common table expressions.
"""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import measures
from .functions.predicates import commute, predicate
from .model import FD, Plan, Repair, between, cmp, eq, eq_all, is_null, prefix
from .operators.dependencies import FDChase, StatisticalFD
from .operators.outliers import GaussOutlier, HistOutlier, PCAOutlier, last_good, last_good_bucketed
from .operators.strings import EditMatch, FillMissing, MinHashReplace, RangeNullify, SpellReplace, SplitFields, apply_pool
from .plans.apply import apply_plan, compile_layers, compose, disjoint_rows, plan_predicate
from .plans.pool import bind, bundle, canonicalize, consensus, expand_keys, generalize, pool_of
from .session import written
from .sources.fixtures import WIDE_ATTRS, WIDE_FDS, build, ctes

QUERIES, ORACLES = {}, {}


def query(sql: str | None = None, fixture: str | None = None):
    def add(fn):
        QUERIES[fn.__name__] = fn
        if sql is not None:
            # A query's own common table expressions go on with those of the fixture.
            body = sql.strip()
            if fixture and body.lower().startswith("with "):
                body = f"{ctes(fixture)}, {body[5:]}"
            elif fixture:
                body = f"{ctes(fixture)} {body}"
            ORACLES[fn.__name__] = body
        return fn

    return add


def catalog(spark: SparkSession, sf: str, which: str = "dirty") -> DataFrame:
    return build(spark, sf, "catalog", f"catalog_{which}")


ITEMS = "select distinct item as word from catalog_clean"


def items(spark: SparkSession, sf: str) -> DataFrame:
    return catalog(spark, sf, "clean").select(F.col("item").alias("word")).distinct()


# Repairs.


@query("select rec_id, case when item = 'old ring' then 'cold ring' else item end as item from catalog_dirty", "catalog")
def r_apply_eq(spark, sf):
    return apply_plan(catalog(spark, sf).select("rec_id", "item"), Plan([Repair((eq("item", "old ring"),), "item", "cold ring")]))


@query("select rec_id, case when item = 'old ring' and noun = 'ring' and brand = 'Brand#1' then 'one' else type end as type from catalog_dirty", "catalog")
def r_apply_eq_list(spark, sf):
    pred = eq_all({"item": "old ring", "noun": "ring", "brand": "Brand#1"})
    return apply_plan(catalog(spark, sf), Plan([Repair(pred, "type", "one")])).select("rec_id", "type")


@query("select rec_id, case when price < 905.0 then null when price >= 950.0 and price < 960.0 then 955.0 else price end as price from catalog_dirty", "catalog")
def r_apply_range(spark, sf):
    plan = Plan([Repair((cmp("price", "lt", 905.0),), "price", None), Repair((between("price", 950.0, 960.0, True, False),), "price", 955.0)])
    return apply_plan(catalog(spark, sf).select("rec_id", "price"), plan)


@query("select rec_id, case when starts_with(item, 'blu') then 'blue' else type end as type from catalog_dirty", "catalog")
def r_apply_prefix(spark, sf):
    return apply_plan(catalog(spark, sf), Plan([Repair((prefix("item", "blu"),), "type", "blue")])).select("rec_id", "type")


@query("select rec_id, case when noun is null then 'missing' when noun = 'rod' then null else noun end as noun from catalog_dirty", "catalog")
def r_apply_null(spark, sf):
    plan = Plan([Repair((is_null("noun"),), "noun", "missing"), Repair((eq("noun", "rod"),), "noun", None)])
    return apply_plan(catalog(spark, sf).select("rec_id", "noun"), plan)


@query("select rec_id, case when noun in ('ring', 'rod') then 'bar' else noun end as noun from catalog_dirty", "catalog")
def r_apply_pipeline_order(spark, sf):
    one, two = Plan([Repair((eq("noun", "ring"),), "noun", "rod")]), Plan([Repair((eq("noun", "rod"),), "noun", "bar")])
    return apply_plan(catalog(spark, sf).select("rec_id", "noun"), compose(one, two))


def _many_repairs(names: list[str] | None = None) -> Plan:
    if names is None:
        names = [f"{a} {n}" for a in ("blue", "cold", "hot", "new", "old", "red") for n in ("anvil", "bolt", "gear", "rod", "ring", "plate", "gizmo", "widget")]
    rs = [Repair((eq("item", name),), "type", "-".join(reversed(name.split(" ", 1)))) for name in names]
    rs += [Repair((eq("type", "rod-old"),), "noun", "changed"), Repair((eq("noun", "changed"),), "item", "new one"), Repair((cmp("price", "gt", 990.0),), "type", "dear")]
    return Plan(rs)


@query(
    """with step as (select rec_id, case when split_part(item, ' ', 1) in ('blue', 'cold', 'hot', 'new', 'old', 'red') and split_part(item, ' ', 2) in ('anvil', 'bolt', 'gear', 'rod', 'ring', 'plate', 'gizmo', 'widget')
    and item = concat(split_part(item, ' ', 1), ' ', split_part(item, ' ', 2)) then concat(split_part(item, ' ', 2), '-', split_part(item, ' ', 1)) else type end as type, noun, item, price from catalog_dirty)
    select rec_id, case when price > 990.0 then 'dear' else type end as type, case when type = 'rod-old' then 'changed' else noun end as noun, case when type = 'rod-old' then 'new one' else item end as item from step""",
    "catalog",
)
def r_layers(spark, sf):
    return apply_plan(catalog(spark, sf), _many_repairs(), mode="layers").select("rec_id", "type", "noun", "item")


@query(ORACLES["r_layers"])
def r_layers_case(spark, sf):
    return apply_plan(catalog(spark, sf), _many_repairs(), mode="case").select("rec_id", "type", "noun", "item")


@query("select rec_id, cast('blue' as varchar) as value from catalog_dirty where starts_with(item, 'blue') and type is distinct from 'blue'", "catalog")
def r_expand_keys(spark, sf):
    pool = expand_keys(Repair((prefix("item", "blue"),), "type", "blue"), catalog(spark, sf))
    return pool.select(F.col("pred")[0]["lo"].cast("long").alias("rec_id"), "value")


@query("select cast(null as varchar) as value, 'price' as attr, 'le' as op, cast(count(*) as bigint) as n from catalog_dirty where price <= 912.5", "catalog")
def r_generalize(spark, sf):
    df = catalog(spark, sf)
    pool = expand_keys(Repair((cmp("price", "le", 912.5),), "price", None), df)
    return generalize(pool, df, ["price", "brand"]).filter("op = 'le'").select("value", "attr", "op", "n")


CONFLICT_PAIRS = [
    (Repair((eq("a", 1.0),), "b", "old rod"), Repair((eq("a", 2.0),), "b", "new rod"), True),
    (Repair((eq("a", 1.0),), "a", 2.0), Repair((eq("a", 2.0),), "b", "new rod"), False),
    (Repair((cmp("a", "lt", 3.0),), "b", "old rod"), Repair((cmp("a", "ge", 3.0),), "b", "new rod"), True),
    (Repair((cmp("a", "le", 3.0),), "b", "old rod"), Repair((cmp("a", "ge", 3.0),), "b", "new rod"), False),
    (Repair((prefix("b", "old"),), "a", 1.0), Repair((eq("b", "old ring"),), "a", 2.0), False),
    (Repair((prefix("b", "old"),), "a", 1.0), Repair((eq("b", "new ring"),), "a", 2.0), True),
    (Repair((is_null("b"),), "a", 1.0), Repair((eq("b", "hot bolt"),), "a", 2.0), True),
]
PAIRED = "select cast(rec_id % 5 as double) as a, item as b, price as c from catalog_dirty"


def _step_sql(source: str, r: Repair, mark: str = "") -> str:
    """One repair over the columns a, b, c, or with a mark over their copies."""
    text = lambda v: f"'{v}'" if isinstance(v, str) else str(v)
    sign = {"eq": "=", "lt": "<", "le": "<=", "gt": ">", "ge": ">="}
    test = {"prefix": "starts_with({0}, {1})", "is_null": "{0} is null"}
    conds = [test.get(c.op, f"{{0}} {sign.get(c.op)} {{1}}").format(c.attr + mark, text(c.lo)) for c in r.pred]
    case = f"case when {' and '.join(conds)} then {text(r.value)} else {r.target}{mark} end"
    return f"(select " + ", ".join(f"{case} as {x}" if x == r.target + mark else x for x in ("a", "b", "c", "a_", "b_", "c_")) + f" from {source}) s"


def _orders_sql(pairs: list) -> str:
    parts = []
    for i, (x, y, ok) in enumerate(pairs):
        steps = f"(select a, b, c, a as a_, b as b_, c as c_ from ({PAIRED}) p) s"
        for r, mark in ((x, ""), (y, ""), (y, "_"), (x, "_")):
            steps = _step_sql(steps, r, mark)
        differ = " or ".join(f"{k} is distinct from {k}_" for k in "abc")
        parts.append(f"select {i} as pair, {str(ok).lower()} as commutes, cast(count(*) filter ({differ}) as bigint) as differ from {steps}")
    return " union all ".join(parts)


def _orders(df: DataFrame, pairs: list, extended: bool = False) -> DataFrame:
    """Each pair of repairs: whether it is held to commute, and how many records of a, b, c
    its two orders leave different, which is none for those that commute."""
    copy = lambda r: replace(r, pred=tuple(replace(c, attr=f"{c.attr}_") for c in r.pred), target=f"{r.target}_")
    twice = df.select("a", "b", "c", *[F.col(k).alias(f"{k}_") for k in "abc"])
    differ = F.count_if(~(F.col("a").eqNullSafe(F.col("a_")) & F.col("b").eqNullSafe(F.col("b_")) & F.col("c").eqNullSafe(F.col("c_"))))
    parts = [apply_plan(twice, Plan([x, y, copy(y), copy(x)])).agg(differ.alias("differ")).select(F.lit(i).alias("pair"), F.lit(commute(x, y, extended)).alias("commutes"), "differ") for i, (x, y, _) in enumerate(pairs)]
    return reduce(DataFrame.unionByName, parts)


def _paired(spark, sf) -> DataFrame:
    return catalog(spark, sf).select((F.col("rec_id") % 5).cast("double").alias("a"), F.col("item").alias("b"), F.col("price").alias("c"))


@query(_orders_sql(CONFLICT_PAIRS), "catalog")
def r_conflicts(spark, sf):
    return _orders(_paired(spark, sf), CONFLICT_PAIRS)


@query("select cast(count(distinct item) + 3 as bigint) as repairs, 4 as layers from catalog_clean", "catalog")
def r_layer_count(spark, sf):
    """A repair for each name of the catalog, and three that meet them."""
    names = catalog(spark, sf, "clean").select("item").distinct().dropna().orderBy("item")  # made of few words
    plan = _many_repairs([r["item"] for r in names.collect()])
    return spark.createDataFrame([(len(plan.repairs), len(compile_layers(plan)))], "repairs long, layers int")


# Operators.

SPELL = """near as (select d.item as v, w.word, levenshtein(d.item, w.word) as dist, coalesce(f.cnt, 0) as freq from (select distinct item from catalog_dirty where item is not null and item not in ({lex})) d
 join ({lex}) w on levenshtein(d.item, w.word) <= {rec} left join (select item, count(*) as cnt from catalog_dirty group by 1) f on f.item = w.word)"""


@query("with " + SPELL.format(lex=ITEMS, rec=2) + " select v, word from (select *, row_number() over (partition by v order by dist, freq desc, word) as rn from near) t where rn = 1", "catalog")
def o_spell(spark, sf):
    return SpellReplace(items(spark, sf), attr="item", rec=2).replacements(catalog(spark, sf))


EDIT = """vals as (select {a} as v, count(*) as cnt from {t} where {a} is not null group by 1),
 near as (select x.v, y.v as word, y.cnt from vals x join vals y on abs(length(x.v) - length(y.v)) <= {d} and levenshtein(x.v, y.v) <= {d})
 select v, word from (select *, row_number() over (partition by v order by cnt desc, word) as rn from near) t where rn = 1 and v <> word"""


@query("with " + EDIT.format(a="noun", t="catalog_dirty", d=2), "catalog")
def o_edit_match(spark, sf):
    return EditMatch(attr="noun", thresh=2).replacements(catalog(spark, sf))


@query(
    """with vals as (select distinct item as v from catalog_dirty where item is not null),
    grams as (select distinct v, substr(v, i::int, 3) as g from vals, range(1, 40) r(i) where i <= greatest(length(v) - 2, 1)),
    hashed as (select v, g, ('0x' || substr(md5(g), 1, 7))::bigint as h from grams),
    sig as (select v, k, min(((k * 1000003 + 17)::hugeint * h + (k * 998244353 + 11) % 2147483647) % 2147483647) as m from hashed, range(64) r(k) group by 1, 2),
    band as (select v, k // 4 as b, string_agg(m::varchar, '-' order by k) as s from sig group by 1, 2),
    cand as (select distinct x.v as a, y.v as b from band x join band y on x.b = y.b and x.s = y.s and x.v < y.v),
    n as (select v, count(*) as n from grams group by 1),
    common as (select c.a, c.b, count(*) as k from cand c join grams g on g.v = c.a join grams h on h.v = c.b and h.g = g.g group by 1, 2)
    select c.a, c.b, round(k::double / (x.n + y.n - k), 6) as jaccard from common c join n x on x.v = c.a join n y on y.v = c.b where k::double / (x.n + y.n - k) >= 0.6""",
    "catalog",
)
def o_minhash_pairs(spark, sf):
    return MinHashReplace(attr="item", thresh=0.6).pairs(catalog(spark, sf)).select("a", "b", F.round("jaccard", 6).alias("jaccard"))


_MINHASH_PAIRS = ORACLES["o_minhash_pairs"]


@query(
    "with recursive jp as (" + _MINHASH_PAIRS + "), both_ as (select a, b from jp union all select b, a from jp), reach as (select a, a as b from both_ union select r.a, e.b from reach r join both_ e on r.b = e.a),"
    + " cnts as (" + ctes("catalog") + " select item as v, count(*) as cnt from catalog_dirty where item is not null group by 1),"
    + " heads as (select a as v, b as word, row_number() over (partition by a order by c.cnt desc, b) as rn from reach join cnts c on c.v = reach.b) select v, word from heads where rn = 1 and v <> word"
)
def o_minhash_replace(spark, sf):
    return MinHashReplace(attr="item", thresh=0.6).replacements(catalog(spark, sf))


CHASE = """select {x} as x, y, best from (select d.{x}, d.{y} as y, b.best from (select {x}, {y}, count(*) as n from {t} where {x} is not null group by 1, 2) d
 join (select {x}, {y} as best from (select *, row_number() over (partition by {x} order by n desc, {y}) as rn from (select {x}, {y}, count(*) as n from {t} where {x} is not null and {y} is not null group by 1, 2) u) v where rn = 1) b
 on d.{x} = b.{x} where d.{y} is null or d.{y} <> b.best) w"""
ITEM_NOUN = FD.parse("item -> noun")


def _chase_rows(pool: DataFrame, x: str) -> DataFrame:
    pick = lambda attr: F.filter("pred", lambda c: c["attr"] == attr)[0]["lo"]
    return pool.select(pick(x).alias("x"), F.filter("pred", lambda c: c["attr"] != x)[0]["lo"].alias("y"), F.col("value").alias("best"))


@query(CHASE.format(x="item", y="noun", t="catalog_dirty"), "catalog")
def o_chase_one(spark, sf):
    return _chase_rows(FDChase([ITEM_NOUN]).repairs(catalog(spark, sf)), "item")


@query(CHASE.format(x="item", y="noun", t="(select * from catalog_dirty where brand <> 'Brand#1')"), "catalog")
def o_chase_conditional(spark, sf):
    return _chase_rows(FDChase([FD.parse("item -> noun", "brand <> 'Brand#1'")]).repairs(catalog(spark, sf)), "item")


@query(
    """select d.rec_id, d.item, case when d.item is null then d.noun else b.best end as noun from catalog_dirty d left join
    (select item, noun as best from (select *, row_number() over (partition by item order by n desc, noun) as rn from (select item, noun, count(*) as n from catalog_dirty where item is not null and noun is not null group by 1, 2) u) v where rn = 1) b on d.item = b.item
    where b.best is not null or d.noun is null or d.item is null""",
    "catalog",
)
def o_chase_set(spark, sf):
    chased = FDChase([ITEM_NOUN]).chase(catalog(spark, sf).select("rec_id", "item", "noun"))
    return chased


STAT_SQL = """with rows_ as (select * from catalog_dirty where item is not null),
 seen as (select item, noun as c, count(*) as n from rows_ where noun is not null group by 1, 2),
 grp as (select item, count(*) as m, count(distinct noun) as k, count(*) filter (noun is null) as z from rows_ group by 1 having count(distinct noun) >= 1 and (count(distinct noun) > 1 or count(*) filter (noun is null) > 0)),
 tot as (select noun as c, count(*) as t from rows_ where noun is not null group by 1),
 pair as (select noun as c, type as e, count(*) as p from rows_ where noun is not null and type is not null group by 1, 2), dd as (select count(distinct type) as d from rows_),
 sc as (select r.rec_id, r.noun as old, s.c, ln((s.n + 1.0) / (g.m + 1.0 * g.k)) + case when r.type is null then 0 else ln((coalesce(p.p, 0) + 1.0) / (t.t + 1.0 * dd.d)) end as s
  from rows_ r join grp g on r.item = g.item join seen s on s.item = r.item join tot t on t.c = s.c left join pair p on p.c = s.c and p.e = r.type cross join dd),
 best as (select rec_id, old, c as new, 1 / (select sum(exp(b.s - a.s)) from sc b where b.rec_id = a.rec_id) as conf, row_number() over (partition by rec_id order by round(s, 9) desc, c desc) as rn from sc a)
 select rec_id, old, new, round(conf, 6) as confidence from best where rn = 1"""


@query(STAT_SQL, "catalog")
def o_stat_fd(spark, sf):
    tool = StatisticalFD([ITEM_NOUN], ["type"], threshold=0.5)
    got = tool.decisions(catalog(spark, sf), ITEM_NOUN, "noun")
    return got.select("rec_id", "old", "new", F.round("confidence", 6).alias("confidence"))


def series(spark: SparkSession, sf: str) -> DataFrame:
    return build(spark, sf, "series", "series_dirty")


def detector(kind, **params):
    return kind("station", ["ts", "rec_id"], attr="reading", **params)


GAUSS_SQL = """flags as (select rec_id, station, ts, reading, truth, coalesce(count(reading) over w >= 3 and abs(reading - avg(reading) over w) > {k} * stddev_samp(reading) over w, false) as flagged
 from series_dirty window w as (partition by station order by ts, rec_id rows between 20 preceding and 1 preceding))"""


@query("with " + GAUSS_SQL.format(k=3) + " select rec_id, flagged from flags where flagged", "series")
def o_gauss(spark, sf):
    return detector(GaussOutlier, k=3, window_size=20).flag(series(spark, sf)).filter("flagged").select("rec_id", "flagged")


HIST_SQL = """nn as (select *, (row_number() over (partition by station order by ts, rec_id) - 1) // 50 as w from series_dirty),
 bb as (select *, min(reading) over (partition by station, w) as lo, max(reading) over (partition by station, w) as hi, count(reading) over (partition by station, w) as n from nn),
 bins as (select *, case when hi > lo then least(floor((reading - lo) / (hi - lo) * 20), 19) else 0 end as b from bb),
 flags as (select rec_id, count(reading) over (partition by station, w, b)::double / n as share from bins)"""


@query("with " + HIST_SQL + " select rec_id, true as flagged from flags where share < 0.04 and share < 0.1", "series")
def o_hist(spark, sf):
    return detector(HistOutlier, outlier_threshold=0.04, peak_threshold=0.1, window_size=50, tumbling=True).flag(series(spark, sf)).filter("flagged").select("rec_id", "flagged")


SLIDING_SQL = """ws as (select rec_id, reading, list(reading) over (partition by station order by ts, rec_id rows between 49 preceding and current row) as seen from series_dirty),
 bw as (select rec_id, reading, seen, list_min(seen) as lo, list_max(seen) - list_min(seen) as wide from ws),
 flags as (select rec_id, case when wide > 0 then len(list_filter(seen, lambda x: least(floor((x - lo) / wide * 20), 19) = least(floor((reading - lo) / wide * 20), 19))) else len(seen) end::double / len(seen) as share from bw)"""


@query("with " + SLIDING_SQL + " select rec_id, true as flagged from flags where share < 0.04 and share < 0.1", "series")
def o_hist_sliding(spark, sf):
    """Each reading against the histogram of the fifty up to it."""
    return detector(HistOutlier, outlier_threshold=0.04, peak_threshold=0.1, window_size=50).flag(series(spark, sf)).filter("flagged").select("rec_id", "flagged")


@query("with " + GAUSS_SQL.format(k=3) + " select rec_id, flagged from flags where flagged", "series")
def o_gauss_bucketed(spark, sf):
    """The same flags where a series is cut into days with a halo of the window."""
    return detector(GaussOutlier, k=3, window_size=20, bucket=F.date_trunc("day", "ts")).flag(series(spark, sf)).filter("flagged").select("rec_id", "flagged")


PCA_SQL = """lg as (select rec_id, reading as x, lag(reading) over (partition by station order by ts, rec_id) as y from series_dirty),
 st as (select avg(x) as mx, avg(y) as my, covar_pop(x, x) as a, covar_pop(x, y) as b, covar_pop(y, y) as c from lg where x is not null and y is not null)"""


@query("with " + PCA_SQL + " select rec_id, true as flagged from lg, st where y is not null and (c * (x - mx) * (x - mx) - 2 * b * (x - mx) * (y - my) + a * (y - my) * (y - my)) / (a * c - b * b) > 20", "series")
def o_pca_pair(spark, sf):
    """Vectors of two readings, for which the components have a closed form."""
    return detector(PCAOutlier, outlier_threshold=20.0, window_size=2).flag(series(spark, sf)).filter("flagged").select("rec_id", "flagged")


@query()
def o_pca(spark, sf):
    return detector(PCAOutlier, outlier_threshold=30.0, window_size=4).flag(series(spark, sf)).filter("flagged").select("rec_id", "flagged")


LAST_SQL = "with " + GAUSS_SQL.format(k=3) + """, f as (select *, case when not flagged then reading end as ok from flags)
 select rec_id, round(coalesce(last_value(ok ignore nulls) over (partition by station order by ts, rec_id rows between unbounded preceding and current row),
 first_value(ok ignore nulls) over (partition by station order by ts, rec_id rows between current row and unbounded following)), 6) as good from f"""


@query(LAST_SQL, "series")
def o_last_good(spark, sf):
    flagged = detector(GaussOutlier, k=3, window_size=20).flag(series(spark, sf))
    return last_good(flagged, "flagged", "reading", "station", ["ts", "rec_id"]).select("rec_id", F.round("good", 6).alias("good"))


@query(LAST_SQL, "series")
def o_last_good_bucketed(spark, sf):
    flagged = detector(GaussOutlier, k=3, window_size=20).flag(series(spark, sf))
    return last_good_bucketed(flagged, "flagged", "reading", "station", ["ts", "rec_id"], F.date_trunc("day", "ts")).select("rec_id", F.round("good", 6).alias("good"))


@query("select rec_id, case when price < 910.0 or price > 985.0 then null else price end as price from catalog_dirty", "catalog")
def o_nullify(spark, sf):
    df = catalog(spark, sf)
    return apply_pool(df, RangeNullify(attr="price", lo=910.0, hi=985.0).repairs(df)).select("rec_id", "price")


def split_dirty(spark, sf):
    return build(spark, sf, "split", "split_dirty")


@query("select distinct str1 as v, split_part(str1, ':', 1) as first, split_part(str1, ':', 2) as second from split_dirty where length(str1) - length(replace(str1, ':', '')) = 1", "split")
def o_split(spark, sf):
    pool = SplitFields(attr="str1", other="str2", sep=":").repairs(split_dirty(spark, sf))
    v = F.col("pred")[0]["lo"].alias("v")
    return pool.groupBy(v).agg(F.max(F.when(F.col("target") == "str1", F.col("value"))).alias("first"), F.max(F.when(F.col("target") == "str2", F.col("value"))).alias("second"))


@query("select rec_id, coalesce(type, (select type from catalog_dirty where type is not null group by 1 order by count(*) desc, 1 limit 1)) as type from catalog_dirty", "catalog")
def o_fill(spark, sf):
    df = catalog(spark, sf)
    return apply_pool(df, FillMissing(attr="type").repairs(df)).select("rec_id", "type")


@query(
    """select d.rec_id, coalesce(d.noun, b.noun) as noun from catalog_dirty d left join (select item, noun, row_number() over (partition by item order by count(*) desc, noun) as rn
    from catalog_dirty where item is not null and noun is not null group by 1, 2) b on d.item = b.item and b.rn = 1""",
    "catalog",
)
def o_fill_by_group(spark, sf):
    df = catalog(spark, sf)
    return apply_pool(df, FillMissing(attr="noun", by="item").repairs(df)).select("rec_id", "noun")


@query("select rec_id, upper(type) as new from catalog_dirty where type <> upper(type)", "catalog")
def o_wrapped(spark, sf):
    from .operators.base import from_table

    tool = from_table(lambda d: d.withColumn("type", F.upper("type")))
    pool = tool.repairs(catalog(spark, sf).select("rec_id", "type"))
    return pool.select(F.col("pred")[0]["lo"].cast("long").alias("rec_id"), F.col("value").alias("new"))


@query(
    "with " + SPELL.format(lex=ITEMS, rec=1) + """, sp as (select v, word from (select *, row_number() over (partition by v order by dist, freq desc, word) as rn from near) t where rn = 1),
    vals as (select item as v, count(*) as cnt from catalog_dirty where item is not null group by 1),
    ed as (select v, word from (select x.v, y.v as word, row_number() over (partition by x.v order by y.cnt desc, y.v) as rn from vals x join vals y on abs(length(x.v) - length(y.v)) <= 1 and levenshtein(x.v, y.v) <= 1) t where rn = 1 and v <> word)
    select rec_id, 'item' as target, sp.word as new, cast(2 as bigint) as votes from catalog_dirty d join sp on d.item = sp.v join ed on d.item = ed.v and ed.word = sp.word""",
    "catalog",
)
def r_consensus(spark, sf):
    df = catalog(spark, sf)
    pool = SpellReplace(items(spark, sf), attr="item", rec=1).repairs(df).unionByName(EditMatch(attr="item", thresh=1).repairs(df))
    return consensus(pool, df)


# Workloads: the dirty relations and the tools on them.


@query("select rec_id, word, truth from words_dirty", "words")
def w1_words_dirty(spark, sf):
    return build(spark, sf, "words", "words_dirty").select("rec_id", "word", "truth")


def _words(spark, sf):
    return build(spark, sf, "words", "words_dirty").select("rec_id", "word", "truth"), build(spark, sf, "words", "dictionary").select("word")


W1_SPELL = """near as (select d.word as v, w.word, levenshtein(d.word, w.word) as dist, coalesce(f.cnt, 0) as freq from (select distinct word from words_dirty where word not in (select word from dictionary)) d
 join dictionary w on levenshtein(d.word, w.word) <= {rec} left join (select word, count(*) as cnt from words_dirty group by 1) f on f.word = w.word),
 sp as (select v, word from (select *, row_number() over (partition by v order by dist, freq desc, word) as rn from near) t where rn = 1)"""


@query("with " + W1_SPELL.format(rec=2) + " select v, word from sp", "words")
def w1_spell_repairs(spark, sf):
    dirty, lexicon = _words(spark, sf)
    return SpellReplace(lexicon, attr="word", rec=2).replacements(dirty)


@query("with " + EDIT.format(a="word", t="words_dirty", d=1), "words")
def w1_edit_repairs(spark, sf):
    return EditMatch(attr="word", thresh=1).replacements(_words(spark, sf)[0])


F1_SQL = """select {i} as rec, count(*) filter (c <> d) as changed, count(*) filter (c <> d and c = t) as correct, count(*) filter (d <> t) as erroneous
 from (select d.word as d, coalesce(s.word, d.word) as c, d.truth as t from words_dirty d left join sp{i} s on d.word = s.v) x"""


@query(
    "with "
    + ", ".join(W1_SPELL.format(rec=i).replace("near as", f"near{i} as").replace("from near)", f"from near{i})").replace("sp as", f"sp{i} as") for i in (1, 2, 3))
    + ", c as (" + " union all ".join(F1_SQL.format(i=i) for i in (1, 2, 3)) + ") select rec, round(2.0 * correct / (changed + erroneous), 6) as f1 from c",
    "words",
)
def w1_f1_by_threshold(spark, sf):
    dirty, lexicon = _words(spark, sf)
    out = None
    for rec in (1, 2, 3):
        cleaned = apply_pool(dirty, SpellReplace(lexicon, attr="word", rec=rec).repairs(dirty))
        truth = dirty.select("rec_id", F.col("truth").alias("word"))
        part = measures.cell_f1(dirty, cleaned, truth, ["word"]).select(F.lit(rec).alias("rec"), F.round("f1", 6).alias("f1"))
        out = part if out is None else out.unionByName(part)
    return out


@query("select * from catalog_dirty", "catalog")
def w2_dirty(spark, sf):
    return catalog(spark, sf)


@query("select item, cast(count(*) as bigint) as n from catalog_dirty where item is not null group by 1 having count(*) = 1", "catalog")
def w2_singletons(spark, sf):
    return catalog(spark, sf).filter("item is not null").groupBy("item").agg(F.count("*").alias("n")).filter("n = 1")


@query("select rec_id, station, round(reading, 6) as reading, round(truth, 6) as truth from series_dirty", "series")
def w3_dirty(spark, sf):
    return series(spark, sf).select("rec_id", "station", F.round("reading", 6).alias("reading"), F.round("truth", 6).alias("truth"))


@query("select rec_id, " + ", ".join(WIDE_ATTRS) + " from wide_dirty", "wide")
def w4_dirty(spark, sf):
    return build(spark, sf, "wide", "wide_dirty").select("rec_id", *WIDE_ATTRS)


_FD_ONE = """select '{fd}' as fd, cast(coalesce(sum(t * t - s), 0) as double) as pairs from (select sum(n) as t, sum(n * n) as s from
 (select {x}, {y}, count(*) as n from wide_dirty where {x} is not null and {y} is not null group by 1, 2) a group by {x}) b"""


@query(" union all ".join(_FD_ONE.format(fd=f, x=f.split(" -> ")[0], y=f.split(" -> ")[1]) for f in WIDE_FDS), "wide")
def w4_fd_violations(spark, sf):
    from .quality.quality import with_block
    from .quality.terms import FDViolations

    df = with_block(written(build(spark, sf, "wide", "wide_dirty"), "wide"))  # one join for all dependencies
    out = None
    for f in WIDE_FDS:
        part = FDViolations(FD.parse(f)).cost(df).select(F.lit(f).alias("fd"), F.col("cost").alias("pairs"))
        out = part if out is None else out.unionByName(part)
    return out


@query(" union all ".join(f"select '{f}' as fd, cast(x as varchar) as x, y, best from (" + CHASE.format(x=f.split(" -> ")[0], y=f.split(" -> ")[1], t="wide_dirty") + ") q" for f in WIDE_FDS), "wide")
def w4_chase_all(spark, sf):
    df = written(build(spark, sf, "wide", "wide_dirty"), "wide")  # one join for all dependencies
    out = None
    for f in WIDE_FDS:
        part = _chase_rows(FDChase([FD.parse(f)]).repairs(df), FD.parse(f).lhs[0]).select(F.lit(f).alias("fd"), "x", "y", "best")
        out = part if out is None else out.unionByName(part)
    return out


@query("select rec_id, str1, str2, t1, t2 from split_dirty", "split")
def w5_dirty(spark, sf):
    return split_dirty(spark, sf)


@query(
    """with s as (select *, case when length(str1) - length(replace(str1, ':', '')) = 1 then ':' when length(str1) - length(replace(str1, ',', '')) = 1 then ',' when length(str1) - length(replace(str1, '-', '')) = 1 then '-' end as sep from split_dirty)
    select rec_id, case when sep is null then str1 else split_part(str1, sep, 1) end as str1, case when sep is null then str2 else split_part(str1, sep, 2) end as str2 from s""",
    "split",
)
def w5_split_applied(spark, sf):
    # Each step reads its input three times, so inputs are written: the plan would grow with the power of the steps.
    df = split_dirty(spark, sf).select("rec_id", "str1", "str2")
    for sep in (":", ",", "-"):
        df = written(df, "split")
        df = apply_pool(df, SplitFields(attr="str1", other="str2", sep=sep).repairs(df))
    return df


TYPED = """typed as (select rec_id, price > 950 as dear, price * 10000 as big, cast(rec_id % 7 as int) as digit, item from catalog_dirty)"""


def _typed(spark, sf) -> DataFrame:
    return catalog(spark, sf).select("rec_id", (F.col("price") > 950).alias("dear"), (F.col("price") * 10000).alias("big"), (F.col("rec_id") % 7).cast("int").alias("digit"), "item")


TYPED_REPAIRS = [
    Repair((eq("dear", True), cmp("big", "ge", 9.6e6)), "item", "dear one"), Repair((eq("big", 9.01e6),), "item", "nine"), Repair((eq("digit", 3.0),), "item", "three"),
    Repair((between("big", 9.2e6, 9.3e6),), "digit", 9.0), Repair((eq("dear", False), eq("digit", 1)), "dear", True),
]


@query(
    "with " + TYPED + " select rec_id, 'item' as target, 'dear one' as new from typed where dear and big >= 9.6e6 and item is distinct from 'dear one' union all select rec_id, 'item', 'nine' from typed where big = 9.01e6 and item is distinct from 'nine'"
    " union all select rec_id, 'item', 'three' from typed where digit = 3 and item is distinct from 'three' union all select rec_id, 'digit', '9.0' from typed where big between 9.2e6 and 9.3e6 union all select rec_id, 'dear', 'True' from typed where not dear and digit = 1",
    "catalog",
)
def r_typed_bind(spark, sf):
    """Literals of booleans, large doubles and whole numbers bind by value, not by text."""
    df = _typed(spark, sf)
    return bind(pool_of(spark, TYPED_REPAIRS), df, ("rec_id",)).select("rec_id", "target", "new")


@query("with " + TYPED + " select rec_id, case when dear then true else digit = 1 end as dear, big, digit, case when dear then 'yes' else case when big = 9.01e6 then 'nine' else item end end as item from typed".replace("case when dear then true else digit = 1 end", "dear or digit = 1"), "catalog")
def r_typed_layers(spark, sf):
    plan = Plan([Repair((eq("big", 9.01e6),), "item", "nine"), Repair((eq("dear", True),), "item", "yes"), Repair((eq("dear", False), eq("digit", 1.0)), "dear", True)])
    return apply_plan(_typed(spark, sf), plan, mode="layers")


EXTENDED_PAIRS = [
    (Repair((eq("a", 1.0),), "b", "old rod"), Repair((cmp("c", "ge", 950.0),), "b", "old rod"), True),
    (Repair((eq("a", 1.0),), "b", "old rod"), Repair((cmp("c", "ge", 950.0),), "b", "new rod"), False),
    (Repair((eq("a", 1.0),), "b", "old rod"), Repair((eq("a", 1.0),), "c", 2.0), True),
    (Repair((eq("b", "old rod"),), "b", "new rod"), Repair((eq("b", "new rod"),), "b", "old rod"), False),
]


@query(_orders_sql(EXTENDED_PAIRS), "catalog")
def r_extended(spark, sf):
    return _orders(_paired(spark, sf), EXTENDED_PAIRS, extended=True)


@query("select count(*) filter (noun = 'rod' and price > 990.0 and type is distinct from 'dear') = 0 as disjoint from catalog_dirty", "catalog")
def r_disjoint_rows(spark, sf):
    changes = _bound(spark, sf)[1]
    units = {r["target"]: r["unit"] for r in changes.select("unit", "target").distinct().collect()}
    return spark.createDataFrame([("noun" not in units or "type" not in units or disjoint_rows(changes, units["noun"], units["type"]),)], "disjoint boolean")


@query("select count(*) as rows_ from catalog_dirty where noun = 'rod' or price > 990.0", "catalog")
def r_plan_predicate(spark, sf):
    """Records that any repair of a plan reads as its own."""
    plan = Plan([Repair((eq("noun", "rod"),), "noun", "bar"), Repair((cmp("price", "gt", 990.0),), "type", "dear"), Repair((eq("noun", "rod"),), "type", "rods")])
    either = F.lit(False)
    for p in plan_predicate(plan):
        either = either | F.coalesce(predicate(p), F.lit(False))
    return catalog(spark, sf).filter(either).agg(F.count("*").alias("rows_"))


@query("select 1 as units, count(*) as repairs from (" + CHASE.format(x="item", y="noun", t="catalog_dirty") + ") q", "catalog")
def r_bundle(spark, sf):
    """All repairs of a tool and setting as one unit, those made twice counted once."""
    pool = FDChase([ITEM_NOUN]).repairs(catalog(spark, sf))
    return canonicalize(bundle(pool.unionByName(pool))).agg(F.count_distinct("unit").cast("int").alias("units"), F.count("*").alias("repairs"))


def _bound(spark, sf):
    df = catalog(spark, sf)
    return df, bind(pool_of(spark, [Repair((eq("noun", "rod"),), "noun", "bar"), Repair((cmp("price", "gt", 990.0),), "type", "dear")]), df, ("rec_id",))


@query(
    """select rec_id, 'noun' as target, 'bar' as new from catalog_dirty where noun = 'rod' union all
    select rec_id, 'type' as target, 'dear' as new from catalog_dirty where price > 990.0 and type is distinct from 'dear'""",
    "catalog",
)
def r_bind(spark, sf):
    return _bound(spark, sf)[1].select("rec_id", "target", "new")

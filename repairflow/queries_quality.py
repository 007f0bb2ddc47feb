"""Queries of quality terms, their deltas and the accuracy measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .functions import measures
from .model import FD
from .operators.dependencies import FDChase
from .operators.outliers import GaussOutlier
from .operators.strings import FillMissing, SpellReplace, apply_pool
from .quality.quality import Quality, prepared, with_block
from .quality.terms import EditPenalty, EmptyStrings, FDViolations, GoldCells, GoldF1, MasterMismatch, ModelError, OutlierCount, OutOfDictionary, Singletons, SqlTerm, WindowAR
from .queries_repair import GAUSS_SQL, ITEM_NOUN, ITEMS, SPELL, catalog, detector, items, series, split_dirty
from .search.engine import Session
from .session import written
from .sources.fixtures import WIDE_FDS, ctes
from .sources.tables import load

QUERIES, ORACLES = {}, {}


def query(sql: str | None = None, fixture: str | None = None):
    def add(fn):
        QUERIES[fn.__name__] = fn
        if sql is not None:
            body = sql.strip()
            if fixture and body.lower().startswith("with "):
                body = f"{ctes(fixture)}, {body[5:]}"
            elif fixture:
                body = f"{ctes(fixture)} {body}"
            ORACLES[fn.__name__] = body
        return fn

    return add


def one(df: DataFrame, name: str = "cost") -> DataFrame:
    return df.agg(F.round(F.sum("cost"), 6).alias(name))


XY = "(select item, noun, count(*) as n from catalog_dirty where item is not null and noun is not null group by 1, 2) u"
X = f"(select item, sum(n) as t, sum(n * n) as s, count(*) as k from {XY} group by 1) v"


@query(f"select round(cast(coalesce(sum(t * t - s), 0) as double), 6) as cost from {X}", "catalog")
def q_fd_pairs(spark, sf):
    return one(FDViolations(ITEM_NOUN).cost(with_block(catalog(spark, sf))))


@query("select round(cast(count(*) as double), 6) as cost from catalog_dirty a join catalog_dirty b on a.item = b.item and a.noun <> b.noun", "catalog")
def q_fd_selfjoin(spark, sf):
    return one(FDViolations(ITEM_NOUN).selfjoin_cost(with_block(catalog(spark, sf))))


@query(f"select round(cast(coalesce(sum(t), 0) as double), 6) as cost from {X} where k > 1", "catalog")
def q_fd_tuples(spark, sf):
    return one(FDViolations(ITEM_NOUN, "tuples").cost(with_block(catalog(spark, sf))))


@query(f"select round(cast(count(*) as double), 6) as cost from {X} where k > 1", "catalog")
def q_fd_groups(spark, sf):
    return one(FDViolations(ITEM_NOUN, "groups").cost(with_block(catalog(spark, sf))))


@query(
    "select round(cast(coalesce(sum(t * t - s), 0) as double), 6) as cost from (select item, sum(n) as t, sum(n * n) as s from (select item, noun, count(*) as n from catalog_dirty where item is not null and noun is not null and brand = 'Brand#2' group by 1, 2) u group by 1) v",
    "catalog",
)
def q_fd_conditional(spark, sf):
    df = with_block(catalog(spark, sf))
    term = FDViolations(FD.parse("item -> noun", "brand = 'Brand#2'"))
    term.columns = tuple(df.columns)
    return one(term.cost(df))


@query("select round(cast(count(*) as double), 6) as cost from (select item from catalog_dirty where item is not null group by 1 having count(*) = 1) t", "catalog")
def q_singletons(spark, sf):
    return one(Singletons("item").cost(with_block(catalog(spark, sf))))


@query("select round(avg(case when (d.n_chars > 1500)::int = l.quality then 0.0 else 1.0 end), 6) as cost from labels l join documents d on l.doc_id = d.doc_id")
def q_model_error(spark, sf):
    rows = load(spark, sf, "labels").join(load(spark, sf, "documents").select("doc_id", "n_chars"), "doc_id")
    term = ModelError(lambda n, y: F.when((n > 1500).cast("int") == y, 0.0).otherwise(1.0), ("n_chars",), "quality", rows.count())
    return one(term.cost(with_block(rows)))


@query("select round(avg(abs(d.n_chars / 1000.0 - l.quality)), 4) as cost from labels l join documents d on l.doc_id = d.doc_id")
def q_model_error_udf(spark, sf):
    """A model behind an Arrow function, as users bring them."""

    @F.pandas_udf("double")
    def error(n, y):
        return (n / 1000.0 - y).abs()

    rows = load(spark, sf, "labels").join(load(spark, sf, "documents").select("doc_id", "n_chars"), "doc_id")
    term = ModelError(error, ("n_chars",), "quality", rows.count())
    return term.cost(with_block(rows)).select(F.round("cost", 4).alias("cost"))


AR_PAIRS = """pr as (select station, lag(reading) over (partition by station order by ts, rec_id) as p, reading as c, time_bucket(interval '5 hours', ts, timestamp '1970-01-01') as win from series_dirty),
 sm as (select station, win, count(*) as n, sum(p) as sx, sum(c) as sy, sum(p*p) as sxx, sum(p*c) as sxy, sum(c*c) as syy from pr where p is not null group by 1, 2 having count(*) >= 3),
 ft as (select *, case when abs(n*sxx - sx*sx) > 1e-9 then (n*sxy - sx*sy) / (n*sxx - sx*sx) else 0 end as b from sm), fi as (select *, (sy - b*sx)/n as a from ft)"""


@query(f"with {AR_PAIRS} select round(avg(greatest(syy - a*sy - b*sxy, 0) / n), 3) as cost from fi", "series")
def q_ar_error(spark, sf):
    return WindowAR("reading", "station", "ts").cost(with_block(series(spark, sf))).select(F.round("cost", 3).alias("cost"))


@query(f"with {AR_PAIRS} select round(avg(e), 4) as cost from (select avg(abs(c - b*p - a)) as e from pr join fi using (station, win) where p is not null group by station, win) t", "series")
def q_ar_error_absolute(spark, sf):
    return WindowAR("reading", "station", "ts", error="absolute").cost(with_block(series(spark, sf))).select(F.round("cost", 4).alias("cost"))


@query(
    f"with {AR_PAIRS} select station, count(*) as windows, round(avg(e), 4) as error from (select station, avg(abs(c - b*p - a)) as e from pr join fi using (station, win) where p is not null group by station, win) t group by 1",
    "series",
)
def w3_ar_error(spark, sf):
    err = WindowAR("reading", "station", "ts", error="absolute").errors(with_block(series(spark, sf)))
    return err.groupBy(F.col("series").alias("station")).agg(F.count("*").alias("windows"), F.round(F.avg("err"), 4).alias("error"))


def _filled(spark, sf) -> tuple[DataFrame, DataFrame]:
    df = catalog(spark, sf)
    return df, apply_pool(df, FillMissing(attr="noun", by="item").repairs(df))


FILLED = """filled as (select d.rec_id, d.item, d.type, coalesce(d.noun, b.noun) as noun from catalog_dirty d left join (select item, noun, row_number() over (partition by item order by count(*) desc, noun) as rn
 from catalog_dirty where item is not null and noun is not null group by 1, 2) b on d.item = b.item and b.rn = 1)"""


@query(f"with {FILLED} select round(cast(sum(case when f.noun is not distinct from d.noun then 0 when f.noun is null or d.noun is null then length(coalesce(f.noun, d.noun)) else levenshtein(f.noun, d.noun) end) as double), 6) as cost from filled f join catalog_dirty d using (rec_id)", "catalog")
def q_edit_penalty(spark, sf):
    dirty, clean = _filled(spark, sf)
    rows = clean.join(dirty.select("rec_id", F.col("noun").alias("_base_noun")), "rec_id")
    return one(EditPenalty(("noun",)).cost(with_block(rows)))


@query("select round(cast(sum((d.item is distinct from c.item)::int + (d.noun is distinct from c.noun)::int + (d.type is distinct from c.type)::int) as double), 6) as cost from catalog_dirty d join catalog_clean c using (rec_id)", "catalog")
def q_gold_cells(spark, sf):
    rows = prepared(catalog(spark, sf), ["item", "noun", "type"], catalog(spark, sf, "clean"))
    return one(GoldCells(("item", "noun", "type")).cost(rows))


@query(f"select round(cast(count(*) as double), 6) as cost from catalog_dirty where item is not null and item not in ({ITEMS})", "catalog")
def q_out_of_dict(spark, sf):
    return one(OutOfDictionary("item", items(spark, sf)).cost(with_block(catalog(spark, sf))))


@query("select round(cast(count(*) as double), 6) as cost from catalog_dirty where brand not in (select p_brand from part where p_size > 25)", "catalog")
def q_master_mismatch(spark, sf):
    master = load(spark, sf, "part").filter("p_size > 25")
    return one(MasterMismatch("brand", master, "p_brand").cost(with_block(catalog(spark, sf))))


@query("select round(cast(count(*) as double), 6) as cost from split_dirty where str2 = ''", "split")
def q_empty(spark, sf):
    return one(EmptyStrings("str2").cost(with_block(split_dirty(spark, sf))))


@query("with " + GAUSS_SQL.format(k=3) + " select round(cast(count(*) as double), 6) as cost from flags where flagged", "series")
def q_outliers(spark, sf):
    return one(OutlierCount(detector(GaussOutlier, k=3, window_size=20)).cost(with_block(series(spark, sf))))


@query("select round(max(price) - min(price), 6) as cost from catalog_dirty", "catalog")
def q_sql_term(spark, sf):
    return one(SqlTerm("select max(price) - min(price) as spread from T").cost(with_block(catalog(spark, sf))))


WEIGHTED = f"""select round((select cast(coalesce(sum(t * t - s), 0) as double) from {X}) / 3 + (select count(*) from (select item from catalog_dirty where item is not null group by 1 having count(*) = 1) t) / 3.0
 + (select count(*) from catalog_dirty where item is not null and item not in ({ITEMS})) / 3.0, 6) as cost"""


@query(WEIGHTED, "catalog")
def q_weighted(spark, sf):
    q = Quality([FDViolations(ITEM_NOUN), Singletons("item"), OutOfDictionary("item", items(spark, sf))])
    return one(q.costs(catalog(spark, sf)))


def _scored(spark, sf, pool: DataFrame, quality: Quality) -> tuple[Session, DataFrame]:
    """Root scores of a pool: (block, plan, unit, delta)."""
    s = Session(catalog(spark, sf), quality)
    s.add(pool)
    plans = s.rows.select("block").distinct().withColumn("plan", F.lit(0).cast("long"))
    return s, quality.deltas(*_root(s, plans, quality))


def _root(s: Session, plans: DataFrame, quality: Quality) -> tuple[DataFrame, list]:
    """Images and states, written once as every term reads them several times."""
    return written(s.images(s.hits(plans, None)), "images"), [None if x is None else written(x, "state") for x in quality.states(s.rows)]


def _chase_scores(spark, sf, quality: Quality) -> DataFrame:
    s, got = _scored(spark, sf, FDChase([ITEM_NOUN]).repairs(catalog(spark, sf)), quality)
    pick = lambda a: F.filter("pred", lambda c: c["attr"] == a)[0]["lo"]
    named = s.pool.select("unit", pick("item").alias("x"), pick("noun").alias("y"), F.col("value").alias("best"))
    return got.join(named, "unit").select("x", "y", "best", F.round("delta", 6).alias("delta"))


CHASED = """cnt as (select item, noun, count(*) as n from catalog_dirty where item is not null group by 1, 2), best as (select item, noun as b, n as nb from (select *, row_number() over (partition by item order by n desc, noun) as rn from cnt where noun is not null) u where rn = 1),
 tot as (select item, sum(n) as t from cnt where noun is not null group by 1)"""


@query(f"with {CHASED} select c.item as x, c.noun as y, b.b as best, round(cast(case when c.noun is null then 2 * t.t * c.n - 2 * b.nb * c.n else -2 * c.n * b.nb end as double), 6) as delta from cnt c join best b using (item) join tot t using (item) where c.noun is null or c.noun <> b.b", "catalog")
def q_delta_fd(spark, sf):
    return _chase_scores(spark, sf, Quality([FDViolations(ITEM_NOUN)]))


@query(f"with {CHASED} select c.item as x, c.noun as y, b.b as best, round(cast(case when c.noun is null then c.n * (t.t - b.nb) else c.n * (t.t - b.nb) - c.n * (t.t - c.n) end as double), 6) as delta from cnt c join best b using (item) join tot t using (item) where c.noun is null or c.noun <> b.b", "catalog")
def q_delta_first_order(spark, sf):
    """The two-join approximation beside the exact delta above."""
    df = catalog(spark, sf)
    term = FDViolations(ITEM_NOUN)
    s = Session(df, Quality([term]))
    s.add(FDChase([ITEM_NOUN]).repairs(df))
    plans = s.rows.select("block").distinct().withColumn("plan", F.lit(0).cast("long"))
    got = term.first_order_delta(s.images(s.hits(plans, None)), s.rows)
    pick = lambda a: F.filter("pred", lambda c: c["attr"] == a)[0]["lo"]
    named = s.pool.select("unit", pick("item").alias("x"), pick("noun").alias("y"), F.col("value").alias("best"))
    return named.join(got, "unit").select("x", "y", "best", F.round("delta", 6).alias("delta"))


SP2 = SPELL.format(lex=ITEMS, rec=2) + """, sp as (select v, word from (select *, row_number() over (partition by v order by dist, freq desc, word) as rn from near) t where rn = 1),
 vc as (select item, count(*) as n from catalog_dirty where item is not null group by 1)"""


def _spell_scores(spark, sf, quality: Quality) -> DataFrame:
    pool = SpellReplace(items(spark, sf), attr="item", rec=2).repairs(catalog(spark, sf))
    s, got = _scored(spark, sf, pool, quality)
    named = s.pool.select("unit", F.col("pred")[0]["lo"].alias("v"), F.col("value").alias("word"))
    return got.join(named, "unit").select("v", "word", F.round("delta", 6).alias("delta"))


SINGLE = "(case when coalesce(w.n, 0) + c.n = 1 then 1 else 0 end) - (case when w.n = 1 then 1 else 0 end) - (case when c.n = 1 then 1 else 0 end)"


@query(f"with {SP2} select v, word, round(cast({SINGLE} as double), 6) as delta from sp join vc c on c.item = v left join vc w on w.item = word", "catalog")
def q_delta_singletons(spark, sf):
    return _spell_scores(spark, sf, Quality([Singletons("item")]))


@query(f"with {SP2} select v, word, round(cast(({SINGLE} - c.n) / 2.0 as double), 6) as delta from sp join vc c on c.item = v left join vc w on w.item = word", "catalog")
def q_delta_all_candidates(spark, sf):
    return _spell_scores(spark, sf, Quality([Singletons("item"), OutOfDictionary("item", items(spark, sf))]))


PAIRS_OF = "coalesce((select sum(n) * sum(n) - sum(n * n) from (select noun, sum(n) as n from cnt where noun is not null and item in ({xs}) group by 1) q), 0)"


@query(
    f"""with {SP2}, cnt as (select item, noun, count(*) as n from catalog_dirty where item is not null group by 1, 2)
    select v, word, round(cast(({PAIRS_OF.format(xs='v, word')} - {PAIRS_OF.format(xs='v')} - {PAIRS_OF.format(xs='word')}) / 2.0 + ({SINGLE}) / 2.0 as double), 6) as delta
    from sp join vc c on c.item = v left join vc w on w.item = word""",
    "catalog",
)
def s_round1_scores(spark, sf):
    """All candidates of the first round, scored in one job: repairs of a left-hand side."""
    return _spell_scores(spark, sf, Quality([FDViolations(ITEM_NOUN), Singletons("item")]))


WINDOWED = """fl as (select rec_id, station, ts, reading, coalesce(count(reading) over w >= 3 and abs(reading - avg(reading) over w) > 6 * stddev_samp(reading) over w, false) as off
 from series_dirty window w as (partition by station order by ts, rec_id rows between 50 preceding and 1 preceding)),
 ok as (select *, case when not off then reading end as g from fl),
 fix as (select rec_id as unit, station, v from (select rec_id, station, off, coalesce(last_value(g ignore nulls) over (partition by station order by ts, rec_id rows between unbounded preceding and current row),
 first_value(g ignore nulls) over (partition by station order by ts, rec_id rows between current row and unbounded following)) as v from ok) q where off and v is not null),
 pr as (select station, rec_id as id, lag(rec_id) over o as before, lag(reading) over o as p, reading as c, time_bucket(interval '5 hours', ts, timestamp '1970-01-01') as win from series_dirty window o as (partition by station order by ts, rec_id)),
 tw as (select distinct unit, v, x.station, win from fix join pr x on x.id = unit or x.before = unit),
 bp as (select unit, t.station, t.win, p, c, case when before = unit then v else p end as p2, case when id = unit then v else c end as c2 from tw t join pr on pr.station = t.station and pr.win = t.win where p is not null),
 alls as (select 'all' as k, -1 as unit, station, win, p, c from pr where p is not null union all select 'old', unit, station, win, p, c from bp union all select 'new', unit, station, win, p2, c2 from bp),
 sm as (select k, unit, station, win, count(*) as n, sum(p) as sx, sum(c) as sy, sum(p*p) as sxx, sum(p*c) as sxy, sum(c*c) as syy from alls group by all having count(*) >= 3),
 ft as (select *, case when abs(n*sxx - sx*sx) > 1e-9 then (n*sxy - sx*sy) / (n*sxx - sx*sx) else 0 end as b from sm),
 er as (select k, unit, greatest(syy - (sy - b*sx)/n*sy - b*sxy, 0) / n as e from ft),
 tot as (select count(*) as w, sum(e) as s from er where k = 'all'),
 mv as (select unit, sum(case when k = 'new' then e else -e end) as d from er where k <> 'all' group by 1)"""


@query(f"with {WINDOWED} select unit as rec_id, round(d / w, 4) as delta from mv, tot", "series")
def q_delta_window(spark, sf):
    """Change of the windowed error by each outlier's repair; tests hold it to full evaluation."""
    df = series(spark, sf).drop("truth")
    term = WindowAR("reading", "station", "ts")
    q = Quality([term])
    s = Session(df, q)
    s.add(detector(GaussOutlier, k=6, window_size=50).repairs(df))
    plans = s.rows.select("block").distinct().withColumn("plan", F.lit(0).cast("long"))
    got = q.deltas(*_root(s, plans, q))
    return got.join(s.pool.select("unit", F.col("pred")[0]["lo"].cast("long").alias("rec_id")), "unit").select("rec_id", F.round("delta", 4).alias("delta"))


_PAIRS_OF_WIDE = "cast(coalesce((select sum(t * t - s) from (select sum(n) as t, sum(n * n) as s from (select {x}, {y}, count(*) as n from {t} where {x} is not null and {y} is not null{more} group by 1, 2) a group by {x}) b), 0) as double)"


@query(
    "select " + _PAIRS_OF_WIDE.format(x="c_custkey", y="c_name", t="wide_dirty", more="") + " as exact, round("
    + _PAIRS_OF_WIDE.format(x="c_custkey", y="c_name", t="wide_dirty", more=" and ('0x' || substr(md5(cast(c_custkey as varchar)), 1, 8))::bigint % 10000 < 1000") + " / 0.1, 6) as estimate", "wide"
)
def q_sampled(spark, sf):
    """An estimate from a tenth of the left-hand groups beside the exact cost."""
    q = Quality([FDViolations(FD.parse("c_custkey -> c_name"))])
    from .sources.fixtures import build

    df = build(spark, sf, "wide", "wide_dirty")
    return spark.createDataFrame([(q.cost(df), round(q.sampled_cost(df, ["c_custkey"], 0.1), 6))], "exact double, estimate double")


@query(f"with {SP2} select v, word, round(cast((select sum((t.item is distinct from word)::int - (t.item is distinct from d.item)::int) from catalog_dirty d join catalog_clean t using (rec_id) where d.item = v) as double), 6) as delta from sp", "catalog")
def q_delta_gold(spark, sf):
    """Candidates under the truth as the objective: what each repair of a value is worth."""
    df = catalog(spark, sf)
    s = Session(df, Quality([(1.0, GoldCells(("item",)))]), truth=catalog(spark, sf, "clean"))
    s.add(SpellReplace(items(spark, sf), attr="item", rec=2).repairs(df))
    plans = s.rows.select("block").distinct().withColumn("plan", F.lit(0).cast("long"))
    got = s.quality.deltas(*_root(s, plans, s.quality))
    named = s.pool.select("unit", F.col("pred")[0]["lo"].alias("v"), F.col("value").alias("word"))
    return got.join(named, "unit").select("v", "word", F.round("delta", 6).alias("delta"))


MEASURED = f"""{FILLED}, m as (select count(*) filter (f.noun is distinct from d.noun) as changed, count(*) filter (f.noun is distinct from d.noun and f.noun is not distinct from c.noun) as correct,
 count(*) filter (d.noun is distinct from c.noun) as erroneous, count(*) filter (f.noun is not distinct from c.noun) as equal, count(*) as cells from filled f join catalog_dirty d using (rec_id) join catalog_clean c using (rec_id))"""


@query(f"with {MEASURED} select round(correct::double / changed, 6) as precision, round(correct::double / erroneous, 6) as recall, round(2.0 * correct / (changed + erroneous), 6) as f1, round(1 - 2.0 * correct / (changed + erroneous), 6) as error from m", "catalog")
def m_f1(spark, sf):
    dirty, clean = _filled(spark, sf)
    got = measures.cell_f1(dirty, clean, catalog(spark, sf, "clean"), ["noun"])
    return got.select(*[F.round(c, 6).alias(c) for c in ("precision", "recall", "f1", "error")])


@query(f"with {MEASURED} select round(1 - 2.0 * correct / (changed + erroneous), 6) as cost from m", "catalog")
def q_gold_f1(spark, sf):
    """One less F1 as an objective: the cost of the relation with nulls filled."""
    dirty, clean = _filled(spark, sf)
    base = prepared(dirty.select("rec_id", "noun"), ["noun"], catalog(spark, sf, "clean").select("rec_id", "noun"))
    rows = base.drop("noun").join(clean.select("rec_id", "noun"), "rec_id")
    return one(GoldF1(("noun",)).cost(rows))


@query(f"with {MEASURED} select round(equal::double / cells, 6) as accuracy from m", "catalog")
def m_cell_accuracy(spark, sf):
    dirty, clean = _filled(spark, sf)
    return measures.cell_f1(dirty, clean, catalog(spark, sf, "clean"), ["noun"]).select(F.round("accuracy", 6).alias("accuracy"))


@query(
    f"with cleaned as (select t * t - s as p from (select item, sum(n) as t, sum(n * n) as s from (select item, noun, count(*) as n from catalog_clean group by 1, 2) a group by 1) b) select round((coalesce(sum(p), 0) + 1e-9) / ((select sum(t * t - s) from {X}) + 1e-9), 6) as suboptimality from cleaned",
    "catalog",
)
def m_suboptimality(spark, sf):
    q = Quality([FDViolations(ITEM_NOUN)])
    truth, now = q.cost(catalog(spark, sf, "clean")), q.cost(catalog(spark, sf))
    return spark.createDataFrame([(round(measures.suboptimality(truth, now), 6),)], "suboptimality double")


@query(
    """with t as (select event_type, cast(date_diff('hour', timestamp '1970-01-01 00:00:00', ts) as double) * 3600 as elapsed_s, max(value) as cost from events group by 1, 2)
    select elapsed_s, (select min(cost) from t b where b.event_type = 'purchase' and b.elapsed_s <= a.elapsed_s) / (select min(cost) from t c where c.event_type = 'click' and c.elapsed_s <= a.elapsed_s) as ratio
    from t a where event_type = 'click' and exists (select 1 from t b where b.event_type = 'purchase' and b.elapsed_s <= a.elapsed_s)"""
)
def m_quality_ratio(spark, sf):
    """The greatest values of each hour, of two types of events, as traces of costs."""
    hour = F.expr("timestampdiff(HOUR, timestamp_ntz'1970-01-01 00:00:00', ts)").cast("double") * 3600
    hourly = load(spark, sf, "events").groupBy("event_type", hour.alias("elapsed_s")).agg(F.max("value").alias("cost"))
    trace = lambda kind: hourly.filter(F.col("event_type") == kind).select("elapsed_s", "cost")
    return measures.quality_ratio(trace("click"), trace("purchase"))


@query(" union all ".join(f"select '{c}' as term, round(cast(({s}) as double), 6) as cost" for c, s in (
    ("fd", "select coalesce(sum(t * t - s), 0) from (select str1, sum(n) as t, sum(n * n) as s from (select str1, str2, count(*) as n from split_dirty group by 1, 2) a group by 1) b"),
    ("spelling", "select count(*) from split_dirty where str1 not in (select t1 from split_clean)"),
    ("empty", "select count(*) from split_dirty where str2 = ''"))), "split")
def w5_quality_terms(spark, sf):
    from .sources.fixtures import build

    df = with_block(split_dirty(spark, sf))
    lexicon = build(spark, sf, "split", "split_clean").select(F.col("t1").alias("word"))
    terms = {"fd": FDViolations(FD.parse("str1 -> str2")), "spelling": OutOfDictionary("str1", lexicon), "empty": EmptyStrings("str2")}
    out = None
    for name, t in terms.items():
        part = one(t.cost(df)).select(F.lit(name).alias("term"), "cost")
        out = part if out is None else out.unionByName(part)
    return out


@query(
    "select " + ", ".join("round((" + " + ".join(_PAIRS_OF_WIDE.format(x=f.split(" -> ")[0], y=f.split(" -> ")[1], t=t, more="") for f in WIDE_FDS) + f") / {len(WIDE_FDS)}, 6) as {n}" for t, n in (("wide_dirty", "dirty"), ("wide_clean", "truth"))),
    "wide",
)
def w4_quality(spark, sf):
    """Mean of the eight dependency terms on the wide relation, dirty and true."""
    from .sources.fixtures import build

    q = Quality([FDViolations(FD.parse(f)) for f in WIDE_FDS])
    return spark.createDataFrame([tuple(round(q.cost(written(build(spark, sf, "wide", f"wide_{w}"), "wide")), 6) for w in ("dirty", "clean"))], "dirty double, truth double")

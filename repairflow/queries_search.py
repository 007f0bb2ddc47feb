"""Queries of the search, the learnt pruner and the tuning baselines."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .baselines import tuners
from .functions import measures
from .learn.pruner import Pruner, confusion, featurize, label_examples, score_with, threshold_of
from .model import FD
from .operators.base import coarse
from .operators.dependencies import FDChase
from .operators.outliers import GaussOutlier
from .operators.strings import EditMatch, MinHashReplace, RangeNullify, SpellReplace, SplitFields
from .quality.quality import Quality, with_block
from .quality.terms import EmptyStrings, FDViolations, GoldCells, OutOfDictionary, Singletons, WindowAR
from .queries_quality import CHASED, SINGLE, SP2
from .queries_quality import query as _query
from .queries_repair import CHASE, ITEM_NOUN, ITEMS, SPELL, catalog, detector, items, series, split_dirty
from .runtime.generators import SyncGenerators, search_async
from .search.blocks import BlockBy
from .search.engine import Session
from .search.merge import pack_disjoint
from .search.prune import prune_global, prune_local, rebalance, utility
from .search.waves import search_waves
from .session import written
from .sources.fixtures import build, ctes

QUERIES, ORACLES = {}, {}
del _query


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


# Pruning, merging, balancing.


def _priced(spark, sf) -> DataFrame:
    """Candidates with costs: parts, their prices."""
    return catalog(spark, sf).select(F.col("rec_id").alias("unit"), utility(F.col("price")).alias("utility"), F.pmod(F.col("rec_id"), F.lit(4)).alias("worker"))


PRICED = "c as (select rec_id as unit, 1.0 / (1.0 + price) as utility, rec_id % 4 as worker from catalog_dirty)"


@query(f"with {PRICED} select unit, worker from (select *, max(utility) over (partition by worker) as best from c) t where utility >= 0.9 * greatest(best, 0.0009)", "catalog")
def s_gamma_local(spark, sf):
    return prune_local(_priced(spark, sf), 0.9, 0.0009, F.col("worker")).select("unit", "worker")


@query(f"with {PRICED}, l as (select * from (select *, max(utility) over (partition by worker) as best from c) t where utility >= 0.9 * best) select unit, worker from l where utility >= 0.9 * (select max(utility) from l)", "catalog")
def s_gamma_local_global(spark, sf):
    return prune_global(prune_local(_priced(spark, sf), 0.9, worker=F.col("worker")), 0.9).select("unit", "worker")


@query("select cast(count(*) as bigint) as plans from catalog_dirty", "catalog")
def s_rebalance(spark, sf):
    frontier = catalog(spark, sf).select(F.col("rec_id").alias("plan"))
    return rebalance(frontier, 8).agg(F.count("*").alias("plans"))


@query("select min(rec_id) as unit from catalog_dirty where item is not null group by item", "catalog")
def s_merge_disjoint(spark, sf):
    """Packing records that share no item: the first of each item is taken."""
    df = catalog(spark, sf).filter("item is not null")
    cand = df.select(F.lit(0).cast("long").alias("block"), F.lit(0).cast("long").alias("plan"), F.col("rec_id").alias("unit"), F.col("rec_id").alias("rank"), F.col("item").alias("key"))
    return pack_disjoint(cand.drop("key"), cand.drop("rank")).select("unit")


ROUND_ONE = f"""{SP2}, sc as (select v, word, round(cast(({SINGLE} - c.n) / 2.0 as double), 6) as delta from sp join vc c on c.item = v left join vc w on w.item = word),
 c0 as (select (select count(*) from vc where n = 1) / 2.0 + (select count(*) from catalog_dirty where item is not null and item not in ({ITEMS})) / 2.0 as cost)"""


@query(f"with {ROUND_ONE}, u as (select v, word, 1.0 / (1.0 + cost + delta) as utility from sc, c0) select v, word from u where utility >= 0.9995 * (select max(utility) from u)", "catalog")
def s_gamma_candidates(spark, sf):
    """Candidates of a first round that both cuts by the bound leave."""
    df = catalog(spark, sf)
    s = Session(df, Quality([Singletons("item"), OutOfDictionary("item", items(spark, sf))]), gamma=0.9995)
    s.add(SpellReplace(items(spark, sf), attr="item", rec=2).repairs(df))
    plans = s.rows.select("block").distinct().select("block", F.lit(0).cast("long").alias("plan"))
    scored = written(s.score(written(s.images(s.hits(plans, None)), "images"), [None if x is None else written(x, "state") for x in s.quality.states(s.rows)], None), "scored")
    rows = scored.withColumn("utility", utility(F.lit(s.quality.cost(s.rows)) + F.round("delta", 6)))
    left = prune_global(prune_local(rows, s.gamma, worker=F.pmod(F.xxhash64("unit"), F.lit(8))), s.gamma)
    return left.join(s.pool, "unit").select(F.col("pred")[0]["lo"].alias("v"), F.col("value").alias("word"))


@query(f"with {CHASED}, cand as (select c.item as x, c.noun as y, b.b as best, case when c.noun is null then 2 * t.t * c.n - 2 * b.nb * c.n else -2 * c.n * b.nb end as delta from cnt c join best b using (item) join tot t using (item) where c.noun is null or c.noun <> b.b) select x, y from (select *, row_number() over (partition by x order by delta, y nulls first) as rn from cand) q where rn = 1", "catalog")
def s_merge_candidates(spark, sf):
    """Packing scored candidates by the groups of the dependency that they touch: the best
    of each left-hand group is taken."""
    df = catalog(spark, sf)
    s = Session(df, Quality([FDViolations(ITEM_NOUN)]))
    s.add(FDChase([ITEM_NOUN]).repairs(df))
    plans = s.rows.select("block").distinct().select("block", F.lit(0).cast("long").alias("plan"))
    images = written(s.images(s.hits(plans, None)), "images")
    scored = s.score(images, [written(x, "state") for x in s.quality.states(s.rows)], None)
    pick = lambda a: F.filter("pred", lambda c: c["attr"] == a)[0]["lo"]
    named = s.pool.select("unit", pick("item").alias("x"), pick("noun").alias("y"))
    ranked = scored.join(named, "unit").withColumn("rank", F.row_number().over(Window.orderBy("delta", "x", F.col("y").asc_nulls_first())))  # candidates of a fixture
    taken = pack_disjoint(written(ranked.select("block", "plan", "unit", "rank"), "ranked"), s.quality.keys(images))
    return taken.join(named, "unit").select("x", "y")


@query("select brand, cast(count(*) as bigint) as n from catalog_dirty group by 1", "catalog")
def s_rebalance_plans(spark, sf):
    """Plans dealt anew to workers, with copies for idle ones, which fall away again."""
    frontier = catalog(spark, sf).groupBy("brand").agg(F.count("*").alias("n")).withColumn("plan", F.xxhash64("brand"))
    return rebalance(frontier, 64, replicate=True).dropDuplicates(["plan"]).select("brand", "n")


# Blocks.


@query("select cast(count(*) as bigint) as n from catalog_dirty group by brand", "catalog")
def s_blocks(spark, sf):
    return BlockBy.columns(catalog(spark, sf), "brand").groupBy("block").agg(F.count("*").alias("n")).select("n")


@query("select cast(count(*) as bigint) as n from series_dirty group by station, date_trunc('day', ts)", "series")
def s_blocks_time(spark, sf):
    return BlockBy.time(series(spark, sf), "ts", "day", "station").groupBy("block").agg(F.count("*").alias("n")).select("n")


@query("select cast(count(*) as bigint) as n from catalog_dirty where item is not null and noun is not null group by item having count(distinct noun) > 1", "catalog")
def s_components(spark, sf):
    blocked = BlockBy.fds(catalog(spark, sf), [ITEM_NOUN])
    return blocked.filter("block <> -1").groupBy("block").agg(F.count("*").alias("n")).select("n")


# Searches.


def catalog_library(spark, sf, coarse_units: bool = False) -> list:
    lexicon = items(spark, sf)
    ops = [
        SpellReplace(lexicon, domains={"rec": [1, 2]}, attr="item"),
        MinHashReplace(domains={"thresh": [0.7]}, attr="item"),
        FDChase([ITEM_NOUN]),
    ]
    return [coarse(o) for o in ops] if coarse_units else ops


def catalog_quality(spark, sf) -> Quality:
    return Quality([FDViolations(ITEM_NOUN), Singletons("item"), OutOfDictionary("item", items(spark, sf))])


def catalog_session(spark: SparkSession, sf: str, coarse_units: bool = False, **options) -> Session:
    """The flagship's session: its pool is filled in a fixed order."""
    df = catalog(spark, sf)
    s = Session(df, catalog_quality(spark, sf), **options)
    SyncGenerators(catalog_library(spark, sf, coarse_units)).fill(s, df)
    return s


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """The catalog cleaned by the best plan of a synchronous search."""
    return catalog_session(spark, sf).run().cleaned()


@query()
def s_cleaned_catalog(spark, sf):
    return flagship(spark, sf)


def _trace(spark, rows: list[dict]) -> DataFrame:
    cols = "method string, step int, cost double, pool_size long, n_evaluated long, n_pruned_bound long"
    return spark.createDataFrame([(r["method"], r["step"], float(r["cost"]), r.get("pool_size"), r.get("n_evaluated"), r.get("n_pruned_bound")) for r in rows], cols)


@query()
def s_trace(spark, sf):
    """Cost of the incumbent, pool and evaluations, round by round."""
    s = catalog_session(spark, sf)
    s.run()
    return _trace(spark, s.trace.rows)


@query()
def s_greedy_depth2(spark, sf):
    """Two rounds without merging, four plans kept."""
    r = catalog_session(spark, sf, max_rounds=2, beam=4, merge=False).run()
    return r.units


@query()
def s_coarse(spark, sf):
    s = catalog_session(spark, sf, coarse_units=True)
    s.run()
    return _trace(spark, s.trace.rows)


@query()
def s_gold(spark, sf):
    """The truth as the objective: what a search can reach at best."""
    df = catalog(spark, sf)
    s = Session(df, Quality([GoldCells(("item", "noun"))]), truth=catalog(spark, sf, "clean"))
    SyncGenerators(catalog_library(spark, sf)).fill(s, df)
    s.run()
    return _trace(spark, s.trace.rows)


@query()
def s_async(spark, sf):
    """Generators in threads; the best result after all have ended."""
    df = catalog(spark, sf)
    s = Session(df, catalog_quality(spark, sf))
    best = None
    for best in search_async(s, catalog_library(spark, sf), df, budget_s=120):  # noqa: B007
        pass
    return spark.createDataFrame([(float(best.cost),)], "cost double")


@query()
def s_waves(spark, sf):
    """Block-wise search by brand with a pruner learnt after each wave."""
    df = BlockBy.columns(catalog(spark, sf), "brand")
    pool = written(FDChase([ITEM_NOUN]).repairs(catalog(spark, sf)).unionByName(SpellReplace(items(spark, sf), attr="item", rec=1).repairs(catalog(spark, sf))), "pool")
    pruner = Pruner(["item", "noun", "type"], ["chase", "spell"])
    q = Quality([FDViolations(ITEM_NOUN), OutOfDictionary("item", items(spark, sf))])
    cleaned, _, _, _ = search_waves(df, q, pool, pruner, waves=2, max_rounds=3)
    return cleaned.select("rec_id", "item", "noun")


# Learning.


@query(
    f"select x, y, best, true as reads_item, true as reads_noun, false as reads_type, false as writes_item, true as writes_noun, true as is_chase from ({CHASE.format(x='item', y='noun', t='catalog_dirty')}) q", "catalog"
)
def l_features(spark, sf):
    pool = featurize(FDChase([ITEM_NOUN]).repairs(catalog(spark, sf)), ["item", "noun", "type"], ["chase", "spell"], [])
    pick = lambda a: F.filter("pred", lambda c: c["attr"] == a)[0]["lo"]
    bit = lambda i, n: (F.col("features")[i] == 1).alias(n)
    return pool.select(pick("item").alias("x"), pick("noun").alias("y"), F.col("value").alias("best"), bit(0, "reads_item"), bit(1, "reads_noun"), bit(2, "reads_type"), bit(3, "writes_item"), bit(4, "writes_noun"), bit(6, "is_chase"))


def _examples(spark, sf) -> DataFrame:
    """Parts as examples: blocks of ten brands, units that are dear chosen."""
    df = catalog(spark, sf).select(F.pmod(F.col("rec_id"), F.lit(10)).alias("block"), F.col("rec_id").alias("unit"), "price")
    return label_examples(df, df.filter("price > 980"))


@query("select rec_id % 10 as block, rec_id as unit, case when price > 980 then 1.0::double else 0.0::double end as label from catalog_dirty", "catalog")
def l_labels(spark, sf):
    return _examples(spark, sf)


@query("with p as (select price > 980 as pos, 1 / (1 + exp(-(price * 0.01 - 9.5))) as p from catalog_dirty) select round(min(p), 6) as threshold, count(*) filter (p >= (select min(p) from p where pos)) as kept from p where pos or true having true".replace("min(p), 6) as threshold", "(select min(p) from p where pos), 6) as threshold"), "catalog")
def l_threshold(spark, sf):
    df = catalog(spark, sf).select(F.array("price").alias("features"), (F.col("price") > 980).cast("double").alias("label"))
    scored = score_with(df, [0.01], -9.5)
    t = threshold_of(scored)
    return scored.agg(F.lit(round(t, 6)).alias("threshold"), F.count_if(F.col("p") >= t).alias("kept"))


def _fitted(spark, sf) -> tuple[Pruner, DataFrame, DataFrame]:
    df = catalog(spark, sf)
    chase, spell = FDChase([ITEM_NOUN]).repairs(df), SpellReplace(items(spark, sf), attr="item", rec=2).repairs(df)
    pool = written(chase.unionByName(spell), "pool")
    tried = pool.select(F.pmod("unit", F.lit(8)).alias("block"), "unit")
    examples = written(label_examples(tried, tried.join(pool.filter("op = 'chase'"), "unit", "left_semi")), "examples")
    return Pruner(["item", "noun"], ["chase", "spell"], ["rec"]).fit(examples, pool), examples, pool


@query()
def l_fit(spark, sf):
    """Coefficients of a pruner that learns that one tool's repairs help."""
    return spark.createDataFrame(_fitted(spark, sf)[0].rules(), "feature string, weight double")


@query()
def m_pruner_confusion(spark, sf):
    return spark.createDataFrame([tuple(confusion(*_fitted(spark, sf)).values())], "true_positive long, false_negative long, false_positive long, true_negative long")


# Baselines.


def _tuner(spark, sf, name: str) -> tuners.Tuner:
    ops = [SpellReplace(items(spark, sf), domains={"rec": [1, 2]}, attr="item"), EditMatch(domains={"thresh": [1, 2]}, attr="noun")]
    return tuners.Tuner(name, catalog(spark, sf), ops, Quality([OutOfDictionary("item", items(spark, sf)), Singletons("noun")]))


def _settings(spark, t: tuners.Tuner) -> DataFrame:
    show = lambda c, k: 0 if "off" in c else int(c[k])
    return spark.createDataFrame([(show(s[0], "rec"), show(s[1], "thresh"), round(c, 6)) for s, c in t.trials], "rec int, thresh int, cost double")


def _fixed(rec: int, name: str) -> str:
    if not rec:
        return f"{name} as (select item from catalog_dirty)"
    near = SPELL.format(lex=ITEMS, rec=rec).replace("near as", f"{name}_n as")
    return f"{near}, {name}_s as (select v, word from (select *, row_number() over (partition by v order by dist, freq desc, word) as rn from {name}_n) t where rn = 1), {name} as (select coalesce(s.word, d.item) as item from catalog_dirty d left join {name}_s s on d.item = s.v)"


def _matched(d: int, name: str) -> str:
    if not d:
        return f"{name} as (select noun from catalog_dirty)"
    vals = f"{name}_v as (select noun as v, count(*) as cnt from catalog_dirty where noun is not null group by 1)"
    pick = f"{name}_p as (select v, word from (select x.v, y.v as word, row_number() over (partition by x.v order by y.cnt desc, y.v) as rn from {name}_v x join {name}_v y on levenshtein(x.v, y.v) <= {d}) t where rn = 1)"
    return f"{vals}, {pick}, {name} as (select coalesce(p.word, d.noun) as noun from catalog_dirty d left join {name}_p p on d.noun = p.v)"


@query(
    "with " + ", ".join([_fixed(r, f"i{r}") for r in (0, 1, 2)] + [_matched(t, f"n{t}") for t in (0, 1, 2)]) + " "
    + " union all ".join(
        f"select {r} as rec, {t} as thresh, round(0.5 * (select count(*) from i{r} where item is not null and item not in ({ITEMS})) + 0.5 * (select count(*) from (select noun from n{t} where noun is not null group by 1 having count(*) = 1) q), 6) as cost"
        for r in (0, 1, 2) for t in (0, 1, 2)
    ),
    "catalog",
)
def b_grid_scores(spark, sf):
    return _settings(spark, tuners.grid_search(_tuner(spark, sf, "grid"), parallel=3))


_GRID = ORACLES["b_grid_scores"]


@query(f"with g as ({_GRID}) select * from g where thresh = 0 union all select * from g where rec = 0 union all select * from g where rec = (select rec from g where thresh = 0 order by cost, rec limit 1) and thresh = (select thresh from g where rec = 0 order by cost, thresh limit 1)")
def b_greedy_choice(spark, sf):
    return _settings(spark, tuners.greedy_tune(_tuner(spark, sf, "greedy")))


@query()
def b_tpe(spark, sf):
    return _settings(spark, tuners.tpe_search(_tuner(spark, sf, "tpe"), 12, n_startup=6))


@query()
def b_random(spark, sf):
    return _settings(spark, tuners.random_search(_tuner(spark, sf, "random"), 6))


@query(" union all ".join(f"select {k} as k, (select count(*) from series_dirty d window_{k}) as flagged".replace(f"(select count(*) from series_dirty d window_{k})", f"(select count(*) from (select coalesce(count(reading) over w >= 3 and abs(reading - avg(reading) over w) > {k} * stddev_samp(reading) over w, false) as f from series_dirty window w as (partition by station order by ts, rec_id rows between 20 preceding and 1 preceding)) t where f)") for k in (2, 3, 4)), "series")
def b_standalone(spark, sf):
    """A detector by itself at several settings."""
    rows = [(k, detector(GaussOutlier, k=k, window_size=20).flag(series(spark, sf)).filter("flagged").count()) for k in (2, 3, 4)]
    return spark.createDataFrame(rows, "k int, flagged long")


@query("select 5 as tools, 2 as slots, cast((7 + count(distinct lo)) * (7 + count(distinct lo)) as bigint) as pipelines from (select brand, min(price) as lo from catalog_dirty group by 1) t", "catalog")
def b_slot_encoding(spark, sf):
    """Size of the space of two slots over five tools: six settings, and one for each least
    price of a brand."""
    lows = catalog(spark, sf).groupBy("brand").agg(F.min("price").alias("lo")).select("lo").distinct().dropna()  # at most one a brand
    ops = [SpellReplace(None, domains={"rec": [1, 2]}), EditMatch(domains={"thresh": [1, 2]}), MinHashReplace(domains={"thresh": [0.7]}), FDChase([ITEM_NOUN])]
    ops.append(RangeNullify(domains={"lo": sorted(r["lo"] for r in lows.collect())}, attr="price"))
    space = tuners.encode_slots(ops, 2)
    return spark.createDataFrame([(len(ops), 2, len(space[0]) * len(space[1]))], "tools int, slots int, pipelines long")


# Workload searches.


@query()
def w1_search(spark, sf):
    """Words: matcher, speller and both, tuned for F1 against the truth."""
    dirty = written(build(spark, sf, "words", "words_dirty").select("rec_id", "word"), "words")
    full = build(spark, sf, "words", "words_dirty")
    truth, lexicon = full.select("rec_id", F.col("truth").alias("word")), build(spark, sf, "words", "dictionary").select("word")
    df = with_block(dirty)
    tools = {"speller": [SpellReplace(lexicon, domains={"rec": [1, 2]}, attr="word")], "matcher": [EditMatch(domains={"thresh": [1]}, attr="word")]}
    out = []
    for name, ops in (tools | {"both": tools["matcher"] + tools["speller"]}).items():
        s = Session(df, Quality([GoldCells(("word",))]), truth=truth)
        SyncGenerators(ops).fill(s, dirty)
        f1 = measures.cell_f1(dirty, s.run().cleaned(), truth, ["word"]).first()["f1"]
        out.append((name, round(float(f1), 6)))
    return spark.createDataFrame(out, "tools string, f1 double")


@query()
def w2_search_cleaned(spark, sf):
    """Catalog: accuracy before and after the search."""
    dirty, truth = catalog(spark, sf), catalog(spark, sf, "clean")
    cleaned = flagship(spark, sf)
    return measures.cell_f1(dirty, cleaned, truth, ["item", "noun"])


@query()
def w3_search(spark, sf):
    """Series: detector settings, whole and reading by reading, as candidates under the
    windowed error, over several rounds by deltas that read the windows touched."""
    df = written(series(spark, sf).drop("truth"), "series")  # every setting of a tool reads it
    gauss = detector(GaussOutlier, k=4, window_size=50)
    gauss.domains = {"k": [4, 8]}
    s = Session(df, Quality([WindowAR("reading", "station", "ts", error="absolute")]), max_rounds=3)
    SyncGenerators([coarse(gauss), gauss]).fill(s, df)
    s.run()
    return _trace(spark, s.trace.rows)


@query()
def w5_comb_search(spark, sf):
    """Split fields: final cost of split-only, string-only and combined libraries."""
    full = split_dirty(spark, sf)  # written: every tool, term and round reads it
    df, lexicon = full.select("rec_id", "str1", "str2"), written(full.select(F.col("t1").alias("word")).distinct(), "lexicon")
    q = Quality([FDViolations(FD.parse("str1 -> str2")), OutOfDictionary("str1", lexicon), EmptyStrings("str2")])
    split = [SplitFields(domains={"sep": [":", ",", "-"]}, attr="str1", other="str2")]
    string = [SpellReplace(lexicon, domains={"rec": [1]}, attr="str1")]

    def final_cost(library: tuple[str, list]) -> tuple[str, float]:
        s = Session(df, q, max_rounds=4)
        SyncGenerators(library[1]).fill(s, df)
        return library[0], float(s.run().cost)

    # Each round is many short jobs: the searches, which share nothing but what they read, run side by side.
    with ThreadPoolExecutor(3) as pool:
        out = list(pool.map(inheritable_thread_target(spark)(final_cost), [("split", split), ("string", string), ("combined", split + string)]))
    return spark.createDataFrame(out, "library string, cost double")

"""The experiments: traces of the engine and of the tuners on the fixtures.

Each function takes (spark, sf_dir, budget_s) and returns trace rows or a table of
outcomes as plain dictionaries.  Times are wall clock, so results are compared in
direction, not in value.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines import tuners
from ..functions import measures
from ..functions.measures import speedup
from ..learn.pruner import Pruner
from ..model import FD
from ..operators.base import coarse, replicate_library, with_delay
from ..operators.dependencies import FDChase, StatisticalFD
from ..operators.outliers import GaussOutlier, HistOutlier
from ..operators.strings import EditMatch, SpellReplace, SplitFields
from ..plans.pool import consensus
from ..quality.quality import Quality, prepared, with_eval_delay
from ..quality.terms import EditPenalty, EmptyStrings, FDViolations, GoldCells, GoldF1, OutOfDictionary, Singletons, WindowAR
from ..queries_repair import ITEM_NOUN, catalog, items, series, split_dirty
from ..queries_search import catalog_library
from ..runtime.generators import SyncGenerators, search_async
from ..search.blocks import BlockBy
from ..search.engine import Session
from ..search.waves import search_waves
from ..session import written
from ..sources.fixtures import WIDE_FDS, build

ATTRS = ["item", "noun", "type"]


def user_quality(spark, sf) -> Quality:
    """Dependency, singletons and spelling, with a penalty for edits."""
    return Quality([(1 / 3, FDViolations(ITEM_NOUN)), (1 / 3, Singletons("item")), (1 / 3, OutOfDictionary("item", items(spark, sf))), (0.01, EditPenalty(("item", "noun")))])


def _engine(spark, sf, quality, df, ops, budget_s, truth=None, **options) -> Session:
    s = Session(df, quality, truth=truth, budget_s=budget_s, **options)
    SyncGenerators(ops).fill(s, df)
    s.run()
    return s


def _tuned(name, kind, df, ops, quality, budget_s, attrs, truth=None, **options) -> tuners.Tuner:
    base = prepared(df, attrs, truth)
    extra = [c for c in base.columns if c not in df.columns]
    side = written(base.select("rec_id", *extra), "side")
    t = tuners.Tuner(name, df, ops, quality, budget_s, prepare=lambda d: d.join(side, "rec_id"))
    kind(t, **options)
    return t


METHODS = {
    "grid": (tuners.grid_search, {"parallel": 1}),
    "tpe": (tuners.tpe_search, {"trials": 40, "n_startup": 6}),
    "greedy": (tuners.greedy_tune, {}),
}


def quality_convergence(spark: SparkSession, sf: str, budget_s: float = 60, gold: bool = False) -> list[dict]:
    """Engine and tuners under the user's quality, or under the truth."""
    df, truth = written(catalog(spark, sf), "dirty"), catalog(spark, sf, "clean")
    q = Quality([GoldCells(("item", "noun"))]) if gold else user_quality(spark, sf)
    ops = catalog_library(spark, sf)
    rows = list(_engine(spark, sf, q, df, ops, budget_s, truth=truth).trace.rows)
    for name, (kind, options) in METHODS.items():
        rows += _tuned(name, kind, df, ops, q, budget_s, ATTRS, truth, **options).trace.rows
    level = q.cost(prepared(truth, ATTRS, truth))
    return [r | {"suboptimality": measures.suboptimality(level, r["cost"])} for r in rows]


def gold_convergence(spark, sf, budget_s: float = 60) -> list[dict]:
    return quality_convergence(spark, sf, budget_s, gold=True)


def ablation(spark, sf, budget_s: float = 60) -> list[dict]:
    """Naive, incremental, asynchronous and learnt: seconds and final cost."""
    df = written(catalog(spark, sf), "dirty")
    q, out = Quality([FDViolations(ITEM_NOUN), OutOfDictionary("item", items(spark, sf))]), []
    ops = catalog_library(spark, sf)

    def timed(name, run):
        began = time.monotonic()
        out.append({"method": name, "cost": float(run()), "elapsed_s": time.monotonic() - began})

    timed("naive", lambda: _engine(spark, sf, q, df, [coarse(o) for o in ops], budget_s, incremental=False, max_rounds=2).trace.best())
    timed("incremental", lambda: _engine(spark, sf, q, df, ops, budget_s).trace.best())

    def asynchronous():
        best = None
        for best in search_async(Session(df, q), ops, df, budget_s):  # noqa: B007
            pass
        return best.cost

    timed("async", asynchronous)

    def learnt():
        blocked = BlockBy.columns(df, "brand")
        pool = None
        for b in SyncGenerators(ops).batches(df):
            pool = b if pool is None else pool.unionByName(b)
        cleaned, _, _, _ = search_waves(blocked, q, written(pool, "pool"), Pruner(ATTRS, ["spell", "minhash", "chase"], ["rec"]), waves=2)
        return q.cost(cleaned.drop("block"))

    timed("learning", learnt)
    return out


def evaluation_speedup(spark, sf) -> dict:
    """Seconds a candidate: all scored at once by deltas, and one by one in full."""
    df = written(catalog(spark, sf), "dirty")
    q = Quality([FDViolations(ITEM_NOUN), Singletons("item")])
    s = Session(df, q)
    s.add(SpellReplace(items(spark, sf), attr="item", rec=2).repairs(df))
    plans = s.rows.select("block").distinct().withColumn("plan", F.lit(0).cast("long"))
    began = time.monotonic()
    n = s.score(s.images(s.hits(plans, None)), q.states(s.rows), None).count()
    each = (time.monotonic() - began) / max(n, 1)
    began = time.monotonic()
    for _ in range(3):
        q.cost(df)
    full = (time.monotonic() - began) / 3
    return {"candidates": n, "delta_s": each, "full_s": full, "speedup": measures.speedup(full, each)}


def _asynchronous(q, df, ops, budget_s, **options) -> Session:
    """A session searched while each tool works in a thread of its own."""
    s = Session(df, q, **options)
    for _ in search_async(s, ops, df, budget_s):
        pass
    return s


def redundancy(spark, sf, times=(1, 4, 8, 16), budget_s: float = 60) -> list[dict]:
    """Libraries with redundant copies, a thread for each: same pool, same cost; a grid
    beside them, whose space grows with the power of the copies."""
    df, out = written(catalog(spark, sf), "dirty"), []
    q = Quality([FDViolations(ITEM_NOUN), Singletons("item")])
    for n in times:
        ops = replicate_library(catalog_library(spark, sf), n)
        began = time.monotonic()
        s = _asynchronous(q, df, ops, budget_s)
        out.append({"method": "engine", "copies": n, "pool": s.pool.count(), "cost": s.trace.best(), "elapsed_s": time.monotonic() - began})
        t = _tuned("grid", tuners.grid_search, df, ops, q, budget_s, ATTRS, parallel=1)
        out.append({"method": "grid", "copies": n, "pool": len(t.trials), "cost": t.best_cost, "elapsed_s": t.trace.rows[-1]["elapsed_s"]})
    return out


def scaling(spark, sf, threads=(1, 2, 4, 8), budget_s: float = 60) -> list[dict]:
    """Seconds to the final cost by threads: evaluations of the grid side by side, and the
    tasks of the engine's jobs held to as many partitions."""
    df, out = written(catalog(spark, sf), "dirty"), []
    q, ops = Quality([FDViolations(ITEM_NOUN), Singletons("item")]), catalog_library(spark, sf)
    before = spark.conf.get("spark.sql.shuffle.partitions")
    base: dict[str, float] = {}
    try:
        for n in threads:
            spark.conf.set("spark.sql.shuffle.partitions", str(n))
            s = _engine(spark, sf, q, df.coalesce(n), ops, budget_s)
            t = _tuned("grid", tuners.grid_search, df, ops, q, budget_s, ATTRS, parallel=n)
            for name, rows in (("engine", s.trace.rows), ("grid", t.trace.rows)):
                level = min(r["cost"] for r in rows)
                took = measures.time_to(rows, level)
                base.setdefault(name, took)
                out.append({"method": name, "threads": n, "cost": level, "time_to_best_s": took, "speedup": speedup(base[name], took), "evaluations_s": rows[-1]["n_evaluated"] / max(rows[-1]["elapsed_s"], 1e-9)})
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    return out


def toy_f1(spark, sf, trials: int = 12, budget_s: float = 60) -> list[dict]:
    """Words tuned for F1 as a black box: the matcher alone, the speller alone, and both
    jointly, whose larger space takes longer; the engine on the same objective beside."""
    full = build(spark, sf, "words", "words_dirty")
    df, truth = written(full.select("rec_id", "word"), "words"), full.select("rec_id", F.col("truth").alias("word"))
    lexicon = build(spark, sf, "words", "dictionary").select("word")
    speller, matcher = SpellReplace(lexicon, domains={"rec": [1, 2, 3]}, attr="word"), EditMatch(domains={"thresh": [1, 2, 3]}, attr="word")
    q, out = Quality([(1.0, GoldF1(("word",)))]), []
    for name, ops in (("speller", [speller]), ("matcher", [matcher]), ("both", [matcher, speller])):
        t = _tuned(name, tuners.tpe_search, df, ops, q, budget_s, ["word"], truth, trials=trials, n_startup=4)
        out += [{"method": f"tuner {name}", "trial": r["step"], "f1": 1 - r["cost"], "elapsed_s": r["elapsed_s"]} for r in t.trace.rows]
    s = _engine(spark, sf, q, df, [matcher, speller], budget_s, truth=truth)
    return out + [{"method": "engine", "trial": r["step"], "f1": 1 - r["cost"], "elapsed_s": r["elapsed_s"]} for r in s.trace.rows]


def series_convergence(spark, sf, budget_s: float = 60) -> list[dict]:
    """Readings end to end: the engine by deltas of the windowed error, and the tuners."""
    df = written(series(spark, sf).drop("truth"), "dirty")
    gauss = GaussOutlier("station", ["ts", "rec_id"], domains={"k": [3, 4, 6]}, attr="reading", window_size=50, k=4)
    hist = HistOutlier("station", ["ts", "rec_id"], domains={"outlier_threshold": [0.02, 0.05]}, attr="reading", window_size=50, peak_threshold=0.1, outlier_threshold=0.02)
    q = Quality([WindowAR("reading", "station", "ts", error="absolute")])
    rows = list(_engine(spark, sf, q, df, [coarse(gauss), coarse(hist), gauss], budget_s).trace.rows)
    for name, (kind, options) in METHODS.items():
        rows += _tuned(name, kind, df, [gauss, hist], q, budget_s, ["reading"], **options).trace.rows
    return rows


def wide_convergence(spark, sf, budget_s: float = 60) -> list[dict]:
    """The wide relation end to end: eight dependencies, a chase for each."""
    df = written(build(spark, sf, "wide", "wide_dirty"), "dirty")
    fds = [FD.parse(f) for f in WIDE_FDS]
    q, ops = Quality([FDViolations(fd) for fd in fds]), [FDChase([fd]) for fd in fds]
    rows = list(_engine(spark, sf, q, df, ops, budget_s).trace.rows)
    for name, (kind, options) in METHODS.items():
        rows += _tuned(name, kind, df, ops, q, budget_s, [], **options).trace.rows
    return rows


def consensus_search(spark, sf, budget_s: float = 60) -> list[dict]:
    """Each tool tuned by itself; the cells that two of them agree on are repaired."""
    df, truth = written(catalog(spark, sf), "dirty"), catalog(spark, sf, "clean")
    q, pools, out = user_quality(spark, sf), None, []
    for op in catalog_library(spark, sf):
        t = _tuned(op.name, tuners.grid_search, df, [op], q, budget_s, ATTRS, truth, parallel=1)
        out.append({"method": op.name, "cost": t.best_cost} | _accuracy(df, t.cleaned(), truth, ["item", "noun"]))
        for choice in t.best or []:
            if "off" not in choice:
                pool = op.with_params({k: v for k, v in choice.items() if k != "op"}).repairs(df)
                pools = pool if pools is None else pools.unionByName(pool)
    if pools is not None:
        votes = consensus(pools, df, min_votes=2)
        fix = votes.groupBy("rec_id").pivot("target", ["item", "noun"]).agg(F.first("new"))
        joined = df.join(fix.select("rec_id", *[F.col(a).alias(f"_{a}") for a in ("item", "noun")]), "rec_id", "left")
        cleaned = written(joined.withColumns({a: F.coalesce(f"_{a}", a) for a in ("item", "noun")}).select(*df.columns), "voted")
        out.append({"method": "consensus", "cost": q.cost(prepared(df, ATTRS).drop(*df.columns[1:]).join(cleaned, "rec_id"))} | _accuracy(df, cleaned, truth, ["item", "noun"]))
    return out


def slow_parts(spark, sf, lo_ms: float, hi_ms: float, which: str, budget_s: float = 60) -> list[dict]:
    """Delayed tools (``which='tools'``) or delayed evaluations, engine and tuner."""
    df = written(catalog(spark, sf), "dirty")
    q, ops = Quality([FDViolations(ITEM_NOUN), Singletons("item")]), catalog_library(spark, sf)
    if which == "tools":
        ops = [with_delay(o, lo_ms, hi_ms, i) for i, o in enumerate(ops)]
    else:
        q = with_eval_delay(q, lo_ms, hi_ms)
    plain = catalog_library(spark, sf), Quality([FDViolations(ITEM_NOUN), Singletons("item")])
    out = []
    for method in ("engine", "tpe"):
        traces = []
        for library, quality in (plain, (ops, q)):
            if method == "engine":
                traces.append(_asynchronous(quality, df, library, budget_s).trace.rows)
            else:
                traces.append(_tuned("tpe", tuners.tpe_search, df, library, quality, budget_s, ATTRS, trials=15, n_startup=5).trace.rows)
        out += [{"method": method, "which": which, "delay_ms": hi_ms, "cost": min(r["cost"] for r in traces[1]), "degradation": measures.degradation(*traces)}]
    return out


def granularity(spark, sf, budget_s: float = 60) -> list[dict]:
    """Single repairs against bundles of a setting, and bundles first, then single ones."""
    df = written(catalog(spark, sf), "dirty")
    q, ops, out = Quality([FDViolations(ITEM_NOUN), Singletons("item"), OutOfDictionary("item", items(spark, sf))]), catalog_library(spark, sf), []
    for name, library in (("fine", ops), ("coarse", [coarse(o) for o in ops])):
        s = _engine(spark, sf, q, df, library, budget_s)
        out.append({"method": name, "cost": s.trace.best(), "elapsed_s": s.trace.rows[-1]["elapsed_s"]})
    first = Session(df, q)
    SyncGenerators([coarse(o) for o in ops]).fill(first, df)
    cleaned = written(first.run().cleaned(), "coarse")
    s = _engine(spark, sf, q, cleaned, ops, budget_s)
    out.append({"method": "coarse_then_fine", "cost": s.trace.best(), "elapsed_s": s.trace.rows[-1]["elapsed_s"]})
    return out


def sequence(spark, sf, budget_s: float = 60) -> list[dict]:
    """Split-only, string-only and combined libraries on concatenated fields."""
    df = written(split_dirty(spark, sf).select("rec_id", "str1", "str2"), "dirty")
    lexicon = written(build(spark, sf, "split", "split_clean").select(F.col("t1").alias("word")).distinct(), "lexicon")
    q = Quality([FDViolations(FD.parse("str1 -> str2")), OutOfDictionary("str1", lexicon), EmptyStrings("str2")])
    split = [SplitFields(domains={"sep": [":", ",", "-"]}, attr="str1", other="str2")]
    string = [SpellReplace(lexicon, domains={"rec": [1]}, attr="str1"), FDChase([FD.parse("str1 -> str2")])]
    return [{"method": n, "cost": _engine(spark, sf, q, df, ops, budget_s, max_rounds=4).trace.best()} for n, ops in {"split": split, "string": string, "combined": split + string}.items()]


def _accuracy(dirty: DataFrame, cleaned: DataFrame, truth: DataFrame, attrs: list[str]) -> dict:
    r = measures.cell_f1(dirty, cleaned, truth, attrs).first()
    return {"f1": float(r["f1"]), "accuracy": float(r["accuracy"])}


def standalone_fd(spark, sf, budget_s: float = 60) -> list[dict]:
    """The statistical repairer alone (best and random settings), the engine without and
    with it as a tool, on the wide relation."""
    attrs = ["c_name", "c_mktsegment"]
    cols = ["rec_id", "c_custkey", *attrs, "n_name"]
    dirty = written(build(spark, sf, "wide", "wide_dirty").select(*cols), "dirty")
    truth = build(spark, sf, "wide", "wide_clean").select(*cols)
    fds = [FD.parse(f) for f in WIDE_FDS[:2]]
    tool = StatisticalFD(fds, ["n_name"], domains={"threshold": [0.3, 0.5, 0.7, 0.9]}, threshold=0.5)
    out = [{"method": "standalone", "setting": str(s)} | _accuracy(dirty, d, truth, attrs) for s, d in tuners.standalone(dirty, tool, {"threshold": 0.5}, n_random=5)]
    q = Quality([FDViolations(fd) for fd in fds])
    spell = SpellReplace(truth.select(F.col("c_mktsegment").alias("word")).distinct(), domains={"rec": [1]}, attr="c_mktsegment")
    for name, ops in (("engine", [spell]), ("engine with tool", [spell, coarse(tool)])):
        s = Session(dirty, q, budget_s=budget_s, max_rounds=3)
        SyncGenerators(ops).fill(s, dirty)
        out.append({"method": name, "setting": ""} | _accuracy(dirty, s.run().cleaned(), truth, attrs))
    return out


def standalone_series(spark, sf) -> list[dict]:
    """Detectors alone at several settings, and the engine choosing among them."""
    full = series(spark, sf)
    dirty, truth = written(full.drop("truth"), "dirty"), full.select("rec_id", F.col("truth").alias("reading"))
    gauss = GaussOutlier("station", ["ts", "rec_id"], domains={"k": [2, 3, 4, 6, 8]}, attr="reading", window_size=50, k=4)
    hist = HistOutlier("station", ["ts", "rec_id"], domains={"outlier_threshold": [0.02]}, attr="reading", window_size=50, peak_threshold=0.1, outlier_threshold=0.02)
    out = [{"method": "gauss", "setting": str(s)} | _accuracy(dirty, d, truth, ["reading"]) for s, d in tuners.standalone(dirty, gauss, {"k": 4}, n_random=5)]
    q = Quality([WindowAR("reading", "station", "ts", error="absolute")])
    s = Session(dirty, q, max_rounds=3)
    SyncGenerators([coarse(gauss), coarse(hist)]).fill(s, dirty)
    out.append({"method": "engine", "setting": ""} | _accuracy(dirty, s.run().cleaned(), truth, ["reading"]))
    return out

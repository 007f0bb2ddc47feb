"""Best-first search over pipelines of repairs, all candidates of a round in one job.

A frontier holds, for each block, up to ``beam`` plans; a plan is kept as the records it
changes (``patched``: base image and present image), never as a relation.  A round
binds the pool to the records as each plan leaves them and scores every extension by
exact deltas against the plan.  Extensions are cut twice by the bound gamma: against the
best that their worker knows of, and against the best of all.  Improving ones that cannot
interfere are packed into one plan; that plan, the best single extensions (with a wider
frontier also such as do not improve, from which two steps may) and the plans as they
were are held against each other by their exact costs, and the best stay: a merged plan
only counts if it is better.  Rounds end in written tables, so lineage stays short and
lost executors cost one round.
"""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.predicates import literal
from ..plans.pool import bind, canonicalize
from ..quality.quality import Quality, prepared
from ..session import written
from .merge import pack_disjoint
from .prune import prune_global, prune_local, rebalance, utility

_PLAN = ["block", "plan"]
_EPS = 1e-9


@dataclass
class Trace:
    method: str
    run_id: str = field(default_factory=lambda: uuid.uuid4().hex[:8])
    rows: list[dict] = field(default_factory=list)
    began: float = field(default_factory=time.monotonic)

    def add(self, step: int, cost: float, **counts) -> None:
        self.rows.append({"run_id": self.run_id, "method": self.method, "step": step, "elapsed_s": time.monotonic() - self.began, "cost": cost} | counts)

    def best(self) -> float:
        return min(r["cost"] for r in self.rows)


@dataclass
class Result:
    """The best plan found: its units in order, the records it changes, the trace."""

    session: Session
    cost: float
    units: DataFrame  # block, step, unit
    patched: DataFrame  # block, plan, rec, b, a
    trace: Trace

    def cleaned(self) -> DataFrame:
        """The relation with the plan applied; schema and records as given."""
        s = self.session
        cols = s.given.columns
        fix = self.patched.select(F.col("rec").alias(s.key), F.col("a").alias("_a"))
        joined = s.given.join(fix, s.key, "left")
        return joined.select(*[F.when(F.col("_a").isNotNull(), F.col(f"_a.{c}")).otherwise(F.col(c)).alias(c) if c != s.key else F.col(c) for c in cols])

    def repairs(self) -> DataFrame:
        """(block, step, *pool columns) of the plan's repairs, in order."""
        return self.units.join(self.session.pool, "unit").orderBy("block", "step", "pos")


class Session:
    """One relation, its quality and a pool of repairs.

    ``beam`` plans a block are kept; ``merge`` packs disjoint survivors; ``gamma``
    is the bound; ``budget_s`` cancels what runs when it is over; ``keep`` may filter the pool before binding (the learnt pruner);
    ``incremental=False`` scores every candidate by full recomputation.
    """

    def __init__(
        self,
        df: DataFrame,
        quality: Quality,
        key: str = "rec_id",
        truth: DataFrame | None = None,
        gamma: float = 0.9,
        max_rounds: int = 8,
        beam: int = 1,
        merge: bool = True,
        patience: int = 1,
        incremental: bool = True,
        keep=None,
        budget_s: float | None = None,
        restrict: DataFrame | None = None,
        utility_kind: str = "reciprocal",
    ):
        self.given = df.drop("block") if "block" in df.columns else df
        self.key, self.quality, self.gamma, self.max_rounds, self.beam, self.merge = key, quality, gamma, max_rounds, beam, merge
        self.patience, self.incremental, self.keep, self.budget_s, self.utility_kind = patience, incremental, keep, budget_s, utility_kind
        attrs = [c for c in self.given.columns if c != key]
        rows = prepared(df, attrs, truth, key)
        self.rows = written(rows if quality.by_block else rows.withColumn("block", F.lit(0).cast("long")), "relation")
        self.pool: DataFrame | None = None
        self.restrict = restrict  # (block, unit) pairs allowed, for per-block pruning
        self.trace = Trace("engine")

    def fork(self, quality: Quality) -> Session:
        """The same relation and pool under another quality hypothesis."""
        other = object.__new__(Session)
        other.__dict__ = dict(self.__dict__) | {"quality": quality, "trace": Trace("engine")}
        return other

    def add(self, pool: DataFrame) -> None:
        """Take a batch of repairs into the pool; known edits collapse."""
        both = pool if self.pool is None else self.pool.unionByName(pool.select(*self.pool.columns))
        self.pool = written(canonicalize(both), "pool")
        self._root = None

    # A round, step by step.

    def hits(self, plans: DataFrame, patched: DataFrame | None) -> DataFrame:
        """Cells that each unit changes under each plan."""
        pool = self.keep(self.pool) if self.keep else self.pool
        if self._root is None:
            self._root = written(bind(pool, self.rows, ("block", self.key), True).withColumnRenamed(self.key, "rec"), "hits")
        root = self._root.join(plans.select(*_PLAN), "block")
        if self.restrict is not None:
            root = root.join(self.restrict, ["block", "unit"], "left_semi")
        if patched is None:
            return root
        root = root.join(patched.select(*_PLAN, "rec"), [*_PLAN, "rec"], "left_anti")
        now = patched.select("plan", "a.*")
        more = bind(pool, now, ("block", "plan", self.key), True).withColumnRenamed(self.key, "rec")
        more = more.withColumn("b", F.struct(*[F.col(f"b.{c}").alias(c) for c in self.rows.columns]))
        if self.restrict is not None:
            more = more.join(self.restrict, ["block", "unit"], "left_semi")
        return root.unionByName(more.select(*root.columns))

    def images(self, hits: DataFrame) -> DataFrame:
        """(block, plan, unit, rec, b, a): records before and after each unit."""
        cand = [*_PLAN, "unit", "rec"]
        last = hits.groupBy(*cand, "target").agg(F.max_by(F.struct("new"), F.struct("pos", "repair_id")).alias("n"), F.first("b").alias("b"))
        rows = last.groupBy(*cand).agg(F.first("b").alias("b"), F.map_from_entries(F.collect_list(F.struct("target", F.col("n.new").alias("new")))).alias("m"))
        types = dict(zip(self.rows.columns, [f.dataType for f in self.rows.schema.fields], strict=True))
        targets = [c for c in self.given.columns if c != self.key]
        value = lambda c: literal(F.col("m")[c], types[c].simpleString()).cast(types[c])
        cols = [F.when(F.map_contains_key("m", F.lit(c)), value(c)).otherwise(F.col(f"b.{c}")).alias(c) if c in targets else F.col(f"b.{c}").alias(c) for c in self.rows.columns]
        return rows.select(*cand, "b", F.struct(*cols).alias("a"))

    def score(self, images: DataFrame, states: list, drifts: list | None) -> DataFrame:
        """(block, plan, unit, delta)."""
        if self.incremental and self.quality.incremental:
            return self.quality.deltas(images, states, drifts)
        return self._score_full(images)

    def _score_full(self, images: DataFrame) -> DataFrame:
        """One full evaluation for each candidate: the naive way."""
        images = written(images, "images")
        rows = []
        for c in images.select(*_PLAN, "unit").distinct().collect():
            mine = images.filter((F.col("block") == c["block"]) & (F.col("plan") == c["plan"]) & (F.col("unit") == c["unit"])).withColumn("plan", F.lit(0))
            base = self._patched if self._patched is None else self._patched.filter((F.col("block") == c["block"]) & (F.col("plan") == c["plan"]))
            before = self.patch(self.rows.filter(F.col("block") == c["block"]), base)
            after = self.patch(before, mine)
            self.n_evaluated += 1
            rows.append((c["block"], c["plan"], c["unit"], self.quality.cost(after) - self.quality.cost(before)))
        return self.rows.sparkSession.createDataFrame(rows, "block long, plan long, unit long, delta double")

    def patch(self, rows: DataFrame, images: DataFrame | None) -> DataFrame:
        """A relation with images put in place of their records."""
        if images is None:
            return rows
        fix = images.select(F.col("rec").alias(self.key), F.col("a").alias("_a"))
        out = rows.join(fix, self.key, "left")
        return out.select(*[F.when(F.col("_a").isNotNull(), F.col(f"_a.{c}")).otherwise(F.col(c)).alias(c) if c != self.key else F.col(c) for c in rows.columns])

    def iter(self) -> Iterator[Result]:
        """Better and better results, one for each round that improved."""
        spark = self.rows.sparkSession
        exact = self.quality.incremental and self.incremental
        states = [None if s is None else written(s, "state") for s in self.quality.states(self.rows)] if exact else []
        start = self.quality.costs(self.rows)
        blocks = self.rows.select("block").distinct()
        plans = written(blocks.join(start, "block", "left").select("block", F.lit(0).cast("long").alias("plan"), F.coalesce("cost", F.lit(0.0)).alias("cost")), "plans")
        chosen = drifts = None  # chosen: block, plan, step, unit
        self._patched, self.n_evaluated = None, 0
        total = float(plans.agg(F.sum("cost")).first()[0] or 0.0)
        pool_size = self.pool.count()
        self.trace.add(0, total, pool_size=pool_size, n_evaluated=0, n_pruned_bound=0)
        idle, best = 0, None
        for step in range(1, self.max_rounds + 1):
            left = None if self.budget_s is None else self.budget_s - (time.monotonic() - self.trace.began)
            if left is not None and left <= 0:
                break
            try:
                with _time_limit(spark, left):
                    done = self._round(step, plans, states, drifts, chosen, total, exact)
            except Exception:
                if left is None or time.monotonic() - self.trace.began < self.budget_s:
                    raise
                break  # out of time within a round: the jobs were cancelled
            if done is None:
                self.trace.add(step, total, pool_size=pool_size, n_evaluated=self.n_evaluated, n_pruned_bound=0)
                break
            plans, chosen, self._patched, drifts, cut = done
            now = float(plans.groupBy("block").agg(F.min("cost").alias("c")).agg(F.sum("c")).first()[0])
            self.trace.add(step, min(now, total), pool_size=pool_size, n_evaluated=self.n_evaluated, n_pruned_bound=cut)
            if now < total - _EPS:
                total, idle = now, 0
                top = self._best(plans)
                best = Result(self, total, chosen.join(top, _PLAN, "left_semi").select("block", "step", "unit"), self._patched.join(top, _PLAN, "left_semi"), self.trace)
                yield best
            else:
                idle += 1
                if idle >= self.patience:
                    break
        if best is None:
            none = spark.createDataFrame([], "block long, step int, unit long")
            row = F.struct(*[F.col(c) for c in self.rows.columns])
            empty = self.rows.limit(0).select("block", F.lit(0).cast("long").alias("plan"), F.col(self.key).alias("rec"), row.alias("b"), row.alias("a"))
            yield Result(self, total, none, empty, self.trace)

    def _survivors(self, scored: DataFrame, plans: DataFrame, start_cost: float) -> DataFrame:
        """Scored extensions within gamma of the best: of their worker, then of all."""
        worth = lambda c: utility(c, self.utility_kind, start_cost)
        rows = scored.join(plans, _PLAN).withColumn("utility", worth(F.col("cost") + F.col("delta")))
        known = plans.groupBy("block").agg(F.max(worth(F.col("cost"))).alias("_known"))
        workers = rows.sparkSession.sparkContext.defaultParallelism
        local = prune_local(rows, self.gamma, worker=F.struct("block", F.pmod(F.xxhash64("unit", "plan"), F.lit(workers))))
        final = prune_global(local, self.gamma, by=["block"])
        # What improves on its plan stays for merging; the rest must be near the frontier's best.
        return final.join(F.broadcast(known), "block").filter((F.col("delta") < -_EPS) | (F.lit(self.beam > 1) & (F.col("utility") >= self.gamma * F.col("_known")))).drop("_known", "utility")

    def _round(self, step, plans, states, drifts, chosen, total, exact):
        """One round: (plans, chosen, patched, drifts, candidates cut), None if none is left."""
        # What only this round needs is cached; what the next one starts from is written, and so are the steps
        # in between: the plan of a cached table holds the plans of all that it reads, once for each reading.
        images = self.images(self.hits(plans, self._patched)).persist()
        cached = [images]
        try:
            scored = written(self.score(images, states, drifts), "scored")
            n = scored.count()
            self.n_evaluated += n if exact else 0
            good = self._survivors(scored, plans, total).persist()
            cached.append(good)
            kept = good.count()
            if not kept:
                return None
            lead = self._best(plans)
            singles = Window.partitionBy("block").orderBy(F.col("cost") + F.col("delta"), "plan", "unit")
            picks = good.withColumn("slot", F.row_number().over(singles)).filter(F.col("slot") <= self.beam).select(*_PLAN, "unit", "slot")
            if self.merge:
                mine = good.filter(F.col("delta") < -_EPS).join(lead, _PLAN, "left_semi")
                ranked = mine.withColumn("rank", F.row_number().over(Window.partitionBy(*_PLAN).orderBy("delta", "unit"))).select(*_PLAN, "unit", "rank")
                held = images.join(ranked.select(*_PLAN, "unit"), [*_PLAN, "unit"], "left_semi")
                packed = pack_disjoint(ranked, self.quality.keys(held)).withColumn("_n", F.count("*").over(Window.partitionBy("block")))
                picks = picks.unionByName(packed.filter("_n > 1").select(*_PLAN, "unit", F.lit(0).alias("slot")))
            picks = written(picks.withColumn("next", F.lit(step * 1000).cast("long") + F.col("slot")), "picks")
            # The next plans' changed records, as their parents leave them and afterwards.
            new = written(images.join(picks, [*_PLAN, "unit"]).groupBy("block", "next", "plan", "rec").agg(F.first("b").alias("b"), F.first("a").alias("a")), "new")
            if exact:
                as_unit = new.select(*_PLAN, F.col("next").alias("unit"), "rec", "b", "a")
                fresh = self.quality.deltas(as_unit, states, drifts).join(plans, _PLAN).select("block", F.col("unit").alias("plan"), (F.col("cost") + F.col("delta")).alias("cost"))
            else:
                fresh = self._full_costs(self._patched_by(new, picks))
            # Plans as they were, merged and single ones: the best stay.
            both = plans.withColumn("old", F.lit(1)).unionByName(fresh.withColumn("old", F.lit(0)))
            near = Window.partitionBy("block").orderBy("cost", "old", "plan")
            after = both.withColumn("_r", F.row_number().over(near)).filter(F.col("_r") <= self.beam).select("block", "plan", "cost")
            if self.beam > 1:
                after = rebalance(after, min(self.rows.sparkSession.sparkContext.defaultParallelism, 64))
            after = written(after, "plans")
            alive = after.select(*_PLAN)
            steps = picks.select("block", F.col("next").alias("plan"), F.lit(step).alias("step"), "unit")
            if chosen is not None:
                parents = picks.select("block", "plan", "next").distinct()
                before = chosen.join(parents, _PLAN).select("block", F.col("next").alias("plan"), "step", "unit")
                steps = steps.unionByName(before).unionByName(chosen)
            steps = written(steps.join(alive, _PLAN, "left_semi"), "steps")
            patched = self._patched_by(new, picks)
            if self._patched is not None:
                patched = patched.unionByName(self._patched)
            patched = written(patched.join(alive, _PLAN, "left_semi"), "patched")
            moved = [None if d is None else written(d, "drift") for d in self.quality.drifts(patched.withColumn("unit", F.lit(0).cast("long")), states)] if exact else None
            return after, steps, patched, moved, n - kept
        finally:
            _release(cached)

    def _best(self, plans: DataFrame) -> DataFrame:
        """(block, plan) of the best plan of each block."""
        if self.beam == 1:
            return plans.select(*_PLAN)
        return plans.withColumn("_r", F.row_number().over(Window.partitionBy("block").orderBy("cost", "plan"))).filter("_r = 1").select(*_PLAN)

    def _patched_by(self, new: DataFrame, picks: DataFrame) -> DataFrame:
        """(block, plan, rec, b, a) of the next plans: their parents' records, overwritten."""
        mine = new.select("block", F.col("next").alias("plan"), "rec", "b", "a")
        if self._patched is None:
            return mine
        parents = picks.select("block", "plan", "next").distinct()
        old = self._patched.join(parents, _PLAN).select("block", F.col("next").alias("plan"), "rec", F.col("b").alias("b0"), F.col("a").alias("a0"))
        both = old.join(mine, [*_PLAN, "rec"], "full")
        return both.select(*_PLAN, "rec", F.coalesce("b0", "b").alias("b"), F.coalesce("a", "a0").alias("a"))

    def _full_costs(self, patched: DataFrame) -> DataFrame:
        rows = []
        for c in patched.select(*_PLAN).distinct().collect():
            mine = patched.filter((F.col("block") == c["block"]) & (F.col("plan") == c["plan"]))
            rows.append((c["block"], c["plan"], self.quality.cost(self.patch(self.rows.filter(F.col("block") == c["block"]), mine))))
        return self.rows.sparkSession.createDataFrame(rows, "block long, plan long, cost double")

    def run(self) -> Result:
        result = None
        for result in self.iter():  # noqa: B007
            pass
        return result


def _release(cached: list[DataFrame]) -> None:
    for df in cached:
        df.unpersist()


@contextmanager
def _time_limit(spark, seconds: float | None):
    """Cancel the jobs that this thread has started when the time is over."""
    if seconds is None:
        yield
        return
    tag, sc = f"search-{uuid.uuid4().hex[:12]}", spark.sparkContext
    sc.addJobTag(tag)
    timer = threading.Timer(seconds, lambda: sc.cancelJobsWithTag(tag))
    timer.daemon = True
    timer.start()
    try:
        yield
    finally:
        timer.cancel()
        sc.removeJobTag(tag)

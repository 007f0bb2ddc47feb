"""Repair generators beside the search: threads, a bounded pool, a scheduler for tests."""

from __future__ import annotations

import queue
import threading
import time
from collections.abc import Callable, Iterable

from pyspark import InheritableThread
from pyspark.sql import DataFrame

from ..operators.base import CleaningOperator
from ..session import written
from .sampler import iterate


class RepairPool:
    """Batches of repairs, bounded in rows: ``put`` blocks while full, ``drain`` never."""

    def __init__(self, max_size: int = 100_000):
        self.max_size, self.size, self.peak = max_size, 0, 0
        self._batches: queue.SimpleQueue = queue.SimpleQueue()
        self._room = threading.Condition()

    def put(self, batch: DataFrame, rows: int, stop: threading.Event | None = None) -> None:
        with self._room:
            while self.size and self.size + rows > self.max_size and not (stop and stop.is_set()):
                self._room.wait(0.1)
            self.size += rows
            self.peak = max(self.peak, self.size)
        self._batches.put((batch, rows))

    def drain(self, limit: int | None = None) -> list[DataFrame]:
        out = []
        while limit is None or len(out) < limit:
            try:
                batch, rows = self._batches.get_nowait()
            except queue.Empty:
                break
            out.append(batch)
            with self._room:
                self.size -= rows
                self._room.notify_all()
        return out


class SyncGenerators:
    """All settings of all tools, in order, in the calling thread: same pool every time."""

    def __init__(self, ops: list[CleaningOperator], sampler: Callable[[CleaningOperator], Iterable[dict]] = iterate):
        self.ops, self.sampler = ops, sampler

    def batches(self, df: DataFrame):
        for op in self.ops:
            for setting in self.sampler(op):
                yield op.with_params(setting).repairs(df)

    def fill(self, session, df: DataFrame) -> None:
        """One union of all batches, added to a session's pool."""
        both = None
        for b in self.batches(df):
            both = b if both is None else both.unionByName(b)
        session.add(both)


class AsyncGenerators:
    """A thread for each tool, its settings in turn; each in its own scheduler pool."""

    def __init__(self, ops: list[CleaningOperator], pool: RepairPool, sampler: Callable[[CleaningOperator], Iterable[dict]] = iterate, weights: dict[str, int] | None = None):
        self.ops, self.pool, self.sampler, self.weights = ops, pool, sampler, weights or {}
        self.stop, self.threads, self.errors = threading.Event(), [], []

    def start(self, df: DataFrame) -> None:
        spark = df.sparkSession

        def work(op: CleaningOperator, label: str) -> None:
            spark.sparkContext.setLocalProperty("spark.scheduler.pool", label)
            try:
                for setting in self.sampler(op):
                    if self.stop.is_set():
                        return
                    batch = written(op.with_params(setting).repairs(df), "batch")
                    self.pool.put(batch, batch.count(), self.stop)
            except Exception as e:  # noqa: BLE001  reported by join()
                self.errors.append(e)

        for i, op in enumerate(self.ops):
            t = InheritableThread(target=work, args=(op, f"{op.name}-{i}"), daemon=True)
            t.start()
            self.threads.append(t)

    def running(self) -> bool:
        return any(t.is_alive() for t in self.threads)

    def join(self) -> None:
        for t in self.threads:
            t.join()
        if self.errors:
            raise self.errors[0]


def allocate(cores: int, n_ops: int) -> dict[str, int]:
    """A thread for each tool, the rest to the search (one at least)."""
    return {"generators": n_ops, "search": max(1, cores - n_ops)}


def search_async(session, ops: list[CleaningOperator], df: DataFrame, budget_s: float, max_size: int = 100_000, sampler=iterate):
    """Search what the pool holds, while tools still work; yields the best result so far.

    A tool that sleeps delays nothing: each pass drains what is there and searches.
    """
    pool = RepairPool(max_size)
    gen = AsyncGenerators(ops, pool, sampler)
    gen.start(df)
    began, best = time.monotonic(), None
    while time.monotonic() - began < budget_s:
        alive = gen.running()  # before draining: a tool may put its last batch and end meanwhile
        batches = pool.drain()
        for b in batches:
            session.add(b)
        if batches:
            for result in session.iter():  # each round that improves, not only the last
                if best is None or result.cost < best.cost:
                    best = result
                    yield best
        elif not alive:
            break
        else:
            time.sleep(0.05)
    gen.stop.set()
    for b in pool.drain():
        del b
    gen.join()

"""Block-wise search in waves, with a pruner learnt between them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..learn.pruner import Pruner, label_examples
from ..quality.quality import Quality
from ..session import written
from .engine import Session


def search_waves(df: DataFrame, quality: Quality, pool: DataFrame, pruner: Pruner | None = None, warmup: float = 0.2, waves: int = 4, key: str = "rec_id", **options) -> tuple[DataFrame, DataFrame, Pruner | None, list[dict]]:
    """Search every block of ``df`` (a column ``block``); all blocks of a wave advance in
    the same jobs.  The first ``warmup`` of the blocks are searched with the whole
    pool, later waves with what the pruner keeps, refitted after each.

    Returns (cleaned relation, chosen (block, step, unit), pruner, trace rows).
    """
    share = F.pmod(F.xxhash64("block"), F.lit(1000)) / 1000.0
    bounds = [0.0, warmup] + [warmup + (1 - warmup) * i / max(waves - 1, 1) for i in range(1, waves)]
    bounds[-1] = 1.0
    cleaned = chosen = examples = None
    trace: list[dict] = []
    for i in range(len(bounds) - 1):
        part = df.filter((share >= bounds[i]) & (share < bounds[i + 1]))
        if part.isEmpty():
            continue
        keep = pruner.keep if pruner is not None and pruner.active else None
        s = Session(part, quality, key, keep=keep, **options)
        s.add(pool)
        result = s.run()
        block_of = s.rows.select(key, "block")
        out = written(result.cleaned().join(block_of, key), "wave")
        cleaned = out if cleaned is None else cleaned.unionByName(out)
        chosen = result.units if chosen is None else chosen.unionByName(result.units)
        total = pool.select("unit").distinct().count()
        kept = keep(pool).select("unit").distinct().count() if keep else total
        trace += [r | {"wave": i, "n_pruned_model": total - kept} for r in s.trace.rows]
        if pruner is not None:
            tried = s._root.select("block", "unit").distinct()
            got = written(label_examples(tried, result.units), "examples")
            examples = got if examples is None else examples.unionByName(got)
            pruner.fit(examples, pool)
    return cleaned, chosen, pruner, trace

"""Mixing sources to target weights by packed blocks.

Each source's words, its documents in a hashed order, form one stream that is cut
into blocks of ``block_words``.  A source's target of words becomes whole passes
over its blocks and a part of one more.  The output is shards of ``shard_slots``
slots; every shard draws multinomial source counts from what is still due, so the
shards together meet the targets.  A source's k-th slot reads the block that a
keyed pseudorandom permutation gives for it, a new one each pass, and slots and
blocks meet in a join on (source, block).

Defined results: null text has size 0 and is never taken; a null source is a
source of its own, last in order; equal rows are separate documents; an empty
table gives an empty mix.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import NULL_ID, text_hash_unit

WEIGHTS, MOST_REPEATS, BLOCK_WORDS, SHARD_SLOTS = (5.0, 2.0, 1.0), 3.0, 64, 1 << 16
_BUCKETS = 1024
MAX_SOURCES = 100_000
WORD = r"[^\x20\x09-\x0D]+"


def targets(sizes: list[float], weights: list[float], most: float = MOST_REPEATS, total: float | None = None) -> list[float]:
    """Shares of the total by weight; what exceeds ``most`` times a size is shared anew."""
    total = float(sum(sizes)) if total is None else total
    out, open_ = [0.0] * len(sizes), {i for i, w in enumerate(weights) if w > 0}
    left = total
    while open_:
        weight = sum(weights[i] for i in open_)
        over = {i for i in open_ if left * weights[i] / weight > most * sizes[i]}
        if not over:
            for i in open_:
                out[i] = left * weights[i] / weight
            break
        for i in over:
            out[i] = most * sizes[i]
            left -= out[i]
        open_ -= over
    return out


def draw_shards(slots: np.ndarray, shard_slots: int, seed: int) -> np.ndarray:
    """Source counts of each shard: multinomial draws from the slots still due.

    A draw above what a source still has is cut to it and the rest drawn again.
    """
    rng = np.random.default_rng(seed)
    due, shards = slots.astype(np.int64).copy(), []
    while due.sum():
        need, got = min(shard_slots, int(due.sum())), np.zeros_like(due)
        while need:
            left = due - got
            got += np.minimum(rng.multinomial(need, left / left.sum()), left)
            need = min(shard_slots, int(due.sum())) - int(got.sum())
        shards.append(got)
        due -= got
    return np.array(shards, dtype=np.int64).reshape(len(shards), len(slots))


def shuffled_index(index, size, *key, rounds: int = 4, walks: int = 64):
    """Image of ``index`` under a keyed bijection of [0, size), as a column.

    The number is written as two digits in base ceil(sqrt(size)); each round adds a
    hash of one digit to the other, which is invertible.  Images outside [0, size)
    are mapped on until inside: there are at most about 2*sqrt(size) such places,
    so 64 steps are a proof for sizes up to 1,000 and certain enough beyond.
    """
    base = F.ceil(F.sqrt(size.cast("double"))).cast("long")

    def once(x):
        high, low = (x / base).cast("long"), F.pmod(x, base)
        for r in range(rounds):
            if r % 2:
                low = F.pmod(low + F.pmod(F.xxhash64(high, F.lit(r), *key), base), base)
            else:
                high = F.pmod(high + F.pmod(F.xxhash64(low, F.lit(r), *key), base), base)
        return high * base + low

    first = once(index)
    walk = F.aggregate(F.sequence(F.lit(1), F.lit(walks)), first, lambda x, _: F.when(x < size, x).otherwise(once(x)))
    return F.when(first < size, first).otherwise(walk)


def mix_documents(
    documents: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    source_col: str = "source",
    weights: tuple[float, ...] = WEIGHTS,
    most: float = MOST_REPEATS,
    block_words: int = BLOCK_WORDS,
    shard_slots: int = SHARD_SLOTS,
    seed: int = 17,
) -> DataFrame:
    """(doc_id, source, size, source_size, target, taken), a row for each document."""
    spark = documents.sparkSession
    docs = documents.select(
        F.col(id_col).cast("long").alias("doc_id"),
        F.col(source_col).cast("string").alias("source"),
        F.coalesce(F.regexp_count(F.col(text_col), F.lit(WORD)), F.lit(0)).cast("long").alias("size"),
    )
    sums = docs.groupBy("source").agg(F.sum("size").alias("size")).limit(MAX_SOURCES + 1).collect()
    if len(sums) > MAX_SOURCES:
        raise ValueError(f"over {MAX_SOURCES} sources: give coarser ones")
    sums = sorted(sums, key=lambda r: (r["source"] is None, (r["source"] or "").encode("utf-8")))
    size = [r["size"] for r in sums]
    goal = targets([float(x) for x in size], [weights[i % len(weights)] for i in range(len(size))], most)
    n_blocks = np.array([-(-x // block_words) for x in size], dtype=np.int64)
    passes = np.array([min(int(g // x), int(most)) if x else 0 for g, x in zip(goal, size, strict=True)], dtype=np.int64)
    rest = np.array([round((g - p * x) / block_words) for g, x, p in zip(goal, size, passes, strict=True)], dtype=np.int64)
    slots = passes * n_blocks + np.where(passes < most, np.minimum(rest, n_blocks), 0)
    plan = spark.createDataFrame(
        [(i, r["source"], int(size[i]), float(goal[i]), int(n_blocks[i])) for i, r in enumerate(sums)], "sid int, source string, source_size long, target double, n_blocks long"
    )

    # Offsets of the documents in their source's stream: bucket sums, then in buckets.
    rows = docs.join(F.broadcast(plan), docs.source.eqNullSafe(plan.source)).drop(plan.source)
    order = F.xxhash64(F.coalesce("doc_id", F.lit(NULL_ID)), F.lit(seed))
    rows = rows.withColumn("bucket", F.pmod(order, F.lit(_BUCKETS)).cast("int")).withColumn("place", order)
    before = rows.groupBy("sid", "bucket").agg(F.sum("size").alias("s"))
    before = before.select("sid", "bucket", (F.sum("s").over(Window.partitionBy("sid").orderBy("bucket")) - F.col("s")).alias("base"))
    inside = Window.partitionBy("sid", "bucket").orderBy("place", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    placed = rows.withColumn("within", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    placed = placed.join(before, ["sid", "bucket"]).withColumn("at", F.col("base") + F.col("within"))

    pieces = placed.filter("size > 0").withColumn("block", F.explode(F.expr(f"sequence(at div {block_words}, (at + size - 1) div {block_words})")))
    pieces = pieces.withColumn("words", F.least(F.col("at") + F.col("size"), (F.col("block") + 1) * block_words) - F.greatest(F.col("at"), F.col("block") * block_words))

    taken_blocks = slot_blocks(spark, draw_shards(slots, shard_slots, seed), n_blocks, seed).groupBy("sid", "block").agg(F.count("*").alias("times"))
    # The slots' size is not known before they are made: never to be broadcast.
    taken = pieces.join(taken_blocks.hint("merge"), ["sid", "block"]).groupBy("sid", "at").agg(F.sum(F.col("words") * F.col("times")).alias("taken"))
    # A stream offset is one document of positive size.
    some = placed.filter("size > 0").join(taken, ["sid", "at"], "left")
    none = placed.filter("size = 0").withColumn("taken", F.lit(0).cast("long"))
    cols = ["doc_id", "source", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken")]
    return some.select(*cols).unionByName(none.select(*cols))


def slot_blocks(spark, shards: np.ndarray, n_blocks: np.ndarray, seed: int) -> DataFrame:
    """(shard, slot, sid, block) of every output slot, made on the executors.

    A row for each (shard, source) is spread into its slots; the slot's ordinal in
    the source gives the pass and, through that pass's permutation, the block.
    """
    first = np.cumsum(shards, axis=0) - shards if len(shards) else shards
    rows = [(int(i), int(j), int(first[i, j]), int(shards[i, j]), int(n_blocks[j])) for i, j in zip(*np.nonzero(shards), strict=True)]
    draws = spark.createDataFrame(rows, "shard long, sid int, first long, n long, n_blocks long")
    draws = draws.repartition(max(1, min(len(rows), 2 * spark.sparkContext.defaultParallelism)), "shard", "sid")
    slots = draws.withColumn("k", F.explode(F.expr("sequence(first, first + n - 1)"))).withColumn("pass", F.expr("k div n_blocks")).withColumn("index", F.expr("k % n_blocks"))
    return slots.withColumn("block", shuffled_index(F.col("index"), F.col("n_blocks"), F.col("sid"), F.col("pass"), F.lit(seed)))


def mixed_corpus(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", seed: int = 17, **options) -> DataFrame:
    """The documents as the mix takes them: each row as often as its words are taken.

    A part of a document's words taken is rounded to whole copies with that chance,
    by a hash, so sources keep their totals; documents without words stay once.
    """
    mix = mix_documents(documents, id_col, text_col, source_col, seed=seed, **options).filter("size > 0")
    unit = text_hash_unit(F.coalesce("doc_id", F.lit(NULL_ID)), F.lit(seed + 1))
    mix = mix.groupBy("doc_id", "source", "size").agg((F.sum("taken") / F.count("*") / F.col("size")).alias("rate"))
    mix = mix.select(F.col("doc_id").alias("_mix_id"), F.col("source").alias("_mix_source"), F.col("size").alias("_mix_size"), F.floor(F.col("rate") + unit).cast("int").alias("_mix_copies"))
    size = F.coalesce(F.regexp_count(F.col(text_col), F.lit(WORD)), F.lit(0)).cast("long")
    sized = documents.withColumn("_mix_n", size)
    meets = sized[id_col].cast("long").eqNullSafe(mix["_mix_id"]) & sized[source_col].cast("string").eqNullSafe(mix["_mix_source"]) & (sized["_mix_n"] == mix["_mix_size"])
    rows = sized.join(mix, meets, "left").withColumn("_mix_copies", F.when(F.col("_mix_n") == 0, 1).otherwise(F.coalesce("_mix_copies", F.lit(0))))
    rows = rows.filter("_mix_copies > 0").withColumn("_mix_copy", F.explode(F.sequence(F.lit(1), F.col("_mix_copies"))))
    return rows.select(*documents.columns)

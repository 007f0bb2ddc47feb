"""Benchmark decontamination: rare n-gram seeds, then local alignment.

The word n-grams of the test items that stand in at most ``rare_items`` items, and not
of the ``common_words`` most frequent words of all items alone, are seeds; an item left
without one keeps all of its n-grams.  Documents are scanned once, however many items
there are: those that hold a seed go on with their word hashes, and seeds join them to
the items.  A document and an item are aligned by Smith-Waterman over words, in windows
around the places where the seeds would put the item; the score is the share of the
item's best possible score.

The distinct seeds are sent to the scan as a filter if their number is below a checked
bound; beyond it every n-gram goes to the join.  Hot seeds and items are joined by
broadcast, of which there are at most ``HOT_SHARE``.

Defined results: null or empty texts match nothing, null or empty items are in no text;
items of fewer than ``seed`` words are found whole; equal items are reported under each
id, rows that repeat a document's id and text once; null ids stay null; of equally good
spans of an item the first is reported; empty tables give no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .common import NULL_ID, join_unique, materialize, small_batches

MATCH, MISMATCH, GAP = 2, -1, -1
#: A passage that scores as so many equal words is found, however long its item.
EXCERPT_WORDS = 50
#: At most so many distinct seeds are sent to the scan as a filter (8 bytes each).
FILTER_SEEDS = 4_000_000
#: At most so many documents found are broadcast to take them out; beyond it a join.
FEW_FOUND = 500_000


def smith_waterman(item: np.ndarray, text: np.ndarray) -> tuple[int, int, int]:
    """Best local score and the text span [start, end) it covers.

    Row by row over the item; gaps along the text are a running maximum.
    """
    n = len(text)
    steps = -GAP * np.arange(1, n + 1)
    prev, origin = np.zeros(n + 1, np.int64), np.arange(n + 1)
    best = (0, 0, 0)
    for w in item:
        diag = prev[:-1] + np.where(text == w, MATCH, MISMATCH)
        up = prev[1:] + GAP
        cell = np.maximum(diag, up)
        start = np.where(diag >= up, origin[:-1], origin[1:])
        fresh = cell <= 0
        cell = np.where(fresh, 0, cell)
        start = np.where(fresh, np.arange(1, n + 1), start)
        lifted = cell + steps
        run = np.maximum.accumulate(lifted)
        source = np.maximum.accumulate(np.where(lifted == run, np.arange(n), 0))
        score = run - steps
        prev = np.concatenate(([0], score))
        origin = np.concatenate(([0], np.where(score > cell, start[source], start)))
        top = int(np.argmax(score))
        if score[top] > best[0]:
            best = (int(score[top]), int(origin[top + 1]), top + 1)
    return best


def align_item(item: np.ndarray, words: np.ndarray, begin: np.ndarray, seed: int) -> tuple[int, int, int]:
    """Best alignment of an item in the windows where its seeds would put it to begin."""
    slack = len(item) // 2 + seed
    best = (0, 0, 0)
    begin = np.unique(begin)
    cut = np.flatnonzero(np.diff(begin) > 2 * slack + len(item)) + 1
    for group in np.split(begin, cut):
        a, b = max(0, int(group[0]) - slack), min(len(words), int(group[-1]) + len(item) + slack)
        for lo in range(a, b, 50 * len(item) + 1000):  # long runs of seeds in overlapping pieces
            score, s, e = smith_waterman(item, words[lo : min(b, lo + 50 * len(item) + 1000 + 2 * len(item))])
            best = max(best, (score, s + lo, e + lo), key=lambda x: x[0])
    return best


def sized_grams(words: np.ndarray, n: int) -> np.ndarray:
    """Hashes of the n-grams, different for each n."""
    return K.mix64(K.ngram_hashes(words, n) + np.uint64(n))


def frequent_words(items: DataFrame, n: int) -> set[int]:
    """Hashes of the ``n`` most frequent words of all items."""

    def run(batches):
        for batch in batches:
            words = [K.text_words(t.as_py()).view(np.int64) for t in batch.column(0)]
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([*words, np.zeros(0, np.int64)]))], ["word"])

    counts = small_batches(items).select("text").mapInArrow(run, "word long").groupBy("word").count()
    return {r["word"] % (1 << 64) for r in counts.orderBy(F.desc("count"), "word").limit(n).collect()}


def item_seeds(items: DataFrame, seed: int, frequent: set[int], rare_items: int) -> DataFrame:
    """(seed, item, place, n): the seeds of the items (item long, text), n words each."""
    usual = np.array(sorted(frequent), dtype=np.uint64)

    def run(batches):
        for batch in batches:
            out = [[np.zeros(0, np.int64)] for _ in range(5)]
            for item, text in zip(batch.column("item").to_pylist(), batch.column("text"), strict=True):
                words = K.text_words(text.as_py())
                n = min(seed, len(words))
                grams = sized_grams(words, n) if n else np.zeros(0, np.uint64)
                plain = np.convolve(np.isin(words, usual), np.ones(n, int), "valid") == n if n else np.zeros(0, bool)
                for o, c in zip(out, (grams.view(np.int64), np.full(len(grams), item), np.arange(len(grams)), np.full(len(grams), n), plain), strict=True):
                    o.append(c)
            seeds, item, place, n, plain = (np.concatenate(o) for o in out)
            yield pa.RecordBatch.from_arrays([pa.array(seeds), pa.array(item), pa.array(place.astype(np.int32)), pa.array(n.astype(np.int32)), pa.array(plain.astype(bool))], ["seed", "item", "place", "n", "plain"])

    grams = materialize(small_batches(items).select("item", "text").mapInArrow(run, "seed long, item long, place int, n int, plain boolean"), "item-grams")
    df = grams.groupBy("seed").agg(F.count_distinct("item").alias("items"))
    rare = grams.join(df, "seed").withColumn("rare", (F.col("items") <= rare_items) & ~F.col("plain"))
    some = rare.groupBy("item").agg(F.max("rare").alias("some"))
    return materialize(rare.join(some, "item").filter("rare or not some").select("seed", "item", "place", "n"), "item-seeds")


def _matches(documents: DataFrame, benchmark: DataFrame, id_col: str, text_col: str, item_col: str, item_text_col: str, seed: int, common_words: int, rare_items: int, threshold: float) -> DataFrame:
    """(rid, mark, doc_id, item_id, score, word_start, word_end) of the items found."""
    spark = documents.sparkSession
    items = benchmark.select(F.col(item_col).cast("long").alias("item_id"), F.col(item_text_col).alias("text")).filter("text is not null").distinct().withColumn("item", F.xxhash64("item_id", "text"))
    seeds = item_seeds(items, seed, frequent_words(items, common_words), rare_items)
    sizes = sorted(r["n"] for r in seeds.select("n").distinct().collect())  # at most ``seed`` values
    few = [r["seed"] for r in seeds.select("seed").distinct().limit(FILTER_SEEDS + 1).toLocalIterator()]
    sent = spark.sparkContext.broadcast(np.sort(np.array(few, dtype=np.int64))) if len(few) <= FILTER_SEEDS else None

    def scan(batches):
        schema = pa.schema([("rid", pa.int64()), ("mark", pa.int64()), ("doc_id", pa.int64()), ("words", pa.binary()), ("seeds", pa.list_(pa.int64())), ("places", pa.list_(pa.int32()))])
        for batch in batches:
            out = []
            for rid, mark, doc, text in zip(*(batch.column(c) for c in ("rid", "mark", "doc_id", "text")), strict=True):
                words = K.text_words(text.as_py())
                grams = [sized_grams(words, n).view(np.int64) for n in sizes]
                places = np.concatenate([np.zeros(0, np.int64), *(np.arange(len(g)) for g in grams)])
                grams = np.concatenate([np.zeros(0, np.int64), *grams])
                if sent is not None:
                    known = sent.value
                    at = np.flatnonzero(known[np.minimum(np.searchsorted(known, grams), len(known) - 1)] == grams) if len(known) else np.zeros(0, np.int64)
                    grams, places = grams[at], places[at]
                if len(grams):
                    out.append((rid.as_py(), mark.as_py(), doc.as_py(), words.tobytes(), grams, places.astype(np.int32)))
            yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], f.type) for i, f in enumerate(schema)], schema=schema)

    docs = small_batches(documents).select(
        F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID)).alias("rid"), F.xxhash64(F.col(text_col)).alias("mark"), F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")
    )
    hits = materialize(docs.mapInArrow(scan, "rid long, mark long, doc_id long, words binary, seeds array<long>, places array<int>"), "seed-hits")
    places = hits.select("rid", "mark", F.inline(F.arrays_zip(F.col("seeds").alias("seed"), F.col("places").alias("at"))))
    often = places.groupBy("seed").agg(F.count("*").alias("times"))
    posts = seeds.groupBy("seed").agg(F.collect_list(F.struct("item", "place")).alias("posts")).join(often, "seed")
    total = max(1, hits.agg(F.sum(F.size("seeds"))).first()[0] or 0)
    met = join_unique(places, posts, "seed", total, "times").select("rid", "mark", "at", F.inline("posts"))
    pairs = materialize(met.groupBy("rid", "mark", "item").agg(F.collect_set(F.col("at") - F.col("place")).alias("begin")), "seed-pairs")
    held = items.join(pairs.groupBy("item").agg(F.count("*").alias("times")), "item").withColumnRenamed("text", "item_text")
    pairs = join_unique(pairs, held, "item", max(1, pairs.count()), "times").select("rid", "mark", "item_id", "item_text", "begin")
    both = pairs.join(hits.select("rid", "mark", "doc_id", "words").dropDuplicates(["rid", "mark"]), ["rid", "mark"])

    def align(batches):
        schema = pa.schema([("rid", pa.int64()), ("mark", pa.int64()), ("doc_id", pa.int64()), ("item_id", pa.int64()), ("score", pa.float64()), ("word_start", pa.int64()), ("word_end", pa.int64())])
        for batch in batches:
            out = []
            for rid, mark, doc, item, text, begin, words in zip(*(batch.column(c) for c in ("rid", "mark", "doc_id", "item_id", "item_text", "begin", "words")), strict=True):
                wanted, words = K.text_words(text.as_py()), np.frombuffer(words.as_py(), dtype=np.uint64)
                begin = begin.values.to_numpy()
                if len(wanted) < seed:  # found whole, at the first place
                    best = (MATCH * len(wanted), int(begin.min()), int(begin.min()) + len(wanted))
                else:
                    best = align_item(wanted, words, begin, seed)
                share = best[0] / (MATCH * len(wanted))
                if share >= threshold or best[0] >= MATCH * EXCERPT_WORDS:
                    out.append((rid.as_py(), mark.as_py(), doc.as_py(), item.as_py(), share, best[1], best[2]))
            yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], f.type) for i, f in enumerate(schema)], schema=schema)

    return both.mapInArrow(align, "rid long, mark long, doc_id long, item_id long, score double, word_start long, word_end long")


def contaminated(
    documents: DataFrame,
    benchmark: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    item_col: str = "item_id",
    item_text_col: str = "text",
    seed: int = 5,
    common_words: int = 40,
    rare_items: int = 8,
    threshold: float = 0.5,
) -> DataFrame:
    """Rows (doc_id, item_id, score, word_start, word_end) of items found in documents."""
    return _matches(documents, benchmark, id_col, text_col, item_col, item_text_col, seed, common_words, rare_items, threshold).drop("rid", "mark")


def drop_contaminated(documents: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", seed: int = 5, common_words: int = 40, rare_items: int = 8, threshold: float = 0.5) -> DataFrame:
    """The documents, all columns and repeated rows, in which no item is found."""
    found = _matches(documents, benchmark, id_col, text_col, "item_id", "text", seed, common_words, rare_items, threshold)
    found = materialize(found.select(F.col("rid").alias("_rid"), F.col("mark").alias("_mark")).distinct(), "contaminated")
    if found.count() <= FEW_FOUND:
        found = F.broadcast(found)
    rows = documents.withColumn("_rid", F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID))).withColumn("_mark", F.xxhash64(F.col(text_col)))
    return rows.join(found, ["_rid", "_mark"], "left_anti").select(*[F.col(f"`{c}`") for c in documents.columns])

"""Document fingerprints by consistent weighted sampling.

A text is its word n-grams with their counts as weights.  For each of ``samples``
positions every term draws two Gamma(2, 1) variables and a uniform one, all
functions of the term and the position; they give a level below the term's weight
and a rank, and the term of least rank is the sample, together with its level.
Two texts agree at a position with the generalised Jaccard probability, the sum
of least over the sum of largest weights, so the share of agreeing positions
estimates it without bias.

Defined results: null and empty texts have no terms and one common fingerprint;
texts of fewer than n words are one term; equal texts have equal fingerprints.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .common import NULL_ID, small_batches

SAMPLES, NGRAM = 64, 3
_KEPT_TERMS = 50_000


class Sampler:
    def __init__(self, samples: int = SAMPLES, ngram: int = NGRAM):
        self.samples, self.ngram = samples, ngram
        rng = np.random.default_rng(1105)
        self.keys = rng.integers(0, 1 << 63, samples, dtype=np.uint64)

    def terms(self, text: str | None) -> tuple[np.ndarray, np.ndarray]:
        words = K.text_words(text)
        if not len(words):
            return np.empty(0, np.uint64), np.empty(0, np.int64)
        return np.unique(K.ngram_hashes(words, min(self.ngram, len(words))), return_counts=True)

    def _draws(self, terms: np.ndarray, keys: np.ndarray):
        """Gamma r, gamma c and uniform b of each term (row) at each key (column)."""
        v = terms ^ keys
        v *= np.uint64(0xBF58476D1CE4E5B9)
        v ^= v >> np.uint64(29)
        v *= np.uint64(0x94D049BB133111EB)
        v ^= v >> np.uint64(32)
        u = v[..., None].view(np.uint16).astype(np.float32)
        u += np.float32(0.5)
        u *= np.float32(2**-16)
        r = -np.log(u[..., 0] * u[..., 1])
        c = -np.log(u[..., 2] * u[..., 3])
        v *= np.uint64(0x9E3779B97F4A7C15)
        b = (v >> np.uint64(40)).astype(np.float32) * np.float32(2**-24)
        return r, c, b

    def ranks(self, terms: np.ndarray, weights: np.ndarray) -> np.ndarray:
        """Log rank of each term at each position."""
        r, c, b = self._draws(terms[:, None], self.keys)
        log_w = np.log(weights.astype(np.float32))
        level = np.zeros_like(b)
        many = np.flatnonzero(weights > 1)
        level[many] = np.floor(log_w[many, None] / r[many] + b[many])
        return np.log(c) - r * (level - b) - r

    def least(self, terms: np.ndarray, weights: np.ndarray, ranks: np.ndarray | None = None):
        """(rank, term, weight) of the least term at each position; long texts in pieces."""
        best = np.full(self.samples, np.inf, dtype=np.float32), np.zeros(self.samples, np.uint64), np.ones(self.samples, np.int64)
        for lo in range(0, len(terms), 4096):
            part = self.ranks(terms[lo : lo + 4096], weights[lo : lo + 4096]) if ranks is None else ranks[lo : lo + 4096]
            at = np.argmin(part, axis=0)
            best = self.lesser(best, (part[at, np.arange(self.samples)], terms[lo + at], weights[lo + at]))
        return best

    @staticmethod
    def lesser(a, b):
        # Equal ranks: the lesser term hash, so the order of pieces does not matter.
        take = (b[0] < a[0]) | ((b[0] == a[0]) & (b[1] < a[1]))
        return tuple(np.where(take, y, x) for x, y in zip(a, b, strict=True))

    def codes(self, best) -> np.ndarray:
        """16-bit codes of (term, level) at each position."""
        rank, term, weight = best
        r, _, b = self._draws(term, self.keys)
        level = np.floor(np.log(weight.astype(np.float32)) / r + b).astype(np.int64)
        code = K.mix64(term ^ (level.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)))
        return np.where(np.isfinite(rank), code & np.uint64(0xFFFF), 0).astype(">u2")


class Signed:
    """A text with its terms, their ranks (if not too many) and its fingerprint."""

    def __init__(self, sampler: Sampler, text: str | None):
        self.text = text or ""
        self.terms, self.weights = sampler.terms(self.text)
        self.ranks = sampler.ranks(self.terms, self.weights) if len(self.terms) <= _KEPT_TERMS else None
        self.codes = sampler.codes(sampler.least(self.terms, self.weights, self.ranks))


def edited_text(text: str, other: str) -> str:
    """The last half of the code points replaced by as many of the other text (or all)."""
    half = len(text) // 2
    return text[: len(text) - half] + other[:half]


def edited_codes(sampler: Sampler, text: str, a: Signed, b: Signed) -> np.ndarray:
    """Fingerprint of an edited text, taking known ranks from its two sources."""
    terms, weights = sampler.terms(text)
    best = sampler.least(terms[:0], weights[:0])
    todo = np.ones(len(terms), dtype=bool)
    for s in (a, b):
        if s.ranks is None or not len(s.terms):
            continue
        at = np.minimum(np.searchsorted(s.terms, terms), len(s.terms) - 1)
        same = todo & (s.terms[at] == terms) & (s.weights[at] == weights)
        best = sampler.lesser(best, sampler.least(terms[same], weights[same], s.ranks[at[same]]))
        todo &= ~same
    return sampler.codes(sampler.lesser(best, sampler.least(terms[todo], weights[todo])))


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    return float((a == b).mean())


def fingerprint(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text", samples: int = SAMPLES, ngram: int = NGRAM) -> DataFrame:
    """(doc_id, n_chars, fingerprint): hex of ``samples`` 16-bit codes."""
    docs = small_batches(documents).select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))

    def run(batches):
        sampler = Sampler(samples, ngram)
        for batch in batches:
            texts = batch.column(1).to_pylist()
            prints = [sampler.codes(sampler.least(*sampler.terms(t))).tobytes().hex() for t in texts]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(t or "") for t in texts], pa.int64()), pa.array(prints, pa.string())], ["doc_id", "n_chars", "fingerprint"])

    return docs.mapInArrow(run, "doc_id long, n_chars long, fingerprint string")


def with_next(documents: DataFrame, id_col: str, text_col: str, rows_per_range: int) -> DataFrame:
    """Rows (bucket, helper, rid, named, text) such that a bucket, sorted by helper and
    descending id, holds each document followed by the next one of the whole table.

    Buckets are ranges of ids; the greatest rows of a bucket also go, as helpers, to
    the bucket above it, and those of the top bucket to the lowest.
    """
    docs = small_batches(documents).select(F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID)).alias("rid"), F.col(id_col).isNotNull().alias("named"), F.col(text_col).alias("text"))
    parts = max(1, -(-docs.count() // rows_per_range))
    cuts = docs.stat.approxQuantile("rid", [i / parts for i in range(1, parts)], 0.2 / parts) if parts > 1 else []
    bounds = np.unique(np.array(cuts, dtype=np.int64))  # bucket i: bounds[i-1] <= id < bounds[i]
    spark = documents.sparkSession
    shared = spark.sparkContext.broadcast(bounds)

    def most(batches):
        for batch in batches:
            rid = batch.column(0).to_numpy()
            bucket = np.searchsorted(shared.value, rid, side="right")
            order = np.lexsort((rid, bucket))
            last = np.flatnonzero(np.append(np.diff(bucket[order]) != 0, True)) if len(rid) else order
            yield pa.RecordBatch.from_arrays([pa.array(bucket[order][last], pa.int32()), pa.array(rid[order][last], pa.int64())], ["bucket", "top"])

    tops = docs.select("rid").mapInArrow(most, "bucket int, top long").groupBy("bucket").agg(F.max("top").alias("top")).collect()  # one row a range
    tops = sorted((r["bucket"], r["top"]) for r in tops)
    helps = spark.sparkContext.broadcast({top: tops[(i + 1) % len(tops)][0] for i, (_, top) in enumerate(tops)})

    def deal(batches):
        for batch in batches:
            rid = batch.column("rid").to_numpy()
            bucket = np.searchsorted(shared.value, rid, side="right")
            extra = [i for i, x in enumerate(rid.tolist()) if x in helps.value]
            for at, where, helper in ((None, bucket, False), (extra, [helps.value[int(rid[i])] for i in extra], True)):
                rows = batch if at is None else batch.take(pa.array(at, pa.int64()))
                if rows.num_rows:
                    yield pa.RecordBatch.from_arrays([pa.array(where, pa.int32()), pa.array([helper] * rows.num_rows), *rows.columns], ["bucket", "helper", "rid", "named", "text"])

    dealt = docs.mapInArrow(deal, "bucket int, helper boolean, rid long, named boolean, text string")
    return dealt.repartition("bucket").sortWithinPartitions(F.col("bucket"), F.col("helper"), F.col("rid").desc(), F.xxhash64("text"))


def compare_edited(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text", samples: int = SAMPLES, ngram: int = NGRAM, rows_per_range: int = 2048) -> DataFrame:
    """Fingerprints of each document, of its edited text and their likeness."""

    def run(batches):
        sampler = Sampler(samples, ngram)
        before = None  # (bucket, helper, rid, signed text) waiting for its next
        schema = pa.schema([("doc_id", pa.int64()), ("n_chars", pa.int64()), ("edited_sha256", pa.string()), ("fingerprint", pa.string()), ("edited_fingerprint", pa.string()), ("near_edited", pa.float64()), ("near_next", pa.float64())])
        for batch in batches:
            out = []
            for bucket, helper, rid, named, text in zip(*(batch.column(c).to_pylist() for c in ("bucket", "helper", "rid", "named", "text")), strict=True):
                if before and before[0] == bucket and before[1] and helper:
                    continue  # more helpers of the same id
                now = Signed(sampler, text)
                if before and before[0] == bucket and not before[1]:
                    a = before[3]
                    new = edited_text(a.text, now.text)
                    codes = edited_codes(sampler, new, a, now)
                    digest = hashlib.sha256(new.encode("utf-8", "surrogatepass")).hexdigest()
                    out.append((before[2], len(a.text), digest, a.codes.tobytes().hex(), codes.tobytes().hex(), likeness(a.codes, codes), likeness(a.codes, now.codes)))
                before = (bucket, helper, rid if named else None, now)
            yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], f.type) for i, f in enumerate(schema)], schema=schema)

    dealt = with_next(documents, id_col, text_col, rows_per_range)
    return dealt.mapInArrow(run, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")

"""Fuzzy substring deduplication by seeds, collinear chains and alignment.

Seeds are word k-mers at the minimizers of each text.  A seed found in several
documents ties each of them to the first one that holds it, the pivot: as many
ties as occurrences, never all pairs.  The ties of a pair of documents are chained
in order, best first score with gap costs by a tree of maxima over the window that a
gap may reach, and what lies between the seeds of a chain is aligned word by word.  Chains of enough
words at enough identity are passages; passages of a document are merged, and the
ones over ``min_words`` are reported against the pivots they repeat.

A seed is first tied inside a task, so that however many documents hold it, one row
a task goes on to meet the others.  Seeds carry two bits of each of the words beside
them: a chain of a single seed goes on to be aligned only if the words before it or
those after it mostly agree, which chance does for one pair of places in twenty.

Defined results: null and empty texts have no passage; of equal texts all but the
first are reported as repeats of a whole text; rows that repeat an id are one
document and do not repeat each other; null ids stay null, one document for each
text.  Spans are code points, end exclusive.
"""

from __future__ import annotations

from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import kernels as K
from .common import NULL_ID, small_batches

SEED_WORDS, WINDOW, MIN_WORDS, PART_WORDS, IDENTITY = 5, 4, 50, 25, 0.7
_GAP = 60


class RangeMax:
    """Tree of the maxima of (score, index) over ranges of places; places can be emptied."""

    def __init__(self, n: int):
        self.n = n
        self.best = [(-1e18, -1)] * (2 * n)

    def put(self, i: int, score: float = -1e18, index: int = -1) -> None:
        best, i = self.best, i + self.n
        best[i] = (score, index)
        while i > 1:
            i >>= 1
            best[i] = max(best[2 * i], best[2 * i + 1])

    def within(self, lo: int, hi: int) -> tuple[float, int]:
        """Best among places lo <= i < hi."""
        best, out, lo, hi = self.best, (-1e18, -1), lo + self.n, hi + self.n
        while lo < hi:
            if lo & 1:
                out, lo = max(out, best[lo]), lo + 1
            if hi & 1:
                hi -= 1
                out = max(out, best[hi])
            lo, hi = lo >> 1, hi >> 1
        return out


def seed_runs(pa_: np.ndarray, pb: np.ndarray, k: int, reach: int) -> np.ndarray:
    """Merge seeds on one diagonal that follow within ``reach``: rows (a, b, length)."""
    order = np.lexsort((pb, pa_ - pb))
    a, b = pa_[order], pb[order]
    new = np.ones(len(a), dtype=bool)
    new[1:] = ((a - b)[1:] != (a - b)[:-1]) | (np.diff(b) > reach)
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(a)) - 1
    return np.stack((a[first], b[first], b[last] - b[first] + k), axis=1)


def chains(runs: np.ndarray, gap: int = _GAP, gap_cost: float = 0.5) -> list[np.ndarray]:
    """Disjoint collinear chains of runs (a, b, length), best first.

    A run may follow another that ends before it in both texts and by at most
    ``gap`` words in each; what it gains is the other's score less the words between
    them.  Runs are taken in order of their start in a: those that ended more than
    ``gap`` words before it leave the tree, and the tree over the ends in b is asked for
    the best of the window of ``gap`` words.  Chains that share a run are cut where the
    better one has it.
    """
    n = len(runs)
    if n == 1:
        return [runs]
    runs = runs[np.lexsort((runs[:, 1], runs[:, 0]))]
    end_a, end_b = runs[:, 0] + runs[:, 2], runs[:, 1] + runs[:, 2]
    by_a, by_b = np.argsort(end_a, kind="stable"), np.argsort(end_b, kind="stable")
    place = np.empty(n, dtype=np.int64)
    place[by_b] = np.arange(n)
    lo = np.searchsorted(end_b[by_b], runs[:, 1] - gap).tolist()
    hi = np.searchsorted(end_b[by_b], runs[:, 1], side="right").tolist()
    old = np.searchsorted(end_a[by_a], runs[:, 0] - gap).tolist()
    new = np.searchsorted(end_a[by_a], runs[:, 0], side="right").tolist()
    by_a, place, worth = by_a.tolist(), place.tolist(), (gap_cost * (end_a + end_b) / 2).tolist()
    tree, gone, done = RangeMax(n), 0, 0
    score, back = [0.0] * n, [-1] * n
    for i, (a, b, m) in enumerate(runs.tolist()):
        for j in by_a[done : new[i]]:
            tree.put(place[j], score[j] + worth[j], j)
        for j in by_a[gone : old[i]]:
            tree.put(place[j])
        done, gone = new[i], old[i]
        value, j = tree.within(lo[i], hi[i])
        gain = value - gap_cost * (a + b) / 2
        score[i], back[i] = (m + gain, j) if j >= 0 and gain > 0 else (m, -1)
    used, out = [False] * n, []
    for i in sorted(range(n), key=lambda i: -score[i]):
        path = []
        while i >= 0 and not used[i]:
            used[i] = True
            path.append(i)
            i = back[i]
        if path:
            out.append(runs[path[::-1]])
    return out


def common_words(a: np.ndarray, b: np.ndarray) -> int:
    """Longest common subsequence of two short word arrays, by rows."""
    if not len(a) or not len(b):
        return 0
    row = np.zeros(len(b) + 1, dtype=np.int64)
    for w in a:
        hit = np.where(b == w, row[:-1] + 1, 0)
        row[1:] = np.maximum.accumulate(np.maximum(row[1:], hit))
    return int(row[-1])


@cache
def _skips(slack: int) -> list[tuple[int, int]]:
    return sorted(((p, q) for p in range(slack + 1) for q in range(slack + 1) if p or q), key=lambda s: (max(s), abs(s[0] - s[1])))


def extend(a: np.ndarray, b: np.ndarray, i: int, j: int, step: int, slack: int = 2) -> tuple[int, int, int]:
    """Extend an end of a chain over equal words, past at most ``slack`` unequal ones in
    a row, or more on one side than on the other where two equal words follow; returns
    the new ends and the words matched."""
    at = 1 if step > 0 else 0
    a, b = (a[i:], b[j:]) if step > 0 else (a[:i][::-1], b[:j][::-1])
    a, b = a.tolist(), b.tolist()
    skips, n, m = _skips(slack), len(a), len(b)
    good, x, y = 0, 0, 0
    while True:
        while x < n and y < m and a[x] == b[y]:
            good, x, y = good + 1, x + 1, y + 1
        for p, q in skips:
            u, v = x + p, y + q
            if u < n and v < m and a[u] == b[v] and (p == q or u + 1 < n and v + 1 < m and a[u + 1] == b[v + 1]):
                x, y = u, v
                break
        else:
            return (i + x, j + y, good) if at else (i - x, j - y, good)


def align_chain(chain: np.ndarray, a: np.ndarray, b: np.ndarray) -> tuple[int, int, int, int, int]:
    """Span of a chain in both texts and its matched words, gaps aligned, ends extended."""
    matched, at = 0, None
    for x, y, m in chain.tolist():
        if at is not None:
            matched += common_words(a[at[0] : x], b[at[1] : y])
        matched += int((a[x : x + m] == b[y : y + m]).sum())
        at = (x + m, y + m)
    a0, b0, more = extend(a, b, int(chain[0, 0]), int(chain[0, 1]), -1)
    a1, b1, most = extend(a, b, at[0], at[1], 1)
    return a0, a1, b0, b1, matched + more + most


_BESIDE, _AGREE = 8, 5
#: Of a seed's hash 48 bits are kept, and 16 of a word's in what is aligned: what is equal
#: by chance only is a single seed, or a word in 65,536, and passes no alignment.
_SEED_BITS = np.uint64(0xFFFFFFFFFFFF0000)


def beside(bits: np.ndarray, where: np.ndarray, seed_words: int) -> np.ndarray:
    """Two bits of each of the eight words before and after the seeds at ``where``; ``bits``
    has those of each word after eight zeros."""
    out = np.zeros(len(where), dtype=np.uint32)
    for i in range(_BESIDE):
        out |= bits[where + _BESIDE - 1 - i] << np.uint32(2 * i)
        out |= bits[where + _BESIDE + seed_words + i] << np.uint32(2 * (_BESIDE + i))
    return out.view(np.int32)


def agreeing(one: np.ndarray, two: np.ndarray) -> np.ndarray:
    """Whether five of the eight words on either side agree, by their two bits."""
    differ = one.view(np.uint32) ^ two.view(np.uint32)
    equal = ~(differ | differ >> np.uint32(1)) & np.uint32(0x55555555)
    half = np.uint32((1 << 2 * _BESIDE) - 1)
    return (np.bitwise_count(equal & half) >= _AGREE) | (np.bitwise_count(equal & ~half) >= _AGREE)


def local_ties(seed: np.ndarray, node: np.ndarray, place: np.ndarray, context: np.ndarray) -> tuple[np.ndarray, ...]:
    """Sort seeds by (seed, node, place) and tie each to the first of its seed.

    Returns the sorted arrays with the pivot's node and place for each row, and whether
    the words beside both agree.
    """
    before, after = node[:-1], node[1:]
    listed = bool(((before < after) | ((before == after) & (place[:-1] <= place[1:]))).all())  # mostly: ids rise in a file
    order = np.argsort(seed, kind="stable") if listed else np.lexsort((place, node, seed))
    seed, node, place, context = seed[order], node[order], place[order], context[order]
    first = np.ones(len(seed), dtype=bool)
    first[1:] = seed[1:] != seed[:-1]
    head = np.maximum.accumulate(np.where(first, np.arange(len(seed)), 0))
    return seed, node, place, context, node[head], place[head], agreeing(context, context[head])


def seeds_of(texts: list[str], seed_words: int, window: int) -> tuple[np.ndarray, ...]:
    """Seeds of several texts in one pass: (text's number, seed, place, context)."""
    parts = [t.encode("utf-8", "surrogatepass") for t in texts]
    data = np.frombuffer(b" ".join(parts), dtype=np.uint8)
    starts, ends = K.word_bounds(data)
    words = K.hash_words(data, starts, ends)
    bound = np.cumsum([0] + [len(t) + 1 for t in parts])
    first = np.searchsorted(starts, bound)  # of each text its first word, and of all the last one's end
    count = np.diff(first)
    at = np.arange(len(words))
    left = np.repeat(first[1:], count) - at - seed_words  # grams of the text behind the one at a word; negative: none there
    grams = np.full(len(words) + window, ~np.uint64(0), dtype=np.uint64)
    grams[: max(len(words) - seed_words + 1, 0)] = K.ngram_hashes(words, seed_words)
    grams[: len(words)][left < 0] = ~np.uint64(0)
    # A window lies in a text, or starts at the first word of one with fewer grams; ties go to the first.
    here = np.flatnonzero((left >= window - 1) | ((left >= 0) & (at == np.repeat(first[:-1], count))))
    least, where = grams[here], here.copy()
    for i in range(1, window):
        other = grams[here + i]
        less = other < least
        least[less], where[less] = other[less], here[less] + i
    where = where[np.diff(where, prepend=-1) > 0]  # the places of the minima of successive windows never fall
    text = np.searchsorted(first, where, side="right") - 1
    # Two bits of each word; a text ends in zeros, which the words beside a seed reach into.
    bits = np.zeros(len(words) + 2 * _BESIDE * len(texts), dtype=np.uint32)
    bits[at + np.repeat(np.arange(len(texts)), count) * 2 * _BESIDE + _BESIDE] = words >> np.uint64(62)
    return text, (grams[where] & _SEED_BITS).view(np.int64), (where - first[text]).astype(np.int32), beside(bits, where + text * 2 * _BESIDE, seed_words)


_PACKED_ROWS = pa.schema([("bucket", pa.int32()), ("tied", pa.bool_()), ("planes", pa.binary())])
_SEED_ROWS = pa.schema([("seed", pa.int64()), ("node", pa.int64()), ("place", pa.int32()), ("context", pa.int32()), ("a", pa.int64()), ("at", pa.int32()), ("near", pa.int8())])
_TIE_ROWS = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("at", pa.int32()), ("place", pa.int32()), ("near", pa.int8())])


def to_planes(cols: list[np.ndarray]) -> bytes:
    """Integers as planes of equal bytes, of which the shuffle's codec leaves little."""
    return b"".join(np.ascontiguousarray(c).view(np.uint8).reshape(len(c), c.itemsize).T.tobytes() for c in cols)


def from_planes(data: bytes, kinds: list) -> list[np.ndarray]:
    sizes = [np.dtype(k).itemsize for k in kinds]
    n, raw = len(data) // sum(sizes), np.frombuffer(data, dtype=np.uint8)
    ends = np.cumsum([0] + sizes) * n
    return [np.ascontiguousarray(raw[lo:hi].reshape(size, n).T).view(k).ravel() for k, size, lo, hi in zip(kinds, sizes, ends[:-1], ends[1:], strict=True)]


#: Bytes of text that are hashed together: enough to spare calls, few enough for a core's cache.
_AT_ONCE = 1 << 17


def seed_rows(seed_words: int, window: int, buckets: int, flush: int = 1 << 19):
    """Seeds of documents, tied inside the task: one entry of a seed stands for all the
    documents of about ``flush`` seeds that hold it, the others name it as pivot.

    Entries go out packed by bucket: of the seed, or of the tie where there is one.
    """

    def packed(tied: bool, to: np.ndarray, cols: list[np.ndarray]):
        bucket = (K.mix64(to.view(np.uint64)) % np.uint64(buckets)).astype(np.int32)
        order = np.argsort(bucket, kind="stable")
        bucket, cols = bucket[order], [c[order] for c in cols]
        first = np.flatnonzero(np.diff(bucket, prepend=-1))
        ends = np.append(first, len(bucket))[1:]
        return [(int(bucket[lo]), tied, to_planes([c[lo:hi] for c in cols])) for lo, hi in zip(first, ends, strict=True)]

    def flat(held):
        seed, node, place, context, a, at, near = local_ties(*[np.concatenate(x) for x in zip(*held, strict=True)])
        own = np.ones(len(seed), dtype=bool)
        own[1:] = seed[1:] != seed[:-1]
        tied = ~own & (node != a)  # a document repeats a seed: its first place is enough
        out = packed(False, seed[own], [seed[own], node[own], place[own], context[own]])
        out += packed(True, seed[tied] ^ node[tied], [node[tied], place[tied], a[tied], at[tied], near[tied].astype(np.int8)])
        return pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], f.type) for i, f in enumerate(_PACKED_ROWS)], schema=_PACKED_ROWS)

    def run(batches):
        held, n = [], 0
        for batch in batches:
            rids, sizes = batch.column("rid").to_numpy(), np.cumsum(pc.binary_length(batch.column("text")).to_numpy(zero_copy_only=False))
            lo = 0
            while lo < len(rids):
                hi = max(lo + 1, int(np.searchsorted(sizes, _AT_ONCE + (sizes[lo - 1] if lo else 0), side="right")))
                text, seed, place, context = seeds_of(batch.column("text").slice(lo, hi - lo).to_pylist(), seed_words, window)
                ends, begun = np.cumsum(np.bincount(text, minlength=hi - lo)), 0
                node = rids[lo:hi][text]
                while begun < len(seed):
                    # As many whole texts as bring what is held to ``flush``.
                    full = int(np.searchsorted(ends, begun + flush - n))
                    stop = int(ends[min(full, hi - lo - 1)])
                    held.append((seed[begun:stop], node[begun:stop], place[begun:stop], context[begun:stop]))
                    n, begun = n + stop - begun, stop
                    if n >= flush:
                        yield flat(held)
                        held, n = [], 0
                lo = hi
        if n:
            yield flat(held)

    return run


def unpack_rows(batches):
    """Seed rows of packed ones: (seed, node, place, context), or of a tie, which has no
    need of its seed, (node, place, a, at, near)."""
    for batch in batches:
        tied = batch.column("tied").to_numpy(zero_copy_only=False)
        for kind in (False, True):
            names = ("node", "place", "a", "at", "near") if kind else ("seed", "node", "place", "context")
            rows = [from_planes(x, [_SEED_ROWS.field(c).type.to_pandas_dtype() for c in names]) for x in batch.column("planes").filter(pa.array(tied == kind)).to_pylist()]
            if rows:
                cols = dict(zip(names, (np.concatenate(x) for x in zip(*rows, strict=True)), strict=True))
                n = len(cols["node"])
                yield pa.RecordBatch.from_arrays([pa.array(cols[f.name]) if f.name in cols else pa.array(np.zeros(n, np.int64)) if f.name == "seed" else pa.nulls(n, f.type) for f in _SEED_ROWS], schema=_SEED_ROWS)


def global_ties(batches):
    """Ties of seed rows that come sorted by seed: local pivots to the first, others as named."""
    last = None  # (seed, node, place, context) of the run at hand
    for batch in batches:
        seed, node, place = (batch.column(c).to_numpy() for c in ("seed", "node", "place"))
        tied = batch.column("a").is_valid().to_numpy(zero_copy_only=False)
        a, at, near, context = (batch.column(c).fill_null(0).to_numpy().copy() for c in ("a", "at", "near", "context"))
        own = np.flatnonzero(~tied)
        if len(own):
            s = seed[own]
            first = np.ones(len(s), dtype=bool)
            first[1:] = s[1:] != s[:-1]
            head = np.maximum.accumulate(np.where(first, np.arange(len(s)), 0))
            a[own], at[own], pivot = node[own][head], place[own][head], context[own][head]
            if last is not None:
                same = int(np.searchsorted(head, 1)) if s[0] == last[0] else 0
                a[own[:same]], at[own[:same]], pivot[:same] = last[1:]
            near[own] = agreeing(context[own], pivot)
            tail = own[-1]
            last = (seed[tail], a[tail], at[tail], pivot[-1])
        keep = node != a
        yield pa.RecordBatch.from_arrays([pa.array(x[keep]) for x in (a, node, at, place, near)], schema=_TIE_ROWS)


def chain_rows(seed_words: int, window: int):
    """Chains of each pair: (doc, pivot, other, x, y, lo, hi, runs) rows, one for each side,
    so that the text of either is met once; (x, y) is where the chain starts in both."""
    schema = pa.schema([("doc", pa.int64()), ("pivot", pa.bool_()), ("other", pa.int64()), ("x", pa.int32()), ("y", pa.int32()), ("lo", pa.int32()), ("hi", pa.int32()), ("runs", pa.list_(pa.int32()))])

    def run(batches):
        for batch in batches:
            out = []
            for a, b, xs, ys, zs in zip(batch.column("a").to_pylist(), batch.column("b").to_pylist(), batch.column("at"), batch.column("place"), batch.column("near"), strict=True):
                x, y, near = (v.values.to_numpy().astype(np.int64) for v in (xs, ys, zs))
                agree = set(zip(x[near > 0].tolist(), y[near > 0].tolist(), strict=True))
                for c in chains(seed_runs(x, y, seed_words, window + seed_words)):
                    single = len(c) == 1 and c[0, 2] == seed_words
                    if single and (int(c[0, 0]), int(c[0, 1])) not in agree:
                        continue
                    around = _GAP
                    for pivot, doc, other, k in ((True, a, b, 0), (False, b, a, 1)):
                        lo = max(0, int(c[0, k]) - around)
                        out.append((doc, pivot, other, int(c[0, 0]), int(c[0, 1]), lo, int(c[-1, k] + c[-1, 2]) + around, None if pivot else c.ravel().astype(np.int32)))
            yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], f.type) for i, f in enumerate(schema)], schema=schema)

    return run


def cut_words(batches):
    """The words around each chain as 16-bit hashes; for the repeating side also where
    they start, as steps in code points, and their lengths."""
    schema = pa.schema([("x", pa.int32()), ("y", pa.int32()), ("pivot", pa.bool_()), ("doc", pa.int64()), ("other", pa.int64()), ("lo", pa.int32()), ("runs", pa.list_(pa.int32())), ("words", pa.binary()), ("marks", pa.binary()), ("length", pa.int64())])
    last = None
    for batch in batches:
        n, texts, runs = len(batch), batch.column("text"), batch.column("runs")
        docs, los, his = (batch.column(c).to_pylist() for c in ("doc", "lo", "hi"))
        own = pc.invert(batch.column("pivot")).to_pylist()
        same = [False, *pc.equal(texts.slice(1), texts.slice(0, n - 1)).to_pylist()] if n else []
        words, marks, length = [], [], []
        for k, (doc, i, j) in enumerate(zip(docs, los, his, strict=True)):
            if not (k and same[k] and docs[k - 1] == doc):
                text = texts[k]
                if last is None or last[0] != doc or last[1] != text:
                    data = np.frombuffer(text.as_py().encode("utf-8", "surrogatepass"), dtype=np.uint8)
                    s, e = K.word_bounds(data)
                    chars = K.char_offsets(data)
                    hashes, first, wide = (K.hash_words(data, s, e) >> np.uint64(48)).astype(np.uint16), chars[s], (chars[e] - chars[s]).astype(np.int32)
                    last = (doc, text, hashes, first.astype(np.int32), np.diff(first, prepend=0).astype(np.int32), wide)
            _, _, hashes, first, steps, wide = last
            words.append(hashes[i:j].tobytes())
            if own[k]:
                step = steps[i:j].copy()
                step[:1] = first[i : i + 1]
                marks.append(to_planes([step, wide[i:j]]))
                length.append(len(hashes))
            else:
                marks.append(None)
                length.append(None)
        made = {"words": pa.array(words, pa.binary()), "marks": pa.array(marks, pa.binary()), "length": pa.array(length, pa.int64())}
        yield pa.RecordBatch.from_arrays([made[f.name] if f.name in made else batch.column(f.name).cast(f.type) for f in schema], schema=schema)


def align_rows(part_words: int, identity: float):
    """Aligned chains: (doc, other, first, last, start, stop, n) of the repeating side."""
    schema = pa.schema([("doc", pa.int64()), ("other", pa.int64()), ("first", pa.int64()), ("last", pa.int64()), ("start", pa.int64()), ("stop", pa.int64()), ("n", pa.int64())])

    def run(batches):
        for batch in batches:
            out = []
            names = ("doc", "other", "length", "a_lo", "lo", "a_words", "words")
            runs, marks = batch.column("runs"), batch.column("marks")
            for k, (doc, other, length, a_lo, lo, a_words, words) in enumerate(zip(*(batch.column(c).to_pylist() for c in names), strict=True)):
                c = runs[k].values.to_numpy(zero_copy_only=False).astype(np.int64).reshape(-1, 3) - (a_lo, lo, 0)
                a, b = np.frombuffer(a_words, dtype=np.uint16), np.frombuffer(words, dtype=np.uint16)
                a0, a1, b0, b1, matched = align_chain(c, a, b)
                if b1 - b0 >= part_words and matched >= identity * max(a1 - a0, b1 - b0):
                    s, e = from_planes(marks[k].as_py(), [np.int32, np.int32])
                    s = np.cumsum(s)
                    e = s + e
                    out.append((doc, other, b0 + lo, b1 + lo, int(s[b0]), int(e[b1 - 1]), length))
            yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], f.type) for i, f in enumerate(schema)], schema=schema)

    return run


def repeated_passages(
    documents: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    seed_words: int = SEED_WORDS,
    window: int = WINDOW,
    min_words: int = MIN_WORDS,
    part_words: int = PART_WORDS,
    identity: float = IDENTITY,
) -> DataFrame:
    """(doc_id, start, stop, n_words, partners, whole): passages that repeat others'.

    ``partners`` are ids of documents that hold the passage, or parts that make it
    up; ``whole`` marks a repeat of the whole text.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    nameless = F.lit(NULL_ID) + F.pmod(F.xxhash64(text), F.lit(1 << 52))
    docs = small_batches(documents).select(F.coalesce(F.col(id_col).cast("long"), nameless).alias("rid"), text.alias("text"))

    buckets = 16 * int(documents.sparkSession.conf.get("spark.sql.shuffle.partitions", "200"))
    packed = docs.mapInArrow(seed_rows(seed_words, window, buckets), "bucket int, tied boolean, planes binary").repartition("bucket")
    seeds = packed.mapInArrow(unpack_rows, "seed long, node long, place int, context int, a long, at int, near byte")
    ties = seeds.sortWithinPartitions("seed", "node", "place").mapInArrow(global_ties, "a long, b long, at int, place int, near byte")
    pairs = ties.groupBy("a", "b").agg(F.collect_list("at").alias("at"), F.collect_list("place").alias("place"), F.collect_list("near").alias("near"))
    pairs = pairs.filter((F.size("at") > 1) | (F.col("near")[0] > 0))
    sides = pairs.mapInArrow(chain_rows(seed_words, window), "doc long, pivot boolean, other long, x int, y int, lo int, hi int, runs array<int>")
    met = sides.join(docs, sides.doc == docs.rid).drop("rid")
    cuts = met.mapInArrow(cut_words, "x int, y int, pivot boolean, doc long, other long, lo int, runs array<int>, words binary, marks binary, length long")
    chain = (F.when(F.col("pivot"), F.col("doc")).otherwise(F.col("other")).alias("of_a"), F.when(F.col("pivot"), F.col("other")).otherwise(F.col("doc")).alias("of_b"), "x", "y")
    one_side = F.max_by(F.when(F.col("pivot"), F.struct(F.col("lo").alias("a_lo"), F.col("words").alias("a_words"))), F.col("pivot"))
    other_side = F.max_by(F.when(~F.col("pivot"), F.struct("doc", "other", "lo", "runs", "words", "marks", "length")), ~F.col("pivot"))
    both = cuts.groupBy(*chain).agg(one_side.alias("one"), other_side.alias("two")).filter("one is not null and two is not null").select("one.*", "two.*")
    spans = both.mapInArrow(align_rows(part_words, identity), "doc long, other long, first long, last long, start long, stop long, n long")
    return merged_passages(spans, min_words)


def merged_passages(spans: DataFrame, min_words: int, joint: int = 3) -> DataFrame:
    """Spans of a document that touch within ``joint`` words are one passage."""
    order = Window.partitionBy("doc").orderBy("first", "last", "other")
    reach = F.max("last").over(order.rowsBetween(Window.unboundedPreceding, -1))
    numbered = spans.withColumn("new", F.when(reach.isNull() | (F.col("first") > reach + joint), 1).otherwise(0)).withColumn("part", F.sum("new").over(order))
    passages = numbered.groupBy("doc", "part").agg(
        F.min("start").alias("start"), F.max("stop").alias("stop"), (F.max("last") - F.min("first")).alias("n_words"), F.array_sort(F.collect_set("other")).alias("partners"), F.max("n").alias("n")
    )
    back = lambda c: F.when(c > NULL_ID // 2, c)
    return passages.filter(F.col("n_words") >= min_words).select(
        back(F.col("doc")).alias("doc_id"), "start", "stop", "n_words", F.transform("partners", back).alias("partners"), (F.col("n_words") == F.col("n")).alias("whole")
    )


def remove_passages(documents: DataFrame, passages: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents with their repeated passages cut out of the text."""
    spans = passages.filter("doc_id is not null").groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct("start", "stop"))).alias("_cuts")).withColumnRenamed("doc_id", "_cut_id")
    rows = documents.join(spans, F.col(id_col) == F.col("_cut_id"), "left")
    text = F.col(text_col)
    kept = F.aggregate(
        "_cuts",
        F.struct(F.lit(0).cast("long").alias("at"), F.lit("").alias("out")),
        lambda acc, s: F.struct(s["stop"].alias("at"), F.concat(acc["out"], F.substring(text, acc["at"].cast("int") + 1, (s["start"] - acc["at"]).cast("int"))).alias("out")),
        lambda acc: F.concat(acc["out"], F.substring(text, acc["at"].cast("int") + 1, F.length(text))),
    )
    return rows.withColumn(text_col, F.when(F.col("_cuts").isNull(), text).otherwise(kept)).select(*documents.columns)

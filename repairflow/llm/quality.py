"""Quality classification by nearest-neighbour voting in a latent-semantic space.

Terms are trigrams of character classes (so no language is a feature) and binned
shares that tell repetition: distinct words, the commonest word, repeated lines,
word length.  Their weighted term-document matrix over a bounded labelled sample
is reduced by a truncated SVD; the labelled vectors are broadcast, every document
is projected, and its exact cosines with all of them are computed block by block.
The score is the vote of the nearest neighbours weighted by similarity.

Defined results: a text without words scores 0; rows without a label are not
learnt from; with no labelled rows, or an empty table of them, every score is 0.5;
repeated rows score alike, each labelled one is learnt from; of neighbours of equal
similarity at the edge any may vote; texts of any length are read whole.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import kernels as K
from .common import small_batches

#: At most this many labelled documents of each class are learnt from.
PER_CLASS = 2000
_CLASSES = np.full(256, 0, dtype=np.int32)  # 0: letters in lower case and bytes beyond ASCII
_CLASSES[65:91] = 1
_CLASSES[48:58] = 2
_CLASSES[[32, 9]] = 3
_CLASSES[[10, 13]] = 4
for _i, _c in enumerate(b"!\"#$%&'()*+,-./:;<=>?@[\\]_`{|}~^"):
    _CLASSES[_c] = min(5 + _i, 36)
_CLASSES[[*range(0, 9), 11, 12, *range(14, 32), 127]] = 37
_KINDS = 38
_TRIGRAMS = _KINDS**3
_BINS = 12
TERMS = _TRIGRAMS + 5 * _BINS


def _bin(share: float) -> int:
    return min(int(share * _BINS), _BINS - 1)


def term_weights(text: str | None) -> tuple[np.ndarray, np.ndarray] | None:
    """(terms, weights) of a whole text, None if it has no word."""
    text = text or ""
    data = np.frombuffer(text.encode("utf-8", "surrogatepass"), dtype=np.uint8)
    starts, ends = K.word_bounds(data)
    if not len(starts):
        return None
    c = _CLASSES[data]
    grams = (c[:-2] * _KINDS + c[1:-1]) * _KINDS + c[2:] if len(c) > 2 else c[:1]
    terms, counts = np.unique(grams, return_counts=True)
    weights = np.sqrt(counts / counts.sum())
    words = K.hash_words(data, starts, ends)
    _, often = np.unique(words, return_counts=True)
    lines = [x for x in text.split("\n") if x.strip()]
    repeated = 1 - len(Counter(lines)) / max(len(lines), 1)
    length = float((ends - starts).mean())
    n = len(words)
    # Distinct words against what a text of the length usually has (a root law).
    shares = (min(1.0, len(often) / max(n**0.8, 1)), min(1.0, 2 * often.max() / n), repeated, min(1.0, length / 16), min(1.0, np.log10(n) / 5))
    own = np.array([_TRIGRAMS + i * _BINS + _bin(s) for i, s in enumerate(shares)])
    return np.concatenate((terms, own)), np.concatenate((weights, np.full(len(own), 0.35)))


class NeighbourVote:
    """Projection and labelled vectors; ``score`` takes whole texts."""

    def __init__(self, texts: list[str], labels: list[int], sample_weight: list[float], rank: int = 48, neighbours: int = 31, sharpness: float = 12.0):
        self.neighbours, self.sharpness = neighbours, sharpness
        rows = [(term_weights(t), y, w) for t, y, w in zip(texts, labels, sample_weight, strict=True)]
        rows = [r for r in rows if r[0] is not None]
        self.empty = not rows
        if self.empty:
            return
        df = np.zeros(TERMS)
        for (terms, _), _, _ in rows:
            df[terms] += 1
        active = np.flatnonzero(df >= min(3, len(rows)))
        self.column = np.full(TERMS, -1, dtype=np.int32)
        self.column[active] = np.arange(len(active))
        self.idf = np.log(1 + len(rows) / df[active])
        matrix = np.zeros((len(rows), len(active)), dtype=np.float32)
        for i, (tw, _, _) in enumerate(rows):
            matrix[i] = self._dense(*tw)
        # Truncated SVD by subspace iteration on the term side.
        rank = min(rank, *matrix.shape)
        basis = np.random.default_rng(5).standard_normal((matrix.shape[1], rank)).astype(np.float32)
        for _ in range(6):
            basis, _ = np.linalg.qr(matrix.T @ (matrix @ basis))
        self.basis = basis.astype(np.float32)
        self.vectors = self._unit(matrix @ self.basis)
        self.labels = np.array([r[1] for r in rows], dtype=np.float32)
        self.weights = np.array([r[2] for r in rows], dtype=np.float32)

    def _dense(self, terms: np.ndarray, weights: np.ndarray) -> np.ndarray:
        row = np.zeros(len(self.idf), dtype=np.float32)
        at = self.column[terms]
        row[at[at >= 0]] = weights[at >= 0]
        row *= self.idf
        return row / max(float(np.linalg.norm(row)), 1e-9)

    @staticmethod
    def _unit(v: np.ndarray) -> np.ndarray:
        return v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-9)

    def score(self, texts: list, block: int = 512) -> np.ndarray:
        out = np.full(len(texts), 0.5 if self.empty else 0.0)
        if self.empty:
            return out
        for lo in range(0, len(texts), block):
            tw = [(i, term_weights(t)) for i, t in enumerate(texts[lo : lo + block], lo)]
            tw = [(i, x) for i, x in tw if x is not None]
            if not tw:
                continue
            cosine = self._unit(np.stack([self._dense(*x) for _, x in tw]) @ self.basis) @ self.vectors.T
            k = min(self.neighbours, cosine.shape[1])
            near = np.argpartition(-cosine, k - 1, axis=1)[:, :k]
            similar = np.take_along_axis(cosine, near, axis=1)
            vote = np.exp(self.sharpness * (similar - similar.max(axis=1, keepdims=True))) * self.weights[near]
            out[[i for i, _ in tw]] = np.clip((vote * self.labels[near]).sum(axis=1) / vote.sum(axis=1), 0, 1)
        return out


def fit(documents: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", per_class: int = PER_CLASS, **options) -> NeighbourVote:
    """Learn from at most ``per_class`` labelled documents a class, those of least id hash.

    Only labels of the given documents count, in the sample, its shares and the votes'
    weights: what other rows of ``labels`` say changes no score.
    """
    marks = labels.filter(F.col(label_col).isNotNull() & F.col(id_col).isNotNull()).select(F.col(id_col).alias("id"), F.col(label_col).cast("int").alias("label"))
    ids = documents.select(F.col(id_col).alias("id"))
    known = ids.join(marks, "id")
    counts = {r["label"]: r["count"] for r in known.groupBy("label").count().collect()}
    if not counts:
        return NeighbourVote([], [], [], **options)
    unit = F.pmod(F.xxhash64("id"), F.lit(1 << 40)) / float(1 << 40)
    share = F.create_map(*[x for k, n in counts.items() for x in (F.lit(k), F.lit(min(1.0, (per_class + 6 * per_class**0.5) / n)))])
    few = known.filter(unit < share[F.col("label")]).select("id", "label", unit.alias("u")).distinct()  # bounded by per_class
    texts = documents.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).join(F.broadcast(few), "id")
    by = {}
    for k in sorted(counts):
        rows = texts.filter(F.col("label") == k).orderBy("u", "id", F.xxhash64("text")).limit(per_class).collect()
        by[k] = [r["text"] for r in sorted(rows, key=lambda r: (r["u"], r["id"], r["text"] or ""))]
    used = [(t, k, counts[k] / len(v)) for k, v in sorted(by.items()) for t in v]
    return NeighbourVote([u[0] for u in used], [u[1] for u in used], [u[2] for u in used], **options)


def classify(documents: DataFrame, model: NeighbourVote, text_col: str = "text", threshold: float = 0.7) -> DataFrame:
    """All columns of ``documents`` plus score and predicted (1 if score >= threshold)."""
    shared = documents.sparkSession.sparkContext.broadcast(model)
    docs = small_batches(documents).select(*[F.col(f"`{c}`") for c in documents.columns if c not in ("score", "predicted")])

    def run(batches):
        for batch in batches:
            score = shared.value.score(batch.column(text_col).to_pylist())
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(score), pa.array((score >= threshold).astype(np.int32))], [*batch.schema.names, "score", "predicted"])

    return docs.mapInArrow(run, T.StructType(docs.schema.fields + [T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())]))

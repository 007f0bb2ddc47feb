"""Language identification by prediction by partial matching.

For every language a byte context tree of variable order is grown from training
texts and frozen: a node holds the symbols seen after its context, a symbol not
seen there is coded by an escape and then by the parent node, down to uniform
bytes.  Node code lengths are tabulated once, so the exact code length of a text
under all languages is two array reads a byte.

Defined results: ``und`` with score 0 for a null text or one without a letter (a
character that Unicode calls one: no digit, fraction or superscript); rows whose
training language is null are not learnt from; with no training rows, or an empty
table of them, every text is ``und``; of languages with equal code lengths the first
by name; repeated rows are predicted alike and learnt from once; texts of any length
are coded whole, in pieces.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import small_batches

UNDETERMINED = "und"
_PIECE = 1 << 18


class ContextTrees:
    """Frozen per-language context trees of order at most 3, sharing node numbers."""

    def __init__(self, texts: dict[str, list[bytes]], order: int = 3):
        self.order = min(order, 3)
        self.langs = sorted(texts)
        joined = {k: np.frombuffer(b"\n".join(v), dtype=np.uint8) for k, v in texts.items()}
        seen = np.unique(np.concatenate([*joined.values(), np.zeros(0, np.uint8)])) if joined else np.zeros(0, np.uint8)
        self.code = np.zeros(256, dtype=np.int64)  # 0: a byte never trained on
        self.code[seen] = np.arange(1, len(seen) + 1)
        self.size = a = len(seen) + 1
        coded = {k: self.code[v] for k, v in joined.items()}
        # Nodes: contexts of each order that some language has seen, shortest first.
        contexts: list[np.ndarray] = [np.zeros(1, np.int64)]
        for d in range(1, self.order + 1):
            contexts.append(np.unique(np.concatenate([self._windows(v[:-1], d) for v in coded.values()] + [np.zeros(0, np.int64)])))
        first = np.cumsum([0] + [len(c) for c in contexts])
        self.table = np.zeros((first[-1], a, len(self.langs)), dtype=np.float32)
        for j, lang in enumerate(self.langs):
            for d, ctx in enumerate(contexts):
                pairs, counts = np.unique(self._windows(coded[lang], d + 1), return_counts=True)
                row, sym = np.searchsorted(ctx, pairs // a), pairs % a
                total, distinct = np.bincount(row, counts, len(ctx)), np.bincount(row, minlength=len(ctx))
                if d:
                    shorter = contexts[d - 1]
                    base = self.table[first[d - 1] + np.searchsorted(shorter, ctx % (a ** (d - 1))), :, j]
                else:
                    base = np.full((1, a), 8.0, dtype=np.float32)
                with np.errstate(divide="ignore", invalid="ignore"):
                    escape = np.where(total > 0, -np.log2(distinct / (total + distinct)), 0.0)
                base += escape.astype(np.float32)[:, None]
                base[row, sym] = -np.log2(counts / (total + distinct)[row])
                self.table[first[d] : first[d + 1], :, j] = base
        # The deepest node of any ``order`` coded bytes, a byte further back at a time.
        self.node = np.zeros(1, dtype=np.int32)
        for d in range(1, self.order + 1):
            self.node = np.tile(self.node, a)
            self.node[contexts[d]] = first[d] + np.arange(len(contexts[d]))
        self.table = self.table.reshape(len(self.table) * a, len(self.langs))

    def _windows(self, v: np.ndarray, n: int) -> np.ndarray:
        """Base-``size`` numbers of the n-symbol windows."""
        m = len(v) - n + 1
        out = np.zeros(max(m, 0), dtype=np.int64)
        for i in range(n):
            out = out * self.size + v[i : i + max(m, 0)]
        return out

    def code_lengths(self, text: str) -> np.ndarray:
        """Bits of the whole text under each language; it starts after a line break."""
        total = np.zeros(len(self.langs))
        start = self.code[10]
        past = np.full(self.order, start, dtype=np.int64)
        data = np.frombuffer(text.encode("utf-8", "surrogatepass"), dtype=np.uint8)
        for lo in range(0, len(data), _PIECE):
            v = np.concatenate((past, self.code[data[lo : lo + _PIECE]]))
            past = v[-self.order :]
            ctx = self._windows(v[:-1], self.order)
            at = self.node[ctx].astype(np.int64) * self.size + v[self.order :]
            total += self.table[at].sum(axis=0, dtype=np.float64)
        return total

    def predict(self, text: str | None) -> tuple[str, float, float]:
        """(language, score in [0, 1], bits a byte under it)."""
        if not text or not self.langs or not any(map(str.isalpha, text)):
            return UNDETERMINED, 0.0, 0.0
        bits = self.code_lengths(text)
        best = int(np.argmin(bits))
        odds = np.exp2(np.maximum(bits[best] - bits, -1000.0))
        return self.langs[best], float(1.0 / odds.sum()), float(bits[best] / len(text.encode("utf-8", "surrogatepass")))


def fit(training: DataFrame, text_col: str = "text", lang_col: str = "lang", per_language: int = 400, order: int = 3) -> ContextTrees:
    """Grow the trees from at most ``per_language`` whole texts of each language.

    The sample is the distinct texts of least content hash in each language, however
    many rows hold them.  A hash threshold from the estimated number of distinct texts
    cuts most rows first and copies meet in an aggregate, so the driver gets one row
    for each text and few more than it keeps; a language that comes out short of texts
    is read again with a higher threshold, so the estimate never decides the result.
    """
    rows = training.filter(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.col(lang_col).alias("lang"), F.col(text_col).alias("text"))
    counts = {r["lang"]: r["n"] for r in rows.groupBy("lang").agg(F.approx_count_distinct(F.xxhash64("text"), 0.02).alias("n")).collect()}
    unit = F.pmod(F.xxhash64("text"), F.lit(1 << 40)) / float(1 << 40)
    shares = {k: (per_language + 6 * per_language**0.5 + 10) / max(n, 1) for k, n in counts.items()}
    texts: dict[str, list[bytes]] = {}
    while shares:
        share = F.create_map(*[x for k, v in shares.items() for x in (F.lit(k), F.lit(v))])
        found: dict[str, list[tuple[float, bytes]]] = {k: [] for k in shares}
        for r in rows.filter(unit < share[F.col("lang")]).select("lang", "text", unit.alias("u")).distinct().toLocalIterator():
            found[r["lang"]].append((r["u"], r["text"].encode("utf-8", "surrogatepass")))
        texts |= {k: [x for _, x in sorted(v)[:per_language]] for k, v in found.items()}
        shares = {k: 2 * v for k, v in shares.items() if v < 1 and len(texts[k]) < per_language}
    return ContextTrees(texts, order)


def identify(documents: DataFrame, trees: ContextTrees, text_col: str = "text") -> DataFrame:
    """All columns of ``documents`` plus lang_pred, lang_score, lang_bits (bits a byte)."""
    spark = documents.sparkSession
    shared = spark.sparkContext.broadcast(trees)
    keep = [c for c in documents.columns if c not in ("lang_pred", "lang_score", "lang_bits")]
    docs = small_batches(documents).select(*[F.col(f"`{c}`") for c in keep])

    def run(batches):
        model = shared.value
        for batch in batches:
            got = [model.predict(t.as_py()) for t in batch.column(text_col)]
            cols = [pa.array([g[i] for g in got], kind) for i, kind in enumerate((pa.string(), pa.float64(), pa.float64()))]
            yield pa.RecordBatch.from_arrays([*batch.columns, *cols], [*batch.schema.names, "lang_pred", "lang_score", "lang_bits"])

    schema = T.StructType(docs.schema.fields + [T.StructField("lang_pred", T.StringType()), T.StructField("lang_score", T.DoubleType()), T.StructField("lang_bits", T.DoubleType())])
    return docs.mapInArrow(run, schema)


def held_out(id_col: str, parts: int, part: int):
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string")), F.lit(parts)) == part, F.lit(False))

"""Token-id output in an Arrow stream file of fixed-size lists.

Documents are encoded in ascending id order, an end id after each, and packed
into sequences of equal length: one record batch holds ``batch_rows`` rows of
``ids fixed_size_list<uint16|uint32>[seq_len]`` and ``mask fixed_size_list<bool>
[seq_len]`` (true: a token; the last sequence of a file is padded).  A sequence is
reached without a copy through a memory map.  Beside each file stands an index of
its documents (id, start in the file, length).

A file is written under an attempt's own name and moved into place when whole, so
a task that runs again replaces it by the same bytes.  Null texts are empty: only
the end id.  Null ids sort first; equal ids by text, then as they come.
"""

from __future__ import annotations

import os
import re
import uuid
import zlib

import numpy as np
import pyarrow as pa
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .common import scratch_path, small_batches

SEQ_LEN, BATCH_ROWS = 2048, 64
_MOST_CHUNKS = 1 << 19
_NONE = np.uint64(0xFFFFFFFFFFFFFFFF)
# Fixed value: how the tokenizer's file cuts texts into pieces.
_PIECES_OF_FILE = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
#: The same for plain characters: ASCII and the letters of Latin-1.
_PIECES = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z\u00df-\u00f6\u00f8-\u00ff]+|[0-9]|[^a-z0-9\u00df-\u00f6\u00f8-\u00ff]+")
_NOT_PLAIN = re.compile(r"[^\t-\r -~\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]")


def _cut(chunk: str) -> str:
    """The pieces of a plain chunk, folded, with spaces between them."""
    if chunk.isalpha():
        return chunk.lower()
    if chunk[:-1].isalpha() and chunk[-1] in ".,;:!?":
        return f"{chunk[:-1]} {chunk[-1]}".lower()
    return " ".join(_PIECES.findall(chunk.lower()))


class Encoder:
    """Encodes by parts: white-space-separated chunks, then the tokenizer's own pieces.

    The tokenizer folds case, drops white space and never joins across it or across
    its pieces (a run of letters, a digit, a run of other signs), and every piece
    ends in a token that is marked so.  Pieces not yet known are encoded together
    and cut at those marks.  The chunks of many texts are looked up at once, by two
    64-bit hashes in an open table of arrays, which takes no more entries when full.
    Texts with other characters than plain ones (where folding or composing could
    differ) are encoded whole.  Tests hold this against encoding whole texts.
    """

    def __init__(self, path: str):
        import json

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer, normalizers, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        # The same model for pieces that are folded and cut already.
        self.bare = Tokenizer.from_file(path)
        self.bare.normalizer = normalizers.Sequence([])
        self.bare.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)])
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        suffix = spec["model"].get("end_of_word_suffix")
        own = [x["pattern"].get("Regex") for x in (spec.get("pre_tokenizer") or {}).get("pretokenizers", []) if x["type"] == "Split"]
        steps = [x["type"] for x in (spec.get("normalizer") or {}).get("normalizers", [])]
        # By parts only for a tokenizer of this very make; any other encodes whole texts.
        self.by_parts = bool(suffix) and own == [_PIECES_OF_FILE] and steps == ["NFC", "Replace", "Lowercase"]
        vocab = self.tokenizer.get_vocab(with_added_tokens=True)
        self.last = np.zeros(max(vocab.values()) + 1, dtype=bool)
        for token, i in vocab.items():
            self.last[i] = bool(suffix) and token.endswith(suffix)
        self.slots = np.zeros((3, 2 * _MOST_CHUNKS), dtype=np.uint64)  # hash, other hash, place << 16 | length
        self.pool, self.used, self.entries = np.zeros(1 << 16, dtype="<u4"), 0, 0

    def _chunks(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of plain chunks, one after another, and how many each has.

        All pieces are encoded in one call; tokens that end a piece give the cuts.
        """
        cut = [_cut(c) for c in chunks]
        ids = np.array(self.bare.encode_batch_fast([" ".join(cut)], add_special_tokens=False)[0].ids, dtype="<u4")
        stop = np.flatnonzero(self.last[ids]) + 1
        last = np.cumsum([c.count(" ") + 1 for c in cut]) - 1
        if len(stop) != last[-1] + 1:  # a piece that the tokenizer reads otherwise
            parts = [self.tokenizer.encode(c, add_special_tokens=False).ids for c in chunks]
            return np.array([x for p in parts for x in p], dtype="<u4"), np.array([len(p) for p in parts], dtype=np.int64)
        return ids, np.diff(stop[last], prepend=0)

    def encode(self, text: str | None) -> np.ndarray:
        return self.encode_many([text])[0]

    def encode_many(self, texts: list) -> list[np.ndarray]:
        """Ids of each text, texts taken together by about a megabyte."""
        out: list[np.ndarray] = [None] * len(texts)
        held, size = [], 0
        for i, text in enumerate(texts):
            text = text or ""
            if not self.by_parts or _NOT_PLAIN.search(text) or "<|" in text:
                out[i] = np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, dtype="<u4")
                continue
            held.append((i, text.encode()))
            size += len(text)
            if size > 1 << 20:
                self._plain(held, out)
                held, size = [], 0
        self._plain(held, out)
        return out

    def _plain(self, held: list[tuple[int, bytes]], out: list) -> None:
        if not held:
            return
        raw = b" ".join(t for _, t in held)
        data = np.frombuffer(raw, dtype=np.uint8)
        starts, ends = K.word_bounds(data)
        one, two = K.hash_words(data, starts, ends, second=True) if len(starts) else (np.empty(0, np.uint64),) * 2
        one |= np.uint64(1)  # 0 marks an empty slot
        code = self._find(one, two)
        pool = self.pool
        miss = np.flatnonzero(code == _NONE)
        if len(miss):
            _, first, which = np.unique(one[miss], return_index=True, return_inverse=True)
            at = miss[first]
            flat, length = self._chunks([raw[s:e].decode() for s, e in zip(starts[at].tolist(), ends[at].tolist(), strict=True)])
            length = length.astype(np.uint64)
            place = np.uint64(self.used) + np.concatenate(([0], np.cumsum(length)[:-1])).astype(np.uint64)
            fits = int(length.max()) < 1 << 16
            codes = (place << np.uint64(16)) | length
            if self.used + len(flat) > len(pool):
                pool = np.concatenate((pool[: self.used], flat, np.zeros(len(pool), dtype="<u4")))
            else:
                pool[self.used : self.used + len(flat)] = flat
            if self.entries + len(length) <= _MOST_CHUNKS and fits:
                self.pool, self.used, self.entries = pool, self.used + len(flat), self.entries + len(length)
                self._put(one[at], two[at], codes)
            code[miss] = codes[which]
            lengths, places = (code & np.uint64(0xFFFF)).astype(np.int64), (code >> np.uint64(16)).astype(np.int64)
            if not fits:  # a chunk of very many tokens
                lengths[miss], places[miss] = length[which].astype(np.int64), place[which].astype(np.int64)
        else:
            lengths, places = (code & np.uint64(0xFFFF)).astype(np.int64), (code >> np.uint64(16)).astype(np.int64)
        stop = np.cumsum(lengths)
        ids = pool[np.repeat(places - stop + lengths, lengths) + np.arange(int(stop[-1]) if len(stop) else 0)]
        bounds = np.cumsum([len(t) + 1 for _, t in held])  # word starts below it belong to the text
        cuts = np.concatenate(([0], stop))[np.searchsorted(starts, bounds)]
        for (i, _), part in zip(held, np.split(ids, cuts[:-1]), strict=True):
            out[i] = part

    def _find(self, one: np.ndarray, two: np.ndarray) -> np.ndarray:
        code = np.full(len(one), _NONE, dtype=np.uint64)
        mask = np.uint64(self.slots.shape[1] - 1)
        at, slot = np.arange(len(one)), one >> np.uint64(8) & mask
        while len(at):
            key = self.slots[0, slot]
            hit = (key == one[at]) & (self.slots[1, slot] == two[at])
            code[at[hit]] = self.slots[2, slot[hit]]
            go = ~hit & (key != 0)
            at, slot = at[go], (slot[go] + np.uint64(1)) & mask
        return code

    def _put(self, one: np.ndarray, two: np.ndarray, codes: np.ndarray) -> None:
        mask = np.uint64(self.slots.shape[1] - 1)
        at, slot = np.arange(len(one)), one >> np.uint64(8) & mask
        while len(at):
            free = np.flatnonzero(self.slots[0, slot] == 0)
            _, first = np.unique(slot[free], return_index=True)
            won = free[first]
            self.slots[:, slot[won]] = one[at[won]], two[at[won]], codes[at[won]]
            rest = np.ones(len(at), dtype=bool)
            rest[won] = False
            at, slot = at[rest], (slot[rest] + np.uint64(1)) & mask


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """The worker process's encoder, whose tables serve all its tasks."""
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


class StreamFileWriter:
    """Packs token arrays into sequences; memory is one batch and the document index."""

    def __init__(self, sink, seq_len: int, batch_rows: int, wide: bool):
        self.seq_len, self.rows = seq_len, batch_rows
        self.dtype = np.uint32 if wide else np.uint16
        kind = pa.list_(pa.from_numpy_dtype(self.dtype), seq_len)
        self.schema = pa.schema([("ids", kind), ("mask", pa.list_(pa.bool_(), seq_len))])
        self.writer = pa.ipc.new_stream(sink, self.schema)
        self.pending: list[np.ndarray] = []
        self.held = 0

    def add(self, ids: np.ndarray) -> None:
        self.pending.append(ids.astype(self.dtype))
        self.held += len(ids)
        if self.held >= self.seq_len * self.rows:
            flat = np.concatenate(self.pending)
            cut = len(flat) // (self.seq_len * self.rows) * self.seq_len * self.rows
            for lo in range(0, cut, self.seq_len * self.rows):
                self._batch(flat[lo : lo + self.seq_len * self.rows], self.seq_len * self.rows)
            self.pending, self.held = [flat[cut:]], len(flat) - cut

    def _batch(self, flat: np.ndarray, valid: int) -> None:
        lists = [pa.FixedSizeListArray.from_arrays(pa.array(x), self.seq_len) for x in (flat, np.arange(len(flat)) < valid)]
        self.writer.write_batch(pa.RecordBatch.from_arrays(lists, schema=self.schema))

    def close(self) -> None:
        flat = np.concatenate([*self.pending, np.zeros(0, self.dtype)]).astype(self.dtype)
        if len(flat):
            self._batch(np.concatenate((flat, np.zeros(-len(flat) % self.seq_len, self.dtype))), len(flat))
        self.writer.close()


class StreamFile:
    """Random access to the sequences of one file; local files are memory-mapped."""

    def __init__(self, uri: str):
        system, path = pafs.FileSystem.from_uri(uri)
        self.source = pa.memory_map(path) if isinstance(system, pafs.LocalFileSystem) else system.open_input_file(path)
        reader = pa.ipc.open_stream(self.source)
        self.seq_len = reader.schema.field("ids").type.list_size
        self.batches = list(reader)
        self.per_batch = self.batches[0].num_rows if self.batches else 1

    def __len__(self) -> int:
        return sum(b.num_rows for b in self.batches)

    def sequence(self, i: int) -> tuple[np.ndarray, np.ndarray]:
        """(ids without a copy, mask) of the i-th sequence."""
        batch, row = self.batches[i // self.per_batch], i % self.per_batch
        ids = batch.column(0).flatten().to_numpy(zero_copy_only=True)[row * self.seq_len : (row + 1) * self.seq_len]
        mask = batch.column(1).flatten().slice(row * self.seq_len, self.seq_len).to_numpy(zero_copy_only=False)
        return ids, mask

    def tokens(self, start: int, length: int) -> np.ndarray:
        per = self.per_batch * self.seq_len
        out = [self.batches[b].column(0).flatten().to_numpy(zero_copy_only=True)[max(0, start - b * per) : start + length - b * per] for b in range(start // per, (start + length - 1) // per + 1)]
        return np.concatenate(out) if out else np.zeros(0, np.uint16)


def write_token_files(
    documents: DataFrame,
    tokenizer_path: str,
    out_uri: str,
    id_col: str = "doc_id",
    text_col: str = "text",
    end_id: int = 1,
    seq_len: int = SEQ_LEN,
    batch_rows: int = BATCH_ROWS,
    rows_per_file: int = 8192,
    wide: bool = False,
) -> DataFrame:
    """Write the files; returns (file, first_start) rows, one for each file in order."""
    from .common import NULL_ID

    docs = small_batches(documents).select(F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID)).alias("rid"), F.col(id_col).isNotNull().alias("named"), F.col(text_col).alias("text"))
    # Ranges of ids in order, one task and one file for each.
    files = max(1, -(-docs.count() // rows_per_file))
    dealt = docs.repartitionByRange(files, "rid").sortWithinPartitions("rid", "text")

    def run(batches):
        encode = encoder(tokenizer_path).encode_many
        system, root = pafs.FileSystem.from_uri(out_uri)
        file, temp = TaskContext.get().partitionId(), f"{root}/_attempt-{uuid.uuid4().hex}"
        writer, ids_of, sizes = None, [], []
        for batch in batches:
            for rid, named, ids in zip(batch.column("rid").to_pylist(), batch.column("named").to_pylist(), encode(batch.column("text").to_pylist()), strict=True):
                if writer is None:
                    system.create_dir(root, recursive=True)
                    sink = system.open_output_stream(temp)
                    writer = StreamFileWriter(sink, seq_len, batch_rows, wide)
                ids = np.append(ids, np.uint32(end_id))
                writer.add(ids)
                ids_of.append(rid if named else None)
                sizes.append(len(ids))
        if writer is None:
            return
        writer.close()
        sink.close()
        starts = np.concatenate(([0], np.cumsum(sizes)[:-1])).astype(np.int64)
        index = pa.table({"doc_id": pa.array(ids_of, pa.int64()), "start": pa.array(starts), "n_tokens": pa.array(sizes, pa.int64())})
        with system.open_output_stream(temp + ".index") as out, pa.ipc.new_stream(out, index.schema) as w:
            w.write_table(index)
        name = f"{root}/part-{file:06d}"
        system.move(temp, name + ".arrow")
        system.move(temp + ".index", name + ".index")
        yield pa.RecordBatch.from_pydict({"file": [file], "tokens": [int(sum(sizes))]}, schema=pa.schema([("file", pa.int32()), ("tokens", pa.int64())]))

    sizes = {r["file"]: r["tokens"] for r in dealt.mapInArrow(run, "file int, tokens long").collect()}
    at, rows = 0, []
    for file in sorted(sizes):
        rows.append((f"{out_uri}/part-{file:06d}", at))
        at += sizes[file]
    return documents.sparkSession.createDataFrame(rows, "file string, first_start long")


def read_token_files(files: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document, read back from the files."""

    def run(batches):
        for batch in batches:
            for name, first in zip(batch.column("file").to_pylist(), batch.column("first_start").to_pylist(), strict=True):
                stream = StreamFile(name + ".arrow")
                system, path = pafs.FileSystem.from_uri(name + ".index")
                with system.open_input_stream(path) as src:
                    index = pa.ipc.open_stream(src).read_all()
                starts, sizes = index.column("start").to_numpy(), index.column("n_tokens").to_numpy()
                crc = [zlib.crc32(stream.tokens(int(s), int(n)).astype("<u4").tobytes()) for s, n in zip(starts, sizes, strict=True)]
                table = pa.table({"doc_id": index.column("doc_id"), "start": pa.array(starts + first, pa.int64()), "n_tokens": pa.array(sizes, pa.int64()), "ids_crc32": pa.array(crc, pa.int64())})
                yield from table.to_batches(max_chunksize=20_000)

    count = max(1, files.count())
    return files.repartition(count, "file").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def tokenizer_file(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def encode_documents(documents: DataFrame, out_uri: str | None = None, tokenizer: str | None = None, **options) -> DataFrame:
    out = out_uri or scratch_path(documents.sparkSession, "tokens")
    return read_token_files(write_token_files(documents, tokenizer or tokenizer_file(), out, **options))

"""N-gram Jaccard self-join of documents by a MinHash LSH forest.

Each of ``trees`` tries orders the documents by a path of MinHash labels.  Documents
match in a trie where their paths share a prefix; the prefix starts at the greatest
depth that is expected to reach the target recall at the threshold and is shortened,
label by label, while the recall measured on the verified links is below the target.
Nodes of the tries that hold the same documents are one node.

Every two documents of a node are compared exactly, in tasks of bounded size and
without writing pairs.  A document's home is the least document that two steps over
trie nodes reach; documents of one home are compared as one group, and a node whose
documents have several homes is a group as well, in which a pair counts if its homes
differ and if the node's trie is the first where it meets.  So chains of candidates make
no large groups, and only verified links make classes.

Defined results: a null or empty text (no word) has class = its own id and no
link; texts of one to four words are one shingle; documents with equal shingle
sets are linked to each other and counted through one representative; repeated
rows count as separate documents; null ids stay null; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .common import HOT_SHARE, NULL_ID, connected_components, join_unique, materialize, small_batches

_CHUNK = 1024


def expected_recall(similarity, trees: int, depth: int):
    """Chance that two sets meet: they agree on ``depth`` labels of some of the tries."""
    return 1 - (1 - similarity**depth) ** trees


def first_depth(threshold: float, trees: int, depth_max: int, target: float) -> int:
    """Greatest depth whose expected recall at the threshold meets the target."""
    return next((d for d in range(depth_max, 1, -1) if expected_recall(threshold, trees, d) >= target), 1)


def _hash_family(k: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20240229)
    a = rng.integers(1, 1 << 31, k, dtype=np.uint64).astype(np.uint32) * np.uint32(2) + np.uint32(1)
    return a, rng.integers(0, 1 << 32, k, dtype=np.uint64).astype(np.uint32)


def minhash(shingles: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    low = (shingles >> np.uint64(16)).astype(np.uint32)
    best = np.full(len(a), 0xFFFFFFFF, dtype=np.uint32)
    for i in range(0, len(low), 1024):
        np.minimum(best, (low[i : i + 1024, None] * a + b).min(axis=0), out=best)
    return best


def _set_key(s: np.ndarray) -> bytes:
    return hashlib.blake2b(s.tobytes(), digest_size=16).digest()


def signatures(docs: DataFrame, shingle: int, width: int) -> DataFrame:
    """(rid, mark, key, n, sig): the shingle set's identity, size and MinHash labels."""

    def run(batches):
        a, b = _hash_family(width)
        for batch in batches:
            keys, sizes, sigs = [], [], []
            for text in batch.column("text"):
                s = K.shingle_set(K.text_words(text.as_py()), shingle)
                keys.append(_set_key(s))
                sizes.append(len(s))
                sigs.append(minhash(s, a, b).view(np.int32) if len(s) else None)
            cols = [batch.column("rid"), batch.column("mark"), pa.array(keys, pa.binary()), pa.array(sizes, pa.int64()), pa.array(sigs, pa.list_(pa.int32()))]
            yield pa.RecordBatch.from_arrays(cols, ["rid", "mark", "key", "n", "sig"])

    return docs.select("rid", "mark", "text").mapInArrow(run, "rid long, mark long, key binary, n long, sig array<int>")


def trie_nodes(classes: DataFrame, trees: int, stride: int, depth: int) -> tuple[DataFrame, DataFrame]:
    """The trie nodes at a depth that hold several classes, as (label, tree, held), and
    (node, label) of the classes they hold; of nodes with the same classes only that of
    the first trie."""
    labels = [F.struct(F.lit(t).alias("tree"), F.xxhash64(F.lit(t), F.slice("sig", t * stride + 1, depth)).alias("label")) for t in range(trees)]
    paths = classes.select("node", F.inline(F.array(*labels)))
    several = paths.groupBy("label").agg(
        F.first("tree").alias("tree"), F.count("*").alias("held"), F.min("node").alias("least"), F.bit_xor(F.xxhash64("node")).alias("one"), F.bit_xor(F.xxhash64("node", F.lit(1))).alias("two")
    )
    several = several.filter("held > 1").groupBy("held", "one", "two").agg(F.min(F.struct("tree", "label", "least")).alias("first"))
    nodes = materialize(several.select("held", "first.*"), "trie-nodes")
    return nodes, materialize(paths.join(nodes.select("label", "least"), "label").select("node", "label", "least"), "trie-paths")


def _common_counts(sets: list[np.ndarray]) -> np.ndarray:
    """Counts of the shingles that each two sets have in common."""
    n = len(sets)
    owner = np.repeat(np.arange(n), [len(s) for s in sets])
    _, ids, df = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    keep = df[ids] > 1
    owner, ids = owner[keep], ids[keep]
    _, ids = np.unique(ids, return_inverse=True)
    order = np.argsort(ids, kind="stable")
    owner, ids = owner[order], ids[order]
    counts = np.zeros((n, n), dtype=np.float32)
    columns = max(1, min(4096, (1 << 23) // n))
    for lo in range(0, int(ids[-1]) + 1 if len(ids) else 0, columns):
        i, j = np.searchsorted(ids, (lo, lo + columns))
        part = np.zeros((n, columns), dtype=np.float32)
        part[owner[i:j], ids[i:j] - lo] = 1
        counts += part @ part.T
    return counts


def _verify(frame, threshold: float, two_sided: bool, trees: int, depth: int):
    """Links of the classes of one task: (node, links, root, pairs, due).

    ``due`` adds up, over the pairs linked, one over the chance that such a pair meets.
    """
    import pandas as pd

    frame = frame.drop_duplicates("key").sort_values("node").reset_index(drop=True)
    sets = [np.frombuffer(x, dtype=np.uint64) for x in frame.shingles]
    size = np.array([len(s) for s in sets], dtype=np.float32)
    common = _common_counts(sets)
    union = size[:, None] + size[None, :] - common
    link = common >= threshold * union - 1e-6
    np.fill_diagonal(link, False)
    if two_sided:
        side = frame.chunk.to_numpy()
        link &= side[:, None] != side[None, :]
    tree = int(frame.tree.iloc[0])
    if tree >= 0:  # pairs of one home count there, others in the first trie where they meet
        home, labels = frame.home.to_numpy(), np.stack(frame.labels.to_list())
        link &= home[:, None] != home[None, :]
        for t in range(tree):
            link &= labels[:, None, t] != labels[None, :, t]
    links = link.astype(np.float64) @ frame.copies.to_numpy(dtype=np.float64)
    one_over = np.where(link, 1 / expected_recall(np.minimum(common / union, 1).astype(np.float64), trees, depth), 0.0)
    root = np.full(len(sets), -1)
    for i in range(len(sets)):
        if root[i] < 0:
            root[i], front = i, np.array([i])
            while len(front):
                front = np.flatnonzero(link[front].any(axis=0) & (root < 0))
                root[front] = i
    node = frame.node.to_numpy()
    return pd.DataFrame({"node": node, "links": links.astype(np.int64), "root": node[root], "pairs": link.sum(axis=1).astype(np.int64), "due": one_over.sum(axis=1)})


def _verifier(threshold: float, trees: int, depth: int):
    def verify(key, frame):
        return _verify(frame, threshold, key[2] != key[3], trees, depth)

    return verify


def candidate_groups(nodes: DataFrame, paths: DataFrame) -> DataFrame:
    """(node, home, unit, tree, size): the groups in which classes are compared, those of
    a home (tree -1) and the trie nodes whose classes have several homes."""
    home = paths.groupBy("node").agg(F.min("least").alias("home"), F.collect_list("label").alias("labels"))
    spread = home.select("node", "home", F.explode("labels").alias("label"))
    nearer = spread.groupBy("label").agg(F.min("home").alias("home"))
    home = spread.select("node", "label").join(nearer, "label").groupBy("node").agg(F.min("home").alias("home"), F.collect_list("label").alias("labels"))
    home = materialize(home, "homes")
    spread = home.select("node", "home", F.explode("labels").alias("label"))
    mixed = spread.groupBy("label").agg(F.min("home").alias("lo"), F.max("home").alias("hi")).filter("lo <> hi").select("label")
    sizes = home.groupBy("home").agg(F.count("*").alias("size")).filter("size > 1")
    whole = home.join(sizes, "home").select("node", "home", F.col("home").alias("unit"), F.lit(-1).alias("tree"), "size")
    split = spread.join(mixed.join(nodes.drop("least"), "label"), "label")
    return whole.unionByName(split.select("node", "home", F.col("label").alias("unit"), "tree", F.col("held").alias("size")))


def _links(documents: DataFrame, id_col: str, text_col: str, threshold: float, shingle: int, trees: int, depth_max: int, target_recall: float) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Documents as (rid, mark, key, n) rows, their classes as (key, node, rid, copies,
    head) and what was found as (key, root, links) of the linked classes."""
    stride = first_depth(threshold, trees, depth_max, target_recall)
    docs = small_batches(documents).select(F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID)).alias("rid"), F.xxhash64(F.col(text_col)).alias("mark"), F.col(text_col).alias("text"))
    sigs = materialize(signatures(docs, shingle, trees * stride), "signatures")
    heads = sigs.filter("n > 0").groupBy("key").agg(F.min(F.struct("rid", "mark")).alias("head"), F.count("*").alias("copies"), F.first("sig").alias("sig"))
    heads = materialize(heads.select(F.xxhash64("key").alias("node"), "key", "head", "copies", "sig"), "classes")

    def to_sets(batches):
        for batch in batches:
            names = [c for c in batch.schema.names if c != "text"]
            sets = [K.shingle_set(K.text_words(t.as_py()), shingle) for t in batch.column("text")]
            keep = pa.array([i for i, (s, k) in enumerate(zip(sets, batch.column("key"), strict=True)) if _set_key(s) == k.as_py()], pa.int64())
            part = batch.append_column("shingles", pa.array([s.tobytes() for s in sets], pa.binary())).take(keep)
            yield part.select([*names, "shingles"])

    for depth in range(stride, 0, -1):
        nodes, paths = trie_nodes(heads.select("node", "sig"), trees, stride, depth)
        groups = candidate_groups(nodes, paths).withColumn("chunks", F.ceil(F.col("size") / _CHUNK).cast("int"))
        labels = F.when(F.col("tree") >= 0, F.array(*[F.xxhash64(F.lit(t), F.slice("sig", t * stride + 1, depth)) for t in range(trees)]))
        wanted = groups.join(heads, "node").select("node", "home", "key", "copies", "unit", "tree", "chunks", labels.alias("labels"), F.col("head.rid").alias("rid"), F.col("head.mark").alias("mark"))
        sets = wanted.join(docs, ["rid", "mark"]).select("node", "home", "key", "copies", "unit", "tree", "chunks", "labels", "text")
        sets = sets.mapInArrow(to_sets, "node long, home long, key binary, copies long, unit long, tree int, chunks int, labels array<long>, shingles binary")
        sets = sets.withColumn("chunk", F.when(F.col("chunks") > 1, F.pmod(F.xxhash64("key"), F.col("chunks"))).otherwise(0).cast("int"))
        tasks = sets.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
        tasks = tasks.withColumn("one", F.least("chunk", "other")).withColumn("two", F.greatest("chunk", "other"))

        verify = _verifier(threshold, trees, depth)
        found = materialize(tasks.groupBy("unit", "tree", "one", "two").applyInPandas(verify, "node long, links long, root long, pairs long, due double"), "links")
        seen = found.agg(F.sum("pairs").alias("pairs"), F.sum("due").alias("due")).first()
        if not seen["pairs"] or seen["pairs"] >= target_recall * seen["due"]:
            break
    # A class has a root in each task it was in; only roots that share a class are joined up.
    links = found.groupBy("node").agg(F.sum("links").alias("links"), F.min("root").alias("root"), F.collect_set("root").alias("roots"))
    links = materialize(links, "linked")
    edges = links.filter(F.size("roots") > 1).select(F.col("root").alias("u"), F.explode("roots").alias("v"))
    roots = connected_components(edges).select(F.col("node").alias("root"), "comp")
    links = links.join(roots, "root", "left").select("node", "links", F.coalesce("comp", "root").alias("root"))
    return sigs, heads, links


def similar_documents(
    documents: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    threshold: float = 0.8,
    shingle: int = 5,
    trees: int = 20,
    depth_max: int = 8,
    target_recall: float = 0.999,
) -> DataFrame:
    """One row per document: (doc_id, class_id, n_links).

    class_id is the least id of the connected documents (Jaccard of distinct
    word shingles >= threshold), n_links the number of other documents linked.
    """
    sigs, heads, links = _links(documents, id_col, text_col, threshold, shingle, trees, depth_max, target_recall)
    linked = heads.select("node", F.col("head.rid").alias("rid"), "copies").join(links, "node")
    named = linked.join(linked.groupBy("root").agg(F.min("rid").alias("class_id")), "root").select("node", "class_id", "links")
    per_class = heads.join(named, "node", "left").select(
        "key", "copies", F.coalesce("class_id", "head.rid").alias("class_id"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links")
    )
    back = lambda c: F.when(F.col(c) != NULL_ID, F.col(c))
    rows = sigs.select("rid", F.when(F.col("n") > 0, F.col("key")).alias("key"))
    none = rows.filter("key is null").select("rid", F.col("rid").alias("class_id"), F.lit(0).cast("long").alias("n_links"))
    some = join_unique(rows.filter("key is not null"), per_class, "key", max(sigs.count(), HOT_SHARE), "copies")
    out = some.select("rid", "class_id", "n_links").unionByName(none)
    return out.select(back("rid").alias("doc_id"), back("class_id").alias("class_id"), F.col("n_links").cast("long").alias("n_links"))


def distinct_documents(documents: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.8, shingle: int = 5, trees: int = 20, depth_max: int = 8, target_recall: float = 0.999) -> DataFrame:
    """One document, all columns, of each group of similar ones: the one of least id, of
    equal ids that of least text hash, null ids being least.

    Documents without a word are similar to none and stay, all rows of them; rows that
    repeat an id with another text are other documents.
    """
    _, heads, links = _links(documents, id_col, text_col, threshold, shingle, trees, depth_max, target_recall)
    grouped = heads.select("node", "head").join(links.select("node", "root"), "node", "left").groupBy(F.coalesce("root", "node").alias("root")).agg(F.min("head").alias("head"))
    kept = grouped.select(F.col("head.rid").alias("_rid"), F.col("head.mark").alias("_mark"))
    rows = documents.withColumn("_rid", F.coalesce(F.col(id_col).cast("long"), F.lit(NULL_ID))).withColumn("_mark", F.xxhash64(F.col(text_col)))
    worded = F.coalesce(F.col(text_col).rlike(r"[^\x20\x09-\x0D]"), F.lit(False))
    some = rows.filter(worded).join(kept, ["_rid", "_mark"], "left_semi").dropDuplicates(["_rid", "_mark"])
    return some.unionByName(rows.filter(~worded)).select(*[F.col(f"`{c}`") for c in documents.columns])

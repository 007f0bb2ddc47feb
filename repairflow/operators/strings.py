"""Tools on string attributes; all work on distinct values and emit equalities."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.graph import components
from ..functions.text import minhash_pairs, near_pairs, values_of
from ..plans.pool import bind, clause_struct, equality_repairs, repair_rows
from ..session import written
from .base import CleaningOperator


class SpellReplace(CleaningOperator):
    """Values that are no dictionary word become the nearest word within ``rec`` edits;
    ties to the word more frequent in the relation, then to the smaller one."""

    name, threshold_params = "spell", ("rec",)

    def __init__(self, dictionary: DataFrame, domains=None, **params):
        """``dictionary`` has a column ``word``."""
        super().__init__(domains, **params)
        self.dictionary = dictionary

    def replacements(self, df: DataFrame) -> DataFrame:
        """(v, word)."""
        attr, rec = self.p("attr"), int(self.p("rec"))
        values = values_of(df, attr)
        lexicon = self.dictionary.select("word").distinct()
        wrong = values.join(lexicon, values.v == lexicon.word, "left_anti").select("v")
        freq = lexicon.join(values, lexicon.word == values.v, "left").select("word", F.coalesce("cnt", F.lit(0)).alias("freq"))
        near = near_pairs(wrong, freq, "v", "word", rec) if rec > 0 else wrong.crossJoin(freq.limit(0)).withColumn("dist", F.lit(0))
        return near.groupBy("v").agg(F.min_by("word", F.struct("dist", -F.col("freq"), "word")).alias("word"))

    def repairs(self, df):
        found = self.replacements(df)
        return equality_repairs(found, {self.p("attr"): F.col("v")}, self.p("attr"), F.col("word"), self.name, self.params)


class EditMatch(CleaningOperator):
    """A value becomes the most frequent value within ``thresh`` edits of it, itself
    included; ties to the smaller one."""

    name, threshold_params = "edit", ("thresh",)

    def replacements(self, df: DataFrame) -> DataFrame:
        values = values_of(df, self.p("attr"))
        other = values.select(F.col("v").alias("w"), F.col("cnt").alias("freq"))
        near = near_pairs(values.select("v"), other, "v", "w", int(self.p("thresh")))
        return near.groupBy("v").agg(F.min_by("w", F.struct(-F.col("freq"), F.col("w"))).alias("word")).filter("v <> word")

    def repairs(self, df):
        return equality_repairs(self.replacements(df), {self.p("attr"): F.col("v")}, self.p("attr"), F.col("word"), self.name, self.params)


class MinHashReplace(CleaningOperator):
    """Values of verified shingle similarity are one entity, named by its most frequent
    value; ties to the smaller one."""

    name, threshold_params = "minhash", ("thresh",)

    def __init__(self, domains=None, k_hashes: int = 64, bands: int = 16, shingle: int = 3, **params):
        super().__init__(domains, **params)
        self.k, self.bands, self.shingle = k_hashes, bands, shingle

    def pairs(self, df: DataFrame) -> DataFrame:
        return minhash_pairs(values_of(df, self.p("attr")), float(self.p("thresh")), self.k, self.bands, self.shingle)

    def replacements(self, df: DataFrame) -> DataFrame:
        values = values_of(df, self.p("attr"))
        edges = written(self.pairs(df), "pairs")
        comp = components(edges.select(F.col("a").alias("node")).union(edges.select("b")).distinct(), edges)
        named = comp.join(values, comp.node == values.v)
        head = named.groupBy("comp").agg(F.min_by("v", F.struct(-F.col("cnt"), F.col("v"))).alias("word"))
        return named.join(head, "comp").filter("v <> word").select("v", "word")

    def repairs(self, df):
        return equality_repairs(self.replacements(df), {self.p("attr"): F.col("v")}, self.p("attr"), F.col("word"), self.name, self.params)


class SplitFields(CleaningOperator):
    """A value with exactly one separator gives its first part to ``attr`` and its second
    to ``other``; the two repairs are one unit and read the value before it changes."""

    name, attr_params = "split", ("attr", "other")

    def repairs(self, df):
        attr, other, sep = self.p("attr"), self.p("other"), self.p("sep")
        values = values_of(df, attr).filter(F.size(F.split("v", f"\\Q{sep}\\E", -1)) == 2)
        part = lambda i: F.split_part("v", F.lit(sep), F.lit(i))
        second = equality_repairs(values, {attr: F.col("v")}, other, part(2), self.name, self.params)
        first = equality_repairs(values, {attr: F.col("v")}, attr, part(1), self.name, self.params).withColumn("pos", F.lit(1))
        unit = F.conv(F.substring(F.md5(F.concat(F.lit("split|"), F.col("pred")[0]["lo"])), 1, 15), 16, 10).cast("long")
        return second.unionByName(first).withColumn("unit", unit)


class FillMissing(CleaningOperator):
    """Null (and empty) values become the most frequent value, of the whole relation or
    of the group of ``by``; ties to the smaller one."""

    name, attr_params = "fill", ("attr", "by")

    def repairs(self, df):
        attr, by = self.p("attr"), self.params.get("by")
        known = df.filter(F.col(attr).isNotNull() & (F.col(attr).cast("string") != ""))
        keys = [by] if by else []
        counts = known.groupBy(*keys, attr).agg(F.count("*").alias("c"))
        if by:
            counts = counts.filter(F.col(by).isNotNull())
        best = counts.groupBy(*keys).agg(F.min_by(attr, F.struct(-F.col("c"), F.col(attr))).alias("mode")).filter("mode is not null")
        out = None
        for op, lo in (("is_null", None), ("eq", F.lit(""))):
            clauses = [clause_struct(attr, op, lo)] + ([clause_struct(by, "eq", F.col(by))] if by else [])
            sig = f"{attr}:{op}" + (f",{by}:eq" if by else "")
            part = repair_rows(best, clauses, sig, attr, F.col("mode"), self.name, self.params)
            out = part if out is None else out.unionByName(part)
        return out


class RangeNullify(CleaningOperator):
    """Values outside [lo, hi] become null, by one repair for each end."""

    name, threshold_params = "nullify", ("lo", "hi")

    def repairs(self, df):
        spark, attr = df.sparkSession, self.p("attr")
        one = spark.range(1)
        parts = [repair_rows(one, [clause_struct(attr, op, F.lit(self.params[k]))], f"{attr}:{op}", attr, F.lit(None), self.name, self.params) for op, k in (("lt", "lo"), ("gt", "hi")) if self.params.get(k) is not None]
        return parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])


def applied(df: DataFrame, op: CleaningOperator, key: str = "rec_id") -> DataFrame:
    """The relation after all repairs of one setting, for chained tools.

    Every repair reads the tool's input; of two for one cell the later position and
    greater value win.
    """
    return apply_pool(df, op.repairs(df), key)


def apply_pool(df: DataFrame, pool: DataFrame, key: str = "rec_id") -> DataFrame:
    cells = _cells(pool, df, key)
    joined = df.join(cells, key, "left")  # by name: the pool may come from df itself
    cols = [F.when(F.map_contains_key(F.coalesce("_new", F.create_map().cast("map<string,string>")), c), F.col("_new")[c].cast(df.schema[c].dataType)).otherwise(F.col(c)).alias(c) for c in df.columns if c != key]
    out = joined.select(key, *cols)
    return out.select(*df.columns)


def _cells(pool: DataFrame, df: DataFrame, key: str) -> DataFrame:
    last = bind(pool, df, (key,)).groupBy(key, "target").agg(F.max_by("new", F.struct("pos", F.coalesce("new", F.lit("")))).alias("new"))
    return last.groupBy(key).agg(F.map_from_entries(F.collect_list(F.struct("target", "new"))).alias("_new"))

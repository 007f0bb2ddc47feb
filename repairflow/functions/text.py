"""String kernels in DataFrame functions: deletion keys, nearest words, MinHash."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PRIME = (1 << 31) - 1


def deletion_keys(col: Column, depth: int) -> Column:
    """Strings left by deleting up to ``depth`` characters.

    Two strings within ``depth`` edits share one, so a join on the keys finds all
    such pairs.
    """
    keys = F.array(col)
    for _ in range(depth):
        one = lambda s: F.transform(F.sequence(F.lit(1), F.length(s)), lambda i: F.concat(F.substring(s, F.lit(1), i - 1), F.substring(s, i + 1, F.length(s))))
        more = F.flatten(F.transform(F.filter(keys, lambda s: F.length(s) > 0), one))
        keys = F.array_distinct(F.concat(keys, more))
    return keys


def near_pairs(left: DataFrame, right: DataFrame, a: str, b: str, depth: int) -> DataFrame:
    """Rows of left and right whose strings are within ``depth`` edits, with ``dist``."""
    lk = left.withColumn("_key", F.explode(deletion_keys(F.col(a), depth)))
    rk = right.withColumn("_key", F.explode(deletion_keys(F.col(b), depth)))
    pairs = lk.join(rk, "_key").drop("_key").distinct()
    return pairs.withColumn("dist", F.levenshtein(F.col(a), F.col(b), depth)).filter("dist >= 0")


def values_of(df: DataFrame, attr: str) -> DataFrame:
    """(v, cnt): the distinct non-null values of an attribute, the only pass over rows."""
    return df.filter(F.col(attr).isNotNull()).groupBy(F.col(attr).alias("v")).agg(F.count("*").alias("cnt"))


def shingles(col: Column, n: int) -> Column:
    """Distinct character n-grams; a shorter string is one."""
    cut = F.transform(F.sequence(F.lit(1), F.greatest(F.length(col) - (n - 1), F.lit(1))), lambda i: F.substring(col, i, F.lit(n)))
    return F.array_distinct(cut)


def shingle_hash(s: Column) -> Column:
    return F.conv(F.substring(F.md5(s), 1, 7), 16, 10).cast("long")


def minhash_signature(grams: Column, k: int) -> Column:
    """Least of (a*h + b) mod 2**31-1 for k fixed pairs (a, b)."""
    hashes = F.transform(grams, shingle_hash)
    pick = lambda i: F.array_min(F.transform(hashes, lambda h: F.pmod((i * 1_000_003 + 17) * h + (i * 998_244_353 + 11) % PRIME, F.lit(PRIME))))
    return F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda i: pick(i.cast("long")))


def minhash_pairs(values: DataFrame, thresh: float, k: int, bands: int, n: int) -> DataFrame:
    """(a, b, jaccard), a < b: values that share a band and are verified similar."""
    rows = k // bands
    signed = values.select("v", shingles(F.col("v"), n).alias("grams")).withColumn("sig", minhash_signature(F.col("grams"), k))
    band = F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda i: F.concat_ws("-", i.cast("string"), F.array_join(F.slice("sig", i * rows + 1, rows).cast("array<string>"), "-")))
    keyed = signed.select("v", "grams", F.explode(band).alias("band"))
    left, right = keyed.select("band", F.col("v").alias("a"), F.col("grams").alias("ga")), keyed.select("band", F.col("v").alias("b"), F.col("grams").alias("gb"))
    pairs = left.join(right, "band").filter("a < b").dropDuplicates(["a", "b"])
    common = F.size(F.array_intersect("ga", "gb"))
    jaccard = common / (F.size("ga") + F.size("gb") - common)
    return pairs.select("a", "b", jaccard.alias("jaccard")).filter(F.col("jaccard") >= thresh)

"""Window detectors of numeric outliers and the last-good fill they share.

A series is sorted in one task by default.  With ``bucket``, a column that grows with
the order (a day, a month), a series is cut into buckets: a detector's bucket gets a halo
of the rows before it, and the last good value is carried over buckets by a second, small
pass, so that no task sorts a whole series.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..plans.pool import equality_repairs
from .base import CleaningOperator


class WindowDetector(CleaningOperator):
    """Flags readings of ``attr`` by a window of ``window_size`` rows of their series."""

    def __init__(self, series: str, order: list[str], key: str = "rec_id", domains=None, bucket: Column | None = None, **params):
        super().__init__(domains, **params)
        self.series, self.order, self.key, self.bucket = series, order, key, bucket

    def rows_before(self) -> int:
        return int(self.p("window_size"))

    def flag(self, df: DataFrame) -> DataFrame:
        """``df`` with a boolean column ``flagged``."""
        raise NotImplementedError

    def repairs(self, df):
        if self.bucket is None:
            fixed = last_good(self.flag(df), "flagged", self.p("attr"), self.series, self.order)
        else:
            fixed = last_good_bucketed(self.flag(df), "flagged", self.p("attr"), self.series, self.order, self.bucket)
        off = fixed.filter(F.col("flagged") & F.col("good").isNotNull())
        return equality_repairs(off, {self.key: F.col(self.key)}, self.p("attr"), F.col("good"), self.name, self.params)

    def over(self, lo: int, hi: int):
        parts = [self.series] if self.bucket is None else [self.series, "_bucket"]
        return Window.partitionBy(*parts).orderBy(*self.order).rowsBetween(lo, hi)

    def haloed(self, df: DataFrame, halo: int) -> DataFrame:
        """Rows in their bucket, and the last ``halo`` rows before a bucket in it as well
        (``_own`` false): the rows that a window of so many rows back can reach."""
        if self.bucket is None:
            return df.withColumn("_own", F.lit(True))
        rows = df.withColumn("_bucket", self.bucket)
        last = F.row_number().over(Window.partitionBy(self.series, "_bucket").orderBy(*[F.col(c).desc() for c in self.order]))
        sizes = rows.groupBy(self.series, "_bucket").agg(F.count("*").alias("_n"))
        # A bucket's last rows reach the later buckets until ``halo`` rows lie between.
        order = Window.partitionBy(self.series).orderBy("_bucket")
        sizes = sizes.withColumn("_upto", F.sum("_n").over(order.rowsBetween(Window.unboundedPreceding, 0)))
        later = F.collect_list(F.struct(F.col("_bucket").alias("to"), (F.col("_upto") - F.col("_n")).alias("before"))).over(order.rowsBetween(1, max(halo, 1)))
        sizes = sizes.select(F.col(self.series).alias("_s"), F.col("_bucket").alias("_b"), "_upto", later.alias("_later"))
        tails = rows.withColumn("_r", last).filter(F.col("_r") <= halo)
        tails = tails.join(sizes, F.col(self.series).eqNullSafe(F.col("_s")) & F.col("_bucket").eqNullSafe(F.col("_b")))
        reach = tails.withColumn("_to", F.explode(F.filter("_later", lambda x: x["before"] - F.col("_upto") + F.col("_r") <= halo)))
        halos = reach.withColumn("_bucket", F.col("_to.to")).select(*df.columns, "_bucket", F.lit(False).alias("_own"))
        return rows.withColumn("_own", F.lit(True)).unionByName(halos)


def last_good(df: DataFrame, flag: str, attr: str, series: str, order: list[str]) -> DataFrame:
    """Adds ``good``: the last value not flagged before each row, or for leading ones the
    next; for unflagged rows their own value.  Nulls are passed over.

    The next value is the last one of the reverse order: frames that grow a row at a
    time are computed once a row, those that shrink once for all of their rows."""
    ok = F.when(~F.col(flag), F.col(attr))
    back = Window.partitionBy(series).orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    ahead = Window.partitionBy(series).orderBy(*[_reverse(c) for c in order]).rowsBetween(Window.unboundedPreceding, 0)
    good = F.coalesce(F.last(ok, ignorenulls=True).over(back), F.last(ok, ignorenulls=True).over(ahead))
    return df.withColumn("good", good)


def _reverse(col: str) -> Column:
    return F.col(col).desc_nulls_last()


def last_good_bucketed(df: DataFrame, flag: str, attr: str, series: str, order: list[str], bucket: Column) -> DataFrame:
    """``last_good`` for one huge series: inside buckets, then carried from bucket to
    bucket through one row each.  ``bucket`` must grow with the order."""
    ok = F.when(~F.col(flag), F.col(attr))
    rows = df.withColumn("_b", bucket)
    inside = Window.partitionBy(series, "_b").orderBy(*order)
    back = inside.rowsBetween(Window.unboundedPreceding, 0)
    first_ord = F.struct(*order)
    ends = rows.filter(~F.col(flag) & F.col(attr).isNotNull()).groupBy(series, "_b").agg(F.max_by(attr, first_ord).alias("_l"), F.min_by(attr, first_ord).alias("_f"))
    ends = rows.select(series, "_b").distinct().join(ends, [series, "_b"], "left")
    up = Window.partitionBy(series).orderBy("_b")
    ends = ends.withColumn("_prev", F.last("_l", ignorenulls=True).over(up.rowsBetween(Window.unboundedPreceding, -1)))
    down = Window.partitionBy(series).orderBy(_reverse("_b"))
    ends = ends.withColumn("_next", F.last("_f", ignorenulls=True).over(down.rowsBetween(Window.unboundedPreceding, -1)))
    out = rows.withColumn("_in", F.last(ok, ignorenulls=True).over(back)).join(ends.select(series, "_b", "_prev", "_next", "_f"), [series, "_b"], "left")
    return out.withColumn("good", F.coalesce("_in", "_prev", "_f", "_next")).select(*df.columns, "good")


class GaussOutlier(WindowDetector):
    """Beyond ``k`` sample deviations from the mean of the rows before (three at least)."""

    name, threshold_params = "gauss", ("k",)

    def __init__(self, *args, include_self: bool = False, **options):
        super().__init__(*args, **options)
        self.include_self = include_self

    def flag(self, df):
        w = self.over(-int(self.p("window_size")), 0 if self.include_self else -1)
        v = F.col(self.p("attr"))
        mean, sd, n = F.avg(v).over(w), F.stddev_samp(v).over(w), F.count(v).over(w)
        rows = self.haloed(df, int(self.p("window_size")))
        flagged = rows.withColumn("flagged", F.coalesce((n >= 3) & (F.abs(v - mean) > float(self.p("k")) * sd), F.lit(False)))
        return flagged.filter("_own").select(*df.columns, "flagged")


class HistOutlier(WindowDetector):
    """Equal-width bins of windows: a value in a bin of share below ``outlier_threshold``
    that is no peak (share of ``peak_threshold`` or more).

    Windows slide: a reading's is the last ``window_size`` readings up to it.  With
    ``tumbling`` they follow each other, and a reading is held against its own.
    """

    name, threshold_params = "hist", ("outlier_threshold",)

    def __init__(self, *args, bins: int = 20, tumbling: bool = False, **options):
        super().__init__(*args, **options)
        self.bins, self.tumbling = bins, tumbling

    def _off(self, share: Column) -> Column:
        return F.coalesce((share < float(self.p("outlier_threshold"))) & (share < float(self.p("peak_threshold"))), F.lit(False))

    def flag(self, df):
        if self.tumbling:
            return self._flag_tumbling(df)
        v, size = F.col(self.p("attr")), int(self.p("window_size"))
        w = self.over(1 - size, 0)
        rows = self.haloed(df, size - 1).withColumn("_seen", F.collect_list(v.cast("double")).over(w))  # bounded by the window
        # Bounds and the reading's bin are bound once a row, not once for each reading that is seen.
        bin_ = lambda x, b: F.least(F.floor((x - b["lo"]) / b["wide"] * self.bins), F.lit(self.bins - 1))
        bounds = F.array(F.struct(F.array_min("_seen").alias("lo"), (F.array_max("_seen") - F.array_min("_seen")).alias("wide")))
        alike = lambda b: F.transform(F.array(bin_(v.cast("double"), b)), lambda own: F.size(F.filter("_seen", lambda x: bin_(x, b) == own)))[0]
        mates = F.transform(bounds, lambda b: F.when(b["wide"] > 0, alike(b)).otherwise(F.size("_seen")))[0]
        share = F.when(v.isNotNull(), mates / F.size("_seen"))
        return rows.withColumn("flagged", self._off(share)).filter("_own").select(*df.columns, "flagged")

    def _flag_tumbling(self, df):
        v, size = F.col(self.p("attr")), int(self.p("window_size"))
        number = F.row_number().over(Window.partitionBy(self.series).orderBy(*self.order)) - 1
        rows = df.withColumn("_w", F.floor(number / size))
        whole, lo, hi = Window.partitionBy(self.series, "_w"), F.min(v), F.max(v)
        rows = rows.withColumn("_lo", lo.over(whole)).withColumn("_hi", hi.over(whole)).withColumn("_n", F.count(v).over(whole))
        bin_ = F.when(F.col("_hi") > F.col("_lo"), F.least(F.floor((v - F.col("_lo")) / (F.col("_hi") - F.col("_lo")) * self.bins), F.lit(self.bins - 1))).otherwise(0)
        rows = rows.withColumn("_bin", bin_)
        share = F.count(v).over(Window.partitionBy(self.series, "_w", "_bin")) / F.col("_n")
        return rows.withColumn("flagged", self._off(share)).select(*df.columns, "flagged")


class PCAOutlier(WindowDetector):
    """The last ``window_size`` readings as a vector; distance from the mean in the
    principal components, each over its eigenvalue, above ``outlier_threshold``."""

    name, threshold_params = "pca", ("outlier_threshold",)

    def flag(self, df):
        v, w = F.col(self.p("attr")).cast("double"), int(self.p("window_size"))
        order = Window.partitionBy(self.series).orderBy(*self.order)
        lags = [v if i == 0 else F.lag(v, i).over(order) for i in range(w)]
        rows = df.withColumns({f"_x{i}": x for i, x in enumerate(lags)})
        full = rows.dropna(subset=[f"_x{i}" for i in range(w)])
        sums = full.agg(
            F.count("*").alias("n"),
            *[F.avg(f"_x{i}").alias(f"m{i}") for i in range(w)],
            *[F.covar_pop(f"_x{i}", f"_x{j}").alias(f"c{i}_{j}") for i in range(w) for j in range(i, w)],
        ).first()  # w*(w+3)/2 numbers
        if not sums["n"]:
            return df.withColumn("flagged", F.lit(False))
        cov = np.array([[sums[f"c{min(i, j)}_{max(i, j)}"] for j in range(w)] for i in range(w)])
        value, vector = np.linalg.eigh(cov)
        score = F.lit(0.0)
        for k in range(w):
            if value[k] > 1e-9:
                proj = sum(((F.col(f"_x{i}") - float(sums[f"m{i}"])) * float(vector[i, k]) for i in range(w)), F.lit(0.0))
                score = score + proj * proj / float(value[k])
        return rows.withColumn("flagged", F.coalesce(score > float(self.p("outlier_threshold")), F.lit(False))).select(*df.columns, "flagged")

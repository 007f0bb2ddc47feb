"""A classifier of repairs, learnt from searched blocks, that drops what will not help.

Examples are (block, repair), positive if the repair is in the block's best plan.
Features tell which attributes a repair reads and writes, which tool made it and
with what numeric parameters; data values are no features.  The threshold is moved
down to the least positive example, so no training positive is lost.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.ml.classification import LogisticRegression
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MIN_BLOCKS, MIN_POSITIVES = 5, 10


def label_examples(blocks_units: DataFrame, best: DataFrame) -> DataFrame:
    """(block, unit, label): units that were candidates in a block; 1 if in its best plan."""
    chosen = best.select("block", "unit").distinct().withColumn("label", F.lit(1.0))
    return blocks_units.select("block", "unit").distinct().join(chosen, ["block", "unit"], "left").select("block", "unit", F.coalesce("label", F.lit(0.0)).alias("label"))


def feature_names(attrs: list[str], ops: list[str], numbers: list[str]) -> list[str]:
    return [f"reads:{a}" for a in attrs] + [f"writes:{a}" for a in attrs] + [f"tool:{o}" for o in ops] + [f"param:{n}" for n in numbers]


def featurize(pool: DataFrame, attrs: list[str], ops: list[str], numbers: list[str]) -> DataFrame:
    """Adds ``features``, in the order of ``feature_names``."""
    read = F.transform("pred", lambda c: c["attr"])
    cols = [F.array_contains(read, a).cast("double") for a in attrs]
    cols += [(F.col("target") == a).cast("double") for a in attrs]
    cols += [(F.col("op") == o).cast("double") for o in ops]
    cols += [F.coalesce(F.col("num_params")[n], F.lit(0.0)) for n in numbers]
    return pool.withColumn("features", F.array(*cols))


def threshold_of(scored: DataFrame, slack: float = 0.0) -> float:
    """Least probability of a positive example, times 1 - slack."""
    low = scored.agg(F.min(F.when(F.col("label") == 1, F.col("p")))).first()[0]
    return 0.0 if low is None else float(low) * (1 - slack)


def score_with(df: DataFrame, weights: list[float], intercept: float) -> DataFrame:
    """Adds ``p``, the logistic probability under fixed coefficients."""
    dot = F.aggregate(F.zip_with("features", F.array(*[F.lit(float(w)) for w in weights]), lambda x, w: x * w), F.lit(float(intercept)), lambda acc, x: acc + x)
    return df.withColumn("p", 1 / (1 + F.exp(-dot)))


@dataclass
class Pruner:
    attrs: list[str]
    ops: list[str]
    numbers: list[str] = field(default_factory=list)
    weights: list[float] | None = None
    intercept: float = 0.0
    threshold: float = 0.0

    @property
    def active(self) -> bool:
        return self.weights is not None

    def fit(self, examples: DataFrame, pool: DataFrame, slack: float = 0.0, min_blocks: int = MIN_BLOCKS, min_positives: int = MIN_POSITIVES, estimator=None) -> Pruner:
        """Learn from (block, unit, label); stays inactive with too few blocks or one class."""
        n = examples.agg(F.count_distinct("block").alias("b"), F.count_if(F.col("label") == 1).alias("pos"), F.count("*").alias("n")).first()
        if n["b"] < min_blocks or n["pos"] < min_positives or n["pos"] == n["n"]:
            return self
        rows = examples.join(featurize(pool, self.attrs, self.ops, self.numbers).select("unit", "features").dropDuplicates(["unit"]), "unit")
        weighted = rows.withColumn("w", F.when(F.col("label") == 1, F.lit((n["n"] - n["pos"]) / n["pos"])).otherwise(1.0)).withColumn("vector", array_to_vector("features"))
        lr = estimator or LogisticRegression(featuresCol="vector", labelCol="label", weightCol="w", regParam=1e-3, maxIter=50)
        model = lr.fit(weighted)
        self.weights, self.intercept = [float(x) for x in model.coefficients], float(model.intercept)
        self.threshold = threshold_of(score_with(rows, self.weights, self.intercept), slack)
        return self

    def scores(self, pool: DataFrame) -> DataFrame:
        return score_with(featurize(pool, self.attrs, self.ops, self.numbers), self.weights, self.intercept)

    def keep(self, pool: DataFrame) -> DataFrame:
        """The repairs that may help; all of them while inactive."""
        if not self.active:
            return pool
        return self.scores(pool).filter(F.col("p") >= self.threshold * (1 - 1e-9)).select(*pool.columns)

    def rules(self) -> list[tuple[str, float]]:
        """Coefficients by feature, largest first."""
        names = feature_names(self.attrs, self.ops, self.numbers)
        return sorted(zip(names, self.weights or [], strict=False), key=lambda x: -x[1])


def confusion(pruner: Pruner, examples: DataFrame, pool: DataFrame) -> dict[str, int]:
    """Counts with positive = kept: false negatives are useful repairs dropped."""
    rows = examples.join(pruner.scores(pool).select("unit", "p").dropDuplicates(["unit"]), "unit")
    got = rows.groupBy("label", (F.col("p") >= pruner.threshold * (1 - 1e-9)).alias("kept")).count().collect()
    out = dict.fromkeys(("true_positive", "false_negative", "false_positive", "true_negative"), 0)
    for r in got:
        out[("true_positive" if r["kept"] else "false_negative") if r["label"] == 1 else ("false_positive" if r["kept"] else "true_negative")] += r["count"]
    return out


__all__ = ["Pruner", "confusion", "featurize", "label_examples", "score_with", "threshold_of"]

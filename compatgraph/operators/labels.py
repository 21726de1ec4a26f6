"""One-hot, residual and modulated labels, hiding labels, predictions and their measures."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


#: The class of a node that no label reaches.
NO_CLASS = -1


def names(k: int, prefix: str = "b") -> list[str]:
    return [f"{prefix}{c}" for c in range(k)]


def one_hot(seeds: DataFrame, k: int) -> DataFrame:
    return seeds.select("node", *[(F.col("cls") == c).cast("long").alias(f"b{c}") for c in range(k)])


def residual(seeds: DataFrame, k: int) -> DataFrame:
    """One-hot minus 1/k: rows sum to 0."""
    return seeds.select("node", *[((F.col("cls") == c).cast("double") - 1.0 / k).alias(f"b{c}") for c in range(k)])


def modulate(k: int, K: np.ndarray) -> list[Column]:
    """The row times K, as expressions with literals: no join, no UDF."""
    return [reduce(lambda a, b: a + b, [F.col(f"b{c}") * F.lit(float(K[c, d])) for c in range(k)]).alias(f"b{d}") for d in range(k)]


def uniform(key: Column) -> Column:
    """First 32 bits of md5 of the key as a string, as a number."""
    return F.conv(F.substring(F.md5(key.cast("string")), 1, 8), 16, 10).cast("long")


def hide_labels(labels: DataFrame, f: float, run: int | None = None) -> DataFrame:
    """The seeds: labels whose hash falls into the share ``f``.  ``run`` makes another draw."""
    key = F.col("node").cast("string") if run is None else F.concat(F.lit(f"{run}:"), F.col("node").cast("string"))
    return labels.filter(uniform(key) < int(f * 2**32))


def predict(beliefs: DataFrame, k: int, digits: int = 9) -> DataFrame:
    """node, cls, tied: the class of greatest belief, the smallest class on ties (after rounding)."""
    b = [F.round(c, digits) for c in names(k)]
    top = F.greatest(*b)
    cls = F.coalesce(*[F.when(x == top, F.lit(c)) for c, x in enumerate(b)])
    return beliefs.select("node", cls.cast("int").alias("cls"), (sum(((x == top).cast("int") for x in b), F.lit(0)) > 1).alias("tied"))


def hold_out(predictions: DataFrame, labels: DataFrame, seeds: DataFrame) -> DataFrame:
    """Hidden nodes with true class and prediction.  A node that no label reaches gets ``NO_CLASS``: it favours no class and counts as wrong."""
    hidden = labels.join(seeds.select("node"), "node", "left_anti").withColumnRenamed("cls", "truth")
    return hidden.join(predictions, "node", "left").withColumn("cls", F.coalesce("cls", F.lit(NO_CLASS)))


def accuracy(scored: DataFrame) -> DataFrame:
    """hidden, correct, unreached."""
    right, none = (F.col("truth") == F.col("cls")).cast("long"), (F.col("cls") == NO_CLASS).cast("long")
    return scored.agg(F.count(F.lit(1)).alias("hidden"), F.sum(right).alias("correct"), F.sum(none).alias("unreached"))


def per_class(scored: DataFrame, k: int) -> DataFrame:
    """cls, precision, recall, f1 of each class; null where it is never predicted, never true, or neither."""
    counts = confusion(scored)
    right = F.sum(F.when(F.col("truth") == F.col("c"), F.when(F.col("cls") == F.col("c"), F.col("n")).otherwise(0)).otherwise(0)).alias("right")
    true, said = F.sum(F.when(F.col("truth") == F.col("c"), F.col("n"))).alias("true"), F.sum(F.when(F.col("cls") == F.col("c"), F.col("n"))).alias("said")
    sums = counts.withColumn("c", F.explode(F.sequence(F.lit(0), F.lit(k - 1)))).groupBy("c").agg(right, true, said)
    return sums.select(F.col("c").alias("cls"), (F.col("right") / F.col("said")).alias("precision"), (F.col("right") / F.col("true")).alias("recall"), (2 * F.col("right") / (F.col("true") + F.col("said"))).alias("f1"))


def macro_accuracy(scored: DataFrame, k: int) -> DataFrame:
    """macro: mean recall over the classes that occur."""
    return per_class(scored, k).agg(F.avg("recall").alias("macro"))


def random_guess(nodes: DataFrame, k: int, run: int | None = None) -> DataFrame:
    """node, cls: a class drawn by hash; ``run`` makes another draw."""
    key = F.col("node") if run is None else F.concat_ws(":", F.lit(str(run)), F.col("node").cast("string"))
    return nodes.select("node", (uniform(key) % k).cast("int").alias("cls"))


def accuracy_stats(runs: DataFrame) -> DataFrame:
    """mean, std, error of the column ``accuracy`` over runs; error is the standard error of the mean."""
    return runs.agg(F.avg("accuracy").alias("mean"), F.stddev_samp("accuracy").alias("std"), (F.stddev_samp("accuracy") / F.sqrt(F.count(F.lit(1)))).alias("error"))


def row_sum_deviation(state: DataFrame, k: int, total: float = 0.0) -> DataFrame:
    """deviation: the largest distance of a row's sum from ``total``.  Modulation keeps row sums where K has constant ones."""
    return state.agg(F.coalesce(F.max(F.abs(reduce(lambda a, b: a + b, [F.col(c) for c in names(k)]) - F.lit(total))), F.lit(0.0)).alias("deviation"))


def confusion(scored: DataFrame) -> DataFrame:
    return scored.groupBy("truth", "cls").agg(F.count(F.lit(1)).alias("n"))

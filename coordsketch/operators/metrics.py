"""Accuracy and cost measures over repeated rank draws."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def relative_error(estimates: DataFrame, truth: DataFrame, by: tuple[str, ...] = ("estimator",), on: tuple[str, ...] = ("workload",)) -> DataFrame:
    """by, on, avg_rel_error, draws: the mean of |estimate - exact| / exact. estimates: on, by, seed, estimate; truth: on, exact."""
    err = F.abs(F.col("estimate") - F.col("exact")) / F.col("exact")
    return estimates.join(truth, list(on)).groupBy(*on, *by).agg(F.avg(err).alias("avg_rel_error"), F.count(F.lit(1)).alias("draws"))


def improvement_factor(errors: DataFrame, baseline: str = "union", on: tuple[str, ...] = ("workload",)) -> DataFrame:
    """errors with improvement: the baseline estimator's error over each one's."""
    base = errors.where(F.col("estimator") == baseline).select(*on, F.col("avg_rel_error").alias("_base"))
    return errors.join(base, list(on)).withColumn("improvement", F.try_divide("_base", "avg_rel_error")).drop("_base")


def combination_size(combinations: DataFrame, k: int, by: tuple[str, ...] = ("workload", "estimator")) -> DataFrame:
    """by, mean_size, size_over_k: the average number of keys. combinations: by, query_id, one row for each key."""
    sizes = combinations.groupBy(*by, "query_id").agg(F.count(F.lit(1)).alias("l"))
    return sizes.groupBy(*by).agg(F.avg("l").alias("mean_size"), (F.avg("l") / k).alias("size_over_k"))


def predicted_gain(size_over_k: float) -> float:
    return math.sqrt(size_over_k)


def predicted_error(n: float) -> float:
    """The expected average relative error of a uniform union size from n sampled keys."""
    return math.sqrt(2 / (math.pi * n))


def bias_z(adjusted: DataFrame, truth: DataFrame, draws: int) -> DataFrame:
    """key, mean, z: the mean of adj over draws (absent: 0) against the key's exact value, in standard errors."""
    s = adjusted.groupBy("key").agg(F.sum("adj").alias("a"), F.sum(F.col("adj") ** 2).alias("b"))
    joined = truth.join(s, "key", "left").fillna(0.0, ["a", "b"])
    mean = F.col("a") / draws
    sd = F.sqrt(F.greatest(F.col("b") / draws - mean * mean, F.lit(0.0)) / draws)
    return joined.select("key", mean.alias("mean"), F.when(sd > 0, (mean - F.col("exact")) / sd).otherwise(F.lit(0.0)).alias("z"))


def variances(adjusted: DataFrame, truth: DataFrame, draws: int, by: tuple[str, ...] = ("estimator",)) -> DataFrame:
    """by, sum_of_variances: per-key variances of adj over draws (absent keys count 0), added up. truth: key, exact."""
    s = adjusted.groupBy(*by, "key").agg(F.sum("adj").alias("a"), F.sum(F.col("adj") ** 2).alias("b"))
    held = s.join(truth, "key")
    var = F.col("b") / draws - 2 * F.col("exact") * F.col("a") / draws + F.col("exact") ** 2
    n = truth.agg(F.sum(F.col("exact") ** 2).alias("_all"))
    missing = held.groupBy(*by).agg(F.sum(var).alias("_v"), F.sum(F.col("exact") ** 2).alias("_seen"))
    return missing.crossJoin(F.broadcast(n)).select(*by, (F.col("_v") + F.col("_all") - F.col("_seen")).alias("sum_of_variances"))  # n: one row


def covariances(adjusted: DataFrame, truth: DataFrame, draws: int) -> DataFrame:
    """i, j, covariance of adj over draws for the keys that were ever sampled together. Meant for small universes."""
    left = adjusted.select("seed", F.col("key").alias("i"), F.col("adj").alias("x"))
    right = adjusted.select("seed", F.col("key").alias("j"), F.col("adj").alias("y"))
    sums = left.join(right, "seed").where("i < j").groupBy("i", "j").agg((F.sum(F.col("x") * F.col("y")) / draws).alias("_m"))
    a, b = (truth.select(F.col("key").alias(c), F.col("exact").alias(f"_{c}")) for c in "ij")
    return sums.join(a, "i").join(b, "j").select("i", "j", (F.col("_m") - F.col("_i") * F.col("_j")).alias("covariance"))


def cv2(values: DataFrame) -> DataFrame:
    """estimator, cv2: the squared coefficient of variation of an estimate over draws."""
    return values.groupBy("estimator").agg((F.var_pop("estimate") / F.avg("estimate") ** 2).alias("cv2"))


def sum_to_one(rho: DataFrame) -> DataFrame:
    """query_id, total: must be 1 for every estimator of selectivities."""
    return rho.groupBy("query_id").agg(F.sum("rho").alias("total"))


def pair_confusion(found: DataFrame, exact: DataFrame, theta: float) -> DataFrame:
    """true_pairs, reported, correct, precision, recall of similar pairs (a, b). exact: a, b, exact."""
    real = exact.where(F.col("exact") >= theta).select("a", "b", F.lit(1).alias("_r"))
    both = found.select("a", "b", F.lit(1).alias("_f")).join(real, ["a", "b"], "full")
    s = both.agg(F.coalesce(F.sum("_r"), F.lit(0)).alias("true_pairs"), F.coalesce(F.sum("_f"), F.lit(0)).alias("reported"), F.count_if(F.col("_r").isNotNull() & F.col("_f").isNotNull()).alias("correct"))
    return s.withColumn("precision", F.try_divide("correct", "reported")).withColumn("recall", F.try_divide("correct", "true_pairs"))


def short_share(comb: DataFrame, sketch: DataFrame) -> DataFrame:
    """query_id, set_id, share: the part of each set's sketch that the short combination keeps."""
    kept = comb.select("query_id", F.explode("member_of").alias("set_id")).groupBy("query_id", "set_id").agg(F.count(F.lit(1)).alias("_n"))
    sizes = sketch.groupBy("set_id").agg(F.count(F.lit(1)).alias("_k"))
    return kept.join(sizes, "set_id").select("query_id", "set_id", (F.col("_n") / F.col("_k")).alias("share"))


__all__ = [n for n in dir() if not n.startswith("_") and n not in ("DataFrame", "Window", "F", "math")]

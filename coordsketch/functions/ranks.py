"""Shared random ranks: one draw for each key, the same in every set that holds it.

A key's uniform number is a hash of (seed, key), so no state is shared between tasks or runs. Families turn it into a
rank by the key's weight: exponential (the minimum over a set is exponential with the set's weight as rate), priority
(u / w) and uniform (u; weights are ignored).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

FAMILIES = ("exponential", "priority", "uniform")
_UNIT = float(2**52)


def uniform(key: Column, seed: Column | int | str = 0, method: str = "xxhash64") -> Column:
    """A number in (0, 1) from seed and key. md5: the same bits in any SQL engine; xxhash64: faster."""
    seed = seed if isinstance(seed, Column) else F.lit(seed)
    if method == "md5":
        hexes = F.substring(F.md5(F.concat(seed.cast("string"), F.lit(":"), key.cast("string")).cast("binary")), 1, 13)
        return (F.conv(hexes, 16, 10).cast("double") + 0.5) / F.lit(_UNIT)
    if method == "xxhash64":
        return (F.shiftrightunsigned(F.xxhash64(seed.cast("string"), key.cast("string")), 12).cast("double") + 0.5) / F.lit(_UNIT)
    raise ValueError(f"unknown method {method!r}")


def rank(u: Column, weight: Column, family: str) -> Column:
    """The rank of a key; a zero weight ranks last (infinity)."""
    if family == "exponential":
        value = -F.log(u) / weight
    elif family == "priority":
        value = u / weight
    elif family == "uniform":
        value = u + F.lit(0.0)
    else:
        raise ValueError(f"unknown family {family!r}")
    return F.when(weight > 0, value).otherwise(F.lit(float("inf")))


def inclusion(weight: Column, bound: Column, family: str) -> Column:
    """The probability that a key of that weight ranks below bound; 1 for an infinite bound."""
    if family == "exponential":
        value = -F.expm1(-weight * bound)
    elif family == "priority":
        value = F.least(F.lit(1.0), weight * bound)
    elif family == "uniform":
        value = F.least(F.lit(1.0), bound)
    else:
        raise ValueError(f"unknown family {family!r}")
    return F.when(bound == float("inf"), F.lit(1.0)).otherwise(value)


def convert(value: Column, weight: Column, source: str, target: str) -> Column:
    """A rank of one family as the rank of another, by way of the uniform number."""
    u = {"exponential": F.exp(-value * weight), "priority": value * weight, "uniform": value}[source]
    return rank(u, weight, target)


def validated(memberships: DataFrame) -> DataFrame:
    """memberships without null sets or keys; negative or undefined weights raise an error."""
    w = F.col("weight").cast("double")
    checked = F.when((w < 0) | F.isnan(w) | w.isNull(), F.raise_error(F.concat(F.lit("bad weight of key "), F.col("key").cast("string"))).cast("double")).otherwise(w)
    return memberships.where("set_id is not null and key is not null").withColumn("weight", checked)


def weight_conflicts(memberships: DataFrame) -> DataFrame:
    """Keys with more than one weight: key, weights. Weights belong to keys, so this must be empty."""
    return memberships.groupBy("key").agg(F.count_distinct("weight").alias("weights")).where("weights > 1")


def with_rank(memberships: DataFrame, family: str = "exponential", seed: Column | int | str = 0, method: str = "xxhash64") -> DataFrame:
    """memberships with rank; keys of weight zero, which are never sampled, are dropped."""
    held = validated(memberships).where("weight > 0")
    return held.withColumn("rank", rank(uniform(F.col("key"), seed, method), F.col("weight"), family))

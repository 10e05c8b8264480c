"""Adjusted weights: a sampled key's weight over the probability that it is sampled; other keys count zero."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .ranks import inclusion


def inverse_probability(df: DataFrame, p: Column) -> DataFrame:
    """adj = weight / p, for known probabilities."""
    return df.withColumn("adj", F.col("weight") / p)


def conditioned(df: DataFrame, family: str) -> DataFrame:
    """adj and the inclusion probability p, each key's rank being compared with its own bound."""
    return df.withColumn("p", inclusion(F.col("weight"), F.col("bound"), family)).withColumn("adj", F.col("weight") / F.col("p"))


#: One formula serves all: what differs is the bound that the combination gives each key.
rank_conditioned = conditioned
short_rc = conditioned
long_rc = conditioned
poisson_short = conditioned
poisson_long = conditioned


def short_rc_priority(df: DataFrame) -> DataFrame:
    """The closed form for priority ranks: the larger of the weight and 1 / bound."""
    return df.withColumn("adj", F.greatest("weight", F.when(F.col("bound") == float("inf"), 0.0).otherwise(1.0 / F.col("bound"))))

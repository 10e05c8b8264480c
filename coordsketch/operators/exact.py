"""Exact evaluation: the baseline that reads all sets of a query."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans import predicate as P
from ..plans.lineage import stored
from .meeting import Rule, meeting, same, spread
from .sketch import gathered

#: Pairs whose sets are told by a broadcast list of their names.
COUNTED = 100_000


def keys(memberships: DataFrame, query_sets: DataFrame, attrs: tuple[str, ...] = ()) -> DataFrame:
    """query_id, key, weight, member_of, attrs of every key in the union of each query's sets."""
    rows = memberships.join(query_sets, "set_id")
    return rows.groupBy("query_id", "key").agg(F.first("weight").alias("weight"), F.array_sort(F.collect_set("set_id")).alias("member_of"), *[F.first(a).alias(a) for a in attrs])


def weight(memberships: DataFrame, query_sets: DataFrame, pred: P.Pred, attrs: tuple[str, ...] = ()) -> DataFrame:
    """query_id, exact."""
    held = keys(memberships, query_sets, attrs)
    return held.groupBy("query_id").agg(F.sum(F.when(P.to_column(pred), F.col("weight")).otherwise(F.lit(0.0))).alias("exact"))


def selectivity(memberships: DataFrame, query_sets: DataFrame, pred: P.Pred, attrs: tuple[str, ...] = ()) -> DataFrame:
    held = keys(memberships, query_sets, attrs)
    return held.groupBy("query_id").agg((F.sum(F.when(P.to_column(pred), F.col("weight")).otherwise(F.lit(0.0))) / F.sum("weight")).alias("exact"))


def totals(memberships: DataFrame) -> DataFrame:
    """set_id, total, size of every set, repeated rows counted once."""
    return memberships.dropDuplicates(["set_id", "key"]).groupBy("set_id").agg(F.sum("weight").alias("total"), F.count(F.lit(1)).alias("size"))


def jaccard(memberships: DataFrame, pairs: DataFrame) -> DataFrame:
    """query_id, exact: the weighted Jaccard ratio of a and b."""
    qs = pairs.select("query_id", F.explode(F.array("a", "b")).alias("set_id")).distinct()
    held = keys(memberships, qs)
    both = F.sum(F.when(F.size("member_of") == 2, F.col("weight")).otherwise(F.lit(0.0)))
    return held.groupBy("query_id").agg((both / F.sum("weight")).alias("exact"))


def similar_pairs(memberships: DataFrame, theta: float) -> DataFrame:
    """a, b, exact: all pairs of sets whose Jaccard ratio (of keys, not weights) is at least theta. memberships: rows (set_id, key), or
    (set_id, keys) with keys as an array without repeats.

    Sets of n and b keys need theta / (1 + theta) * (n + b) common ones, and the larger has at most 1 / theta times the size of the
    other. Pairs of sets that both hold a key which shares its hash are counted again by their keys."""
    if "keys" in memberships.columns:
        sets = gathered(memberships)
    else:
        rows = memberships.where("set_id is not null and key is not null").select("set_id", "key").distinct()
        sets = stored(rows.groupBy("set_id").agg(F.collect_list("key").alias("keys")))
    size = F.size("keys")
    hashed = sets.select("set_id", F.transform("keys", lambda x: F.xxhash64(x)).alias("of"), size.alias("whole"), size.cast("double").alias("place"), (size * theta - 1e-6).alias("since"), F.lit(None).cast("array<double>").alias("marks"))
    met, held = meeting(hashed, Rule(0.0, theta / (1 + theta)))
    met, held = stored(met), stored(held)
    counted = met.where("sure").select("a", "b", (F.col("both") / (F.col("n_a") + F.col("n_b") - F.col("both"))).alias("exact"))
    unsure = met.where("not sure").select("a", "b")
    if n := unsure.count():
        if n <= COUNTED:  # else all keys are shuffled
            sets = stored(sets.join(F.broadcast(unsure.select(F.explode(F.array("a", "b")).alias("set_id")).distinct()), "set_id", "left_semi"))
        one = lambda c: sets.select(F.col("set_id").alias(c), F.col("keys").alias(f"of_{c}"))
        both = F.size(F.array_intersect("of_a", "of_b"))
        again = unsure.join(one("a"), "a").join(one("b"), "b").select("a", "b", (both / (F.size("of_a") + F.size("of_b") - both)).alias("exact"))
        counted = counted.unionByName(again)
    every = counted.unionByName(same(held).withColumn("exact", F.lit(1.0)))
    return spread(every.where(F.col("exact") >= theta - 1e-12), held)


def native_sketches(memberships: DataFrame, query_sets: DataFrame) -> DataFrame:
    """query_id, approx_distinct, hll, theta: Spark's own binary sketches of the union's number of keys, for comparison.

    They hold no keys, so neither attribute predicates nor weights can be asked of them."""
    rows = memberships.join(query_sets, "set_id")
    parts = rows.groupBy("query_id", "set_id").agg(F.hll_sketch_agg("key").alias("h"), F.expr("theta_sketch_agg(key)").alias("t"))
    merged = parts.groupBy("query_id").agg(F.hll_sketch_estimate(F.hll_union_agg("h")).alias("hll"), F.expr("theta_sketch_estimate(theta_union_agg(t))").alias("theta"))
    return merged.join(rows.groupBy("query_id").agg(F.approx_count_distinct("key").alias("approx_distinct")), "query_id")

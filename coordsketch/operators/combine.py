"""Combinations of coordinated sketches for a collection of sets.

Query sets are rows (query_id, set_id). Every function returns rows (query_id, key, weight, rank, bound, member_of,
attributes): bound is what the key's inclusion probability is conditioned on, member_of the sets whose sketch holds it.

union: the sketch of the union, as if it had been sketched itself. short: all keys ranked below the smallest bound, whose
memberships are fully known. long: all sampled keys, each with the largest bound among the sketches that hold it.

Defined cases: repeated rows of a query count once; sets without a sketch add nothing; a query of no known set has no rows;
an empty sketch gives an empty combination. Keys whose ranks tie stand or fall together, as the comparison is strict.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

INF = float("inf")
_FIXED = ("set_id", "pos", "key", "weight", "rank", "bound", "query_id")


def _attrs(df: DataFrame) -> list[str]:
    return [c for c in df.columns if c not in _FIXED]


def attach(sketch: DataFrame, query_sets: DataFrame) -> DataFrame:
    """Sketch rows of the queries' sets: query_id and the sketch's columns. Rows are narrow; AQE broadcasts small sides."""
    return sketch.join(query_sets.select("query_id", "set_id").distinct(), "set_id")


def _merged(rows: DataFrame, bound) -> DataFrame:
    attrs = [F.first(c).alias(c) for c in _attrs(rows)]
    return rows.groupBy("query_id", "key").agg(F.first("weight").alias("weight"), F.min("rank").alias("rank"), bound.alias("bound"), F.array_sort(F.collect_set("set_id")).alias("member_of"), *attrs)


def short(sketch: DataFrame, query_sets: DataFrame) -> DataFrame:
    """Keys ranked strictly below the smallest bound of the collection."""
    low = F.min("bound").over(Window.partitionBy("query_id"))
    held = attach(sketch, query_sets).withColumn("bound", low).where(F.col("rank") < F.col("bound"))
    return _merged(held, F.first("bound"))


def long(sketch: DataFrame, query_sets: DataFrame) -> DataFrame:
    """All keys of the sketches. member_of lists sketches that hold the key; other memberships may be unknown."""
    return _merged(attach(sketch, query_sets), F.max("bound"))


def union_sketch(sketch: DataFrame, query_sets: DataFrame, k: int) -> DataFrame:
    """The bottom-k sketch of the union. Its bound is the smallest known rank outside, keyless bounds included."""
    rows = attach(sketch, query_sets)
    merged = _merged(rows, F.max("bound"))
    bounds = rows.groupBy("query_id").agg(F.min("bound").alias("low"))
    order = Window.partitionBy("query_id").orderBy("rank", "key")
    placed = merged.drop("bound").withColumn("pos", F.row_number().over(order)).where(F.col("pos") <= k + 1)
    after = F.min(F.when(F.col("pos") == k + 1, F.col("rank"))).over(Window.partitionBy("query_id"))
    bounded = placed.withColumn("after", after).join(bounds, "query_id")
    held = bounded.withColumn("bound", F.least(F.coalesce("after", F.lit(INF)), "low"))
    return held.where((F.col("pos") <= k) & (F.col("rank") < F.col("bound"))).drop("pos", "after", "low")


def union_k_mins(sketch: DataFrame, query_sets: DataFrame) -> DataFrame:
    """query_id, j, min_rank, key, weight, member_of: coordinate-wise minima, and the sets that attain them."""
    rows = attach(sketch, query_sets)
    low = rows.groupBy("query_id", "j").agg(F.min_by(F.struct("min_rank", "key", "weight"), F.struct("min_rank", "key")).alias("low"))
    joined = rows.join(low, ["query_id", "j"]).where(F.col("key") == F.col("low.key"))
    return joined.groupBy("query_id", "j").agg(F.first("low.min_rank").alias("min_rank"), F.first("low.key").alias("key"), F.first("low.weight").alias("weight"), F.array_sort(F.collect_set("set_id")).alias("member_of"))


def long_membership(sketch: DataFrame, query_sets: DataFrame) -> DataFrame:
    """query_id, key, membership: a map from each set to in, out or unknown for every key of the long combination.

    A key outside a set's sketch is outside the set if it ranks below or at the set's bound."""
    rows = attach(sketch, query_sets)
    bounds = rows.groupBy("query_id", "set_id").agg(F.first("bound").alias("b"))
    listed = bounds.groupBy("query_id").agg(F.collect_list(F.struct("set_id", "b")).alias("sets"))
    keys = _merged(rows, F.max("bound")).join(listed, "query_id")
    state = lambda s: F.when(F.array_contains("member_of", s["set_id"]), "in").when(F.col("rank") <= s["b"], "out").otherwise("unknown")
    return keys.select("query_id", "key", F.map_from_entries(F.transform("sets", lambda s: F.struct(s["set_id"], state(s)))).alias("membership"))

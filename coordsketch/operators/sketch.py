"""Sketches of sets: bottom-k, k-mins and Poisson samples, and their merging.

A bottom-k sketch is stored in rows (set_id, key, weight, rank, bound, attributes): the k lowest-ranked keys of the set,
and as bound the rank of the next one (infinity if there is none). Poisson sketches have their threshold as bound, so the
same combinations and estimators serve both.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.ranks import validated, with_rank

INF = float("inf")


def _cut(ranked: DataFrame, k: int, by: list[str]) -> DataFrame:
    """The k + 1 lowest (rank, key) of every group; repeated rows share their place and are dropped after the cut."""
    order = Window.partitionBy(*by).orderBy("rank", "key")
    kept = ranked.withColumn("pos", F.dense_rank().over(order)).where(F.col("pos") <= k + 1)
    return kept.dropDuplicates([*by, "pos"])


def _bounded(cut: DataFrame, k: int, by: list[str]) -> DataFrame:
    bound = F.min(F.when(F.col("pos") == k + 1, F.col("rank"))).over(Window.partitionBy(*by))
    return cut.withColumn("bound", F.coalesce(bound, F.lit(INF))).where(F.col("pos") <= k)


def _allow_group_limit(df: DataFrame, k: int) -> None:
    """Spark cuts groups before the shuffle only up to a threshold, which must not be under k + 1. Plans are made when they run,
    so a raised threshold has to stay; it changes no results."""
    spark, name = df.sparkSession, "spark.sql.optimizer.windowGroupLimitThreshold"
    if int(spark.conf.get(name, "1000")) < k + 1:
        spark.conf.set(name, str(k + 1))


def gathered(memberships: DataFrame) -> DataFrame:
    """Rows (set_id, keys), one for each set that has keys. Only sets of several rows are shuffled."""
    rows = memberships.where("set_id is not null").select("set_id", F.array_compact("keys").alias("keys")).where(F.size("keys") > 0)
    several = memberships.groupBy("set_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1 and set_id is not null").select("set_id")
    if several.isEmpty():
        return rows
    merged = rows.join(several, "set_id", "left_semi").groupBy("set_id").agg(F.array_distinct(F.flatten(F.collect_list("keys"))).alias("keys"))
    return rows.join(several, "set_id", "left_anti").unionByName(merged)


def _of_arrays(memberships: DataFrame, k: int, seed: Column | int | str) -> DataFrame:
    """The nested sketch of memberships by arrays. A key is hashed once for a batch of rows."""
    if isinstance(seed, Column):
        raise ValueError("memberships by arrays of keys need one seed")
    mark = f"{seed}:".encode()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            held = batch.column("keys")
            edges = held.offsets.to_numpy().astype(np.int64)
            names = held.values.slice(edges[0], edges[-1] - edges[0]).dictionary_encode()
            code = names.indices.to_numpy()
            unit = np.fromiter((int(hashlib.md5(mark + n.encode()).hexdigest()[:13], 16) for n in names.dictionary.to_pylist()), np.float64, len(names.dictionary))
            rank = (unit + 0.5) / 2.0**52
            order = pc.sort_indices(pa.table({"rank": rank, "key": names.dictionary}), sort_keys=[("rank", "ascending"), ("key", "ascending")]).to_numpy()
            turn = np.empty(len(order), np.uint64)
            turn[order] = np.arange(len(order), dtype=np.uint64)
            size = np.diff(edges)
            held = np.repeat(np.arange(batch.num_rows, dtype=np.uint64) << np.uint64(32), size) | turn[code]
            held.sort()  # each set's keys by rank
            kept = np.arange(len(held)) - np.repeat(np.cumsum(size) - size, size) <= k
            code = order[held[kept].astype(np.uint32)].astype(np.int64)
            ends = pa.array(np.append(0, np.cumsum(np.minimum(size, k + 1))).astype(np.int32))
            entries = pa.StructArray.from_arrays([pa.array(rank[code]), names.dictionary.take(pa.array(code)), pa.array(np.ones(len(code)))], ["rank", "key", "weight"])
            yield pa.RecordBatch.from_arrays([batch.column("set_id"), pa.ListArray.from_arrays(ends, entries)], names=["set_id", "low"])

    low = gathered(memberships).select("set_id", "keys").mapInArrow(run, "set_id string, low array<struct<rank: double, key: string, weight: double>>")
    sorted_low = F.array_sort("low")  # ties in rank go by key
    bound = F.when(F.size("low") > k, F.element_at(sorted_low, k + 1)["rank"]).otherwise(F.lit(INF))
    return low.select("set_id", F.slice(sorted_low, 1, k).alias("entries"), bound.alias("bound"))


def bottom_k(memberships: DataFrame, k: int, family: str = "exponential", seed: Column | int | str = 0, *, attrs: tuple[str, ...] = (), method: str = "xxhash64", salt: int = 0, by: tuple[str, ...] = ()) -> DataFrame:
    """The sketch of every set: set_id, pos, key, weight, rank, bound, attrs.

    salt > 1 cuts every set in that many parts first, so no task sees all of a heavy set. by: further grouping columns
    (such as a seed column for repeated draws). For k of 1000 and more, spark.sql.optimizer.windowGroupLimitThreshold of the
    session is raised to k + 1.

    memberships may also be rows (set_id, keys), keys an array without repeats, all of weight 1, for uniform ranks by md5: each set is
    then cut within its row, and the sketch is nested as by to_nested.

    Defined cases: rows with a null set_id or key are no memberships, keys of weight zero are never sampled, and a null or
    negative weight raises an error; repeated rows count once; ties in rank go by key; an empty table gives an empty sketch."""
    if "keys" in memberships.columns:
        if (family, method, attrs, by) != ("uniform", "md5", (), ()):
            raise ValueError("memberships by arrays of keys need uniform ranks by md5, without attributes and groups")
        return _of_arrays(memberships, k, seed)
    _allow_group_limit(memberships, k)
    group = [*by, "set_id"]
    ranked = with_rank(memberships.select(*group, "key", "weight", *attrs), family, seed, method)
    if salt > 1:
        parts = ranked.withColumn("part", F.pmod(F.xxhash64("key", F.lit("salt")), F.lit(salt)))
        ranked = _cut(parts, k, [*group, "part"]).drop("pos", "part")
    sketch = _bounded(_cut(ranked, k, group), k, group)
    return sketch.select(*group, "pos", "key", "weight", "rank", "bound", *attrs)


def bottom_k_prefiltered(memberships: DataFrame, k: int, family: str = "exponential", seed: int | str = 0, *, slack: float = 4.0, attrs: tuple[str, ...] = (), method: str = "xxhash64") -> DataFrame:
    """bottom_k for huge sets: rows ranked above a generous threshold are dropped before the shuffle.

    The threshold comes from each set's summed weight (repeated rows only lower it); sets that keep fewer than k + 1 keys
    though they have more rows are sketched again without it, so the result is exact."""
    totals = validated(memberships).groupBy("set_id").agg((F.count(F.lit(1)) if family == "uniform" else F.sum("weight")).alias("total"), F.count(F.lit(1)).alias("rows"))
    limit = (k + 1 + slack * float(k + 1) ** 0.5) / F.col("total")
    ranked = with_rank(memberships.select("set_id", "key", "weight", *attrs), family, seed, method)
    likely = ranked.join(totals, "set_id").where(F.col("rank") < limit)
    cut = _cut(likely, k, ["set_id"])
    full = cut.groupBy("set_id").agg(F.max("pos").alias("got"), F.max("rows").alias("rows"))
    short = totals.join(full.where(f"got >= {k + 1}").select("set_id"), "set_id", "left_anti").select("set_id")
    repaired = bottom_k(memberships.join(short, "set_id", "left_semi"), k, family, seed, attrs=attrs, method=method)
    done = _bounded(cut.join(short, "set_id", "left_anti").drop("total", "rows"), k, ["set_id"])
    return done.select(*repaired.columns).unionByName(repaired)


def merge(*parts: DataFrame, k: int) -> DataFrame:
    """The bottom-k sketch of the union, by set_id, of sets sketched in parts with the same ranks and k.

    A part's bound is a rank without a key. It may be known with its key from another part, so candidates are told apart
    by rank, and keyed ones win."""
    rows = reduce(lambda a, b: a.unionByName(b), parts)
    attrs = [c for c in rows.columns if c not in ("set_id", "pos", "key", "weight", "rank", "bound")]
    empty = [F.lit(None).cast(rows.schema[c].dataType).alias(c) for c in ("key", "weight")]
    bounds = rows.where(F.col("bound") < INF).select("set_id", *empty, F.col("bound").alias("rank"), *[F.lit(None).cast(rows.schema[c].dataType).alias(c) for c in attrs])
    candidates = rows.select("set_id", "key", "weight", "rank", *attrs).unionByName(bounds.distinct())
    order = Window.partitionBy("set_id").orderBy("rank")
    placed = candidates.withColumn("pos", F.dense_rank().over(order)).where(F.col("pos") <= k + 1)
    first = F.row_number().over(Window.partitionBy("set_id", "pos").orderBy(F.col("key").asc_nulls_last()))
    merged = _bounded(placed.withColumn("_first", first).where("_first = 1").drop("_first"), k, ["set_id"])
    return merged.select("set_id", "pos", "key", "weight", "rank", "bound", *attrs)


def rollup_sketches(sketch: DataFrame, mapping: DataFrame, k: int) -> DataFrame:
    """Sketches of coarser sets: mapping has set_id, parent. Exact, as ranks are shared."""
    return merge(sketch.join(mapping, "set_id").drop("set_id").withColumnRenamed("parent", "set_id"), k=k)


def k_mins(memberships: DataFrame, k: int, seed: Column | int | str = 0, family: str = "exponential", *, method: str = "xxhash64") -> DataFrame:
    """set_id, j, min_rank, key, weight: the minimum of each of k independent rank assignments."""
    tag = (seed if isinstance(seed, Column) else F.lit(str(seed))).cast("string").alias("_seed")
    spread = validated(memberships).where("weight > 0").select("set_id", "key", "weight", tag, F.explode(F.sequence(F.lit(1), F.lit(k))).alias("j"))
    ranked = with_rank(spread, family, F.concat("_seed", F.lit("/"), F.col("j").cast("string")), method)
    low = F.min_by(F.struct("key", "weight"), F.struct("rank", "key"))
    return ranked.groupBy("set_id", "j").agg(F.min("rank").alias("min_rank"), low.alias("low")).select("set_id", "j", "min_rank", "low.key", "low.weight")


def poisson(memberships: DataFrame, thresholds: DataFrame | float, family: str = "exponential", seed: int | str = 0, *, attrs: tuple[str, ...] = (), method: str = "xxhash64") -> DataFrame:
    """set_id, key, weight, rank, bound: the keys ranked below their set's threshold. With priority ranks, keys are
    included in proportion to weight, up to certainty. thresholds: one number, or rows (set_id, threshold).

    One scan: rows are dropped by rank before any shuffle of memberships by key (a table of thresholds is joined first, which
    Spark broadcasts if it is small), and only survivors are deduplicated."""
    ranked = with_rank(memberships.select("set_id", "key", "weight", *attrs), family, seed, method)
    held = ranked.withColumn("threshold", F.lit(float(thresholds))) if isinstance(thresholds, int | float) else ranked.join(thresholds.select("set_id", "threshold"), "set_id")
    kept = held.where(F.col("rank") < F.col("threshold")).dropDuplicates(["set_id", "key"])
    return kept.select("set_id", "key", "weight", "rank", F.col("threshold").alias("bound"), *attrs)


def poisson_threshold(memberships: DataFrame, k: int, family: str = "priority", *, steps: int = 60) -> DataFrame:
    """set_id, threshold, expected_size: the threshold for which k keys are expected (infinity for sets of at most k).

    Uniform: k / n. Priority: closed form over weights in descending order. Exponential: bisection over a histogram of the set's
    weights, whose bins span a thousandth of a weight and keep number and mean, so it has about 7000 bins for each three
    orders of magnitude, however many keys there are; the relative error is under 1e-7."""
    keys = validated(memberships).where("weight > 0").select("set_id", "key", "weight").dropDuplicates(["set_id", "key"])
    if family == "uniform":
        sizes = keys.groupBy("set_id").agg(F.count(F.lit(1)).alias("n"))
        found = sizes.select("set_id", F.when(F.col("n") <= k, F.lit(INF)).otherwise(F.lit(float(k)) / F.col("n")).alias("threshold"), F.least(F.lit(k), F.col("n")).cast("double").alias("expected_size"))
        return found
    weights = keys.groupBy("set_id", "weight").agg(F.count(F.lit(1)).alias("m"))
    of_set = Window.partitionBy("set_id")
    if family == "priority":
        above = of_set.orderBy(F.col("weight").desc()).rowsBetween(Window.unboundedPreceding, -1)
        sums = weights.select("set_id", "weight", F.coalesce(F.sum("m").over(above), F.lit(0)).alias("taken"), F.coalesce(F.sum(F.col("m") * F.col("weight")).over(above), F.lit(0.0)).alias("top"), F.sum(F.col("m") * F.col("weight")).over(of_set).alias("total"), F.sum("m").over(of_set).alias("n"))
        tried = sums.withColumn("t", (F.lit(float(k)) - F.col("taken")) / (F.col("total") - F.col("top"))).where((F.col("taken") < k) & (F.col("t") > 0) & (F.col("weight") * F.col("t") <= 1.0))
        sized = weights.groupBy("set_id").agg(F.sum("m").alias("n"))
        best = tried.groupBy("set_id").agg(F.min_by("t", "taken").alias("t"))
        return sized.join(best, "set_id", "left").select("set_id", F.when(F.col("n") <= k, F.lit(INF)).otherwise(F.col("t")).alias("threshold"), F.least(F.lit(k), F.col("n")).cast("double").alias("expected_size"))
    if family != "exponential":
        raise ValueError(f"unknown family {family!r}")
    bins = weights.groupBy("set_id", F.floor(F.log("weight") * 1000).alias("_bin")).agg(F.sum("m").alias("m"), (F.sum(F.col("m") * F.col("weight")) / F.sum("m")).alias("weight"))
    held = bins.groupBy("set_id").agg(F.collect_list(F.struct("weight", "m")).alias("ws"), F.sum("m").alias("n"), F.min("weight").alias("least"))
    expected = lambda t: F.aggregate("ws", F.lit(0.0), lambda a, x: a - x["m"] * F.expm1(-x["weight"] * t))
    start = F.struct(F.lit(0.0).alias("lo"), (F.lit(50.0) / F.col("least")).alias("hi"))

    def halve(s: Column, _: Column) -> Column:
        mid = (s["lo"] + s["hi"]) / 2
        low = expected(mid) < k
        return F.struct(F.when(low, mid).otherwise(s["lo"]).alias("lo"), F.when(low, s["hi"]).otherwise(mid).alias("hi"))

    solved = F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start, halve, lambda s: (s["lo"] + s["hi"]) / 2)
    return held.select("set_id", F.when(F.col("n") <= k, F.lit(INF)).otherwise(solved).alias("threshold"), F.least(F.lit(k), F.col("n")).cast("double").alias("expected_size"))


def as_sequence(sketch: DataFrame) -> DataFrame:
    """The sketch as successive draws without replacement: set_id, draw (from 1), key, weight."""
    return sketch.select("set_id", F.row_number().over(Window.partitionBy("set_id").orderBy("rank", "key")).alias("draw"), "key", "weight")


def to_nested(sketch: DataFrame) -> DataFrame:
    """One row for each set: entries sorted by rank, and the bound."""
    attrs = [c for c in sketch.columns if c not in ("set_id", "pos", "key", "weight", "rank", "bound")]
    return sketch.groupBy("set_id").agg(F.array_sort(F.collect_list(F.struct("rank", "key", "weight", *attrs))).alias("entries"), F.first("bound").alias("bound"))


def to_long(nested: DataFrame) -> DataFrame:
    return nested.select("set_id", "bound", F.posexplode("entries").alias("_i", "e")).select("set_id", (F.col("_i") + 1).alias("pos"), "e.*", "bound")

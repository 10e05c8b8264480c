"""Experiments: repeated draws of all estimators over a workload, as one job. Draws are a column, not a loop."""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .functions.adjust import conditioned
from .functions.ranks import validated
from .operators import combine, estimate, exact, metrics, selectivity
from .operators.sketch import bottom_k, k_mins, poisson, poisson_threshold
from .plans.lineage import stored

MEASURES = ("union", "intersection", "jaccard")
#: Rows of memberships that a task holds at a time.
STRETCH = 1_000_000


def drawn(memberships: DataFrame, draws: int) -> DataFrame:
    """memberships once for each draw: seed, and set ids that carry it."""
    return memberships.withColumn("seed", F.explode(F.sequence(F.lit(1), F.lit(draws)))).withColumn("set_id", F.concat(F.col("seed").cast("string"), F.lit("|"), F.col("set_id")))


def queries_of(memberships: DataFrame, draws: int) -> DataFrame:
    """query_id (the draw), set_id: every draw asks for all sets of the workload."""
    sets = memberships.select("set_id").distinct()
    return sets.withColumn("query_id", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(draws).cast("long")))).select("query_id", F.concat(F.col("query_id").cast("string"), F.lit("|"), F.col("set_id")).alias("set_id"))


def sketches(memberships: DataFrame, k: int, draws: int, family: str = "uniform", method: str = "xxhash64") -> DataFrame:
    if method == "md5":
        rows = lowest(memberships, k, draws, family)
        return bottom_k(rows, k, family, F.col("seed"), method=method, by=("seed",)).drop("seed")
    return bottom_k(drawn(memberships, draws), k, family, F.col("seed"), method=method, by=("seed",)).drop("seed")


def lowest(memberships: DataFrame, k: int, draws: int, family: str) -> DataFrame:
    """drawn(memberships, draws) without rows that are not among the k + 1 lowest md5 ranks of their set in a stretch of rows.

    Every key of a stretch is hashed once for a draw, whatever the number of sets that hold it, and only these few rows are
    sorted or shuffled later. Logarithms may differ in the last bit, so exponential ranks keep some rows more."""
    kept = k + 1 + (8 if family == "exponential" else 0)

    def stretch(table: pa.Table) -> Iterator[pa.RecordBatch]:
        table = table.combine_chunks()
        sets, names = (pc.dictionary_encode(table[c].combine_chunks()) for c in ("set_id", "_name"))
        names, codes = names.dictionary.cast(pa.binary()).to_pylist(), names.indices.to_numpy()
        _, at = np.unique(sets.indices.to_numpy().astype(np.int64) * len(names) + codes, return_index=True)  # repeated rows count once; by set
        owner, code, weight = sets.indices.to_numpy()[at], codes[at], table["weight"].to_numpy()[at]
        first = np.flatnonzero(np.diff(owner, prepend=-1))
        size = np.diff(first, append=len(owner))
        last = first + np.minimum(size, kept) - 1
        for seed in range(1, draws + 1):
            prefix = hashlib.md5(f"{seed}:".encode())
            digests = []
            for name in names:
                h = prefix.copy()
                h.update(name)
                digests.append(h.digest()[:8])
            u = ((np.frombuffer(b"".join(digests), ">u8") >> np.uint64(12)).astype(np.float64) + 0.5) / 2.0**52
            rank = u[code] if family == "uniform" else (-np.log(u)[code] if family == "exponential" else u[code]) / weight
            ordered = rank[np.lexsort((rank, owner))]
            low = at[rank <= np.repeat(ordered[last], size)]
            columns = {"seed": pa.array(np.full(len(low), seed, np.int32))} | {c: table[c].take(pa.array(low)).combine_chunks() for c in ("set_id", "key", "weight")}
            for batch in pa.table(columns).to_batches(max_chunksize=100_000):
                yield batch

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for batch in batches:
            held.append(batch)
            if sum(b.num_rows for b in held) >= STRETCH:
                yield from stretch(pa.Table.from_batches(held))
                held = []
        if sum(b.num_rows for b in held):
            yield from stretch(pa.Table.from_batches(held))

    rows = validated(memberships.select("set_id", "key", "weight")).where("weight > 0").select(F.col("set_id").cast("string").alias("set_id"), "key", "weight", F.col("key").cast("string").alias("_name"))
    types = {f.name: f.dataType.simpleString() for f in rows.schema.fields}
    found = rows.mapInArrow(run, f"seed int, set_id string, key {types['key']}, weight double")
    return found.withColumn("set_id", F.concat(F.col("seed").cast("string"), F.lit("|"), F.col("set_id")))


def _sampled(memberships: DataFrame, k: int, draws: int, family: str, method: str) -> DataFrame:
    """query_id (the draw), key, weight, rank, sets (number of sketches that hold the key), least and most of their bounds; written once.

    As every draw asks for all sets, the three combinations follow from these columns."""
    sk = sketches(memberships, k, draws, family, method).withColumn("query_id", F.split("set_id", r"\|", 2)[0].cast("long"))
    whole = sk.groupBy("query_id", "key").agg(F.first("weight").alias("weight"), F.min("rank").alias("rank"), F.count(F.lit(1)).alias("sets"), F.min("bound").alias("least"), F.max("bound").alias("most"))
    return stored(whole)


def _combined(sampled: DataFrame, combo: str, family: str, k: int) -> DataFrame:
    """The rows of estimate.combined for all sets, with the number of sets in place of member_of."""
    if combo == "long":
        return conditioned(sampled.withColumn("bound", F.col("most")), family)
    low = sampled.groupBy("query_id").agg(F.min("least").alias("low"))
    if combo == "short":
        return conditioned(sampled.join(low, "query_id").where(F.col("rank") < F.col("low")).withColumn("bound", F.col("low")), family)
    order = Window.partitionBy("query_id").orderBy("rank", "key")
    placed = sampled.withColumn("pos", F.row_number().over(order)).where(F.col("pos") <= k + 1)
    after = F.min(F.when(F.col("pos") == k + 1, F.col("rank"))).over(Window.partitionBy("query_id"))
    held = placed.withColumn("after", after).join(low, "query_id").withColumn("bound", F.least(F.coalesce("after", F.lit(float("inf"))), "low"))
    return conditioned(held.where((F.col("pos") <= k) & (F.col("rank") < F.col("bound"))), family)


def union_and_intersection(memberships: DataFrame, k: int, draws: int, family: str = "uniform", method: str = "xxhash64", measures: tuple[str, ...] = MEASURES) -> DataFrame:
    """query_id, measure (union, intersection, jaccard), estimator, estimate, size, for the sets of memberships."""
    sampled = _sampled(memberships, k, draws, family, method)
    n = memberships.select("set_id").distinct().count() if set(measures) - {"union"} else -1
    found = []
    for combo in ("union", "short", "long"):
        rows = _combined(sampled, combo, family, k)
        everywhere = F.col("sets") == n
        sums = rows.groupBy("query_id").agg(F.sum("adj").alias("union"), F.sum(F.when(everywhere, F.col("adj")).otherwise(F.lit(0.0))).alias("intersection"), F.count(F.lit(1)).alias("size"))
        named = {"union": F.col("union")} | ({"intersection": F.col("intersection"), "jaccard": F.col("intersection") / F.col("union")} if combo != "long" else {})
        named = {m: c for m, c in named.items() if m in measures}
        if not named:
            continue
        pairs = F.map_from_arrays(F.array(*map(F.lit, named)), F.array(*named.values()))
        found.append(sums.select("query_id", F.explode(pairs).alias("measure", "estimate"), F.lit(combo).alias("estimator"), "size"))
    return reduce(DataFrame.unionByName, found)


def truths(memberships: DataFrame, measures: tuple[str, ...] = MEASURES) -> DataFrame:
    """measure, exact."""
    if set(measures) == {"union"}:
        held = memberships.groupBy("key").agg(F.first("weight").alias("weight"))
        return held.agg(F.sum("weight").alias("exact")).select(F.lit("union").alias("measure"), "exact").where("exact > 0")
    held = memberships.groupBy("key").agg(F.first("weight").alias("weight"), F.count_distinct("set_id").alias("sets"))
    n = memberships.select("set_id").distinct().count()
    s = held.agg(F.sum("weight").alias("union"), F.sum(F.when(F.col("sets") == n, F.col("weight")).otherwise(F.lit(0.0))).alias("intersection"))
    named = F.map_from_arrays(F.array(F.lit("union"), F.lit("intersection"), F.lit("jaccard")), F.array(F.col("union"), F.col("intersection"), F.col("intersection") / F.col("union")))
    return s.select(F.explode(named).alias("measure", "exact")).where("exact > 0").where(F.col("measure").isin(*measures))


def _gains(est: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """est: query_id, measure, estimator, estimate, size. The errors, sizes, and what sizes alone predict."""
    truth = stored(truth)  # a few rows, read twice
    err = metrics.relative_error(est, truth, by=("estimator",), on=("measure",))
    sizes = est.groupBy("measure", "estimator").agg(F.avg("size").alias("mean_size"))
    gained = metrics.improvement_factor(err, "union", on=("measure",)).join(sizes, ["measure", "estimator"])
    return gained.select("measure", "estimator", "avg_rel_error", "improvement", "mean_size", F.sqrt(F.col("mean_size") / k).alias("predicted_gain"), F.sqrt(F.lit(2 / math.pi) / F.col("mean_size")).alias("predicted_error"))


def errors(memberships: DataFrame, k: int, draws: int, family: str = "uniform", method: str = "xxhash64", measures: tuple[str, ...] = MEASURES) -> DataFrame:
    """measure, estimator, avg_rel_error, improvement, mean_size, predicted_gain, predicted_error (of a uniform union)."""
    return _gains(union_and_intersection(memberships, k, draws, family, method, measures), truths(memberships, measures), k)


def pair_errors(memberships: DataFrame, k: int, draws: int, family: str = "uniform", method: str = "xxhash64") -> DataFrame:
    """The columns of errors for two sets: also their Hamming distance (mixed: union from the long, intersection from the short
    combination), and the intersection as known totals minus the long combination's union (inclusion_exclusion)."""
    rows = stored(union_and_intersection(memberships, k, draws, family, method))
    wide = rows.where("measure <> 'jaccard'").groupBy("query_id").agg(*[F.max(F.when((F.col("measure") == m) & (F.col("estimator") == e), F.col(c))).alias(f"{m[0]}_{e}_{c}") for m in ("union", "intersection") for e in ("union", "short", "long") for c in ("estimate", "size")])
    both = memberships.dropDuplicates(["set_id", "key"]).agg(F.sum("weight").alias("both"))
    wide = wide.crossJoin(F.broadcast(both))  # one row
    u, i = (lambda e: F.col(f"u_{e}_estimate")), (lambda e: F.col(f"i_{e}_estimate"))
    more = [("hamming", "union", u("union") - i("union"), "union"), ("hamming", "short", u("short") - i("short"), "short"), ("hamming", "mixed", u("long") - i("short"), "long"), ("intersection", "inclusion_exclusion", F.col("both") - u("long"), "long")]
    named = F.explode(F.array(*[F.struct(F.lit(m).alias("measure"), F.lit(e).alias("estimator"), x.alias("estimate"), F.col(f"u_{s}_size").alias("size")) for m, e, x, s in more])).alias("r")
    est = rows.unionByName(wide.select("query_id", named).select("query_id", "r.*"))
    held = memberships.groupBy("key").agg(F.first("weight").alias("weight"), F.count_distinct("set_id").alias("sets"))
    apart = held.agg(F.sum(F.when(F.col("sets") == 1, F.col("weight")).otherwise(F.lit(0.0))).alias("exact")).select(F.lit("hamming").alias("measure"), "exact").where("exact > 0")
    return _gains(est, truths(memberships).unionByName(apart), k)


def k_mins_errors(memberships: DataFrame, k: int, draws: int, method: str = "xxhash64") -> DataFrame:
    """measure (union, jaccard of two sets), estimator, avg_rel_error of k-mins sketches; draws are seeds of their coordinates."""
    sk = k_mins(drawn(memberships, draws), k, F.col("seed"), "exponential", method=method)
    qs = queries_of(memberships, draws)
    sets = memberships.select("set_id").distinct().count()
    u = combine.union_k_mins(sk, qs)
    sums = u.groupBy("query_id").agg((F.lit(float(k - 1)) / F.sum("min_rank")).alias("union"), (F.count_if(F.size("member_of") == sets) / F.lit(k)).alias("jaccard"))
    pairs = F.map_from_arrays(F.array(F.lit("union"), F.lit("jaccard")), F.array("union", "jaccard"))
    est = sums.select("query_id", F.explode(pairs).alias("measure", "estimate"), F.lit("k-mins").alias("estimator"))
    return metrics.relative_error(est, truths(memberships), by=("estimator",), on=("measure",)).select("measure", "estimator", "avg_rel_error")


def poisson_sketches(memberships: DataFrame, k: int, draws: int, family: str = "priority", method: str = "xxhash64") -> DataFrame:
    """Poisson samples of expected size k of every set and draw, each draw with its own ranks, as sketches of bound threshold."""
    limits = drawn(poisson_threshold(memberships, k, family), draws).drop("seed")
    return poisson(drawn(memberships, draws), limits, family, F.col("seed"), attrs=("seed",), method=method).drop("seed")


def poisson_errors(memberships: DataFrame, k: int, draws: int, family: str = "priority", method: str = "xxhash64") -> DataFrame:
    """estimator, avg_rel_error, mean_size for the union's weight: order samples (bottom-k) of k keys against Poisson samples of
    as many expected keys, each by the short and the long combination."""
    qs = queries_of(memberships, draws)
    found = None
    for kind, sk in (("order", sketches(memberships, k, draws, family, method)), ("poisson", poisson_sketches(memberships, k, draws, family, method))):
        for combo in ("short", "long"):
            rows = estimate.combined(sk, qs, combo, family)
            sums = rows.groupBy("query_id").agg(F.sum("adj").alias("estimate"), F.count(F.lit(1)).alias("size"))
            one = qs.select("query_id").distinct().join(sums, "query_id", "left").fillna(0).select(F.lit("union").alias("measure"), F.lit(f"{kind}_{combo}").alias("estimator"), "estimate", "size")
            found = one if found is None else found.unionByName(one)
    err = metrics.relative_error(found, truths(memberships), by=("estimator",), on=("measure",))
    return err.join(found.groupBy("estimator").agg(F.avg("size").alias("mean_size")), "estimator").select("estimator", "avg_rel_error", "mean_size")


def sampling_variances(memberships: DataFrame, k: int, draws: int, method: str = "xxhash64") -> DataFrame:
    """set_id, estimator, sum_of_variances: Poisson samples in proportion to weight of expected size k, and priority samples of
    k + 1 keys. The former's sum is no larger in expectation."""
    out = None
    for name, sk in (("poisson", poisson_sketches(memberships, k, draws, "priority", method)), ("priority", sketches(memberships, k + 1, draws, "priority", method))):
        adjusted = conditioned(sk, "priority").select(F.split("set_id", r"\|", 2)[1].alias("set_id"), "key", "weight", "adj")
        one = adjusted.select(F.lit(name).alias("estimator"), "set_id", (F.col("adj") * F.col("adj") - 2 * F.col("weight") * F.col("adj")).alias("x"))
        out = one if out is None else out.unionByName(one)
    base = memberships.dropDuplicates(["set_id", "key"]).groupBy("set_id").agg(F.sum(F.col("weight") * F.col("weight")).alias("squares"))
    sums = out.groupBy("set_id", "estimator").agg(F.sum("x").alias("x"))  # a key that is not sampled adds its square
    return sums.join(base, "set_id").select("set_id", "estimator", (F.col("squares") + F.col("x") / draws).alias("sum_of_variances"))


def law_measures(memberships: DataFrame, k: int, draws: int, family: str = "exponential", method: str = "xxhash64") -> DataFrame:
    """estimator, mean_ratio (mean of the union's estimates over its weight), cv2, sum_of_variances of the keys' adjusted weights."""
    sk, qs = sketches(memberships, k, draws, family, method), queries_of(memberships, draws)
    truth = memberships.groupBy("key").agg(F.first("weight").alias("exact"))
    adjusted = None
    for combo in ("union", "short", "long"):
        one = estimate.combined(sk, qs, combo, family, k).select(F.lit(combo).alias("estimator"), "query_id", "key", "adj")
        adjusted = one if adjusted is None else adjusted.unionByName(one)
    sums = adjusted.groupBy("estimator", "query_id").agg(F.sum("adj").alias("estimate"))
    total = truth.agg(F.sum("exact").alias("total"))
    ratio = sums.groupBy("estimator").agg(F.avg("estimate").alias("mean")).crossJoin(F.broadcast(total)).select("estimator", (F.col("mean") / F.col("total")).alias("mean_ratio"))  # one row
    return ratio.join(metrics.cv2(sums), "estimator").join(metrics.variances(adjusted, truth, draws), "estimator")


def partition_ablation(memberships: DataFrame, k: int, draws: int, parts: int = 4, method: str = "xxhash64") -> DataFrame:
    """estimator, sum_of_variances of adjusted weights that are conditioned on less or more of the other keys' ranks.

    whole: bottom-k of each set, conditioned on its bound. parts: the set cut by key into that many parts of k / parts keys,
    each conditioned on its own part's bound: a finer partition of the space of ranks, whose variance is larger."""
    cut = memberships.withColumn("set_id", F.concat("set_id", F.lit("#"), F.pmod("key", F.lit(parts)).cast("string")))
    truth = memberships.groupBy("set_id", "key").agg(F.first("weight").alias("exact"))
    out = None
    for name, rows, size in (("whole", memberships, k), ("parts", cut, k // parts)):
        adjusted = conditioned(sketches(rows, size, draws, "exponential", method), "exponential").select(F.lit(name).alias("estimator"), F.concat(F.split(F.split("set_id", r"\|", 2)[1], "#")[0], F.lit("/"), F.col("key").cast("string")).alias("key"), "adj")
        out = adjusted if out is None else out.unionByName(adjusted)
    return metrics.variances(out, truth.select(F.concat("set_id", F.lit("/"), F.col("key").cast("string")).alias("key"), "exact"), draws)


def uniform_jaccard_errors(memberships: DataFrame, pairs: DataFrame, k: int, draws: int, method: str = "xxhash64") -> DataFrame:
    """query_id, estimator, avg_rel_error of the two Jaccard estimators for equal weights. pairs: query_id, a, b."""
    sk = sketches(memberships, k, draws, "uniform", method)
    spread = pairs.withColumn("seed", F.explode(F.sequence(F.lit(1), F.lit(draws))))
    named = [F.concat(F.col("seed").cast("string"), F.lit("|"), F.col(c)).alias(c) for c in "ab"]
    asked = spread.select((F.col("query_id") * 1_000_000 + F.col("seed")).alias("query_id"), *named)
    found = None
    for m in ("union", "short"):
        one = estimate.jaccard(sk, asked, m, k=k).select((F.col("query_id") / 1_000_000).cast("long").alias("query_id"), F.lit(m).alias("estimator"), F.col("jaccard").alias("estimate"))
        found = one if found is None else found.unionByName(one)
    return metrics.relative_error(found, exact.jaccard(memberships, pairs), by=("estimator",), on=("query_id",))

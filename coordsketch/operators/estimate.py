"""Estimates of weights, ratios, similarities and further aggregates from sketches alone."""

from __future__ import annotations

import math
from collections import defaultdict

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.adjust import conditioned
from ..plans import predicate as P
from ..plans.lineage import stored
from . import combine
from .meeting import Rule, meeting, same, spread
from .sketch import to_nested

INF = float("inf")


def query_sets(spark: SparkSession, sets_by_query: dict) -> DataFrame:
    """Rows (query_id, set_id) of a few queries written down by hand."""
    rows = [(q, s) for q, sets in sets_by_query.items() for s in sorted(sets)]
    return spark.createDataFrame(rows, "query_id long, set_id string")


def combined(sketch: DataFrame, qs: DataFrame, combo: str, family: str, k: int | None = None) -> DataFrame:
    """The combination with adjusted weights adj and inclusion probabilities p."""
    if combo == "union":
        if k is None:
            raise ValueError("the union sketch needs k")
        return conditioned(combine.union_sketch(sketch, qs, k), family)
    return conditioned({"short": combine.short, "long": combine.long}[combo](sketch, qs), family)


prepare = combined


def _plan(p: P.Pred, combo: str) -> tuple[frozenset[str], str]:
    sets, best = P.relevant_sets(p), P.best_combination(p)
    if not P.bounded(p):
        raise ValueError("keys outside of all sets can satisfy the predicate; add a set that bounds it")
    if combo == "long" and best != "long":
        raise ValueError("the long combination does not know the memberships that the predicate asks for")
    return sets, best if combo == "auto" else combo


def _totals(matches: Column) -> list[Column]:
    taken = F.when(matches, F.col("adj")).otherwise(F.lit(0.0))
    error = F.sqrt(F.sum(F.when(matches, F.col("adj") * F.col("adj") * (1 - F.col("p"))).otherwise(F.lit(0.0))))
    return [F.sum(taken).alias("estimate"), F.count_if(matches).alias("n_sampled"), error.alias("std_error")]


def weight(sketch: DataFrame, pred: P.Pred | str, *, combo: str = "auto", family: str = "exponential", k: int | None = None) -> DataFrame:
    """estimate, n_sampled, std_error, combo: the weight of the keys that satisfy a predicate. One row, always."""
    p = P.parse(pred) if isinstance(pred, str) else pred
    sets, use = _plan(p, combo)
    rows = combined(sketch, query_sets(sketch.sparkSession, {0: sets}), use, family, k)
    found = rows.agg(*_totals(P.to_column(p)))
    return found.select(F.coalesce("estimate", F.lit(0.0)).alias("estimate"), "n_sampled", F.coalesce("std_error", F.lit(0.0)).alias("std_error"), F.lit(use).alias("combo"))


def weight_batch(sketch: DataFrame, queries: dict[int, P.Pred | str], *, combo: str = "auto", family: str = "exponential", k: int | None = None) -> DataFrame:
    """query_id, estimate, n_sampled, std_error, combo.

    Collections of sets are rows, so the plan has one branch for each kind of combination, three at most, however many queries
    there are; predicates over the same sets and combination share their rows."""
    parsed = {q: P.parse(p) if isinstance(p, str) else p for q, p in queries.items()}
    plans = {q: _plan(p, combo) for q, p in parsed.items()}
    spark = sketch.sparkSession
    whole = None
    for use in sorted({u for _, u in plans.values()}):
        groups = {sets: i for i, sets in enumerate(dict.fromkeys(s for s, u in plans.values() if u == use))}
        members = defaultdict(list)
        for q, (sets, u) in plans.items():
            if u == use:
                members[groups[sets]].append(q)
        rows = combined(sketch, query_sets(spark, {i: sets for sets, i in groups.items()}), use, family, k)
        of_group = F.lit(None).cast("array<long>")
        for i, own in members.items():
            hit = F.array_compact(F.array(*[F.when(P.to_column(parsed[q]), F.lit(q).cast("long")) for q in own]))
            of_group = F.when(F.col("query_id") == i, hit).otherwise(of_group)
        found = rows.select(F.explode(of_group).alias("q"), "adj", "p").groupBy("q").agg(*_totals(F.lit(True)))
        asked = spark.createDataFrame([(q, use) for own in members.values() for q in own], "query_id long, combo string")
        one = asked.join(found, F.col("query_id") == F.col("q"), "left")
        whole = one if whole is None else whole.unionByName(one)
    if whole is None:
        return spark.createDataFrame([], "query_id long, estimate double, n_sampled long, std_error double, combo string")
    return whole.select("query_id", *[F.coalesce(c, F.lit(0).cast(t)).alias(c) for c, t in (("estimate", "double"), ("n_sampled", "long"), ("std_error", "double"))], "combo")


def sums(rows: DataFrame, **conditions: Column) -> DataFrame:
    """Per query, the adjusted weight of every named condition over a prepared combination."""
    return rows.groupBy("query_id").agg(*[F.sum(F.when(c, F.col("adj")).otherwise(F.lit(0.0))).alias(name) for name, c in conditions.items()])


def total(rows: DataFrame, pred: P.Pred, h: Column) -> DataFrame:
    """query_id, estimate of the sum of h over the keys that satisfy the predicate (h: a function of the key)."""
    return rows.groupBy("query_id").agg(F.sum(F.when(P.to_column(pred), F.col("adj") * h / F.col("weight")).otherwise(F.lit(0.0))).alias("estimate"))


def ratio(rows: DataFrame, num: P.Pred, den: P.Pred) -> DataFrame:
    both = sums(rows, num=P.to_column(num), den=P.to_column(den))
    return both.select("query_id", F.try_divide("num", "den").alias("estimate"))


def mean_variance(rows: DataFrame, pred: P.Pred, h: Column) -> DataFrame:
    """query_id, mean, variance of h over the subpopulation, each key counted by its weight."""
    matches = P.to_column(pred)
    part = lambda x: F.sum(F.when(matches, F.col("adj") * x).otherwise(F.lit(0.0)))
    s = rows.groupBy("query_id").agg(part(F.lit(1.0)).alias("w"), part(h).alias("a"), part(h * h).alias("b"))
    return s.select("query_id", (F.col("a") / F.col("w")).alias("mean"), (F.col("b") / F.col("w") - (F.col("a") / F.col("w")) ** 2).alias("variance"))


def pair(sketch: DataFrame, pairs: DataFrame, family: str = "exponential", *, hamming: str = "short") -> DataFrame:
    """pairs: query_id, a, b. Weights of union, intersection, a minus b, the Hamming distance and the Jaccard ratio.

    The distance is union minus intersection, both from the short combination (never negative), or with hamming='mixed'
    the union from the long one."""
    qs = pairs.select("query_id", F.explode(F.array("a", "b")).alias("set_id"))
    named = pairs.select(F.col("query_id").alias("q"), "a", "b")
    rows = combined(sketch, qs, "short", family).join(named, F.col("query_id") == F.col("q"))
    in_a, in_b = F.array_contains("member_of", F.col("a")), F.array_contains("member_of", F.col("b"))
    s = sums(rows, union_short=F.lit(True), intersection=in_a & in_b, difference=in_a & ~in_b)
    long = sums(combined(sketch, qs, "long", family), union_long=F.lit(True))
    joined = pairs.select("query_id", "a", "b").join(long, "query_id", "left").join(s, "query_id", "left").fillna(0.0)
    base = F.col("union_short") if hamming == "short" else F.col("union_long")
    return joined.select("query_id", "a", "b", F.col("union_long").alias("union"), "intersection", "difference", (base - F.col("intersection")).alias("hamming"), F.try_divide("intersection", "union_short").alias("jaccard"))


def intersection_ie(sketch: DataFrame, pairs: DataFrame, totals: DataFrame, family: str = "exponential") -> DataFrame:
    """The comparator: known totals minus the long combination's union. totals: set_id, total."""
    union = pair(sketch, pairs, family).select("query_id", "a", "b", "union")
    a, b = (totals.select(F.col("set_id").alias(c), F.col("total").alias(f"w_{c}")) for c in "ab")
    return union.join(a, "a").join(b, "b").select("query_id", (F.col("w_a") + F.col("w_b") - F.col("union")).alias("intersection"))


def confidence(sketch: DataFrame, pairs: DataFrame, family: str = "exponential", totals: DataFrame | None = None) -> DataFrame:
    """query_id, confidence: weight of a and b over weight of b, the latter exact if totals (set_id, total) are given."""
    both = pair(sketch, pairs, family).select("query_id", "b", "intersection")
    if totals is None:
        totals = conditioned(sketch, family).groupBy("set_id").agg(F.sum("adj").alias("total"))
    return both.join(totals.select(F.col("set_id").alias("b"), "total"), "b").select("query_id", F.try_divide("intersection", "total").alias("confidence"))


def jaccard(sketch: DataFrame, pairs: DataFrame, method: str = "short", family: str = "uniform", k: int | None = None) -> DataFrame:
    """query_id, jaccard. Methods: short and union (shares of equally weighted keys), weight (ratio of weights),
    mimic_exact and same_keys (weighted selectivities)."""
    from . import selectivity

    qs = pairs.select("query_id", F.explode(F.array("a", "b")).alias("set_id")).distinct()
    if method == "weight":
        return pair(sketch, pairs, family).select("query_id", F.coalesce("jaccard", F.lit(0.0)).alias("jaccard"))
    comb = combine.union_sketch(sketch, qs, k) if method == "union" else combine.short(sketch, qs)
    rho = {"short": selectivity.uniform_share, "union": selectivity.uniform_share, "mimic_exact": selectivity.rho_mimic_exact, "same_keys": selectivity.rho_same_keys}[method](comb)
    hit = F.sum(F.when(F.size("member_of") == 2, F.col("rho")).otherwise(F.lit(0.0)))
    return pairs.select("query_id").distinct().join(rho.groupBy("query_id").agg(hit.alias("jaccard")), "query_id", "left").fillna(0.0)


def jaccard_k_mins(sketch: DataFrame, pairs: DataFrame, k: int) -> DataFrame:
    """query_id, jaccard: the share of coordinates whose minimum both sets attain."""
    qs = pairs.select("query_id", F.explode(F.array("a", "b")).alias("set_id")).distinct()
    u = combine.union_k_mins(sketch, qs)
    return u.groupBy("query_id").agg((F.count_if(F.size("member_of") == 2) / F.lit(k)).alias("jaccard"))


def weight_k_mins(sketch: DataFrame, qs: DataFrame, pred: P.Pred, k: int) -> DataFrame:
    """query_id, estimate: (k - 1) over the sum of minima is the union's weight; times the matching share. Null for k = 1."""
    u = combine.union_k_mins(sketch, qs)
    union = F.lit(float(k - 1)) / F.sum("min_rank") if k > 1 else F.lit(None).cast("double")
    return u.groupBy("query_id").agg((union * F.count_if(P.to_column(pred)) / F.lit(k)).alias("estimate"))


def intersection_uncoordinated(a: DataFrame, b: DataFrame, family: str) -> Column:
    """Baseline: sketches of two sets with their own ranks; a key in both samples counts its weight over both probabilities."""
    left = conditioned(a, family).select("key", "weight", F.col("p").alias("p_a"))
    right = conditioned(b, family).select("key", F.col("p").alias("p_b"))
    return left.join(right, "key").agg(F.coalesce(F.sum(F.col("weight") / (F.col("p_a") * F.col("p_b"))), F.lit(0.0)).alias("estimate"))


def met_pairs(sketch: DataFrame, theta: float, *, method: str = "short", k: int | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """What similar_pairs judges, stored: the sets, the first one of equal sets for each, and pairs of these that share enough keys.

    With n keys sampled in the set with the smaller bound and b below that bound in the other one, an estimate of theta needs
    theta / (1 + theta) * (n + b) common keys, or by the method union theta * k if that is fewer; so pairs for it serve both methods."""
    if method == "union" and k is None:
        raise ValueError("the union sketch needs k")
    nested = sketch if "entries" in sketch.columns else to_nested(sketch.select("set_id", "rank", "key", "weight", "bound"))
    sets = stored(nested.select("set_id", F.transform("entries", lambda e: e["rank"]).alias("ranks"), F.col("bound").alias("place")))
    cap = theta * k if method == "union" else INF
    fewest = sets.where(F.col("place") < INF).agg(F.min(F.size("ranks"))).first()[0]
    below = max(1, math.ceil(min(cap, theta * fewest) - 1e-9)) if fewest else 0  # so many keys below a finite bound
    since = F.when(F.size("ranks") >= below, F.element_at("ranks", below)).otherwise(F.lit(INF)) if below else F.lit(INF)
    hashed = sets.select("set_id", F.transform("ranks", lambda r: F.xxhash64(r)).alias("of"), F.size("ranks").alias("whole"), "place", since.alias("since"), F.col("ranks").alias("marks"))
    met, held = meeting(hashed, Rule(theta, theta / (1 + theta), cap))
    held = stored(held)
    return sets, held, stored(met.select("a", "b").unionByName(same(held)))


def similar_pairs(sketch: DataFrame, theta: float, *, method: str = "short", k: int | None = None, met: tuple[DataFrame, DataFrame, DataFrame] | None = None) -> DataFrame:
    """a, b, jaccard of all pairs of sets whose estimated Jaccard ratio is at least theta. sketch: in rows, or nested. Pairs that
    share enough keys are found first (met, or by met_pairs), and then judged. short: keys known in both; union: the k lowest of both."""
    sets, held, pairs = met or met_pairs(sketch, theta, method=method, k=k)
    one = lambda c: sets.select(F.col("set_id").alias(c), F.col("ranks").alias(f"of_{c}"), F.col("place").alias(f"bound_{c}"))
    joined = pairs.join(one("a"), "a").join(one("b"), "b")
    low = F.least("bound_a", "bound_b")
    known = F.filter(F.array_sort(F.array_union("of_a", "of_b")), lambda r: r < low)
    counted = joined.withColumn("known", F.slice(known, 1, F.lit(k)) if method == "union" else known)
    hit = F.size(F.array_intersect(F.array_intersect("of_a", "of_b"), "known"))
    judged = counted.select("a", "b", F.try_divide(hit.cast("double"), F.size("known")).alias("jaccard")).where(F.col("jaccard") >= theta)
    return spread(judged, held)


def with_error(rows: DataFrame, pred: P.Pred) -> DataFrame:
    """query_id, estimate, n_sampled, std_error over a prepared combination."""
    return rows.groupBy("query_id").agg(*_totals(P.to_column(pred)))


__all__ = [n for n in dir() if not n.startswith("_") and n not in ("Column", "DataFrame", "SparkSession", "Window")]

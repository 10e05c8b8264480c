"""Maximum-likelihood estimates from sketches with exponential ranks.

In rank order, the gaps between ranks are independent exponentials whose rate is the weight not yet seen. So a weight x
of which the keys s_1, s_2, ... (sums of the weights before each key) were seen up to a bound has its likelihood's
maximum where a sum of 1 / (x - s) balances the bound or other such sums. All are roots of decreasing functions and are
solved by bisection inside column expressions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.solve import reciprocal_sum, solve_decreasing
from ..plans import predicate as P
from . import combine

INF = float("inf")
_BEFORE = (Window.unboundedPreceding, -1)


def rank_gaps(sketch: DataFrame) -> DataFrame:
    """set_id, key, gap, remaining: each rank minus the one before, and the sketch weight seen before it."""
    order = Window.partitionBy("set_id").orderBy("rank", "key")
    return sketch.select("set_id", "key", (F.col("rank") - F.coalesce(F.lag("rank").over(order), F.lit(0.0))).alias("gap"), F.coalesce(F.sum("weight").over(order.rowsBetween(*_BEFORE)), F.lit(0.0)).alias("seen"))


def _shifts(rows: DataFrame, by: list[str], group: Column) -> DataFrame:
    """by, and for the keys of group: n, sum, shifts (weight seen before each of them); the same for the others with _other."""
    marked = rows.withColumn("_in", group)
    order = Window.partitionBy(*by, "_in").orderBy("rank", "key")
    seen = marked.withColumn("_s", F.coalesce(F.sum("weight").over(order.rowsBetween(*_BEFORE)), F.lit(0.0)))
    parts = []
    for name, c in (("", F.col("_in")), ("_other", ~F.col("_in"))):
        parts += [F.count_if(c).alias(f"n{name}"), F.coalesce(F.sum(F.when(c, F.col("weight"))), F.lit(0.0)).alias(f"sum{name}"), F.collect_list(F.when(c, F.col("_s"))).alias(f"shifts{name}"), F.coalesce(F.max(F.when(c, F.col("_s"))), F.lit(0.0)).alias(f"last{name}")]
    return seen.groupBy(*by).agg(F.first("bound").alias("bound"), *parts)


def union_weight(comb: DataFrame) -> DataFrame:
    """query_id, estimate of the union's weight from the short combination: one more draw than keys fits the bound."""
    s = _shifts(comb, ["query_id"], F.lit(True)).withColumn("terms", F.concat("shifts", F.array("sum")))
    root = solve_decreasing(lambda x: reciprocal_sum(x, F.col("terms")) - F.col("bound"), F.col("sum"), F.col("sum") + (F.col("n") + 1) / F.col("bound"))
    return s.select("query_id", F.when(F.col("bound") == INF, F.col("sum")).otherwise(root).alias("estimate"))


def subset_weight(comb: DataFrame, pred: P.Pred) -> DataFrame:
    """query_id, estimate of a subpopulation's weight from the short combination; 0 if none of its keys is held."""
    s = _shifts(comb, ["query_id"], P.to_column(pred))
    root = solve_decreasing(lambda x: reciprocal_sum(x, F.col("shifts")) - F.col("bound"), F.col("last"), F.col("last") + F.col("n") / F.col("bound"))
    return s.select("query_id", F.when(F.col("n") == 0, F.lit(0.0)).when(F.col("bound") == INF, F.col("sum")).otherwise(root).alias("estimate"))


def _known_total(n: Column, m: Column, total: Column) -> Column:
    """The weight of a part of a set of known total: n keys of the part were seen (shifts), m of the rest (shifts_other)."""
    root = solve_decreasing(lambda x: reciprocal_sum(x, F.col("shifts")) - reciprocal_sum(total - x, F.col("shifts_other")), F.col("last"), total - F.col("last_other"))
    return F.when(n == 0, F.lit(0.0)).when(m == 0, total).when(F.col("bound") == INF, F.col("sum")).otherwise(F.least(F.greatest(root, F.col("sum")), total - F.col("sum_other")))


def subset_known_total(sketch: DataFrame, pred: P.Pred, totals: DataFrame) -> DataFrame:
    """set_id, estimate: the weight of a subpopulation of one set whose total (set_id, total) is known."""
    s = _shifts(sketch, ["set_id"], P.to_column(pred)).join(totals, "set_id")
    return s.select("set_id", _known_total(F.col("n"), F.col("n_other"), F.col("total")).alias("estimate"))


def intersection_known_totals(sketch: DataFrame, pairs: DataFrame, totals: DataFrame, form: str = "derived") -> DataFrame:
    """query_id, intersection, union, jaccard of two sets of known totals. pairs: query_id, a, b; totals: set_id, total.

    derived: keys of the symmetric difference have the weight wA + wB - 2x, which enters with its factor and the bound.
    printed: without factor, bound and first term, for comparison. three_part: the rests of both sets apart."""
    qs = pairs.select("query_id", F.explode(F.array("a", "b")).alias("set_id"))
    named = pairs.select(F.col("query_id").alias("q"), "a", "b").join(totals.select(F.col("set_id").alias("a"), F.col("total").alias("wa")), "a").join(totals.select(F.col("set_id").alias("b"), F.col("total").alias("wb")), "b")
    comb = combine.short(sketch, qs)
    s = _shifts(comb, ["query_id"], F.size("member_of") == 2)
    if form == "three_part":
        only = comb.join(named.select("q", "a"), F.col("query_id") == F.col("q")).where(F.size("member_of") == 1)
        split = _shifts(only, ["query_id"], F.array_contains("member_of", F.col("a"))).select(F.col("query_id").alias("q3"), F.col("shifts").alias("only_a"), F.col("shifts_other").alias("only_b"))
        s = s.join(split, F.col("query_id") == F.col("q3"), "left").withColumn("only_a", F.coalesce("only_a", F.array().cast("array<double>"))).withColumn("only_b", F.coalesce("only_b", F.array().cast("array<double>")))
    s = s.join(named, F.col("query_id") == F.col("q"))
    both = F.col("wa") + F.col("wb")

    def f(x: Column) -> Column:
        if form == "derived":
            return reciprocal_sum(x, F.col("shifts")) - 2 * reciprocal_sum(both - 2 * x, F.col("shifts_other")) + F.col("bound")
        if form == "printed":
            return reciprocal_sum(x, F.col("shifts")) - reciprocal_sum(both - 2 * x, F.slice(F.array_sort("shifts_other"), 2, F.greatest(F.size("shifts_other"), F.lit(1))))
        return reciprocal_sum(x, F.col("shifts")) - reciprocal_sum(F.col("wa") - x, F.col("only_a")) - reciprocal_sum(F.col("wb") - x, F.col("only_b")) + F.col("bound")

    top = F.least(F.col("wa"), F.col("wb"))
    high = F.least(top, (both - F.col("last_other")) / 2) if form != "three_part" else F.least(top, *[F.col(w) - F.coalesce(F.array_max(c), F.lit(0.0)) for w, c in (("wa", "only_a"), ("wb", "only_b"))])
    root = F.when(F.col("n") == 0, F.lit(0.0)).when(F.col("bound") == INF, F.col("sum")).otherwise(solve_decreasing(f, F.col("last"), high))
    found = s.withColumn("x", F.least(F.greatest(root, F.col("sum")), top))
    return found.select("query_id", F.col("x").alias("intersection"), (both - F.col("x")).alias("union"), (F.col("x") / (both - F.col("x"))).alias("jaccard"))


def union_known_totals(sketch: DataFrame, query_sets: DataFrame, totals: DataFrame, pred: P.Pred | None = None) -> DataFrame:
    """query_id, estimate of the union's weight (or of a subpopulation) from the long combination and known set totals.

    Sets in the order of their bounds: a key of one set's sketch is known to lie in a later set or not, so each set gives
    the weight that no later set has; the last one is known as a whole."""
    rows = combine.attach(sketch, query_sets)
    place = F.dense_rank().over(Window.partitionBy("query_id").orderBy("bound", "set_id"))
    placed = rows.withColumn("_pos", place)
    last_of_key = F.max("_pos").over(Window.partitionBy("query_id", "key"))
    outside = placed.withColumn("_out", F.col("_pos") == last_of_key)
    wanted = F.col("_out") if pred is None else F.col("_out") & P.to_column(pred, F.array())
    s = _shifts(outside, ["query_id", "set_id"], wanted).join(totals, "set_id")
    each = _known_total(F.col("n"), F.col("n_other"), F.col("total"))
    return s.groupBy("query_id").agg(F.sum(each).alias("estimate"))


def intersection_from_union(sketch: DataFrame, pairs: DataFrame, totals: DataFrame) -> DataFrame:
    """query_id, intersection: the sum of two known totals minus the union estimated with them."""
    qs = pairs.select("query_id", F.explode(F.array("a", "b")).alias("set_id"))
    union = union_known_totals(sketch, qs, totals)
    sums = qs.join(totals, "set_id").groupBy("query_id").agg(F.sum("total").alias("both"))
    return union.join(sums, "query_id").select("query_id", (F.col("both") - F.col("estimate")).alias("intersection"))

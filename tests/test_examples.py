"""The worked example with ten keys, four sets and given ranks, in both membership variants, and the bias example."""

import itertools
import math

import pytest
from pyspark.sql import functions as F

from coordsketch.operators import combine, estimate, selectivity, sketch
from coordsketch.plans import predicate as P

#: Fixed values of the example.
U = {1: 0.487, 2: 0.72, 3: 0.3, 4: 0.832, 5: 0.765, 6: 0.599, 7: 0.131, 8: 0.886, 9: 0.73, 10: 0.341}
WEIGHTS = {2: 2.0, 4: 3.0}
SETS = {"A1": [1, 3, 5, 7, 9], "A2": [2, 5, 6, 9, 10], "A3": [3, 4, 5, 6, 7], "A4": [2, 4, 6, 8, 10]}
TWO, FOUR = ["A1", "A2"], list(SETS)


def sketches(spark, variant, rank4=None):
    sets = SETS | ({"A2": [1, *SETS["A2"]]} if variant == "listed" else {})
    rank = lambda k: rank4 if rank4 and k == 4 else U[k] / WEIGHTS.get(k, 1.0)
    rows = [(s, k, WEIGHTS.get(k, 1.0), rank(k), k) for s, keys in sets.items() for k in keys]
    ranked = spark.createDataFrame(rows, "set_id string, key long, weight double, rank double, j long")
    return sketch._bounded(sketch._cut(ranked, 3, ["set_id"]), 3, ["set_id"])


def adjusted(spark, variant, sets, combo):
    qs = estimate.query_sets(spark, {0: sets})
    rows = estimate.combined(sketches(spark, variant), qs, combo, "priority", 3).collect()
    return {r["key"]: round(r["adj"], 3) for r in rows}


@pytest.mark.parametrize("rank4", [None, 0.208])
def test_order_does_not_depend_on_the_printed_rank(spark, rank4):
    rows = sketches(spark, "matrix", rank4).where("set_id = 'A3'").orderBy("rank").collect()
    assert [r["key"] for r in rows] == [7, 4, 3] and rows[0]["bound"] == 0.599


def test_union_and_short_and_long(spark):
    assert adjusted(spark, "matrix", TWO, "union") == {7: 2.778, 3: 2.778, 10: 2.778}
    assert adjusted(spark, "matrix", TWO, "short") == adjusted(spark, "matrix", TWO, "long") == {7: 1.37, 3: 1.37, 10: 1.37, 2: 2.0, 1: 1.37, 6: 1.37}
    assert adjusted(spark, "matrix", FOUR, "union") == {7: 2.933, 4: 3.0, 3: 2.933}
    assert adjusted(spark, "matrix", FOUR, "short") == {7: 1.669, 3: 1.669, 10: 1.669, 1: 1.669, 4: 3.0, 2: 2.0}
    assert adjusted(spark, "matrix", FOUR, "long") == {7: 1.37, 3: 1.37, 10: 1.37, 1: 1.37, 6: 1.37, 4: 3.0, 2: 2.0}
    assert adjusted(spark, "listed", TWO, "long") == {7: 1.37, 3: 1.37, 1: 1.37, 10: 1.669, 2: 2.0}
    assert 6 not in adjusted(spark, "listed", FOUR, "long")


@pytest.mark.parametrize(
    ("variant", "text", "combo", "expected"),
    [
        ("matrix", "(in(A1) or in(A2)) and j >= 4 and j < 8", "long", 2.740),
        ("listed", "(in(A1) or in(A2)) and j >= 4 and j < 8", "long", 1.370),
        ("listed", "(in(A1) or in(A2)) and j >= 4 and j < 8", "short", 1.669),
        ("matrix", "in(A1) and in(A2) and j >= 4 and j < 8", "short", 0.0),
        ("matrix", "at_least(2, A1, A2, A3, A4)", "short", 10.007),
        ("listed", "at_least(2, A1, A2, A3, A4)", "short", 11.676),
        ("matrix", "(in(A1) or in(A2) or in(A3) or in(A4)) and j % 2 = 1", "long", 4.110),
        ("matrix", "(in(A1) or in(A2) or in(A3) or in(A4)) and j % 2 = 1", "short", 5.007),
    ],
)
def test_predicates(spark, variant, text, combo, expected):
    row = estimate.weight(sketches(spark, variant), text, combo=combo, family="priority").first()
    assert abs(row["estimate"] - expected) < 2e-3


def test_long_is_refused_where_memberships_matter(spark):
    with pytest.raises(ValueError):
        estimate.weight(sketches(spark, "matrix"), "in(A1) and in(A2)", combo="long", family="priority")


def test_bias_example_naive_fractions_and_exact_average(spark):
    """Two sets {1,2,3}, {1,4}, w(1) = 4, k = 2: truth 4/7. All orders of the keys, with their exact probabilities."""
    w = {1: 4.0, 2: 1.0, 3: 1.0, 4: 1.0}
    by_weight = by_count = 0.0
    for order in itertools.permutations(w):
        p, left = 1.0, sum(w.values())
        for k in order:
            p, left = p * w[k] / left, left - w[k]
        union = order[:2]
        by_weight += p * sum(w[k] for k in union if k == 1) / sum(w[k] for k in union)
        by_count += p * sum(k == 1 for k in union) / 2
    assert math.isclose(by_weight, 24 / 35) and math.isclose(by_count, 3 / 7)


def test_mimicking_is_unbiased_on_the_bias_example(spark):
    sets = [("A", k, w) for k, w in ((1, 4.0), (2, 1.0), (3, 1.0))] + [("B", 1, 4.0), ("B", 4, 1.0)]
    rows = spark.createDataFrame(sets, "set_id string, key long, weight double")
    n = 3000
    spread = rows.withColumn("seed", F.explode(F.sequence(F.lit(1), F.lit(n)))).withColumn("set_id", F.concat("seed", F.lit("|"), "set_id"))
    sk = sketch.bottom_k(spread, 2, "exponential", F.col("seed"), by=("seed",)).drop("seed")
    qs = sk.select(F.split("set_id", r"\|")[0].cast("long").alias("query_id"), "set_id").distinct()
    comb = combine.short(sk, qs)
    for rho in (selectivity.rho_mimic_exact(comb), selectivity.rho_same_keys(comb)):
        got = rho.groupBy("query_id").agg(F.sum(F.when(F.col("key") == 1, F.col("rho")).otherwise(F.lit(0.0))).alias("x"), F.sum("rho").alias("t")).agg(F.avg("x"), F.max(F.abs(F.col("t") - 1))).first()
        assert abs(got[0] - 4 / 7) < 0.02 and got[1] < 1e-6


def test_expected_counts_by_enumeration():
    import numpy as np

    w, n = np.array([4.0, 2.0, 1.0]), 5
    sums, total = np.zeros(3), 0.0
    for draw in itertools.product(range(3), repeat=n):
        if len(set(draw)) == 3:
            p = float(np.prod(w[list(draw)]))
            total += p
            sums += p * np.bincount(draw, minlength=3)
    assert np.allclose(selectivity.expected_counts(w, n), sums / total)


def test_predicate_analysis():
    p = P.parse("(in(A) and x > 1) or (in(B) and x > 1)")
    assert P.relevant_sets(p) == {"A", "B"} and P.best_combination(p) == "long"
    assert P.best_combination(P.parse("in(A) and not in(B)")) == "short"
    assert P.relevant_sets(P.parse("in(A) or (in(A) and in(B))")) == {"A"}
    assert not P.bounded(P.parse("not in(A)"))
    with pytest.raises(ValueError):
        P.parse("(in(A)")

"""Invariants, statistics, edge cases, plans and SQL agreement of the sketch engine."""

import math

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from coordsketch import oracles, queries, workloads
from coordsketch.functions import ranks
from coordsketch.functions.adjust import conditioned, short_rc_priority
from coordsketch.operators import combine, estimate, exact, metrics, ml, sketch
from coordsketch.plans import api
from coordsketch.plans import predicate as P
from coordsketch.sources import datasets as D
from coordsketch.sources import store
from coordsketch.streaming import sketches as S

INF = float("inf")


def members(spark, sets, weight=lambda k: 1.0):
    return spark.createDataFrame([(s, int(k), float(weight(k))) for s, keys in sets.items() for k in keys], "set_id string, key long, weight double")


SETS = {"A": range(0, 300), "B": range(200, 500), "C": range(250, 290), "D": range(5)}


@pytest.mark.parametrize("family", ranks.FAMILIES)
def test_combinations_are_nested(spark, family):
    rows = members(spark, SETS, lambda k: 1 + k % 7)
    sk = sketch.bottom_k(rows, 20, family, 3)
    qs = estimate.query_sets(spark, {1: ["A", "B"], 2: ["A", "B", "C", "D"], 3: ["A"]})
    keys = {kind: {(r["query_id"], r["key"]) for r in df.collect()} for kind, df in (("union", combine.union_sketch(sk, qs, 20)), ("short", combine.short(sk, qs)), ("long", combine.long(sk, qs)))}
    assert keys["union"] <= keys["short"] <= keys["long"]
    one = [{k for q, k in v if q == 3} for v in keys.values()]
    assert one[0] == one[1] == one[2] and len(one[0]) == 20
    union = rows.where("set_id in ('A', 'B')").withColumn("set_id", F.lit("U")).distinct()
    direct = sketch.bottom_k(union, 20, family, 3).collect()
    got = combine.union_sketch(sk, qs.where("query_id = 1"), 20).collect()
    assert {r["key"] for r in direct} == {r["key"] for r in got} and abs(direct[0]["bound"] - got[0]["bound"]) < 1e-12


def test_small_sets_are_exact(spark):
    rows = members(spark, {"A": range(10), "B": range(5, 15)}, lambda k: k + 1)
    sk = sketch.bottom_k(rows, 50, "exponential", 1)
    row = estimate.weight(sk, "in(A) and in(B)").first()
    assert row["estimate"] == sum(k + 1 for k in range(5, 10)) and row["std_error"] == 0


def test_edge_rows(spark):
    rows = spark.createDataFrame([("A", 1, 1.0), ("A", 1, 1.0), ("A", None, 1.0), (None, 2, 1.0), ("A", 3, 0.0), ("A", 4, 2.0)], "set_id string, key long, weight double")
    sk = sketch.bottom_k(rows, 5, "priority", 1)
    assert sorted(r["key"] for r in sk.collect()) == [1, 4] and {r["bound"] for r in sk.collect()} == {INF}
    bad = spark.createDataFrame([("A", 1, -1.0)], "set_id string, key long, weight double")
    with pytest.raises(Exception, match="bad weight"):
        sketch.bottom_k(bad, 5, "priority", 1).collect()
    two = spark.createDataFrame([("A", 1, 1.0), ("B", 1, 2.0)], "set_id string, key long, weight double")
    assert ranks.weight_conflicts(two).count() == 1
    assert sketch.bottom_k(rows.where("false"), 5, "priority", 1).count() == 0


def test_merge_order_and_parts_do_not_matter(spark):
    rows = members(spark, SETS, lambda k: 1 + k % 3)
    direct = {tuple(r) for r in sketch.bottom_k(rows, 12, "exponential", 9).collect()}
    parts = [sketch.bottom_k(rows.where(F.col("key") % 4 == i), 12, "exponential", 9) for i in range(4)]
    a = {tuple(r) for r in sketch.merge(*parts, k=12).collect()}
    b = {tuple(r) for r in sketch.merge(sketch.merge(parts[3], parts[1], k=12), sketch.merge(parts[0], parts[2], parts[2], k=12), k=12).collect()}
    assert direct == a == b
    salted = {tuple(r) for r in sketch.bottom_k(rows.repartition(7), 12, "exponential", 9, salt=5).collect()}
    assert direct == salted
    assert direct == {tuple(r) for r in sketch.bottom_k_prefiltered(rows, 12, "exponential", 9, slack=1.0).collect()}
    assert direct == {tuple(r) for r in sketch.to_long(sketch.to_nested(sketch.bottom_k(rows, 12, "exponential", 9))).select("set_id", "pos", "key", "weight", "rank", "bound").collect()}


def _drawn(spark, family, n, k):
    rng = np.random.default_rng(5)
    w = {i: float(x) for i, x in enumerate(np.round(1 + rng.pareto(1.2, 40), 3))}
    sets = {"A": range(0, 25), "B": range(15, 40)}
    rows = members(spark, sets, lambda i: w[i])
    return rows, w, workloads.sketches(rows, k, n, family), workloads.queries_of(rows, n)


def test_unbiased_and_ordered_variances(spark):
    n = 1500
    rows, w, sk, qs = _drawn(spark, "exponential", n, 8)
    truth = spark.createDataFrame([(k, x) for k, x in w.items()], "key long, exact double")
    var = {}
    for kind in ("union", "short", "long"):
        adj = estimate.combined(sk, qs, kind, "exponential", 8).withColumn("estimator", F.lit(kind))
        z = [r["z"] for r in metrics.bias_z(adj, truth, n).collect()]
        assert max(map(abs, z)) < 5
        var[kind] = metrics.variances(adj, truth, n).first()["sum_of_variances"]
    assert var["long"] <= var["short"] * 1.02 and var["short"] <= var["union"] * 1.02


def test_ml_estimates_are_near_the_truth(spark):
    n = 400
    rows, w, sk, qs = _drawn(spark, "exponential", n, 12)
    total = sum(w.values())
    comb = combine.short(sk, qs)
    mean = ml.union_weight(comb).agg(F.avg("estimate")).first()[0]
    assert abs(mean - total) / total < 0.15
    totals = exact.totals(workloads.drawn(rows, n)).select("set_id", "total")
    got = ml.union_known_totals(sk, qs, totals).agg(F.avg("estimate"), F.stddev("estimate")).first()
    assert abs(got[0] - total) / total < 0.1
    pairs = qs.groupBy("query_id").agg(F.min("set_id").alias("a"), F.max("set_id").alias("b"))
    common = sum(w[k] for k in range(15, 25))
    sd = {}
    for form in ("derived", "printed", "three_part"):
        x = ml.intersection_known_totals(sk, pairs, totals, form).agg(F.avg("intersection"), F.stddev("intersection")).first()
        sd[form] = x[1]
        if form != "printed":
            assert abs(x[0] - common) / common < 0.15
    assert sd["derived"] <= sd["printed"] * 1.05


def test_ml_root_is_the_likelihood_maximum(spark):
    rows, w, sk, qs = _drawn(spark, "exponential", 1, 6)
    comb = combine.short(sk, qs).orderBy("rank").collect()
    seen = np.concatenate([[0], np.cumsum([r["weight"] for r in comb])])
    gaps = np.diff(np.concatenate([[0], [r["rank"] for r in comb], [comb[0]["bound"]]]))
    x = np.linspace(seen[-1] + 1e-3, seen[-1] * 20, 400_000)
    log = sum(np.log(x - s) - (x - s) * g for s, g in zip(seen, gaps, strict=True))
    got = ml.union_weight(combine.short(sk, qs)).first()["estimate"]
    assert abs(got - x[np.argmax(log)]) < 1e-2 * got


def test_gain_follows_the_size_of_the_combination(spark):
    rows = members(spark, {f"S{j}": range(400 * j, 400 * j + 400) for j in range(5)})
    e = {(r["measure"], r["estimator"]): r for r in workloads.errors(rows, 40, 120, "uniform").collect()}
    assert e["union", "long"]["mean_size"] == 200
    assert abs(e["union", "long"]["improvement"] - math.sqrt(5)) < 0.7
    assert abs(e["union", "union"]["avg_rel_error"] - metrics.predicted_error(40)) < 0.035


def test_poisson_and_k_mins(spark):
    rows = members(spark, {"A": range(300), "B": range(150, 450)}, lambda k: 1 + k % 5)
    for family in ("priority", "exponential", "uniform"):
        limits = {r["set_id"]: r["threshold"] for r in sketch.poisson_threshold(rows, 40, family).collect()}
        expected = rows.join(spark.createDataFrame(list(limits.items()), "set_id string, t double"), "set_id").groupBy("set_id").agg(F.sum(ranks.inclusion(F.col("weight"), F.col("t"), family)).alias("e")).collect()
        assert all(abs(r["e"] - 40) < 1e-4 for r in expected)
    err = workloads.poisson_errors(rows, 40, 40).collect()
    assert all(r["avg_rel_error"] < 0.25 for r in err)
    assert workloads.k_mins_errors(rows, 64, 3).first()["avg_rel_error"] < 0.4
    km = sketch.k_mins(rows, 16, 1)
    pairs = spark.createDataFrame([(1, "A", "B")], "query_id long, a string, b string")
    assert 0 <= estimate.jaccard_k_mins(km, pairs, 16).first()["jaccard"] <= 1


def test_inclusion_limits(spark):
    row = spark.range(1).select(ranks.inclusion(F.lit(1e-12), F.lit(1e-6), "exponential"), ranks.inclusion(F.lit(1e9), F.lit(1e9), "exponential"), ranks.inclusion(F.lit(2.0), F.lit(INF), "priority")).first()
    assert abs(row[0] / 1e-18 - 1) < 1e-9 and row[1] == 1 and row[2] == 1


def test_closed_form_of_priority_weights(spark):
    rows = members(spark, SETS, lambda k: 1 + k % 9)
    comb = combine.short(sketch.bottom_k(rows, 15, "priority", 2), estimate.query_sets(spark, {1: ["A", "B"]}))
    both = conditioned(comb, "priority").withColumnRenamed("adj", "general").drop("p")
    assert short_rc_priority(both).where("abs(adj - general) > 1e-9").count() == 0


def test_plans(spark, tiny):
    rows = D.periods(spark, tiny, True)
    text = sketch.bottom_k(rows, 32, "exponential", 1)._jdf.queryExecution().executedPlan().toString()
    assert text.count("WindowGroupLimit") >= 2 and "Python" not in text and "CartesianProduct" not in text
    big = sketch.bottom_k(rows, 2000, "exponential", 1)._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in big
    plan = ml.union_weight(combine.short(sketch.bottom_k(rows, 8, "exponential", 1), estimate.query_sets(spark, {1: ["p0", "p1"]})))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Cartesian" not in plan


def test_store_and_text_queries(spark, tiny, tmp_path):
    rows = D.periods(spark, tiny, True)
    sk = sketch.bottom_k(rows, 16, "exponential", 4, attrs=("segment",))
    store.write_sketches(sk, str(tmp_path / "s"), k=16, family="exponential", seed=4)
    held = api.SketchStore(spark, str(tmp_path / "s"), k=16, seed=4)
    a = held.weight("(in(p0) or in(p1)) and segment = 'BUILDING'").first()
    b = estimate.weight(sk, "(in(p0) or in(p1)) and segment = 'BUILDING'").first()
    assert abs(a["estimate"] - b["estimate"]) < 1e-9 and a["combo"] == "long"
    assert held.batch({1: "in(p0)", 2: "in(p0) and in(p1)"}).count() == 2
    assert store.read_prefix(spark, str(tmp_path / "s"), ["p0", "p1"], k=16, family="exponential", seed=4).count() >= 16
    api.register(spark)
    assert spark.sql("select inc_pri(2.0D, 0.25D) p").first()[0] == 0.5
    api.register_udtf(spark)
    assert spark.sql("select * from sketch_relevant('in(A) and in(B)')").count() == 2
    with pytest.raises(ValueError):
        store.checked(sk.drop("bound"))


def test_stream_in_many_batches_equals_the_batch_sketch(spark, tmp_path):
    rows = spark.createDataFrame([(f"s{i % 3}", i % 50, 1.0 + i % 4 if False else 1.0) for i in range(400)], "set_id string, key long, weight double")
    rows.repartition(5).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    S.stream_bottom_k(stream, 6, "uniform", 3, str(tmp_path / "store"), str(tmp_path / "cp")).awaitTermination()
    got = {tuple(r) for r in S.latest(spark, str(tmp_path / "store")).collect()}
    assert got == {tuple(r) for r in sketch.bottom_k(rows, 6, "uniform", 3).collect()}
    fresh = spark.createDataFrame([("s", i, 1.0 + (i % 10 == 0) * 30) for i in range(300)], "set_id string, key long, weight double")
    fresh.repartition(4).write.parquet(str(tmp_path / "in2"))
    stream = spark.readStream.schema(fresh.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in2"))
    S.ipps_reservoir(stream, 40, 3, str(tmp_path / "r"), str(tmp_path / "cp2")).awaitTermination()
    held = S.latest(spark, str(tmp_path / "r"))
    limit = sketch.poisson_threshold(fresh, 40, "priority").first()["threshold"]
    assert abs(held.first()["threshold"] - limit) < 1e-9
    assert {r["key"] for r in held.collect()} == {r["key"] for r in sketch.poisson(fresh, limit, "priority", 3).collect()}


@pytest.mark.parametrize("name", ["bottom_k_exp", "sketch_merge", "poisson_expected_k_ipps", "union_sketch", "long_membership", "est_union_size", "est_at_least_q", "jaccard_weighted_mimic_exact", "ml_union", "ml_intersection_known", "errors_w2", "similar_pairs", "neighborhood_sketch", "stream_bottom_k"])
def test_sql_agrees(spark, tiny, name):
    from compare import rows_of

    db = duckdb.connect()
    for t in ("orders", "customer", "lineitem", "part", "documents", "events"):
        db.sql(f"create view {t} as select * from '{tiny}/{t}.parquet'")
    assert rows_of(queries.QUERIES[name](spark, tiny).toPandas()) == rows_of(db.sql(oracles.ORACLES[name]).df())


@pytest.mark.parametrize("disjoint", [True, False])
def test_ranges_of_many_orders(spark, tmp_path, disjoint):
    n = 3_600_000  # times 619: beyond 32 bits
    spark.range(n).select(F.col("id").alias("o_orderkey")).write.parquet(str(tmp_path / "orders.parquet"))
    u = n * 619 // 7500
    got = D.ranges(spark, str(tmp_path), D.relation_spans(disjoint)).groupBy("set_id").count().collect()
    assert {r["set_id"]: r["count"] for r in got} == {f"S{j}": (2 if disjoint else 6) * u for j in range(5)}


def test_native_sketches_and_similar_pairs(spark, tiny):
    assert exact.native_sketches(D.periods(spark, tiny), estimate.query_sets(spark, {1: ["p0", "p1"]})).first()["hll"] > 0
    rows = members(spark, {"x": range(100), "y": range(5, 105), "z": range(300, 400)})
    found = estimate.similar_pairs(sketch.bottom_k(rows, 50, "uniform", 1), 0.5).collect()
    assert [(r["a"], r["b"]) for r in found] == [("x", "y")]
    assert P.best_combination(P.any_of(["x", "y"])) == "long"

"""Exact laws, measures and plans: against enumeration, simulation and plain versions."""

import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from coordsketch import workloads
from coordsketch.operators import combine, estimate, exact, meeting, metrics, selectivity, sketch
from coordsketch.plans import predicate as P
from coordsketch.streaming import sketches as S


def enumerated(w, n):
    """Expected multiplicities of n draws in proportion to w that hit every key, by going through all draws."""
    w = np.array(w) / sum(w)
    total, mass = np.zeros(len(w)), 0.0
    for draw in itertools.product(range(len(w)), repeat=n):
        if len(set(draw)) == len(w):
            p = math.prod(w[i] for i in draw)
            total += p * np.bincount(draw, minlength=len(w))
            mass += p
    return total / mass


@pytest.mark.parametrize("w,n", [([1, 2, 3], 3), ([1, 2, 3], 5), ([0.1, 5.0], 9), ([1, 1, 1, 4], 7)])
def test_expected_counts_equal_enumeration(w, n):
    assert np.allclose(selectivity.expected_counts(np.array(w, float), n), enumerated(w, n), rtol=1e-9)


@pytest.mark.parametrize("n", [500, 800, 1000, 1900, 5000, 200_000])
def test_expected_counts_of_large_totals(n):
    w = np.array([0.97, 0.02, 0.006, 0.004])
    got = selectivity.expected_counts(w, n)
    assert np.isfinite(got).all() and math.isclose(got.sum(), n, rel_tol=1e-9)
    # inclusion and exclusion over the keys that are missed, in exact fractions of the multinomial
    keys = range(len(w))
    missed = [(s, (-1) ** len(s)) for k in keys for s in itertools.combinations(keys, k)]
    whole = sum(sign * (1 - w[list(s)].sum()) ** n for s, sign in missed)
    want = [n * w[i] * sum(sign * (1 - w[list(s)].sum()) ** (n - 1) for s, sign in missed if i not in s) / whole for i in keys]
    assert np.allclose(got, want, rtol=1e-6)


def test_rho2_of_a_large_total_through_spark(spark):
    rows = [(1, f"k{i}", 10.0 ** (i % 4), 0.001 * (i + 1), 0.2, float(m)) for i, m in enumerate([900, 40, 20, 5, 4, 3, 1, 1, 1, 1])]
    mult = spark.createDataFrame([(q, 0, k, w, r, b, m) for q, k, w, r, b, m in rows], "query_id long, draw int, key string, weight double, rank double, bound double, mult double")
    got = [r["rho"] for r in selectivity.rho2(mult).collect()]
    assert all(x is not None and math.isfinite(x) for x in got) and math.isclose(sum(got), 1, rel_tol=1e-9)


def test_rho_same_order_equals_rejection(spark):
    w, t = np.array([5.0, 1.0, 2.0]), 0.4
    rng = np.random.default_rng(3)
    r = rng.exponential(1 / w, (2_000_000, 3))
    r = r[(r[:, 0] < r[:, 1]) & (r[:, 1] < r[:, 2]) & (r[:, 2] < t)]
    u = rng.poisson(w * (t - r)) + 1.0
    want = (u / u.sum(axis=1, keepdims=True)).mean(axis=0)
    comb = spark.createDataFrame([(1, i, float(w[i]), 0.1 * (i + 1), t) for i in range(3)], "query_id long, key long, weight double, rank double, bound double")
    got = [x["rho"] for x in selectivity.rho_same_order(comb, 4000).orderBy("key").collect()]
    assert np.allclose(got, want, atol=0.01)


def members(spark):
    return spark.range(4000).select(F.concat(F.lit("s"), F.pmod("id", F.lit(3)).cast("string")).alias("set_id"), (F.col("id") % 1500).alias("key"), (1.0 + F.pmod(F.col("id") % 1500, F.lit(50))).alias("weight"))


def test_poisson_drops_rows_before_the_shuffle(spark):
    rows = members(spark)
    got = sketch.poisson(rows, 0.002, "priority")
    plan = got._jdf.queryExecution().executedPlan().toString()
    filtered = [i for i, line in enumerate(plan.splitlines()) if "0.002" in line and "Filter" in line]
    moved = [i for i, line in enumerate(plan.splitlines()) if "Exchange hashpartitioning" in line]
    assert filtered and moved and max(moved) < min(filtered)  # deeper lines run earlier
    assert got.count() == got.select("set_id", "key").distinct().count() > 0


def test_exponential_threshold(spark):
    rows = members(spark)
    for r in sketch.poisson_threshold(rows, 40, "exponential").collect():
        w = np.array([x["weight"] for x in rows.where(F.col("set_id") == r["set_id"]).dropDuplicates(["set_id", "key"]).collect()])
        assert math.isclose((1 - np.exp(-w * r["threshold"])).sum(), 40, rel_tol=1e-6)
    continuous = rows.withColumn("weight", F.exp(F.rand(1) * 9))
    fixed = spark.createDataFrame(continuous.dropDuplicates(["set_id", "key"]).collect(), "set_id string, key long, weight double")
    for r in sketch.poisson_threshold(fixed, 40, "exponential").collect():
        w = np.array([x["weight"] for x in fixed.where(F.col("set_id") == r["set_id"]).collect()])
        assert math.isclose((1 - np.exp(-w * r["threshold"])).sum(), 40, rel_tol=1e-6)


def test_a_sketch_is_a_sequence_of_draws_without_replacement(spark):
    got = sketch.as_sequence(sketch.bottom_k(members(spark), 5)).collect()
    for s in ("s0", "s1", "s2"):
        own = sorted((r["draw"], r["key"]) for r in got if r["set_id"] == s)
        assert [d for d, _ in own] == [1, 2, 3, 4, 5] and len({k for _, k in own}) == 5
    weights = np.array([1.0, 2.0, 5.0])
    rows = spark.createDataFrame([("s", i, float(w)) for i, w in enumerate(weights)], "set_id string, key long, weight double")
    draws = 3000
    first = [r["key"] for r in sketch.as_sequence(workloads.sketches(rows, 2, draws, "exponential")).where("draw = 1").collect()]
    assert np.allclose(np.bincount(first, minlength=3) / draws, weights / weights.sum(), atol=0.04)


def test_covariances_vanish_and_cv2_is_plain(spark):
    rows = spark.createDataFrame([("s", i, 1.0 + i % 4) for i in range(12)], "set_id string, key long, weight double")
    draws = 3000
    from coordsketch.functions.adjust import conditioned

    adjusted = conditioned(workloads.sketches(rows, 4, draws, "exponential"), "exponential").select(F.split("set_id", r"\|")[0].cast("long").alias("seed"), "key", "adj")
    held = metrics.covariances(adjusted, rows.select("key", F.col("weight").alias("exact")), draws).collect()
    assert len(held) == 66 and abs(np.mean([r["covariance"] for r in held])) < 0.15
    values = spark.createDataFrame([("a", 1.0), ("a", 3.0), ("b", 5.0)], "estimator string, estimate double")
    assert {r["estimator"]: r["cv2"] for r in metrics.cv2(values).collect()} == {"a": 0.25, "b": 0.0}


def test_order_against_poisson_samples(spark):
    rows = members(spark)
    got = {(r["set_id"], r["estimator"]): r["sum_of_variances"] for r in workloads.sampling_variances(rows, 40, 60).collect()}
    for s in ("s0", "s1", "s2"):
        assert got[s, "poisson"] < 1.1 * got[s, "priority"]
    err = {r["estimator"]: r["avg_rel_error"] for r in workloads.poisson_errors(rows, 40, 40).collect()}
    assert err["poisson_long"] < 2 * err["order_long"] and err["order_long"] < 0.2


def test_conditioning_on_a_coarser_partition_has_lower_variance(spark):
    got = {r["estimator"]: r["sum_of_variances"] for r in workloads.partition_ablation(members(spark), 24, 60, 4).collect()}
    assert got["whole"] < got["parts"]


def test_large_union_sketches_against_combinations(spark):
    keys = spark.range(30_000).select(F.col("id").alias("key"), F.lit(1.0).alias("weight"))
    rows = keys.withColumn("set_id", F.when(F.col("key") < 15_000, "A").otherwise("B"))
    small = {(r["measure"], r["estimator"]): r for r in workloads.errors(rows, 50, 60).collect()}
    large = {(r["measure"], r["estimator"]): r for r in workloads.errors(rows, 100, 60).collect()}
    assert small["union", "long"]["mean_size"] == 100
    assert 0.7 < small["union", "long"]["avg_rel_error"] / large["union", "union"]["avg_rel_error"] < 1.4
    assert small["union", "union"]["avg_rel_error"] > small["union", "long"]["avg_rel_error"]
    assert math.isclose(small["union", "long"]["predicted_error"], math.sqrt(2 / math.pi / 100), rel_tol=1e-9)


def test_inclusion_exclusion_is_worse(spark):
    keys = spark.range(20_000).select(F.col("id").alias("key"), F.lit(1.0).alias("weight"), F.explode(F.expr("case when id < 9800 then array('A') when id < 10200 then array('A', 'B') else array('B') end")).alias("set_id"))
    got = {(r["measure"], r["estimator"]): r["avg_rel_error"] for r in workloads.pair_errors(keys, 100, 40).collect()}
    assert got["intersection", "inclusion_exclusion"] > 2 * got["intersection", "short"]
    assert got["hamming", "short"] < got["hamming", "union"] * 1.05
    k_mins = {r["measure"]: r["avg_rel_error"] for r in workloads.k_mins_errors(keys, 60, 20).collect()}
    assert k_mins["union"] < 0.25


@pytest.mark.parametrize("family", ["uniform", "exponential", "priority"])
def test_draws_hash_a_key_once(spark, family, monkeypatch):
    monkeypatch.setattr(workloads, "STRETCH", 700)
    rows = spark.range(1500).select(F.explode(F.array(F.lit("a"), F.concat(F.lit("b"), (F.col("id") % 3).cast("string")), F.lit("a"))).alias("set_id"), F.col("id").alias("key"), (1.0 + F.col("id") % 7).alias("weight"))
    rows = rows.unionByName(spark.createDataFrame([("a", None, 1.0), (None, 5, 6.0), ("z", 7, 0.0)], "set_id string, key long, weight double"))
    got = workloads.lowest(rows, 10, 4, family)
    assert got.count() < 4 * 4 * 30 * 8  # of 4 draws and 4 sets, in at most 8 stretches
    want = sketch.bottom_k(workloads.drawn(rows, 4), 10, family, F.col("seed"), method="md5", by=("seed",)).drop("seed")
    found = workloads.sketches(rows, 10, 4, family, "md5")
    key = lambda r: (r["set_id"], r["pos"])
    assert [tuple(r) for r in sorted(found.collect(), key=key)] == [tuple(r) for r in sorted(want.collect(), key=key)]


def test_exact_similar_pairs(spark):
    rng = np.random.default_rng(2)
    base = [set(rng.integers(0, 300, 20).tolist()) for _ in range(30)]
    sets = base + [set(list(b)[: len(b) - int(rng.integers(0, 8))]) | set(rng.integers(0, 300, int(rng.integers(0, 5))).tolist()) for b in base]
    rows = spark.createDataFrame([(f"s{i:02d}", int(k), 1.0) for i, s in enumerate(sets) for k in s], "set_id string, key long, weight double")
    for theta in (0.5, 0.8):
        want = {(f"s{i:02d}", f"s{j:02d}") for i, x in enumerate(sets) for j, y in enumerate(sets) if i < j and len(x & y) >= theta * len(x | y)}
        assert {(r["a"], r["b"]) for r in exact.similar_pairs(rows, theta).collect()} == want and want


@pytest.mark.parametrize("ratio", [0.0, 2.0])
def test_meeting_pairs_are_all_pairs(monkeypatch, ratio):
    monkeypatch.setattr(meeting, "LOOKUPS", 500)
    monkeypatch.setattr(meeting, "CELLS", 900)
    rng = np.random.default_rng(5)
    base = [set(np.minimum(rng.zipf(1.3, 60), 1 << 30).tolist()) for _ in range(60)]
    sets = base + [set(sorted(b)[int(rng.integers(0, 9)) :]) | {1, 2} for b in base]  # a few keys are in nearly all sets
    keys = [np.array(sorted(x), np.int32) for x in sets]
    place = np.array([float(len(x)) for x in sets]) if ratio else rng.random(len(sets))
    for block in (np.zeros(len(sets), int), np.arange(len(sets)) % 2):
        got = list(zip(*(c.tolist() for c in meeting.pairs_of(keys, place, block, 0.5, ratio)), strict=True))
        first = lambda i: (place[i], i)
        want = set()
        for i, j in itertools.combinations(range(len(sets)), 2):
            x, y = sorted((i, j), key=first)
            fits = (block[i] != block[j] or not block.any()) and (not ratio or place[y] <= ratio * place[x])
            if fits and len(sets[x] & sets[y]) >= 0.5 * len(sets[x]):
                want.add((x, y))
        assert len(got) == len(want) and set(got) == want and want


def _like_sets(seed):
    """Sets of many sizes, near and exact copies of some, and many of one size."""
    rng = np.random.default_rng(seed)
    base = [set(np.minimum(rng.zipf(1.4, int(n)), 400).tolist()) | {400 + i} for i, n in enumerate(rng.integers(1, 60, 50))]
    near = [set(sorted(b)[int(rng.integers(0, 3)) :]) | {1} for b in base]
    flat = [set((500 + rng.choice(8, 5, replace=False)).tolist()) | {2, 3, 4} for _ in range(30)]
    return base + near + base[:12] + base[:6] + flat


def test_sets_of_unlike_sizes_do_not_meet(spark, monkeypatch):
    for name, value in (("BLOCK_KEYS", 200), ("PARTNER_KEYS", 300), ("LEAST_BLOCKS", 3), ("LOOKUPS", 400)):
        monkeypatch.setattr(meeting, name, value)
    seen = []
    real = meeting._plan
    monkeypatch.setattr(meeting, "_plan", lambda sets: seen.append(real(sets)) or seen[-1])
    sets = _like_sets(4)
    rows = spark.createDataFrame([(f"s{i:03d}", sorted(map(str, s))) for i, s in enumerate(sets)], "set_id string, keys array<string>")
    got = exact.similar_pairs(rows, 0.5).collect()
    want = {(f"s{i:03d}", f"s{j:03d}"): len(x & y) / len(x | y) for (i, x), (j, y) in itertools.combinations(enumerate(sets), 2) if 2 * len(x & y) >= len(x | y)}
    assert len(got) == len(want) and all(math.isclose(want[r["a"], r["b"]], r["exact"]) for r in got)
    plan = seen[0]
    assert max(x["parts"] for x in plan) > 1 and max(x["chunks"] for x in plan) > 1
    assert plan[0]["last"] < plan[-1]["since"]  # the smallest sets are not sent to the largest ones


@pytest.mark.parametrize("method", ["short", "union"])
def test_similar_pairs_of_sketches(spark, monkeypatch, method):
    for name, value in (("BLOCK_KEYS", 150), ("PARTNER_KEYS", 300), ("LEAST_BLOCKS", 3)):
        monkeypatch.setattr(meeting, name, value)
    k, sets = 8, _like_sets(6)
    nested = spark.createDataFrame([(f"s{i:03d}", sorted(map(str, s))) for i, s in enumerate(sets)], "set_id string, keys array<string>")
    held = {r["set_id"]: ([e["rank"] for e in r["entries"]], r["bound"]) for r in sketch.bottom_k(nested, k, "uniform", 7, method="md5").collect()}
    want = {}
    for (a, (x, p)), (b, (y, q)) in itertools.combinations(sorted(held.items()), 2):
        known = sorted(r for r in set(x) | set(y) if r < min(p, q))
        known = known[:k] if method == "union" else known
        hit = len(set(x) & set(y) & set(known))
        if 2 * hit >= len(known):
            want[a, b] = hit / len(known)
    rows = nested.select("set_id", F.explode("keys").alias("key"), F.lit(1.0).alias("weight"))
    for sk in (sketch.bottom_k(nested, k, "uniform", 7, method="md5"), sketch.bottom_k(rows, k, "uniform", 7, method="md5")):
        got = estimate.similar_pairs(sk, 0.5, method=method, k=k).collect()
        assert len(got) == len(want) > 50 and all(math.isclose(want[r["a"], r["b"]], r["jaccard"]) for r in got)


def test_keys_that_share_a_hash_are_counted_apart(spark):
    low = spark.range(400_000).select(F.col("id").cast("string").alias("key")).groupBy(F.xxhash64("key").bitwiseAND(F.lit(0xFFFFFFFF))).agg(F.min("key").alias("u"), F.max("key").alias("v")).where("u <> v")
    u, v = (r := low.first())["u"], r["v"]
    rows = spark.createDataFrame([("a", ["x", u]), ("b", ["x", v]), ("c", ["x", u, v]), ("d", ["x", u])], "set_id string, keys array<string>")
    got = {(r["a"], r["b"]): round(r["exact"], 4) for r in exact.similar_pairs(rows, 0.5).collect()}
    assert got == {("a", "c"): 0.6667, ("b", "c"): 0.6667, ("a", "d"): 1.0, ("c", "d"): 0.6667}


def test_bottom_k_of_arrays_is_that_of_rows(spark):
    rows = spark.createDataFrame([("a", [f"w{i}" for i in range(40)]), ("a", [f"w{i}" for i in range(30, 60)]), ("b", ["w1"]), ("c", []), ("c", None), (None, ["w2"])], "set_id string, keys array<string>")
    got = sketch.to_long(sketch.bottom_k(rows, 8, "uniform", 7, method="md5"))
    want = sketch.bottom_k(rows.select("set_id", F.explode("keys").alias("key"), F.lit(1.0).alias("weight")), 8, "uniform", 7, method="md5")
    key = lambda r: (r["set_id"], r["pos"])
    columns = ["set_id", "pos", "key", "weight", "rank", "bound"]
    assert [tuple(r) for r in sorted(got.select(columns).collect(), key=key)] == [tuple(r) for r in sorted(want.select(columns).collect(), key=key)]


def test_batches_have_few_branches(spark):
    sk = sketch.bottom_k(members(spark), 32)
    queries = {i: P.any_of([f"s{i % 3}", f"s{(i + 1) % 3}"]) if i % 2 else P.AtLeast(2, ("s0", "s1", "s2")) for i in range(40)}
    got = {r["query_id"]: r for r in estimate.weight_batch(sk, queries).collect()}
    assert set(got) == set(queries)
    for i in (0, 1, 3, 5):
        one = estimate.weight(sk, queries[i]).first()
        assert math.isclose(got[i]["estimate"], one["estimate"], rel_tol=1e-9) and got[i]["n_sampled"] == one["n_sampled"] and got[i]["combo"] == one["combo"]
    plan = estimate.weight_batch(sk, queries)._jdf.queryExecution().analyzed().toString()
    assert plan.count("Union") == 1
    assert estimate.weight_batch(sk, {1: P.any_of(["none"])}).first()["estimate"] == 0.0


def test_late_events_are_left_out_and_counted(spark, tmp_path):
    days = [["2024-01-02 00:00:00", "2024-01-02 05:00:00"], ["2024-01-02 04:30:00", "2024-01-01 00:00:00", "2024-01-03 00:00:00"], ["2024-01-02 00:30:00"]]
    source = tmp_path / "in"
    for i, times in enumerate(days):
        spark.createDataFrame([(t, "a", 10 * i + j, 1.0) for j, t in enumerate(times)], "ts string, set_name string, key long, weight double").coalesce(1).write.mode("append").parquet(f"file://{source}")
        events = spark.readStream.schema("ts string, set_name string, key long, weight double").parquet(f"file://{source}")
        rows = S.memberships(events, "1 day", "1 hour")
        S.stream_bottom_k(rows, 8, "uniform", 1, f"file://{tmp_path}/store", f"file://{tmp_path}/check", lateness="1 hour").awaitTermination()
    held = {r["key"] for r in S.latest(spark, f"file://{tmp_path}/store").collect()}
    assert held == {0, 1, 10, 12} and S.late_rows(spark, f"file://{tmp_path}/store") == 2
    sliding = S.memberships(spark.createDataFrame([("2024-01-02 05:00:00", "a", 1, 1.0)], "ts string, set_name string, key long, weight double"), "2 days", "1 hour", "1 day")
    assert sliding.count() == 2


def test_odd_memberships(spark):
    rows = spark.createDataFrame([("s", 1, 1.0), ("s", 1, 1.0), (None, 2, 1.0), ("s", None, 1.0), ("t", 4, 0.0)], "set_id string, key long, weight double")
    got = sketch.bottom_k(rows, 3).collect()
    assert [(r["set_id"], r["key"], r["bound"]) for r in got if r["set_id"] == "s"] == [("s", 1, math.inf)]
    for bad in (None, -1.0):
        with pytest.raises(Exception, match="bad weight"):
            sketch.bottom_k(spark.createDataFrame([("s", 3, bad)], "set_id string, key long, weight double"), 3).collect()
    none = sketch.bottom_k(rows.where("false"), 3)
    qs = estimate.query_sets(spark, {1: ["s", "t"]})
    assert none.count() == combine.short(none, qs).count() == combine.long(none, qs).count() == combine.union_sketch(none, qs, 3).count() == 0


def _random_predicate(rng, depth):
    kind = int(rng.integers(0, 3 if depth == 0 else 7))
    sets = ["a", "b", "c", "d"]
    if kind == 0:
        return P.In(str(rng.choice(sets)))
    if kind == 1:
        return P.Attr(str(rng.choice(["x > 1", "y = 2"])))
    if kind == 2:
        return P.AtLeast(int(rng.integers(0, 4)), tuple(str(s) for s in rng.choice(sets, 3)))
    if kind == 3:
        return P.Not(_random_predicate(rng, depth - 1))
    parts = tuple(_random_predicate(rng, depth - 1) for _ in range(int(rng.integers(1, 4))))
    return P.And(parts) if kind in (4, 5) else P.Or(parts)


def test_predicates_are_analysed_as_their_truth_tables_say():
    rng = np.random.default_rng(5)
    subsets = lambda names: [frozenset(c) for n in range(len(names) + 1) for c in itertools.combinations(names, n)]
    seen = set()
    for _ in range(600):
        p = _random_predicate(rng, 3)
        true, members = subsets(["x > 1", "y = 2"]), subsets(["a", "b", "c", "d"])
        table = {(t, m): P.holds(p, m, t) for t in true for m in members}
        relevant = {s for s in "abcd" if any(table[t, m] != table[t, m | {s}] for t in true for m in members)}
        assert P.relevant_sets(p) == relevant
        assert P.bounded(p) == (not any(table[t, frozenset()] for t in true))
        plain = all(len({table[t, m] for m in members if m and m <= relevant}) < 2 for t in true)
        assert P.best_combination(p) == ("long" if plain else "short")
        seen.add((plain, P.bounded(p)))
    assert len(seen) == 4
    many = [f"s{i}" for i in range(300)]
    assert P.best_combination(P.any_of(many) & P.Attr("x > 1")) == "long" and P.best_combination(P.AtLeast(3, tuple(many))) == "short"
    assert P.relevant_sets(P.any_of(many) & (P.In("t") | ~P.In("t"))) == frozenset(many) and P.bounded(P.AtLeast(3, tuple(many)))

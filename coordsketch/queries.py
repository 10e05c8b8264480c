"""Registered queries of the sketch engine. Ranks come from md5, so SQL can rebuild every sample; doubles are rounded."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import workloads
from .functions import adjust, ranks
from .functions.ranks import with_rank
from .operators import combine, estimate, exact, graph, metrics, ml, selectivity, sketch
from .plans import predicate as P
from .plans.lineage import shared_folder, stored
from .sources import datasets as D
from .streaming import sketches as S

SEED, K, K_SMALL, DRAWS, ERROR_K = 7, 64, 8, 8, 50
MD5 = {"method": "md5"}
ALL = [f"p{i}" for i in range(5)]
BUILDING = P.Attr("segment = 'BUILDING'")


def r6(c: Column | str) -> Column:
    return F.round(F.col(c) if isinstance(c, str) else c, 6)


def finite(c: str) -> Column:
    return F.when(F.col(c) == float("inf"), F.lit(None).cast("double")).otherwise(F.round(c, 8)).alias(c)


def _sk(spark, d, family="exponential", weighted=True, k=K):
    return sketch.bottom_k(D.periods(spark, d, weighted), k, family, SEED, attrs=("segment",), **MD5)


def _first(spark) -> DataFrame:
    """query_id 2 to 5: the first so many periods."""
    return estimate.query_sets(spark, {i: ALL[:i] for i in range(2, 6)})


def _pairs(spark) -> DataFrame:
    return spark.createDataFrame([(i, f"p{i}", f"p{j}") for i, j in ((0, 1), (1, 2), (2, 4), (3, 4))], "query_id long, a string, b string")


def _totals(spark, d, weighted=True) -> DataFrame:
    return exact.totals(D.periods(spark, d, weighted)).select("set_id", "total")


def _rank(family):
    def run(spark: SparkSession, d: str) -> DataFrame:
        rows = D.load(spark, d, "orders").select(F.lit("o").alias("set_id"), F.col("o_orderkey").alias("key"), D.skewed(F.col("o_orderkey")).alias("weight"))
        return with_rank(rows, family, SEED, "md5").select("key", F.round("rank", 8).alias("rank"))

    return run


def _convert(spark, d):
    rows = D.load(spark, d, "orders").select(F.lit("o").alias("set_id"), F.col("o_orderkey").alias("key"), D.skewed(F.col("o_orderkey")).alias("weight"))
    return with_rank(rows, "exponential", SEED, "md5").select("key", F.round(ranks.convert(F.col("rank"), F.col("weight"), "exponential", "priority"), 8).alias("rank"))


def _bottom(family):
    def run(spark, d):
        sk = sketch.bottom_k(D.part_buyers(spark, d, None, weighted=True), K_SMALL, family, SEED, **MD5)
        return sk.select("set_id", "pos", "key", F.round("rank", 8).alias("rank"), finite("bound"))

    return run


def _prefiltered(spark, d):
    sk = sketch.bottom_k_prefiltered(D.periods(spark, d, True), K, "exponential", SEED, **MD5)
    return sk.select("set_id", "pos", "key", F.round("rank", 8).alias("rank"), finite("bound"))


def _merged(spark, d):
    rows = D.periods(spark, d, True)
    parts = [sketch.bottom_k(rows.where(F.pmod(F.xxhash64("key", "segment"), F.lit(3)) == i), K, "exponential", SEED, **MD5) for i in range(3)]
    return sketch.merge(*parts, k=K).select("set_id", "pos", "key", F.round("rank", 8).alias("rank"), finite("bound"))


def _rollup(spark, d):
    mapping = spark.createDataFrame([(s, "early" if s < "p2" else "late") for s in ALL], "set_id string, parent string")
    return sketch.rollup_sketches(_sk(spark, d).drop("segment"), mapping, K).select("set_id", "pos", "key", finite("bound"))


def _k_mins(spark, d):
    return sketch.k_mins(D.periods(spark, d, True), K_SMALL, SEED, **MD5).select("set_id", F.col("j").cast("long").alias("j"), "key", F.round("min_rank", 8).alias("min_rank"))


def _poisson_fixed(spark, d):
    return sketch.poisson(D.periods(spark, d, True), 0.002, "priority", SEED, **MD5).select("set_id", "key", F.round("rank", 8).alias("rank"))


def _poisson_k(spark, d):
    rows = D.periods(spark, d, True)
    return sketch.poisson(rows, sketch.poisson_threshold(rows, K, "priority"), "priority", SEED, **MD5).select("set_id", "key", finite("bound").alias("threshold"))


def _threshold_exp(spark, d):
    return sketch.poisson_threshold(D.periods(spark, d, True), K, "exponential").select("set_id", F.round("threshold", 8).alias("threshold"))


def _combination(kind):
    def run(spark, d):
        qs, sk = _first(spark), _sk(spark, d)
        rows = combine.union_sketch(sk, qs, K) if kind == "union" else getattr(combine, kind)(sk, qs)
        return rows.select("query_id", "key", finite("bound"), F.size("member_of").cast("long").alias("sets"))

    return run


def _adjusted(kind, family="exponential"):
    def run(spark, d):
        rows = estimate.combined(_sk(spark, d, family), _first(spark), kind, family, K)
        return rows.select("query_id", "key", r6("adj").alias("adj"))

    return run


def _adjusted_poisson(kind):
    def run(spark, d):
        sk = sketch.poisson(D.periods(spark, d, True), 0.002, "priority", SEED, **MD5)
        return estimate.combined(sk, _first(spark), kind, "priority").select("query_id", "key", r6("adj").alias("adj"))

    return run


def _long_membership(spark, d):
    m = combine.long_membership(_sk(spark, d), _first(spark))
    return m.select("query_id", "key", F.explode("membership").alias("set_id", "state"))


def _union_size(spark, d):
    sk, qs = _sk(spark, d, "uniform", False), _first(spark)
    out = exact.keys(D.periods(spark, d), qs).groupBy("query_id").agg(F.sum("weight").alias("exact"))
    for kind in ("union", "short", "long"):
        one = estimate.combined(sk, qs, kind, "uniform", K).groupBy("query_id").agg(r6(F.sum("adj")).alias(kind))
        out = out.join(one, "query_id")
    return out


def _intersection(spark, d):
    rows = estimate.combined(_sk(spark, d), _first(spark), "short", "exponential")
    return rows.groupBy("query_id").agg(r6(F.sum(F.when(F.size("member_of") == F.col("query_id"), F.col("adj")).otherwise(F.lit(0.0)))).alias("estimate"))


def _pair(*columns):
    def run(spark, d):
        return estimate.pair(_sk(spark, d), _pairs(spark), "exponential").select("query_id", *[r6(c).alias(c) for c in columns])

    return run


def _pair_mixed(spark, d):
    return estimate.pair(_sk(spark, d), _pairs(spark), "exponential", hamming="mixed").select("query_id", r6("hamming").alias("hamming"))


def _ie(spark, d):
    return estimate.intersection_ie(_sk(spark, d), _pairs(spark), _totals(spark, d)).select("query_id", r6("intersection").alias("intersection"))


def _batch(queries):
    def run(spark, d):
        found = estimate.weight_batch(_sk(spark, d), queries)
        return found.select("query_id", r6("estimate").alias("estimate"), "n_sampled", r6("std_error").alias("std_error"), "combo")

    return run


def _sum_h(spark, d):
    rows = estimate.combined(_sk(spark, d), _first(spark), "long", "exponential")
    return estimate.total(rows, P.Attr("true"), F.pmod("key", F.lit(7)).cast("double")).select("query_id", r6("estimate").alias("estimate"))


def _ratio(spark, d):
    rows = estimate.combined(_sk(spark, d), _first(spark), "long", "exponential")
    return estimate.ratio(rows, BUILDING, P.Attr("true")).select("query_id", r6("estimate").alias("estimate"))


def _mean_variance(spark, d):
    rows = estimate.combined(_sk(spark, d), _first(spark), "long", "exponential")
    return estimate.mean_variance(rows, BUILDING, F.pmod("key", F.lit(7)).cast("double")).select("query_id", r6("mean").alias("mean"), r6("variance").alias("variance"))


def _confidence(spark, d):
    rows = D.brand_orders(spark, d)
    sk = sketch.bottom_k(rows, 256, "uniform", SEED, **MD5)
    pairs = spark.createDataFrame([(i, f"Brand#{i}", f"Brand#{i + 1}") for i in range(1, 6)], "query_id long, a string, b string")
    return estimate.confidence(sk, pairs, "uniform", exact.totals(rows)).select("query_id", r6("confidence").alias("confidence"))


def _brand_rule(spark, d):
    sk = sketch.bottom_k(D.brand_orders(spark, d), 256, "uniform", SEED, attrs=("lines",), **MD5)
    return estimate.weight(sk, "(in(Brand#1) or in(Brand#2)) and in(Brand#3) and lines <= 3", family="uniform").select(r6("estimate").alias("estimate"), "n_sampled", "combo")


def _jaccard(method, weighted=False):
    def run(spark, d):
        family = "exponential" if weighted else "uniform"
        sk = _sk(spark, d, family, weighted).drop("segment")
        return estimate.jaccard(sk, _pairs(spark), method, family, K).select("query_id", r6("jaccard").alias("jaccard"))

    return run


def _jaccard_k_mins(spark, d):
    sk = sketch.k_mins(D.periods(spark, d), K, SEED, **MD5)
    return estimate.jaccard_k_mins(sk, _pairs(spark), K).select("query_id", r6("jaccard").alias("jaccard"))


def _weight_k_mins(spark, d):
    sk = sketch.k_mins(D.periods(spark, d, True), K, SEED, **MD5)
    return estimate.weight_k_mins(sk, _first(spark), P.Attr("true"), K).select("query_id", r6("estimate").alias("estimate"))


def _uncoordinated(spark, d):
    rows = D.periods(spark, d, True)
    a, b = (sketch.bottom_k(rows.where(F.col("set_id") == s), 256, "exponential", seed, **MD5) for s, seed in (("p0", 1), ("p1", 2)))
    return estimate.intersection_uncoordinated(a, b, "exponential").select(r6("estimate").alias("estimate"))


def _comb(spark, d, kind):
    qs, sk = _first(spark), _sk(spark, d)
    return combine.union_sketch(sk, qs, K) if kind == "union" else combine.short(sk, qs)


def _share(rho: DataFrame) -> DataFrame:
    hit = F.sum(F.when(F.col("segment") == "BUILDING", F.col("rho")).otherwise(F.lit(0.0)))
    return rho.groupBy("query_id").agg(r6(hit).alias("share"), r6(F.sum("rho")).alias("total"))


def _rho(function, kind):
    return lambda spark, d: _share(getattr(selectivity, function)(_comb(spark, d, kind)))


def _rho1(stop, draws=1):
    kind = "short" if stop == "WSRC" else "union"
    return lambda spark, d: _share(selectivity.rho1(selectivity.mimic(_comb(spark, d, kind), stop, draws=draws, seed=SEED, k=K)))


def _rho2(stop):
    kind = "short" if stop == "WSRC" else "union"
    return lambda spark, d: _share(selectivity.rho2(selectivity.mimic(_comb(spark, d, kind), stop, seed=SEED, k=K)))


def _naive(spark, d):
    comb = _comb(spark, d, "short")
    hit = F.col("segment") == "BUILDING"
    w, c = selectivity.naive_weight_fraction(comb, hit), selectivity.naive_count_fraction(comb, hit)
    return w.withColumnRenamed("share", "by_weight").join(c.withColumnRenamed("share", "by_count"), "query_id").select("query_id", r6("by_weight").alias("by_weight"), r6("by_count").alias("by_count"))


def _to_weight(spark, d):
    rho = selectivity.rho_mimic_exact(_comb(spark, d, "short"))
    totals = ml.union_weight(_comb(spark, d, "short")).select("query_id", F.col("estimate").alias("total"))
    held = selectivity.to_weight(rho, totals)
    return held.groupBy("query_id").agg(r6(F.sum(F.when(F.col("segment") == "BUILDING", F.col("adj")).otherwise(F.lit(0.0)))).alias("estimate"))


def _ml(name):
    def run(spark, d):
        sk, totals = _sk(spark, d), _totals(spark, d)
        if name == "union":
            out = ml.union_weight(combine.short(sk, _first(spark)))
        elif name == "subset":
            out = ml.subset_weight(combine.short(sk, _first(spark)), BUILDING)
        elif name == "union_known":
            out = ml.union_known_totals(sk, _first(spark), totals)
        elif name == "union_known_filtered":
            out = ml.union_known_totals(sk, _first(spark), totals, BUILDING)
        elif name == "single":
            return ml.subset_known_total(sk, BUILDING, totals).select("set_id", r6("estimate").alias("estimate"))
        elif name == "from_union":
            out = ml.intersection_from_union(sk, _pairs(spark), totals).withColumnRenamed("intersection", "estimate")
        elif name == "gaps":
            return ml.rank_gaps(sk).select("set_id", "key", F.round("gap", 8).alias("gap"), r6("seen").alias("seen"))
        else:
            return ml.intersection_known_totals(sk, _pairs(spark), totals, name).select("query_id", *[r6(c).alias(c) for c in ("intersection", "union", "jaccard")])
        return out.select("query_id", r6("estimate").alias("estimate"))

    return run


def _exact(kind):
    preds = {"union": P.any_of(ALL), "intersection": P.all_of(["p0", "p1"]), "at_least_q": P.AtLeast(2, tuple(ALL)), "filtered": P.And((P.any_of(ALL), BUILDING))}

    def run(spark, d):
        if kind == "jaccard":
            return exact.jaccard(D.periods(spark, d, True), _pairs(spark)).select("query_id", r6("exact").alias("exact"))
        qs = estimate.query_sets(spark, {1: ALL})
        return exact.weight(D.periods(spark, d, True), qs, preds[kind], ("segment",)).select("query_id", r6("exact").alias("exact"))

    return run


def _similar(spark, d):
    sk = sketch.bottom_k(D.doc_sets(spark, d), K, "uniform", SEED, **MD5)
    return estimate.similar_pairs(sk, 0.5).select("a", "b", r6("jaccard").alias("jaccard"))


def _similar_quality(spark, d):
    rows = stored(D.doc_sets(spark, d))
    sk = stored(sketch.bottom_k(rows, K_SMALL * 2, "uniform", SEED, **MD5))
    real = stored(exact.similar_pairs(rows, 0.5))
    met = estimate.met_pairs(sk, 0.5, method="union", k=K_SMALL * 2)
    out = [metrics.pair_confusion(estimate.similar_pairs(sk, 0.5, method=m, k=K_SMALL * 2, met=met), real, 0.5).select(F.lit(m).alias("method"), "true_pairs", "reported", "correct", r6("precision").alias("precision"), r6("recall").alias("recall")) for m in ("union", "short")]
    return out[0].unionByName(out[1])


_ERRORS = ("avg_rel_error", "improvement", "mean_size", "predicted_gain", "predicted_error")


def _rows(spark, d, spans=None, periods=0, weighted=False):
    return D.ranges(spark, d, spans) if spans else D.periods(spark, d, weighted).where(F.col("set_id").isin(ALL[:periods])).select("set_id", "key", "weight")


def _errors(spans=None, periods=0, family="uniform", k=ERROR_K, draws=DRAWS, function=workloads.errors):
    def run(spark, d):
        e = function(_rows(spark, d, spans, periods, family != "uniform"), k, draws, family, "md5")
        return e.select("measure", "estimator", *[r6(c).alias(c) for c in _ERRORS])

    return run


def _cases(name, cases):
    """One experiment for each case, told apart by a column."""

    def run(spark, d):
        out = None
        for value, case in cases.items():
            one = case(spark, d).select(F.lit(value).alias(name), "*")
            out = one if out is None else out.unionByName(one)
        return out

    return run


def _errors_of(table, k, draws, measures=("union",)):
    """Unions of many sets of unlike sizes."""

    def run(spark, d):
        e = workloads.errors(table(spark, d).select("set_id", "key", "weight"), k, draws, "uniform", "md5", measures)
        return e.select("measure", "estimator", *[r6(c).alias(c) for c in _ERRORS])

    return run


def _errors_k_mins(spark, d):
    rows = D.ranges(spark, d, D.pair_spans("n div 15"))
    order = workloads.errors(rows, K_SMALL, DRAWS, "uniform", "md5").where("measure in ('union', 'jaccard')").select("measure", "estimator", "avg_rel_error")
    return workloads.k_mins_errors(rows, K_SMALL, DRAWS, "md5").unionByName(order).select("measure", "estimator", r6("avg_rel_error").alias("avg_rel_error"))


def _errors_w14(spark, d):
    e = workloads.poisson_errors(D.periods(spark, d, True).select("set_id", "key", "weight"), ERROR_K, DRAWS, "priority", "md5")
    return e.select("estimator", r6("avg_rel_error").alias("avg_rel_error"), r6("mean_size").alias("mean_size"))


def _errors_b8(spark, d):
    """Two disjoint sets: the union sketch of twice the size, which is as large as the long combination, against the latter."""
    rows = D.ranges(spark, d, D.hetero_spans("1.0"))
    e = workloads.errors(rows, ERROR_K, DRAWS, "uniform", "md5").where("measure = 'union'").select("estimator", "avg_rel_error", "mean_size")
    large = workloads.errors(rows, 2 * ERROR_K, DRAWS, "uniform", "md5").where("measure = 'union' and estimator = 'union'").select(F.lit("union_of_size_l").alias("estimator"), "avg_rel_error", "mean_size")
    return e.unionByName(large).select("estimator", r6("avg_rel_error").alias("avg_rel_error"), r6("mean_size").alias("mean_size"))


def _sampling_variances(spark, d):
    v = workloads.sampling_variances(D.periods(spark, d, True).select("set_id", "key", "weight"), ERROR_K, DRAWS, "md5")
    return v.select("set_id", "estimator", F.round("sum_of_variances", 2).alias("sum_of_variances"))


def _law_measures(spark, d):
    m = workloads.law_measures(_rows(spark, d, None, 2, True), ERROR_K, DRAWS, "exponential", "md5")
    return m.select("estimator", r6("mean_ratio").alias("mean_ratio"), r6("cv2").alias("cv2"), F.round("sum_of_variances", 2).alias("sum_of_variances"))


def _law_partition(spark, d):
    v = workloads.partition_ablation(D.periods(spark, d, True).select("set_id", "key", "weight"), K, DRAWS, 4, "md5")
    return v.select("estimator", F.round("sum_of_variances", 2).alias("sum_of_variances"))


def _law_covariance(spark, d):
    """Covariances of adjusted weights over draws, for all pairs of the nations' keys."""
    nations = D.load(spark, d, "nation").select(F.lit("n").alias("set_id"), F.col("n_nationkey").cast("long").alias("key"), D.skewed(F.col("n_nationkey")).alias("weight"))
    sk = workloads.sketches(nations, K_SMALL, 8 * DRAWS, "exponential", "md5")
    adjusted = adjust.conditioned(sk, "exponential").select(F.split("set_id", r"\|", 2)[0].cast("long").alias("seed"), "key", "adj")
    return metrics.covariances(adjusted, nations.select("key", F.col("weight").alias("exact")), 8 * DRAWS).select("i", "j", r6("covariance").alias("covariance"))


def _terms_weighted(spark, d):
    """Terms that two languages' documents share and that have at least five letters, weighted by rarity; and the ratio of shared weight."""
    rows = D.lang_terms(spark, d)
    sk = sketch.bottom_k(rows, 256, "exponential", SEED, attrs=("length",), **MD5)
    langs = ["de", "en", "es", "fr"]
    pairs = spark.createDataFrame([(10 * i + j, langs[i], langs[j]) for i in range(4) for j in range(i + 1, 4)], "query_id long, a string, b string")
    qs = pairs.select("query_id", F.explode(F.array("a", "b")).alias("set_id"))
    both, long = F.size("member_of") == 2, F.col("length") >= 5
    s = estimate.sums(estimate.combined(sk, qs, "short", "exponential"), shared=both & long, all_shared=both)
    ratio = estimate.jaccard(sk.drop("length"), pairs, "mimic_exact", "exponential")
    return s.join(ratio, "query_id").select("query_id", r6("shared").alias("shared"), r6("all_shared").alias("all_shared"), r6("jaccard").alias("jaccard"))


def _restricted(spark, d):
    """Weighted periods and a subpopulation: the exact and estimated weight of customers of one segment in any of the first i."""
    rows = D.periods(spark, d, True)
    out = exact.weight(rows, _first(spark), BUILDING, ("segment",)).select("query_id", r6("exact").alias("exact"))
    for kind in ("union", "short", "long"):
        e = estimate.combined(_sk(spark, d), _first(spark), kind, "exponential", K)
        out = out.join(e.groupBy("query_id").agg(r6(F.sum(F.when(P.to_column(BUILDING), F.col("adj")).otherwise(F.lit(0.0)))).alias(kind)), "query_id")
    return out


def _short_share(spark, d):
    rows = D.ranges(spark, d, D.hetero_spans("0.1"))
    sk = sketch.bottom_k(rows, ERROR_K, "uniform", SEED, **MD5)
    return metrics.short_share(combine.short(sk, estimate.query_sets(spark, {1: ["A", "B"]})), sk).select("set_id", r6("share").alias("share"))


def _baskets(spark, d):
    rows = D.baskets(spark, d)
    sets = D.load(spark, d, "customer").where("c_mktsegment = 'BUILDING' and c_nationkey < 5").select(F.lit(1).cast("long").alias("query_id"), F.concat(F.lit("c"), F.col("c_custkey").cast("string")).alias("set_id"))
    sk = sketch.bottom_k(rows, K_SMALL, "priority", SEED, attrs=("p_type",), **MD5)
    held = estimate.combined(sk, sets, "long", "priority")
    return estimate.with_error(held, P.Attr("p_type = 'PROMO'")).select(r6("estimate").alias("estimate"), "n_sampled", r6("std_error").alias("std_error"))


def _links(spark, d):
    rows = D.page_links(spark, d)
    sk = sketch.bottom_k(rows, K, "priority", SEED, **MD5)
    sets = rows.select(F.lit(1).cast("long").alias("query_id"), "set_id").distinct()  # all targets
    held = estimate.combined(sk, sets, "short", "priority")
    return held.groupBy("query_id").agg(r6(F.sum(F.when(F.size("member_of") >= 2, F.col("adj")).otherwise(F.lit(0.0)))).alias("estimate"))


def _events(spark, d):
    rows = D.event_days(spark, d)
    sk = sketch.bottom_k(rows, 32, "uniform", SEED, **MD5)
    days = [f"2024-01-{i:02d}" for i in (2, 3)]
    types = ("click", "purchase")  # the query's own: users who clicked and bought on these days
    sets = {1: [f"{t}/{x}" for t in types for x in days]}
    both = P.all_of([]) & P.any_of([f"{types[0]}/{x}" for x in days]) & P.any_of([f"{types[1]}/{x}" for x in days])
    held = estimate.combined(sk, estimate.query_sets(spark, sets), "short", "uniform")
    return estimate.with_error(held, both).select(r6("estimate").alias("estimate"), "n_sampled")


def _vectors(spark, d):
    sk = sketch.bottom_k(D.vectors(spark, d), K_SMALL, "uniform", SEED, **MD5)
    return sk.select("set_id", "pos", "key", finite("bound"))


def _native(spark, d):
    return exact.native_sketches(D.periods(spark, d), _first(spark)).select("query_id", "hll", "theta", "approx_distinct")


def _neighborhood(spark, d):
    edges, items = D.supplier_graph(spark, d)
    found = graph.neighborhood_sketches(edges, items, K_SMALL, 2, "uniform", SEED, **MD5)
    return found.select(F.col("hop").cast("long").alias("hop"), "set_id", "pos", "key", finite("bound"))


def _stream(spark, d):
    batch = D.load(spark, d, "events")
    files = batch.inputFiles()
    single = files[0].endswith("events.parquet")
    reader = spark.readStream.schema(batch.schema).option("maxFilesPerTrigger", 1)
    source = reader.option("pathGlobFilter", "events.parquet").parquet(d) if single else reader.parquet(f"{d}/events.parquet")
    events = source.select("ts", F.col("event_type").alias("set_name"), F.col("user_id").alias("key"), F.lit(1.0).alias("weight"))
    folder = f"{shared_folder(spark)}/stream_{uuid.uuid4().hex}"
    rows = S.memberships(events, "1 day", "1 day")
    S.stream_bottom_k(rows, K_SMALL, "uniform", SEED, f"{folder}/store", f"{folder}/checkpoint", method="md5").awaitTermination()
    return S.latest(spark, f"{folder}/store").select(F.regexp_replace("set_id", " 00:00$", "").alias("set_id"), "pos", "key", finite("bound"))


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Users of all five periods from sketches: the estimate, its standard error, the exact value and the error."""
    sk = sketch.bottom_k(D.periods(spark, d), K, "exponential", SEED, attrs=("segment",), **MD5)
    found = estimate.weight(sk, P.any_of(ALL), family="exponential")
    real = exact.weight(D.periods(spark, d), estimate.query_sets(spark, {0: ALL}), P.any_of(ALL))
    return found.crossJoin(F.broadcast(real.select("exact"))).withColumn("rel_error", F.abs(F.col("estimate") - F.col("exact")) / F.col("exact"))  # one row each


_W = "100.0D / (1 + pmod(key, 100))"
QUERIES = {
    "flagship": lambda s, d: flagship(s, d).select(r6("estimate").alias("estimate"), "n_sampled", "combo", "exact"),
    "rank_exponential": _rank("exponential"),
    "rank_priority": _rank("priority"),
    "rank_convert": _convert,
    "bottom_k_exp": _bottom("exponential"),
    "bottom_k_pri": _bottom("priority"),
    "bottom_k_uniform": _bottom("uniform"),
    "bottom_k_prefiltered": _prefiltered,
    "bottom_k_vectors": _vectors,
    "sketch_merge": _merged,
    "sketch_rollup": _rollup,
    "k_mins": _k_mins,
    "poisson_fixed": _poisson_fixed,
    "poisson_expected_k_ipps": _poisson_k,
    "poisson_threshold_exp": _threshold_exp,
    "union_sketch": _combination("union"),
    "short_combination": _combination("short"),
    "long_combination": _combination("long"),
    "long_membership": _long_membership,
    "adj_union": _adjusted("union"),
    "adj_short": _adjusted("short"),
    "adj_long": _adjusted("long"),
    "adj_short_priority": _adjusted("short", "priority"),
    "adj_long_priority": _adjusted("long", "priority"),
    "adj_poisson_short": _adjusted_poisson("short"),
    "adj_poisson_long": _adjusted_poisson("long"),
    "est_union_size": _union_size,
    "est_intersection": _intersection,
    "est_difference": _pair("difference"),
    "est_hamming": _pair("hamming"),
    "est_hamming_mixed": _pair_mixed,
    "est_pair": _pair("union", "intersection", "jaccard"),
    "est_intersection_ie": _ie,
    "est_intersection_uncoordinated": _uncoordinated,
    "est_at_least_q": _batch({1: P.AtLeast(2, tuple(ALL)), 2: P.AtLeast(3, tuple(ALL))}),
    "est_attr_filtered": _batch({1: P.And((P.any_of(ALL), BUILDING)), 2: P.And((P.any_of(ALL[:2]), P.Not(BUILDING)))}),
    "est_sum_h": _sum_h,
    "est_ratio": _ratio,
    "est_mean_variance": _mean_variance,
    "est_confidence": _confidence,
    "est_brand_rule": _brand_rule,
    "est_weight_k_mins": _weight_k_mins,
    "est_baskets": _baskets,
    "est_links_at_least": _links,
    "est_event_days": _events,
    "jaccard_union_uniform": _jaccard("union"),
    "jaccard_short_uniform": _jaccard("short"),
    "jaccard_k_mins": _jaccard_k_mins,
    "jaccard_weighted_mimic_exact": _jaccard("mimic_exact", True),
    "jaccard_weighted_same_keys": _jaccard("same_keys", True),
    "rho_mimic_exact_short": _rho("rho_mimic_exact", "short"),
    "rho_mimic_exact_union": _rho("rho_mimic_exact", "union"),
    "rho_same_keys": _rho("rho_same_keys", "short"),
    "rho_same_order": _rho("rho_same_order", "short"),
    "mimic_wsr": _rho1("WSR"),
    "mimic_wsrd": _rho1("WSRD"),
    "mimic_wsrc": _rho1("WSRC"),
    "mimic_wsrc_averaged": _rho1("WSRC", 16),
    "rho2_wsr": _rho2("WSR"),
    "rho2_wsrd": _rho2("WSRD"),
    "rho2_wsrc": _rho2("WSRC"),
    "naive_fractions": _naive,
    "rho_to_weight": _to_weight,
    "ml_union": _ml("union"),
    "ml_subset": _ml("subset"),
    "ml_single_known": _ml("single"),
    "ml_intersection_known": _ml("derived"),
    "ml_intersection_printed": _ml("printed"),
    "ml_intersection_three_part": _ml("three_part"),
    "ml_union_known": _ml("union_known"),
    "ml_union_known_filtered": _ml("union_known_filtered"),
    "ml_intersection_from_union": _ml("from_union"),
    "ml_rank_gaps": _ml("gaps"),
    "exact_union": _exact("union"),
    "exact_intersection": _exact("intersection"),
    "exact_at_least_q": _exact("at_least_q"),
    "exact_filtered": _exact("filtered"),
    "exact_jaccard": _exact("jaccard"),
    "native_sketches": _native,
    "similar_pairs": _similar,
    "similar_pairs_quality": _similar_quality,
    "errors_w1": _errors(D.pair_spans("n div 15"), function=workloads.pair_errors),
    "errors_w1_large_overlap": _errors(D.pair_spans("n * 3 div 10")),
    "errors_w1_small_overlap": _errors(D.pair_spans("n div 150"), function=workloads.pair_errors),
    "errors_w1_k": _cases("k", {k: _errors(D.pair_spans("n div 15"), k=k) for k in (10, 50, 250)}),
    "errors_w1_many_draws": _errors(D.pair_spans("n div 15"), draws=64),
    "errors_w2_i": _cases("i", {i: _errors(D.multi_spans(i)) for i in (2, 3, 4, 5)}),
    "errors_w4_i": _cases("i", {i: _errors(periods=i) for i in (2, 3, 4, 5)}),
    "errors_w5_brand": _errors_of(D.part_buyers, ERROR_K, DRAWS),
    "errors_w5_all": _errors_of(lambda s, d: D.part_buyers(s, d, None), K_SMALL, DRAWS),
    "errors_w5_documents": _errors_of(D.doc_terms, K_SMALL, DRAWS),
    "errors_w14": _errors_w14,
    "errors_w16": _cases("share", {f: _errors(D.hetero_spans(f)) for f in ("1.0", "0.5", "0.1", "0.01")}),
    "errors_b8": _errors_b8,
    "errors_k_mins": _errors_k_mins,
    "est_terms_weighted": _terms_weighted,
    "est_periods_restricted": _restricted,
    "sampling_variances": _sampling_variances,
    "law_measures": _law_measures,
    "law_covariance": _law_covariance,
    "law_partition": _law_partition,
    "errors_w2": _errors(D.multi_spans(5)),
    "errors_w3_disjoint": _errors(D.relation_spans(True)),
    "errors_w3_overlap": _errors(D.relation_spans(False)),
    "errors_w4": _errors(periods=5),
    "errors_w13_weighted": _errors(periods=5, family="exponential"),
    "short_share": _short_share,
    "neighborhood_sketch": _neighborhood,
    "stream_bottom_k": _stream,
}

__all__ = ["QUERIES", "adjust", "flagship"]

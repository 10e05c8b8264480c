"""Selectivities: shares of the weight of a union, without knowing the union's weight. Every function adds rho per key.

With equal weights every key of a sketch counts the same. With weights, a sketch made with exponential ranks is read as
the first arrivals of independent streams whose rates are the weights; the repeats before the bound, which the sketch
does not hold, turn it into a sample with replacement (mimicking). Repeats are drawn, or averaged over exactly.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.solve import integrate_unit, unit_nodes

INF = float("inf")


def _of_query() -> Window:
    return Window.partitionBy("query_id")


def uniform_share(comb: DataFrame) -> DataFrame:
    """rho = 1 / number of keys: of the union sketch or the short combination."""
    return comb.withColumn("rho", F.lit(1.0) / F.count(F.lit(1)).over(_of_query()))


uniform_union = uniform_short = uniform_share


def naive_weight_fraction(comb: DataFrame, matches: Column) -> DataFrame:
    """Biased, for comparison: the share of the sampled weight."""
    return comb.groupBy("query_id").agg((F.sum(F.when(matches, F.col("weight")).otherwise(F.lit(0.0))) / F.sum("weight")).alias("share"))


def naive_count_fraction(comb: DataFrame, matches: Column) -> DataFrame:
    """Biased for weighted keys, for comparison: the share of the sampled keys."""
    return comb.groupBy("query_id").agg((F.count_if(matches) / F.count(F.lit(1))).alias("share"))


def mimic(comb: DataFrame, stop: str = "WSRC", *, draws: int = 1, seed: int = 0, k: int | None = None) -> DataFrame:
    """query_id, draw, key, mult, and the columns of comb: multiplicities of a mimicked sample with replacement.

    WSRC: all arrivals before the bound of the short combination; WSRD: the same with the union sketch; WSR: the first k
    arrivals of the union sketch. Without a bound the sample is the whole union, and multiplicities are the weights."""
    if stop == "WSR" and k is None:
        raise ValueError("WSR needs k")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["rank", "key"])
        w, r, t = pdf["weight"].to_numpy(), pdf["rank"].to_numpy(), pdf["bound"].iloc[0]
        out = []
        for draw in range(draws):
            rng = np.random.default_rng([seed & 0xFFFFFFFF, int(pdf["query_id"].iloc[0]) & 0xFFFFFFFF, draw])
            if np.isinf(t):
                mult = w.astype(float) if stop != "WSR" else rng.multinomial(k, w / w.sum()).astype(float)
            else:
                more = rng.poisson(w * np.maximum(t - r, 0))
                if stop == "WSR":
                    times = np.concatenate([r, *[rng.uniform(a, t, n) for a, n in zip(r, more, strict=True)]])
                    who = np.concatenate([np.arange(len(r)), np.repeat(np.arange(len(r)), more)])
                    mult = np.bincount(who[np.argsort(times, kind="stable")[:k]], minlength=len(r)).astype(float)
                else:
                    mult = 1.0 + more
            out.append(pdf.assign(draw=draw, mult=mult))
        return pd.concat(out)

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in comb.schema.fields) + ", draw int, mult double"
    return comb.groupBy("query_id").applyInPandas(run, schema)


def rho1(mult: DataFrame) -> DataFrame:
    """rho of every key: its share of the multiplicities, averaged over draws."""
    shared = mult.withColumn("rho", F.col("mult") / F.sum("mult").over(Window.partitionBy("query_id", "draw")))
    keep = [c for c in mult.columns if c not in ("query_id", "key", "draw", "mult", "rho")]
    return shared.groupBy("query_id", "key").agg(F.avg("rho").alias("rho"), *[F.first(c).alias(c) for c in keep])


def rho_mimic_exact(comb: DataFrame, nodes: int = 64) -> DataFrame:
    """rho1 averaged over all mimicked samples, in closed form up to one integral for each query."""
    held = comb.withColumn("_own", F.when(F.col("bound") == INF, F.lit(0.0)).otherwise(F.col("weight") * (F.col("bound") - F.col("rank"))))
    w = _of_query()
    per = held.withColumn("_all", F.sum("_own").over(w)).withColumn("_l", F.count(F.lit(1)).over(w)).withColumn("_w", F.sum("weight").over(w))
    mean = integrate_unit(lambda z: F.exp((F.col("_l") - 1) * F.log(z) - F.col("_all") * (1 - z)), nodes)
    rho = F.when(F.col("bound") == INF, F.col("weight") / F.col("_w")).when(F.col("_all") <= 0, 1.0 / F.col("_l")).otherwise(F.col("_e") + F.col("_own") / F.col("_all") * (1 - F.col("_l") * F.col("_e")))
    return per.withColumn("_e", mean).withColumn("rho", rho).drop("_own", "_all", "_l", "_w", "_e")


def rho_same_keys(comb: DataFrame, nodes: int = 128) -> DataFrame:
    """rho averaged over all ranks that would have sampled the same keys. Equal weights give 1 / number of keys."""
    points = np.array(unit_nodes(nodes))

    def log_expm1(x: np.ndarray) -> np.ndarray:
        return np.where(x > 30, x, np.log(np.expm1(np.minimum(x, 30))))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        w, t = pdf["weight"].to_numpy(float), float(pdf["bound"].iloc[0])
        if np.isinf(t):
            return pdf.assign(rho=w / w.sum())
        x = w[:, None] * t
        z, q = points[:, 0][None, :], points[:, 1]
        log_g = log_expm1(x * z) - log_expm1(x)
        log_d = np.log(x) + x * z - log_expm1(x)
        rho = np.exp(log_d + log_g.sum(axis=0, keepdims=True) - log_g) @ q
        return pdf.assign(rho=rho / rho.sum())

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in comb.schema.fields) + ", rho double"
    return comb.groupBy("query_id").applyInPandas(run, schema)


def rho_same_order(comb: DataFrame, draws: int = 400, seed: int = 0) -> DataFrame:
    """The comparator: the mean of mimic_exact over redrawn ranks of the same order that all lie below the bound.

    The gaps of such ranks are independent and exponential, given that their sum is below the bound. They are drawn by
    rejection; where under draws of 64 times as many are accepted, gaps are drawn evenly below the bound and weighted by their density."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["rank", "key"])
        w, t = pdf["weight"].to_numpy(float), float(pdf["bound"].iloc[0])
        if np.isinf(t):
            return pdf.assign(rho=w / w.sum())
        rng = np.random.default_rng([seed & 0xFFFFFFFF, int(pdf["query_id"].iloc[0]) & 0xFFFFFFFF])
        z, q = np.array(unit_nodes(64)).T
        rates = np.cumsum(w[::-1])[::-1]
        r = np.cumsum(rng.exponential(1 / rates, (64 * draws, len(w))), axis=1)
        r = r[r[:, -1] < t][:draws]
        density = np.ones(len(r))
        if len(r) < draws:
            r = np.sort(rng.uniform(0, t, (64 * draws, len(w))), axis=1)
            log = -(np.diff(r, axis=1, prepend=0.0) * rates).sum(axis=1)
            density = np.exp(log - log.max())
        own = w * (t - r)
        whole = own.sum(axis=1, keepdims=True)
        mean = np.exp((len(w) - 1) * np.log(z) - whole * (1 - z)) @ q
        rho = mean[:, None] + own / whole * (1 - len(w) * mean[:, None])
        return pdf.assign(rho=density @ rho / density.sum())

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in comb.schema.fields) + ", rho double"
    return comb.groupBy("query_id").applyInPandas(run, schema)


def expected_counts(w: np.ndarray, n: int) -> np.ndarray:
    """Expected multiplicities of n draws in proportion to w, given that they hit exactly these keys, for any n.

    They are ratios of the n-th coefficients of the product of (e^(w x) - 1) with and without one factor's derivative. Each
    is an integral around the circle through the saddle point, where a trapezoid rule of some multiples of sqrt(n) points is exact
    up to rounding, and no term overflows."""
    if n == len(w):
        return np.ones(len(w))
    w = w / w.sum()
    low, high = 0.0, float(n)
    for _ in range(200):  # the radius at which the mean total is n
        mid = (low + high) / 2
        low, high = (mid, high) if (w * mid / -np.expm1(-w * mid)).sum() < n else (low, mid)
    r, points = high, 256 + 32 * int(np.ceil(np.sqrt(n)))
    angles = 2 * np.pi * np.arange(points) / points
    x = np.outer(w, r * np.exp(1j * angles))
    left = x.real < 0
    fading = np.where(left, x, -x)  # whose exponential does not overflow
    less = np.expm1(fading)
    logs = np.where(left, np.log(less), x + np.log(-less)).sum(axis=0) - 1j * n * angles
    held = np.exp(logs - logs[0].real)
    return (np.where(left, x * np.exp(fading), -x) / less @ held).real / held.sum().real


def rho2(mult: DataFrame) -> DataFrame:
    """rho of every key: the expectation of rho1 given the distinct keys and the total multiplicity of each draw (averaged
    over draws). A sample that is the whole union, whose multiplicities are its weights, keeps their shares."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        held = pdf[pdf["mult"] > 0].copy()
        m, w = held["mult"].to_numpy(float), held["weight"].to_numpy(float)
        n = int(round(m.sum()))
        drawn = np.array_equal(m, np.round(m)) and not np.isinf(held["bound"].iloc[0])
        held["rho"] = expected_counts(w, n) / n if drawn else m / m.sum()
        return held

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in mult.schema.fields) + ", rho double"
    shared = mult.groupBy("query_id", "draw").applyInPandas(run, schema)
    draws = Window.partitionBy("query_id")
    keep = [c for c in mult.columns if c not in ("query_id", "key", "draw", "mult")]
    summed = shared.withColumn("_n", F.max("draw").over(draws) + 1)
    return summed.groupBy("query_id", "key").agg((F.sum("rho") / F.first("_n")).alias("rho"), *[F.first(c).alias(c) for c in keep])


def to_weight(rho: DataFrame, totals: DataFrame) -> DataFrame:
    """adj = rho times an independent estimate of the union's weight. totals: query_id, total."""
    return rho.join(totals, "query_id").withColumn("adj", F.col("rho") * F.col("total")).drop("total")

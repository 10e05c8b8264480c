"""Sketches of implicit sets: the items within some hops of each node, without materialising these sets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.lineage import cut
from .sketch import bottom_k, merge


def neighborhood_sketches(edges: DataFrame, items: DataFrame, k: int, hops: int, family: str = "uniform", seed: int = 0, *, method: str = "xxhash64") -> DataFrame:
    """hop, set_id (the node), pos, key, weight, rank, bound, for hops 0 to `hops`. edges: src, dst; items: node, key, weight.

    A node's sketch at one more hop is the merge of its own and its neighbours' sketches, so a hop moves at most edges
    times k rows. Sketches merge exactly because ranks are shared; Poisson samples of fixed size have no such step."""
    base = items.select(F.col("node").cast("string").alias("set_id"), "key", "weight")
    level = cut(bottom_k(base, k, family, seed, method=method))
    whole = level.select(F.lit(0).alias("hop"), "*")
    links = edges.select(F.col("src").cast("string").alias("src"), F.col("dst").cast("string").alias("dst")).distinct()
    for hop in range(1, hops + 1):
        heard = level.join(links, F.col("set_id") == F.col("dst")).drop("set_id", "dst").withColumnRenamed("src", "set_id")
        level = cut(merge(level, heard.select(level.columns), k=k))
        whole = whole.unionByName(level.select(F.lit(hop).alias("hop"), "*"))
    return whole

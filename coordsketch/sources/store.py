"""The sketch store: sketches as Parquet, partitioned by how they were made, rows of a set together and sorted by rank.

Row-group statistics then skip other sets, and the part of a set above a rank.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Columns of a long sketch besides the key (bigint or string) and attributes.
COLUMNS = {"set_id": "string", "pos": "int", "weight": "double", "rank": "double", "bound": "double"}


def checked(sketch: DataFrame) -> DataFrame:
    """sketch, if it has the columns of a long sketch with their types."""
    found = dict(sketch.dtypes)
    wrong = {c: found.get(c) for c, t in COLUMNS.items() if found.get(c) != t}
    if wrong or "key" not in found:
        raise ValueError(f"not a long sketch: {wrong or 'no key'}")
    return sketch


def write_sketches(sketch: DataFrame, path: str, *, k: int, family: str, seed: int, mode: str = "append") -> None:
    named = checked(sketch).withColumns({"k": F.lit(k), "family": F.lit(family), "seed": F.lit(seed)})
    named.repartition("set_id").sortWithinPartitions("set_id", "rank").write.mode(mode).partitionBy("family", "k", "seed").parquet(path)


def read_sketches(spark: SparkSession, path: str, *, k: int, family: str, seed: int) -> DataFrame:
    held = spark.read.parquet(path).where((F.col("family") == family) & (F.col("k") == k) & (F.col("seed") == seed))
    return held.drop("family", "k", "seed")


def read_prefix(spark: SparkSession, path: str, sets: list[str], *, k: int, family: str, seed: int) -> DataFrame:
    """Only the rows that the short combination of the sets needs: those below their smallest bound, read in two steps."""
    held = read_sketches(spark, path, k=k, family=family, seed=seed).where(F.col("set_id").isin(sets))
    low = held.agg(F.min("bound")).first()[0]
    return held if low is None else held.where(F.col("rank") < low)

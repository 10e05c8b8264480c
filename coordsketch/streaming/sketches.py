"""Sketches of streams: every micro-batch is sketched by itself and merged into a stored sketch.

The store holds one version for each batch, written whole before it is used, and a batch always starts from the version
before its own. So a repeated batch writes the same version again, and late or repeated events change nothing: ranks
belong to keys. Events later than the watermark are left out and counted: a batch starts from the latest time that the batches
before it have seen, less the allowed lateness, and stores the latest time and the number of late rows with its version.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..functions.ranks import with_rank
from ..operators.sketch import bottom_k, merge

INF = float("inf")


def _versions(spark: SparkSession, store: str) -> list[int]:
    path = spark._jvm.org.apache.hadoop.fs.Path(store)
    files = path.getFileSystem(spark._jsc.hadoopConfiguration())
    if not files.exists(path):
        return []
    done = "_SUCCESS"
    names = [(s.getPath().getName(), s.getPath()) for s in files.listStatus(path)]
    return sorted(int(n.split("=")[1]) for n, p in names if n.startswith("batch=") and files.exists(spark._jvm.org.apache.hadoop.fs.Path(p, done)))


def latest(spark: SparkSession, store: str, before: int | None = None) -> DataFrame | None:
    """The stored sketch, or that before a batch; None if there is none."""
    found = [v for v in _versions(spark, store) if before is None or v < before]
    return spark.read.parquet(f"{store}/batch={found[-1]}") if found else None


def progress(spark: SparkSession, store: str, before: int | None = None):
    """latest and late as stored with the last version, or that before a batch: the latest time seen and all late rows; None at first."""
    found = latest(spark, f"{store}/progress", before)
    return found.first() if found is not None else None


def late_rows(spark: SparkSession, store: str) -> int:
    """Rows left out so far."""
    seen = progress(spark, store)
    return seen["late"] if seen else 0


def memberships(events: DataFrame, window: str, watermark: str, slide: str | None = None) -> DataFrame:
    """Events (ts, set_name, key, weight) as memberships whose sets are names within windows: tumbling ones, or sliding ones if
    slide is given, where an event belongs to several sets."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)
    start = F.date_format(F.window("ts", window, slide)["start"], "yyyy-MM-dd HH:mm")
    return timed.select("ts", F.concat("set_name", F.lit("/"), start).alias("set_id"), "key", "weight")


def stream_bottom_k(rows: DataFrame, k: int, family: str, seed: int, store: str, checkpoint: str, *, method: str = "xxhash64", dedupe: str | None = None, lateness: str | None = None) -> StreamingQuery:
    """Runs over what is available now; rows: set_id, key, weight and, for dedupe within the watermark or lateness, ts.

    lateness (an interval such as "1 hour"): rows whose ts is older than the latest ts of earlier batches less that are left
    out; late_rows tells how many."""
    fresh = rows.dropDuplicatesWithinWatermark(["set_id", "key"]) if dedupe else rows

    def absorb(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        if lateness:
            seen = progress(spark, store, batch_id)
            limit = F.lit(seen["latest"] if seen else None).cast("timestamp") - F.expr(f"interval {lateness}")
            late = F.col("ts") < limit
            now = batch.agg(F.max("ts").alias("latest"), F.count_if(late).alias("late"))
            now = now.select(F.greatest("latest", F.lit(seen["latest"] if seen else None).cast("timestamp")).alias("latest"), (F.col("late") + (seen["late"] if seen else 0)).alias("late"))
            now.coalesce(1).write.mode("overwrite").parquet(f"{store}/progress/batch={batch_id}")
            batch = batch.where(F.coalesce(~late, F.lit(True)))
        sketch = bottom_k(batch.select("set_id", "key", "weight"), k, family, seed, method=method)
        known = latest(spark, store, batch_id)
        merged = sketch if known is None else merge(known, sketch, k=k)
        merged.write.mode("overwrite").parquet(f"{store}/batch={batch_id}")

    return fresh.writeStream.foreachBatch(absorb).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def shrunk(sample: DataFrame, total: DataFrame, k: int) -> DataFrame:
    """set_id, key, weight, rank, threshold: a Poisson sample with priority ranks cut to an expected size of k.

    sample: set_id, key, weight, rank: all keys seen that rank below some larger threshold; total: set_id, total (weight of
    all keys seen). Keys too heavy for the threshold are always held, so the rest's weight is known without their keys."""
    from pyspark.sql import Window

    above = Window.partitionBy("set_id").orderBy(F.col("weight").desc(), "key").rowsBetween(Window.unboundedPreceding, -1)
    tried = sample.join(total, "set_id").select("set_id", "weight", "total", F.count(F.lit(1)).over(above).alias("j"), F.coalesce(F.sum("weight").over(above), F.lit(0.0)).alias("top"))
    t = (F.lit(float(k)) - F.col("j")) / (F.col("total") - F.col("top"))
    found = tried.withColumn("t", t).where((F.col("j") < k) & (F.col("t") > 0) & (F.col("weight") * F.col("t") <= 1)).groupBy("set_id").agg(F.min_by("t", "j").alias("threshold"))
    return sample.join(found, "set_id", "left").fillna(INF, ["threshold"]).where(F.col("rank") < F.col("threshold"))


def ipps_reservoir(rows: DataFrame, k: int, seed: int, store: str, checkpoint: str, *, method: str = "xxhash64") -> StreamingQuery:
    """One-pass Poisson sampling in proportion to weight: a reservoir whose threshold only falls. Keys must be new in the
    stream (deduplicate before). The store holds set_id, key, weight, rank, threshold, total."""

    def absorb(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        fresh = with_rank(batch.select("set_id", "key", "weight"), "priority", seed, method)
        known = latest(spark, store, batch_id)
        sums = fresh.groupBy("set_id").agg(F.sum("weight").alias("total"))
        if known is not None:
            limits = known.groupBy("set_id").agg(F.first("threshold").alias("limit"), F.first("total").alias("total"))
            fresh = fresh.join(limits.select("set_id", "limit"), "set_id", "left").where(F.col("rank") < F.coalesce("limit", F.lit(INF))).drop("limit")
            fresh = fresh.unionByName(known.select("set_id", "key", "weight", "rank"))
            sums = sums.unionByName(limits.select("set_id", "total")).groupBy("set_id").agg(F.sum("total").alias("total"))
        kept = shrunk(fresh, sums, k).join(sums, "set_id")
        kept.write.mode("overwrite").parquet(f"{store}/batch={batch_id}")

    return rows.writeStream.foreachBatch(absorb).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()

"""Proportional stratified interleaving: shards that all match the mixture of sources.

Within each source, rows are ranked in a seeded random order; a row's fractional rank is (rank - 1/2) / rows of its
source. Sorted by fractional rank, every contiguous run of rows holds each source in its overall proportion, so equal
cuts of that order are the shards. Ranks are never taken inside one source or over all rows in one task: counts per
hash bucket are summed first, and rows are ranked within their bucket only.

Defined cases: a null source is a source of its own; null texts have no bytes; repeated rows take different slots, in an
order that nothing distinguishes; ties fall by random order, then doc_id, then text checksum; an empty table gives an
empty result. Shard row counts differ by at most one. Extra columns are ignored by the query.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Rows that a ranking bucket holds on average; buckets are hash ranges, so none grows with a source.
BUCKET_ROWS = 20_000


def _ranked(df: DataFrame, bucket: str, group: list[str], order: list, name: str) -> DataFrame:
    """df with name: the position, from 1, in the order of bucket and then order, within group."""
    counts = df.groupBy(*group, bucket).agg(F.count(F.lit(1)).alias("_n"))
    before = Window.partitionBy(*group).orderBy(bucket).rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select(*[F.col(c).alias(f"_{c}") for c in [*group, bucket]], F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"), F.sum("_n").over(Window.partitionBy(*group)).alias("_size"))
    within = df.withColumn("_row", F.row_number().over(Window.partitionBy(*group, bucket).orderBy(*order)))
    on = [within[c].eqNullSafe(offsets[f"_{c}"]) for c in [*group, bucket]]
    joined = within.join(offsets, on)
    return joined.withColumn(name, F.col("_before") + F.col("_row")).drop("_before", "_row", *[f"_{c}" for c in [*group, bucket]])


def interleaved(rows: DataFrame, shards: int, seed: str = "interleave", stratum: str = "source", key: str = "doc_id", tie: str = "text_crc32") -> DataFrame:
    """rows with shard (from 0) and slot (gapless from 0 within the shard). rows needs stratum, key and tie columns."""
    total = rows.count()
    bits = max(8, (max(total, 1) // BUCKET_ROWS).bit_length())
    drawn = rows.withColumn("_draw", F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col(key).cast("string"), F.lit("null")))))
    drawn = drawn.withColumn("_bucket", F.shiftright(F.conv(F.substring("_draw", 1, 8), 16, 10).cast("long"), 32 - bits)).withColumn("_stratum", F.coalesce(F.concat(F.lit("="), F.col(stratum)), F.lit("")))
    ranked = _ranked(drawn, "_bucket", ["_stratum"], [F.col("_draw"), F.col(key).asc_nulls_first(), F.col(tie).asc_nulls_first()], "_rank")
    mixed = ranked.withColumn("_fraction", (F.col("_rank") * 2.0 - 1.0) / (F.col("_size") * 2.0))
    mixed = mixed.withColumn("_part", F.floor(F.col("_fraction") * F.lit(1 << bits))).drop("_size")
    placed = _ranked(mixed.withColumn("_all", F.lit(0)), "_part", ["_all"], [F.col("_fraction"), F.col("_stratum"), F.col("_draw"), F.col(key).asc_nulls_first(), F.col(tie).asc_nulls_first()], "_place")
    place = F.col("_place") - 1
    shard = F.expr(f"((_place - 1) * {shards}) div {max(total, 1)}")
    out = placed.withColumn("shard", shard.cast("int"))
    first = F.expr(f"(shard * cast({max(total, 1)} as long) + {shards - 1}) div {shards}")
    return out.withColumn("slot", place - first).drop("_draw", "_bucket", "_stratum", "_rank", "_size", "_fraction", "_part", "_all", "_place")


def shard_documents(docs: DataFrame, shards: int = 16, seed: str = "interleave") -> DataFrame:
    """doc_id, source, size (text bytes plus one), text_crc32, shard, slot for every row of docs."""
    raw = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), (F.octet_length(raw) + 1).cast("long").alias("size"), F.crc32(raw).alias("text_crc32"))
    return interleaved(slim, shards, seed)


def query(spark, sf_dir: str) -> DataFrame:
    from .common import load

    placed = shard_documents(load(spark, sf_dir, "documents"))
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))

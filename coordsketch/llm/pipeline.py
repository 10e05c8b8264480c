"""Stages of the corpus pipeline: each works on all documents that its predecessor kept.

quality: documents that the quality rules reject go. copies: of every group of documents linked by SimHash balls and a
similarity of at least 0.8 of their five-word shingles, the one with the smallest doc_id stays. leaks: documents that hold a benchmark item go. privacy: personal spans are replaced by their
kind. packing: what is left is packed into sequences; the pieces, with their ids, are the result.

Defined cases are those of the operators; a document is named by its doc_id, repeated rows of a kept document are merged
by the copies stage, and extra columns are passed on by all stages but the last.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import decontaminate, packing, pii, quality, simhash
from .common import fresh, load, materialize
from .tokens import vocabulary


def _without(docs: DataFrame, bad: DataFrame) -> DataFrame:
    (name,) = fresh(docs.columns, "_gone")
    gone = bad.select(F.col("doc_id").alias(name)).distinct().hint("merge")  # it grows with the documents: never broadcast
    return docs.join(gone, F.col("doc_id").eqNullSafe(F.col(name)), "left_anti").select(docs.columns)


def by_quality(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _without(docs, quality.judged(docs).where("not kept"))


def by_copies(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    first = simhash.similar_components(docs.select("doc_id", "text")).where("doc_id <=> component_id")
    name, rows = fresh(docs.columns, "_kept", "_rows")
    kept = materialize(first.groupBy(F.col("doc_id").alias(name)).agg(F.count(F.lit(1)).alias(rows)))
    joined = docs.join(kept.hint("merge"), F.col("doc_id").eqNullSafe(F.col(name)))
    if not kept.where(F.col(rows) > 1).limit(1).count():
        return joined.select(docs.columns)
    return joined.where(F.col(rows) == 1).unionByName(joined.where(F.col(rows) > 1).dropDuplicates(["doc_id", "text"])).select(docs.columns)


def by_leaks(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    return _without(docs, materialize(decontaminate.leaks(docs, load(spark, sf_dir, "benchmark")).select("doc_id")))


def by_privacy(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    clean = pii.redact(docs)
    if "n_chars" not in docs.columns:
        return clean
    counted = F.when(F.col("n_chars").isNotNull(), F.length("text")).cast(docs.schema["n_chars"].dataType)
    return clean.withColumn("n_chars", F.coalesce(counted, F.col("n_chars")))


def packed(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.packed(docs, vocabulary("word_bpe_49k.json"))


STAGES = [("quality", by_quality), ("copies", by_copies), ("leaks", by_leaks), ("privacy", by_privacy), ("packing", packed)]


def run(spark, sf_dir: str) -> DataFrame:
    """All stages over the documents of sf_dir, each one's rows written and read again by the next."""
    rows = load(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        rows = materialize(stage(spark, rows, sf_dir))
    return STAGES[-1][1](spark, rows, sf_dir)

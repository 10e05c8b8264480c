"""Membership relations (set_id, key, weight, attributes) over the given tables, and the workloads' sets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Start and length in days of the order periods.
FIRST_DAY, PERIOD_DAYS, PERIODS = "1995-01-01", 90, 5


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def skewed(key: Column) -> Column:
    """A weight that depends on the key alone and varies a hundredfold."""
    return F.lit(100.0) / (1 + F.pmod(key, F.lit(100)))


def periods(spark: SparkSession, sf_dir: str, weighted: bool = False) -> DataFrame:
    """Customers by order period p0 to p4, with their market segment."""
    orders = load(spark, sf_dir, "orders").select("o_custkey", F.floor(F.datediff(F.col("o_orderdate"), F.lit(FIRST_DAY)) / PERIOD_DAYS).alias("p")).where(f"p between 0 and {PERIODS - 1}")
    customers = load(spark, sf_dir, "customer").select("c_custkey", F.col("c_mktsegment").alias("segment"))
    weight = skewed(F.col("o_custkey")) if weighted else F.lit(1.0)
    return orders.join(customers, F.col("o_custkey") == F.col("c_custkey")).select(F.concat(F.lit("p"), F.col("p").cast("string")).alias("set_id"), F.col("o_custkey").alias("key"), weight.alias("weight"), "segment")


def part_buyers(spark: SparkSession, sf_dir: str, brand: str | None = "Brand#6", weighted: bool = False) -> DataFrame:
    """Customers by part bought, for the parts of one brand or of all (None)."""
    parts = load(spark, sf_dir, "part").where(F.lit(True) if brand is None else F.col("p_brand") == brand).select("p_partkey")
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").join(parts, F.col("l_partkey") == F.col("p_partkey"))
    joined = lines.join(load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    weight = skewed(F.col("o_custkey")) if weighted else F.lit(1.0)
    return joined.select(F.concat(F.lit("b"), F.col("l_partkey").cast("string")).alias("set_id"), F.col("o_custkey").alias("key"), weight.alias("weight"))


def baskets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts bought by customers, weighted by retail price, with type and brand."""
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey").join(load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    parts = load(spark, sf_dir, "part").select("p_partkey", F.col("p_retailprice").alias("weight"), "p_type", "p_brand")
    return lines.join(parts, F.col("l_partkey") == F.col("p_partkey")).select(F.concat(F.lit("c"), F.col("o_custkey").cast("string")).alias("set_id"), F.col("l_partkey").alias("key"), "weight", "p_type", "p_brand")


def brand_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders by brand bought, with the order's number of lines."""
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    sizes = lines.groupBy(F.col("l_orderkey").alias("o")).agg(F.count(F.lit(1)).alias("lines"))
    parts = load(spark, sf_dir, "part").select("p_partkey", "p_brand")
    return lines.join(parts, F.col("l_partkey") == F.col("p_partkey")).join(sizes, F.col("l_orderkey") == F.col("o")).select(F.col("p_brand").alias("set_id"), F.col("l_orderkey").alias("key"), F.lit(1.0).alias("weight"), "lines")


def event_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users by event type and day."""
    e = load(spark, sf_dir, "events").select("event_type", "ts", "user_id")
    return e.select(F.concat("event_type", F.lit("/"), F.date_format(F.col("ts").cast("timestamp_ntz"), "yyyy-MM-dd")).alias("set_id"), F.col("user_id").alias("key"), F.lit(1.0).alias("weight"))


def doc_terms(spark: SparkSession, sf_dir: str, table: str = "documents", weighted: bool = False) -> DataFrame:
    """Terms (runs of a-z, lower-cased) by document, weighted by rarity, with length, and the document's source."""
    docs = load(spark, sf_dir, table)
    ident = "doc_id" if table == "documents" else "item_id"
    source = F.col("source") if table == "documents" else F.lit(table)
    terms = docs.select(F.col(ident).cast("string").alias("set_id"), source.alias("source"), F.explode(F.array_distinct(F.regexp_extract_all(F.lower(F.coalesce("text", F.lit(""))), F.lit("[a-z]+"), F.lit(0)))).alias("key"))
    if not weighted:
        return terms.select("set_id", "key", F.lit(1.0).alias("weight"), F.length("key").alias("length"), "source")
    n = docs.count()
    df = terms.groupBy(F.col("key").alias("t")).agg(F.count(F.lit(1)).alias("df"))
    return terms.join(df, F.col("key") == F.col("t")).select("set_id", "key", F.log(1 + F.lit(float(n)) / F.col("df")).alias("weight"), F.length("key").alias("length"), "source")


def doc_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_terms by rows of documents: set_id, and keys as an array; a document of several rows has several."""
    docs = load(spark, sf_dir, "documents")
    return docs.select(F.col("doc_id").cast("string").alias("set_id"), F.array_distinct(F.regexp_extract_all(F.lower(F.coalesce("text", F.lit(""))), F.lit("[a-z]+"), F.lit(0))).alias("keys"))


def lang_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Terms by the language of the documents that hold them, weighted by rarity among all documents, with their length."""
    docs = load(spark, sf_dir, "documents").select("doc_id", "lang", F.explode(F.array_distinct(F.regexp_extract_all(F.lower(F.coalesce("text", F.lit(""))), F.lit("[a-z]+"), F.lit(0)))).alias("key"))
    n = load(spark, sf_dir, "documents").agg(F.count(F.lit(1)).alias("n"))
    df = docs.groupBy(F.col("key").alias("t")).agg(F.count(F.lit(1)).alias("df")).crossJoin(F.broadcast(n))  # one row
    held = docs.where("lang is not null").groupBy("lang", "key").agg(F.count(F.lit(1)).alias("_n"))
    return held.join(df, F.col("key") == F.col("t")).select(F.col("lang").alias("set_id"), "key", F.log(1 + F.col("n").cast("double") / F.col("df")).alias("weight"), F.length("key").alias("length"))


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages by link target, weighted by the page's length."""
    p = load(spark, sf_dir, "pages").select("page_id", "html")
    return p.select("page_id", F.length("html").cast("double").alias("weight"), F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))).alias("set_id")).select("set_id", F.col("page_id").alias("key"), "weight")


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors by label."""
    return load(spark, sf_dir, "embeddings").select(F.concat(F.lit("v"), F.col("label").cast("string")).alias("set_id"), F.col("vec_id").alias("key"), F.lit(1.0).alias("weight"))


def ranges(spark: SparkSession, sf_dir: str, spans: dict[str, list[tuple[str, str]]], weight: str = "1.0") -> DataFrame:
    """Order keys by ranges. spans: set -> (from, to) as SQL over n, the number of orders; `to` is exclusive."""
    orders = load(spark, sf_dir, "orders")
    n = orders.count()
    rows = orders.select(F.col("o_orderkey").alias("key"), F.expr(weight).cast("double").alias("weight"), F.lit(n).cast("long").alias("n"))  # a long: spans multiply it
    inside = [F.when(F.expr(" or ".join(f"(key >= {a} and key < {b})" for a, b in parts)), F.lit(name)) for name, parts in spans.items()]
    return rows.select("key", "weight", F.explode(F.array_compact(F.array(*inside))).alias("set_id")).select("set_id", "key", "weight")


def pair_spans(overlap: str) -> dict[str, list[tuple[str, str]]]:
    """Two sets of n / 3 order keys. overlap: the number of common keys, as SQL over n."""
    return {"A": [("0", "n div 3")], "B": [(f"(n div 3 - {overlap})", f"(n div 3 * 2 - {overlap})")]}


def multi_spans(i: int) -> dict[str, list[tuple[str, str]]]:
    """i sets with one common fifth each: n / 30 common keys, and four times as many of their own."""
    u = "(n div 30)"
    return {f"S{j}": [("0", u), (f"({u} + 4 * {u} * {j})", f"({u} + 4 * {u} * {j + 1})")] for j in range(i)}


def relation_spans(disjoint: bool) -> dict[str, list[tuple[str, str]]]:
    """Five sets with the same union: disjoint, or five sixths common."""
    u = "(n * 619 div 7500)"
    if disjoint:
        return {f"S{j}": [(f"({2 * j} * {u})", f"({2 * j + 2} * {u})")] for j in range(5)}
    return {f"S{j}": [("0", f"(5 * {u})"), (f"({5 + j} * {u})", f"({6 + j} * {u})")] for j in range(5)}


def hetero_spans(share: str) -> dict[str, list[tuple[str, str]]]:
    """A set of n / 3 keys, and a disjoint one of a share of that."""
    return {"A": [("0", "n div 3")], "B": [("n div 3", f"(n div 3 + n div 3 * {share})")]}


def supplier_graph(spark: SparkSession, sf_dir: str, days: int = 7) -> tuple[DataFrame, DataFrame]:
    """Edges (src, dst) of suppliers that share an order of the first days, and their parts as items (node, key, weight)."""
    orders = load(spark, sf_dir, "orders").where(F.datediff(F.col("o_orderdate"), F.lit(FIRST_DAY)) < days).select("o_orderkey")
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    near = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"), "left_semi").distinct()
    edges = near.alias("x").join(near.alias("y"), F.expr("x.l_orderkey = y.l_orderkey and x.l_suppkey <> y.l_suppkey")).select(F.col("x.l_suppkey").alias("src"), F.col("y.l_suppkey").alias("dst")).distinct()
    items = load(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("node"), F.col("l_partkey").alias("key"), F.lit(1.0).alias("weight"))
    return edges, items

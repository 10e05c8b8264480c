"""Quality rules with thresholds that adapt to each language and source.

Every document gets integer measures (per mille, or tenths of a character). A quantile sketch of each measure is a
histogram over its integer values: sketches of parts of the data add up bin by bin, in any order, so they merge from
tasks to sources, from sources to languages and from languages to the whole corpus. The fences of a group are its median
plus or minus a multiple of its upper or lower spread; a group with few documents takes the merged sketch of its
language, and a small language that of the corpus. Documents are joined with the fences of their group and rejected
outside of them.

Defined cases: a null text has no words and fails; null languages or sources form groups of their own; repeated rows
count as often as they stand and get equal verdicts; an empty table gives an empty result. Extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD_SPACE, load, materialize

#: measure: (expression over the base counts, sides of its distribution that count, least distance of the fence from the median)
MEASURES = {
    "word_length": ("cast(word_chars * 10 div n_words as int)", ("low", "high"), 10),
    "symbol_share": ("cast(least(1000, n_symbols * 1000 div word_chars) as int)", ("high",), 30),
    "line_repeats": ("cast(n_dup_lines * 1000 div greatest(n_lines, 1) as int)", ("high",), 400),
    "phrase_repeats": ("cast(n_repeat_words * 1000 div n_words as int)", ("high",), 350),
    "capitals": ("cast(n_capitals * 1000 div word_chars as int)", ("high",), 200),
}
#: Spreads (from the median to the 75th or 25th percentile) that a fence lies from the median.
SPREADS = 8
#: A group with fewer documents takes the merged sketch of the next wider group.
LEAST_DOCUMENTS = 200
MIN_WORDS, MAX_REPEAT_PERCENT = 50, 50


def _words(text: Column) -> Column:
    return F.filter(F.split(text, WORD_SPACE), lambda w: w != "")


def _repeat_words(words: Column) -> Column:
    """Words inside three-word windows that stand at least twice in the text, the first one included."""
    n = F.size(words)
    windows = F.transform(F.sequence(F.lit(0), n - 3), lambda i: F.xxhash64(F.get(words, i), F.get(words, i + 1), F.get(words, i + 2)))
    sorted_pairs = F.array_sort(F.transform(windows, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

    def repeated(pairs: Column) -> Column:
        return F.filter(pairs, lambda x, j: (F.get(pairs, j + 1)["h"] == x["h"]) | ((j > 0) & (F.get(pairs, j - 1)["h"] == x["h"])))

    def covered(at: Column) -> Column:
        steps = F.transform(at, lambda x, j: F.least(F.lit(3), F.coalesce(F.get(at, j + 1) - x, F.lit(3))))
        return F.aggregate(steps, F.lit(0), lambda a, b: a + b)

    def bound(value: Column, use) -> Column:  # evaluates value once and hands it to use
        return F.get(F.transform(F.array(value), use), F.lit(0))

    slow = bound(sorted_pairs, lambda p: bound(F.array_sort(F.transform(repeated(p), lambda x: x["i"])), covered))
    return F.when(n < 3, F.lit(0)).otherwise(bound(windows, lambda w: F.when(F.size(F.array_distinct(w)) == F.size(w), F.lit(0)).otherwise(slow)))


def base_counts(docs: DataFrame) -> DataFrame:
    """doc_id, lang, source and the integer counts of every document's whole text."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("source").cast("string").alias("source"), text.alias("t"))
    split = slim.withColumn("w", _words(F.col("t"))).withColumn("lines", F.filter(F.split("t", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")))
    return split.select(
        "doc_id",
        "lang",
        "source",
        F.size("w").cast("long").alias("n_words"),
        F.length(F.translate("t", " \t\n\x0b\x0c\r", "")).cast("long").alias("word_chars"),
        (F.length("t") - F.length(F.translate("t", "#*$%&|<>", ""))).cast("long").alias("n_symbols"),
        (F.length("t") - F.length(F.regexp_replace("t", "[A-Z]", ""))).cast("long").alias("n_capitals"),
        F.size("lines").cast("long").alias("n_lines"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        _repeat_words(F.col("w")).cast("long").alias("n_repeat_words"),
    )


def measured(docs: DataFrame) -> DataFrame:
    """base_counts with base_failed and the integer measures (null where a text has no words)."""
    counts = base_counts(docs)
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    values = {k: F.expr(f"case when n_words > 0 then {e} end") for k, (e, _, _) in MEASURES.items()}
    return counts.withColumn("base_failed", failed).withColumns(values)


def sketches(rows: DataFrame) -> DataFrame:
    """lang, source, measure, bin, n: the mergeable quantile sketches of rows that pass the base rules."""
    long = rows.where("not base_failed").select("lang", "source", F.explode(F.map_from_arrays(F.array(*map(F.lit, MEASURES)), F.array(*MEASURES))).alias("measure", "bin"))
    return long.groupBy("lang", "source", "measure", "bin").agg(F.count(F.lit(1)).alias("n"))


def quantiles(sketch: DataFrame, by: list[str]) -> DataFrame:
    """by, measure, total, q25, q50, q75: lower quantiles of the sketches merged over by."""
    merged = sketch.groupBy(*by, "measure", "bin").agg(F.sum("n").alias("n"))
    within = Window.partitionBy(*by, "measure")
    upto = merged.withColumn("upto", F.sum("n").over(within.orderBy("bin"))).withColumn("total", F.sum("n").over(within))
    found = [F.min(F.when(F.col("upto") * 100 >= F.col("total") * q, F.col("bin"))).alias(f"q{q}") for q in (25, 50, 75)]
    return upto.groupBy(*by, "measure", "total").agg(*found)


def fences(sketch: DataFrame) -> DataFrame:
    """lang, source and low_, high_ of every measure; null: no fence on that side."""
    own = quantiles(sketch, ["lang", "source"])
    wider = quantiles(sketch, ["lang"]).select(F.col("lang").alias("l"), F.col("measure").alias("m"), *[F.col(c).alias(f"l_{c}") for c in ("total", "q25", "q50", "q75")])
    widest = quantiles(sketch, []).select(F.col("measure").alias("a"), *[F.col(c).alias(f"a_{c}") for c in ("q25", "q50", "q75")])
    joined = own.join(wider, own["lang"].eqNullSafe(wider["l"]) & (own["measure"] == wider["m"])).join(F.broadcast(widest), F.col("measure") == F.col("a"))  # widest: a row for each measure
    pick = {q: F.when(F.col("total") >= LEAST_DOCUMENTS, F.col(q)).when(F.col("l_total") >= LEAST_DOCUMENTS, F.col(f"l_{q}")).otherwise(F.col(f"a_{q}")) for q in ("q25", "q50", "q75")}
    least = F.create_map(*[F.lit(x) for k, (_, _, d) in MEASURES.items() for x in (k, d)])[F.col("measure")]
    bounds = joined.select("lang", "source", "measure", (pick["q50"] - F.greatest(SPREADS * (pick["q50"] - pick["q25"]), least)).alias("low"), (pick["q50"] + F.greatest(SPREADS * (pick["q75"] - pick["q50"]), least)).alias("high"))
    columns = [F.max(F.when(F.col("measure") == k, F.col(side))).alias(f"{side}_{k}") for k, (_, sides, _) in MEASURES.items() for side in sides]
    return bounds.groupBy(F.col("lang").alias("f_lang"), F.col("source").alias("f_source")).agg(*columns)


def judged(docs: DataFrame) -> DataFrame:
    """measured with kept: false for base failures and for documents outside a fence of their group."""
    rows = materialize(measured(docs))
    limits = fences(sketches(rows))
    inside = F.lit(True)
    for k, (_, sides, _) in MEASURES.items():
        for side in sides:
            limit = F.col(f"{side}_{k}")
            inside &= F.coalesce(F.col(k) <= limit if side == "high" else F.col(k) >= limit, F.lit(True))
    joined = rows.join(limits, rows["lang"].eqNullSafe(limits["f_lang"]) & rows["source"].eqNullSafe(limits["f_source"]), "left")
    return joined.withColumn("kept", ~F.col("base_failed") & inside).drop(*limits.columns)


def query(spark, sf_dir: str) -> DataFrame:
    return judged(load(spark, sf_dir, "documents")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", *MEASURES)

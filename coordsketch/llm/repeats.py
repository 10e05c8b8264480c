"""Repeated passages by enhanced suffix arrays and their interval trees, over all texts of a table.

Every string of `length` bytes has a first minimum among the hashes of its short grams; the consecutive strings with one
and the same minimal gram are an anchored context, from the first of their starts to the end of the last one. Strings
that are equal have equal minima at equal places, so they meet within a bucket of contexts of one minimum and never
within a single context. Contexts that are equal as a whole are one class with a count.

For each bucket of several classes, the suffixes of the class contexts make an enhanced suffix array: suffixes in
lexicographic order with the lengths of the common prefixes of neighbours. One scan with a stack turns these lengths into
the intervals of the common-prefix tree. An interval whose suffixes are preceded by different bytes (or by a context's
start) cannot be extended to the left: its prefix is a maximal repeat, and the whole interval, not just neighbours, gives
its occurrences. The bytes of maximal repeats are exactly those of strings that start twice or more.

A bucket with very many classes would be a large group in one task; its suffixes are dealt out by the hash of their
first `length` bytes instead, and every such part is an interval by itself.

Defined cases: null and short texts hold no string of that length and stay as they are; matches never cross texts;
repeated rows are repeats of each other; overlapping occurrences count, also within one text; empty tables give an empty
result. Extra columns are ignored. Texts are UTF-8 bytes; what is left may split a character and is a byte string.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import RollingHash, flat_bytes, load, materialize, mix, ranges, row_key, slices

LENGTH, GRAM = 200, 64
#: Buckets with more classes are dealt out by suffix.
MOST_CLASSES = 1024
#: Suffixes that a task takes into one array.
ARRAY_SUFFIXES = 100_000
#: Bytes to which suffixes are sorted and compared; contexts are shorter.
DEPTH = 2 * LENGTH - GRAM + 1

_UPPER = np.uint64(0xFFFFFFFF00000000)
_ANCHORS = "key long, low long, class long, at int, starts int"


def contexts(data: np.ndarray, starts: np.ndarray, lengths: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, ...]:
    """text number, minimum, class hash, first start (in its text) and number of starts of every anchored context."""
    empty = tuple(np.empty(0, t) for t in (np.int64, np.int64, np.int64, np.int32, np.int32))
    long = np.flatnonzero(lengths >= length)
    if not len(long) or len(data) < length:
        return empty
    hashes = RollingHash(data)
    grams, width = hashes.windows(gram), length - gram + 1
    padded = np.full(-(-len(grams) // width) * width, np.iinfo(np.uint64).max, np.uint64)
    padded[: len(grams)] = (grams & _UPPER) | np.arange(len(grams), dtype=np.uint64)  # ties: the first gram
    blocks = padded.reshape(-1, width)
    ahead = np.minimum.accumulate(blocks, axis=1).ravel()
    behind = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    lowest = np.minimum(behind[: len(data) - length + 1], ahead[width - 1 : width - 1 + len(data) - length + 1])
    counts = lengths[long] - length + 1
    at = ranges(starts[long], counts)
    place, text = (lowest[at] & ~_UPPER).astype(np.int64), np.repeat(long, counts)
    first = np.ones(len(at), bool)
    first[1:] = (place[1:] != place[:-1]) | (text[1:] != text[:-1])
    begin = np.flatnonzero(first)
    number = np.diff(np.append(begin, len(at)))
    origin = at[begin]
    classes = mix(hashes.of(origin, origin + number + length - 1) + number.astype(np.uint64))
    return text[begin], grams[place[begin]].view(np.int64), classes.view(np.int64), (origin - starts[text[begin]]).astype(np.int32), number.astype(np.int32)


def anchors(keyed: DataFrame, length: int, gram: int) -> DataFrame:
    """key, low, class, at, starts of the contexts of keyed's texts (columns key, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in slices(batches, "text", 1_000_000):
            data, starts, lengths = flat_bytes(piece["text"])
            text, low, classes, at, number = contexts(data, starts, lengths, length, gram)
            yield pa.RecordBatch.from_arrays([piece["key"].take(pa.array(text)), pa.array(low), pa.array(classes), pa.array(at), pa.array(number)], ["key", "low", "class", "at", "starts"])

    return keyed.mapInArrow(run, _ANCHORS)


def suffix_array(data: np.ndarray, at: np.ndarray, ends: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """The order of the suffixes that start at `at` and end at `ends`, and the common-prefix length of each with the one before."""
    padded = np.concatenate([data, np.zeros(depth, np.uint8)])
    rows = np.lib.stride_tricks.sliding_window_view(padded, depth)[at]
    room = np.minimum(ends - at, depth)
    rows[np.repeat(np.arange(len(at)), depth - room), ranges(room, depth - room)] = 0
    order = np.argsort(rows.view(f"S{depth}").ravel(), kind="stable")
    rows, room = rows[order], room[order]
    common = np.zeros(len(at), np.int64)
    for a in range(1, len(at), 50_000):
        here, back = rows[a : a + 50_000], rows[a - 1 : a - 1 + min(50_000, len(at) - a)]
        differ = here != back
        common[a : a + 50_000] = np.where(differ.any(axis=1), differ.argmax(axis=1), depth)
    common[1:] = np.minimum(common[1:], np.minimum(room[1:], room[:-1]))
    return order, common


def intervals(common: np.ndarray, least: int) -> Iterator[tuple[int, int, int]]:
    """(length, first, last) of the common-prefix intervals of at least `least`, children before parents; one stack scan."""
    stack: list[tuple[int, int]] = []
    for i, value in enumerate([*common.tolist(), 0]):
        value = value if value >= least else 0
        first = i - 1
        while stack and stack[-1][0] > value:
            height, first = stack.pop()
            yield height, first, i - 1
        if value and (not stack or stack[-1][0] < value):
            stack.append((value, first))


def maximal_repeats(data: np.ndarray, at: np.ndarray, ends: np.ndarray, begins: np.ndarray, least: int, depth: int = DEPTH) -> Iterator[tuple[int, np.ndarray]]:
    """(length, suffix numbers) of every maximal repeat of at least `least` bytes: all suffixes of a left-diverse interval.

    begins: where each suffix's context begins; a suffix that starts there has no byte before it and counts as diverse.
    Suffixes that an inner interval has already reported at a greater length stand in the outer ones too."""
    order, common = suffix_array(data, at, ends, depth)
    before = np.where(at > begins, data[np.maximum(at - 1, 0)].astype(np.int64), -1 - np.arange(len(at)))[order]
    for height, first, last in intervals(common, least):
        preceding = before[first : last + 1]
        if (preceding != preceding[0]).any():
            yield height, order[first : last + 1]


def _joined(rows: list[tuple]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The bytes of all contexts, and each context's start and size; rows: (low, class, context)."""
    sizes = np.fromiter((len(r[2]) for r in rows), np.int64, len(rows))
    return np.frombuffer(b"".join(r[2] for r in rows), np.uint8), np.cumsum(sizes) - sizes, sizes


def _repeats_in(rows: list[tuple], length: int) -> Iterator[tuple[int, np.ndarray]]:
    """(length, places in the joined bytes) of every maximal repeat of each bucket; rows: (low, class, context) of whole buckets."""
    data, starts, sizes = _joined(rows)
    counts = sizes - length + 1
    at, owner = ranges(starts, counts), np.repeat(np.arange(len(rows)), counts)
    bucket = np.array([r[0] for r in rows], np.int64)
    full = RollingHash(data).of(at, at + length)
    _, group, times = np.unique(mix(full ^ mix(bucket[owner].view(np.uint64))), return_inverse=True, return_counts=True)
    twice = np.flatnonzero(times[group] > 1)  # other suffixes share no prefix of that length with any
    ends = (starts + sizes)[owner]
    for low in np.unique(bucket[owner[twice]]):
        mine = twice[bucket[owner[twice]] == low]
        for height, members in maximal_repeats(data, at[mine], ends[mine], starts[owner[mine]], length):
            yield height, at[mine][members]


def _groups_in(rows: list[tuple], length: int) -> Iterator[tuple[int, int, int, int, int]]:
    """low, class, start in the context, length and group of every occurrence of the maximal repeats."""
    data, starts, _ = _joined(rows)
    hashes = RollingHash(data)
    for height, places in _repeats_in(rows, length):
        group = int(hashes.of(places[:1], places[:1] + height).view(np.int64)[0])
        for place, o in zip(places.tolist(), (np.searchsorted(starts, places, "right") - 1).tolist(), strict=True):
            yield rows[o][0], rows[o][1], place - int(starts[o]), height, group


def _repeated_in(rows: list[tuple], length: int) -> Iterator[tuple[int, int, int, int]]:
    """low, class, start, end of the context bytes inside maximal repeats."""
    data, starts, _ = _joined(rows)
    marks = np.zeros(len(data) + 1, np.int64)
    for height, places in _repeats_in(rows, length):
        np.add.at(marks, places, 1)
        np.add.at(marks, places + height, -1)
    inside = np.concatenate([[False], np.cumsum(marks)[:-1] > 0, [False]])
    edges = np.flatnonzero(inside[1:] != inside[:-1])
    border = np.isin(np.arange(len(data) + 1), starts)
    for s, e in zip(edges[::2].tolist(), edges[1::2].tolist(), strict=True):
        cuts = [s, *(s + 1 + np.flatnonzero(border[s + 1 : e])).tolist(), e]
        for a, b in zip(cuts, cuts[1:], strict=False):
            o = int(np.searchsorted(starts, a, "right")) - 1
            yield rows[o][0], rows[o][1], a - int(starts[o]), b - int(starts[o])


def _scan(buckets: DataFrame, length: int, groups: bool = False) -> DataFrame:
    """low, class, s, e (or for groups low, class, s, length, group) for the bucket-sorted rows low, class, context."""
    names = ["low", "class", "s", "length", "group"] if groups else ["low", "class", "s", "e"]
    kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64()][: len(names)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        room = 0

        def out(rows: list[tuple]) -> pa.RecordBatch:
            found = list((_groups_in if groups else _repeated_in)(rows, length))
            return pa.RecordBatch.from_arrays([pa.array([f[i] for f in found], t) for i, t in enumerate(kinds)], names)

        for batch in batches:
            for row in zip(batch["low"].to_pylist(), batch["class"].to_pylist(), batch["context"].to_pylist(), strict=True):
                if room > ARRAY_SUFFIXES and row[0] != held[-1][0]:
                    yield out(held)
                    held, room = [], 0
                held.append(row)
                room += len(row[2]) - length + 1
        if held:
            yield out(held)

    dealt = buckets.select("low", "class", "context").repartition("low").sortWithinPartitions("low", "class")
    return dealt.mapInArrow(run, "low long, class long, s int, length int, `group` long" if groups else "low long, class long, s int, e int")


def _buckets(docs_keyed: DataFrame, length: int, gram: int) -> tuple[DataFrame, DataFrame]:
    """The contexts (key, low, class, at, starts) of buckets of several ones, and their classes with counts and one member each."""
    found = anchors(docs_keyed, length, gram)
    # written, so that the join below may split a minimum that very many contexts have
    shared = materialize(found.groupBy("low").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("low"))
    held = materialize(found.join(shared.hint("merge"), "low"))
    # written, so that a minimum with very many classes is dealt out by class here, and may be split in the join below
    classes = materialize(held.groupBy("low", "class").agg(F.count(F.lit(1)).alias("n"), F.first(F.struct("key", "at", "starts")).alias("one")))
    sizes = classes.groupBy("low").agg(F.count(F.lit(1)).alias("classes"), F.min("n").alias("least"))
    return held, materialize(classes.join(sizes, "low").select("low", "class", "n", "one.*", "classes", "least"))


def _fetched(docs_keyed: DataFrame, known: DataFrame, length: int) -> DataFrame:
    """For one member of each class of known: low, class, n and its context, or, in buckets of very many classes, its suffixes."""
    wanted = known.select("key", F.struct("low", "class", "n", "at", "starts", (F.col("classes") > MOST_CLASSES).alias("many")).alias("w"))
    wanted = wanted.groupBy("key").agg(F.collect_list("w").alias("wanted"))

    def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["low", "class", "n", "context", "start", "suffix"]
        for piece in slices(batches, "text", 1_000_000):
            rows: list[tuple] = []
            for text, wishes in zip(piece["text"].cast(pa.binary()).to_pylist(), piece["wanted"].to_pylist(), strict=True):
                for w in wishes:
                    context = text[w["at"] : w["at"] + w["starts"] + length - 1]
                    rows.append((w["low"], w["class"], w["n"], context, w["many"]))
            few = [r for r in rows if not r[4]]
            if few:
                columns = [pa.array([r[i] for r in few], t) for i, t in enumerate((pa.int64(), pa.int64(), pa.int64(), pa.binary()))]
                yield pa.RecordBatch.from_arrays([*columns, pa.nulls(len(few), pa.int32()), pa.nulls(len(few), pa.int64())], names)
            many = [r for r in rows if r[4]]
            for a in range(0, len(many), 1000):
                some = many[a : a + 1000]
                sizes = np.array([len(r[3]) for r in some])
                at, counts = np.cumsum(sizes) - sizes, sizes - length + 1
                windows = ranges(at, counts)
                hashes = RollingHash(np.frombuffer(b"".join(r[3] for r in some), np.uint8)).of(windows, windows + length)
                own = [pa.array(np.repeat(np.array([r[i] for r in some], np.int64), counts)) for i in range(3)]
                yield pa.RecordBatch.from_arrays([*own, pa.nulls(len(windows), pa.binary()), pa.array((windows - np.repeat(at, counts)).astype(np.int32)), pa.array(hashes.view(np.int64))], names)

    return materialize(docs_keyed.join(wanted, "key").select("text", "wanted").mapInArrow(fetch, "low long, class long, n long, context binary, start int, suffix long"))


def repeated_ranges(docs_keyed: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """key, s, e: byte ranges of keyed texts (columns key, text) whose union is all bytes of repeated strings."""
    held, known = _buckets(docs_keyed, length, gram)
    whole = known.where("n > 1").select("low", "class", F.lit(0).alias("s"), (F.col("starts") + length - 1).cast("int").alias("e"))
    fetched = _fetched(docs_keyed, known.where("classes > 1 and least = 1"), length)
    arrays = _scan(fetched.where("context is not null"), length)
    parts = fetched.where("context is null")
    often = parts.groupBy("low", "suffix").agg(F.sum("n").alias("times")).where("times > 1").select("low", "suffix")
    dealt = parts.join(often, ["low", "suffix"]).select("low", "class", F.col("start").alias("s"), (F.col("start") + length).cast("int").alias("e"))
    ranges_of = whole.unionByName(arrays).unionByName(dealt)
    return held.join(ranges_of, ["low", "class"]).select("key", (F.col("at") + F.col("s")).alias("s"), (F.col("at") + F.col("e")).alias("e"))


def repeat_groups(docs: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """group, length, key (of the row's doc_id and text), doc_id, start: every maximal repeat of at least `length` bytes within
    a context, with all of its occurrences. Contexts that are equal as a whole are a group; so a repeat longer than a context is a
    chain of overlapping groups. In buckets of very many classes, groups are the repeated strings of `length` bytes."""
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).withColumn("key", row_key())
    held, known = _buckets(keyed.select("key", "text"), length, gram)
    fetched = _fetched(keyed.select("key", "text"), known.where("classes > 1"), length)
    arrays = materialize(_scan(fetched.where("context is not null"), length, groups=True))
    whole = known.where((F.col("n") > 1) & (F.col("classes") <= MOST_CLASSES)).select("low", "class", F.lit(0).alias("s"), (F.col("starts") + length - 1).cast("int").alias("length"), F.col("class").alias("group"))
    whole = whole.join(arrays, ["low", "class", "s", "length"], "left_anti")  # those stand within other contexts, too, and are there
    parts = fetched.where("context is null")
    often = parts.groupBy("low", "suffix").agg(F.sum("n").alias("times")).where("times > 1").select("low", "suffix")
    dealt = parts.join(often, ["low", "suffix"]).select("low", "class", F.col("start").alias("s"), F.lit(length).alias("length"), F.xxhash64("low", "suffix").alias("group"))
    found = held.join(whole.unionByName(arrays).unionByName(dealt), ["low", "class"]).select("group", "length", "key", (F.col("at") + F.col("s")).alias("start"))
    names = keyed.select("key", "doc_id").distinct()
    return found.join(names, "key").select("group", "length", "key", "doc_id", "start").distinct()


def without_repeats(docs: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept (bytes), spans (start, end of what went) of every row of docs."""
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    keyed = keyed.withColumn("key", row_key())
    spans = repeated_ranges(keyed.select("key", "text"), length, gram)
    merged = spans.groupBy("key").agg(F.array_sort(F.collect_set(F.struct("s", "e"))).alias("found"))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))]
        names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept", "spans"]
        for piece in slices(batches, "text", 1_000_000):
            rows = []
            for doc, raw, found in zip(piece["doc_id"].to_pylist(), piece["text"].cast(pa.binary()).to_pylist(), piece["found"].to_pylist(), strict=True):
                raw, runs = raw or b"", []
                for r in found or ():
                    if runs and r["s"] <= runs[-1][1]:
                        runs[-1][1] = max(runs[-1][1], r["e"])
                    else:
                        runs.append([r["s"], r["e"]])
                ends = [0, *(x for r in runs for x in r), len(raw)]
                kept = b"".join(raw[a:b] for a, b in zip(ends[::2], ends[1::2], strict=True))
                rows.append((doc, len(raw), len(raw) - len(kept), len(runs), kept, [{"start": a, "end": b} for a, b in runs]))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    return keyed.join(merged, "key", "left").select("doc_id", "text", "found").mapInArrow(cut, "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary, spans array<struct<start:long,end:long>>")


def query(spark, sf_dir: str) -> DataFrame:
    left = without_repeats(load(spark, sf_dir, "documents"))
    return left.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


__all__ = ["contexts", "intervals", "maximal_repeats", "query", "repeat_groups", "repeated_ranges", "suffix_array", "without_repeats"]

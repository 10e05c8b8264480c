"""Language-model scoring with a log-frequency Bloom filter.

Word counts of the training documents are exact. Word-pair counts are kept as logarithms in a Bloom filter: a pair seen
c times is inserted with every level from 0 to floor(log2 c), and a pair's level is the last one of the membership probes
that succeed in a row, or -1 if the first one fails. The filter has a segment for each range of pair hashes, so every reducer makes one from the counts it
has summed. It is broadcast to the workers up to `most_bytes`; a larger filter is broadcast in groups of segments,
and as every pair lies in one segment, a worker looks its pairs up in one group after the other, in one pass over the documents.

The model: P(w | v) = (2^level(v w) + PRIOR U(w)) / (count(v) + PRIOR), where level -1 counts as never seen (0 in place of
the power) and U(w) = (count(w) + 1) / (tokens + types + 1). With exact pair counts the probabilities of a history sum to one,
whether it was seen or not; rounding counts down only lowers them.

Word counts reach the documents without a broadcast: documents lie in parts of bounded bytes, every part asks for the
counts of its distinct words, and the answers are grouped with the part. A part holds documents of one class of length, so
that it has twice PART_BYTES at most, or one document.

Defined cases: a null text is empty and has the end token only; a null doc_id belongs to the training documents; repeated
rows count as often as they stand; without training documents every count is 0; an empty table gives an empty result.
Texts of any length are read whole. Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import RollingHash, flat_bytes, load, materialize, mix, ranges, slices

#: Rows of a file that make a part of short texts; texts twice as long come half as many to a part, and so on.
PART_ROWS, PART_BYTES = 2048, 64 << 20
#: Pseudo-count of the word distribution behind every history.
PRIOR = 4.0
BITS_A_KEY, PROBES, MOST_LEVELS = 12, 6, 48
#: Training tokens that a filter segment is made for, on average.
SEGMENT_TOKENS = 2_000_000
MOST_BYTES = 256 << 20
END, START = np.uint64(0x5851F42D4C957F2D), np.uint64(0x14057B7EF767814F)
_PAIR = np.uint64(0xD1342543DE82EF95)
#: Pairs, or tokens, that a task counts before it hands them on.
FLUSH = 3_000_000
#: Text that is looked up in one group of segments after the other.
STRETCH_BYTES = 16 << 20


def token_hashes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The hashes of the tokens (lower-cased words, then the end) of all texts, and each text's number of tokens."""
    data, starts, lengths = flat_bytes(texts)
    low = np.where((data >= 65) & (data <= 90), data + 32, data).astype(np.uint8)
    inside = ~((low == 32) | ((low >= 9) & (low <= 13)))
    begin = inside.copy()
    begin[1:] &= ~inside[:-1]
    begin[starts[lengths > 0]] |= inside[starts[lengths > 0]]
    at = np.flatnonzero(begin)
    stop = inside.copy()
    stop[:-1] &= ~inside[1:]
    ends = (starts + lengths)[lengths > 0] - 1
    stop[ends] |= inside[ends]
    words = RollingHash(low).of(at, np.flatnonzero(stop) + 1) if len(at) else np.empty(0, np.uint64)
    owner = np.searchsorted(starts + lengths, at, "right")
    counts = np.bincount(owner, minlength=len(starts)).astype(np.int64)
    return np.insert(words, np.cumsum(counts), END), counts + 1


def pair_hashes(tokens: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of every token with the one before (the start token at first), and the tokens before."""
    before = np.empty_like(tokens)
    before[1:] = tokens[:-1]
    before[np.cumsum(counts) - counts] = START
    return mix(before * _PAIR + tokens), before


class Segment:
    """One segment of the log-frequency filter: bits for keys (pair, level)."""

    @staticmethod
    def _place(pairs: np.ndarray, level: int, probe: int, bits: int) -> np.ndarray:
        key = mix(pairs + np.uint64(level * 0x9E3779B97F4A7C15 % (1 << 64)))
        step = (key >> np.uint64(32)) | np.uint64(1)
        return (((key & np.uint64(0xFFFFFFFF)) + np.uint64(probe) * step) % np.uint64(bits)).astype(np.int64)

    @classmethod
    def build(cls, pairs: np.ndarray, counts: np.ndarray) -> bytes:
        levels = np.floor(np.log2(np.maximum(counts, 1)) + 1e-9).astype(int)
        bits = max(64, -(-BITS_A_KEY * int((levels + 1).sum()) // 8) * 8)
        held = np.zeros(bits, np.uint8)
        for level in range(int(levels.max(initial=-1)) + 1):
            for probe in range(PROBES):
                held[cls._place(pairs[levels >= level], level, probe, bits)] = 1
        return np.packbits(held, bitorder="little").tobytes()

    @classmethod
    def levels(cls, raw: np.ndarray, pairs: np.ndarray) -> np.ndarray:
        """The level of every pair: the last of the levels from 0 on that are found in a row, each by all of its probes; else -1."""
        return cls.levels_among(raw, np.zeros(len(pairs), np.int64), np.full(len(pairs), 8 * len(raw), np.uint64), pairs)

    @staticmethod
    def levels_among(raw: np.ndarray, offset: np.ndarray, bits: np.ndarray, pairs: np.ndarray) -> np.ndarray:
        """levels for pairs of many segments, all of them in raw: each pair's segment begins at byte offset and has so many bits.

        They are looked up together, so the number of calls does not grow with the number of segments."""
        out, alive = np.full(len(pairs), -1, np.int64), np.arange(len(pairs))
        for level in range(MOST_LEVELS):
            own, start, size = pairs[alive], offset[alive], bits[alive]
            key = mix(own + np.uint64(level * 0x9E3779B97F4A7C15 % (1 << 64)))
            step, at = (key >> np.uint64(32)) | np.uint64(1), key & np.uint64(0xFFFFFFFF)
            for i in range(PROBES):
                if not len(alive):
                    return out
                place = ((at + np.uint64(i) * step) % size).astype(np.int64)
                hit = np.flatnonzero((raw[start + (place >> 3)] >> (place & 7).astype(np.uint8)) & 1)
                if len(hit) < len(alive):
                    alive, step, at, start, size = alive[hit], step[hit], at[hit], start[hit], size[hit]
            out[alive] = level
        return out


def with_parts(docs: DataFrame) -> DataFrame:
    """part, row, doc_id, text, held_out. row is the row's number in its file; a part is of fixed rows of a file, whatever the splits; else docs is written first."""
    size = F.coalesce(F.octet_length(F.col("text").cast("string")), F.lit(0))
    longer = F.when(size < 2 * PART_BYTES // PART_ROWS, 0).otherwise(F.least(F.floor(F.log2(size * PART_ROWS / PART_BYTES)), F.lit(PART_ROWS.bit_length() - 1))).cast("int")
    try:
        named = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.xxhash64(F.col("_metadata.file_path"), longer, F.floor(F.col("_metadata.row_index") * F.pow(F.lit(2), longer) / PART_ROWS)).alias("part"), F.col("_metadata.row_index").alias("row"))
        named.schema  # noqa: B018  analysed here
    except Exception as e:
        if "_metadata" not in str(e):
            raise
        return with_parts(materialize(docs.select("doc_id", "text")))
    held = F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")) % 7 == 2
    return named.withColumn("held_out", held)


def word_counts(parts: DataFrame) -> DataFrame:
    """part, token, count (over all training documents), once (one row of each token): every distinct token of every part."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {}
        room = 0

        def out() -> Iterator[pa.RecordBatch]:
            for now, own in held.items():
                tokens, index = np.unique(np.concatenate([t for t, _ in own]), return_inverse=True)
                n = np.bincount(index, weights=np.concatenate([w for _, w in own]), minlength=len(tokens)).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(tokens), now, np.int64)), pa.array(tokens.view(np.int64)), pa.array(n)], ["part", "token", "n"])

        for piece in slices(batches, "text", 1_000_000):
            part = piece["part"].to_numpy(zero_copy_only=False)
            tokens, counts = token_hashes(piece["text"])
            learns = ~piece["held_out"].to_numpy(zero_copy_only=False)
            ends = np.cumsum(counts)
            for now in np.unique(part).tolist():
                rows = np.flatnonzero(part == now)
                own = tokens[ranges(ends[rows] - counts[rows], counts[rows])]
                distinct, index = np.unique(own, return_inverse=True)
                held.setdefault(now, []).append((distinct, np.bincount(index, weights=np.repeat(learns[rows], counts[rows]), minlength=len(distinct))))
                room += len(distinct)
            if room > FLUSH:
                yield from out()
                held, room = {}, 0
        yield from out()

    asked = parts.select("part", "text", "held_out").mapInArrow(run, "part long, token long, n long")
    of_token = Window.partitionBy("token")
    return asked.select("part", "token", F.sum("n").over(of_token).alias("count"), (F.row_number().over(of_token.orderBy("part")) == 1).alias("once"))


def _runs(keys: np.ndarray) -> Iterator[tuple[int, int]]:
    edges = [0, *(np.flatnonzero(keys[1:] != keys[:-1]) + 1).tolist(), len(keys)]
    yield from zip(edges, edges[1:], strict=False)


def segments(parts: DataFrame, tokens: int) -> DataFrame:
    """segment, bits: the filter over the training documents."""
    shift = max(4, (tokens // SEGMENT_TOKENS).bit_length())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        room = 0

        def out() -> Iterator[pa.RecordBatch]:
            pairs, n = np.unique(np.concatenate(held), return_counts=True)
            segment = (pairs >> np.uint64(64 - shift)).astype(np.int64)
            rows = []
            for a, b in _runs(segment):
                # the 32 bits after the segment's: enough to tell the pairs of a segment apart, as steps from one to the next
                low = ((pairs[a:b] << np.uint64(shift)) >> np.uint64(32)).astype(np.uint32)
                steps = np.diff(low, prepend=np.uint32(0)).astype("<u4")
                planes = np.ascontiguousarray(steps.view(np.uint8).reshape(-1, 4).T).tobytes()
                rows.append((int(segment[a]), planes, n[a:b].astype("<u4").view(np.uint8).reshape(-1, 4).T.tobytes()))
            for a in range(0, len(rows), 64):
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows[a : a + 64], strict=True), (pa.int64(), pa.binary(), pa.binary()), strict=True)], ["segment", "steps", "counts"])

        for piece in slices(batches, "text", 1_000_000):
            pairs, _ = pair_hashes(*token_hashes(piece["text"]))
            held.append(pairs)
            room += len(pairs)
            if room > FLUSH:
                yield from out()
                held, room = [], 0
        if held:
            yield from out()

    def build(table: pa.Table) -> pa.Table:
        plane = lambda x: np.ascontiguousarray(np.frombuffer(x, np.uint8).reshape(4, -1).T).view("<u4")[:, 0]
        low = np.concatenate([np.cumsum(plane(x), dtype=np.uint32) for x in table["steps"].to_pylist()])
        n = np.concatenate([plane(x) for x in table["counts"].to_pylist()])
        pairs, index = np.unique(low, return_inverse=True)
        counts = np.bincount(index, weights=n).astype(np.int64)
        raw = Segment.build(pairs.astype(np.uint64), counts)
        return pa.table({"segment": table["segment"][:1], "bits": pa.array([raw], pa.binary())})

    counted = parts.where("not held_out").select("text").mapInArrow(run, "segment long, steps binary, counts binary")
    return counted.groupBy("segment").applyInArrow(build, "segment long, bits binary")


def _groups(spark: SparkSession, built: DataFrame, most_bytes: int) -> Iterator[dict[int, bytes]]:
    """The segments, in groups of at most most_bytes (or a single one)."""
    group: dict[int, bytes] = {}
    size = 0
    for row in built.select("segment", "bits").orderBy("segment").toLocalIterator():
        if group and size + len(row["bits"]) > most_bytes:
            yield group
            group, size = {}, 0
        group[row["segment"]] = bytes(row["bits"])
        size += len(row["bits"])
    yield group


def scored(docs: DataFrame, most_bytes: int = MOST_BYTES) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row of docs."""
    spark = docs.sparkSession
    parts = with_parts(docs)
    words = materialize(word_counts(parts))
    n, types = words.where("once").agg(F.coalesce(F.sum("count"), F.lit(0)), F.count_if(F.col("count") > 0)).first()
    openings = parts.where("not held_out").count()
    built = materialize(segments(parts, n))
    shift = max(4, (n // SEGMENT_TOKENS).bit_length())
    groups = (_flat(group, 1 << shift) for group in _groups(spark, built, most_bytes))
    return _score(spark, parts, words, groups, built.count(), n, types, openings, shift)


def _flat(group: dict[int, bytes], segments: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The bytes of all segments of a group, and of every segment its place therein and its bits (0: not in the group)."""
    offset, bits = np.zeros(segments, np.int64), np.zeros(segments, np.uint64)
    at = 0
    for segment, raw in group.items():
        offset[segment], bits[segment] = at, 8 * len(raw)
        at += len(raw)
    return np.frombuffer(b"".join(group.values()), np.uint8), offset, bits


def _score(spark: SparkSession, parts: DataFrame, words: DataFrame, filters: Iterator[tuple], known: int, n: int, types: int, openings: int, shift: int) -> DataFrame:
    """All rows' scores in one pass over the documents. A worker holds one group of segments at a time; every stretch of a part
    goes through all groups, and begins with the one that the stretch before ended with."""
    held: list[int] = []
    groups = [spark.sparkContext.broadcast(group) for group in filters]
    partial = len(groups) > 1 or known < 1 << shift  # some pairs' segment is in another group, or there is none

    def group(k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        if held != [k]:
            for other in groups[:k] + groups[k + 1 :]:
                vars(other).pop("_value", None)  # read again from the worker's local copy when needed
            held[:] = [k]
        return groups[k].value

    def order() -> list[int]:
        return list(range(len(groups))) if held in ([], [0]) else list(range(len(groups)))[::-1]

    def stretch(texts: pa.Array, known: np.ndarray, value: np.ndarray) -> Iterator[tuple[np.ndarray, ...]]:
        """n_tokens, n_known, base_score and score of the texts of a stretch, in pieces."""
        pieces = []
        for piece in slices(iter([pa.RecordBatch.from_arrays([texts], ["text"])]), "text", 1_000_000):
            tokens, lengths = token_hashes(piece["text"])
            pairs, before = pair_hashes(tokens, lengths)
            distinct, back = np.unique(tokens, return_inverse=True)
            place = np.minimum(np.searchsorted(known, distinct), len(known) - 1)
            c = np.where(known[place] == distinct, value[place], 0)[back]
            history = np.empty_like(c)
            history[1:] = c[:-1]
            history[before == START] = openings
            where = (pairs >> np.uint64(64 - shift)).astype(np.int32)
            low = ((pairs << np.uint64(shift)) >> np.uint64(32)).astype(np.uint32)
            pieces.append((lengths, c, history, where, low, np.full(len(pairs), -1, np.int8)))
        for k in order():
            raw, offset, bits = group(k)
            for _, _, _, where, low, level in pieces:
                size = bits[where]
                mine = np.flatnonzero(size) if partial else slice(None)
                level[mine] = Segment.levels_among(raw, offset[where[mine]], size[mine], low[mine].astype(np.uint64))
        for lengths, c, history, _, _, level in pieces:
            plain = (c + 1.0) / (n + types + 1.0)
            seen = np.where(level >= 0, np.minimum(np.exp2(level.astype(np.float64)), history), 0.0)
            starts = np.cumsum(lengths) - lengths
            add = lambda x: np.add.reduceat(x, starts)  # noqa: B023, E731
            yield lengths, add((c > 0).astype(np.int64)), add(np.log10(plain)), add(np.log10((seen + PRIOR * plain) / (history + PRIOR)))

    def run(docs: pa.Table, counts: pa.Table) -> pa.Table:
        known = counts["token"].to_numpy().view(np.uint64)
        by_token = np.argsort(known)
        known, value = known[by_token], counts["count"].to_numpy()[by_token]
        texts = docs["text"].combine_chunks()
        texts = texts.chunk(0) if isinstance(texts, pa.ChunkedArray) else texts
        columns: list[list] = [[], [], [], []]
        for part in slices(iter([pa.RecordBatch.from_arrays([texts], ["text"])]), "text", STRETCH_BYTES):
            for piece in stretch(part["text"], known, value):
                for column, x in zip(columns, piece, strict=True):
                    column.append(x)
        merged = [np.concatenate(x) for x in columns]
        return pa.table({"doc_id": docs["doc_id"], "held_out": docs["held_out"], "n_tokens": pa.array(merged[0]), "n_known": pa.array(merged[1]), "train_tokens": pa.array(np.full(len(docs), n)), "base_score": pa.array(merged[2]), "score": pa.array(merged[3])})

    schema = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    return parts.groupBy("part").cogroup(words.select("part", "token", "count").groupBy("part")).applyInArrow(run, schema)


def query(spark, sf_dir: str) -> DataFrame:
    return scored(load(spark, sf_dir, "documents")).withColumn("score_per_token", F.col("score") / F.col("n_tokens"))

"""Length-delimited binary records of token ids, with an offset index for shuffled reads.

A record file is a run of frames, no header. Fixed values of a frame, all little-endian: payload length as unsigned 64
bits; masked checksum of these eight bytes, unsigned 32 bits; the payload; masked checksum of the payload, unsigned 32
bits. The checksum is CRC-32 (zlib's); masked: rotated right by 15 bits, plus 0xA282EAD8, modulo 2^32. A payload is
doc_id as signed 64 bits, then the ids, as unsigned 16 bits where the vocabulary has at most 65,536 ids and unsigned 32
bits otherwise; a flag byte after doc_id says which (2 or 4), and a second one whether doc_id is null.

Documents are dealt out by ranges of doc_id, and each task sorts its range and writes one file, part-NNNNN.rec, and its
index, part-NNNNN.idx: (doc_id, offset, frame length) as three signed 64-bit integers a record, so a reader can fetch
records in any order without scanning. Both carry the name of the attempt that wrote them, part-NNNNN-TAG, and the table
that write_records returns names the attempts that count, so an index always fits its file, and what a lost or repeated task
has left is never read. Files go through Arrow's file systems: any URI that they open works.

Defined cases: a null text is an empty one and has only its end id; a null doc_id sorts first; rows of equal doc_id are
in the order of a hash of their text; repeated rows become repeated records; an id that 16 bits can't hold raises an error; an empty table gives no records. Ids and texts are never cut.
"""

from __future__ import annotations

import struct
import uuid
from collections.abc import Iterator
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import load, materialize, shared_folder, slices
from .tokens import encoder, vocabulary

_HEAD, _SUM = struct.Struct("<QI"), struct.Struct("<I")
_KEY = struct.Struct("<qBB")
INDEX_ROW = np.dtype([("doc_id", "<i8"), ("offset", "<i8"), ("size", "<i8")])


def masked(data: bytes) -> int:
    c = crc32(data)
    return (((c >> 15) | (c << 17)) + 0xA282EAD8) & 0xFFFFFFFF


def frame(payload: bytes) -> bytes:
    head = struct.pack("<Q", len(payload))
    return b"".join((head, _SUM.pack(masked(head)), payload, _SUM.pack(masked(payload))))


def unframe(stream) -> Iterator[bytes]:
    """The payloads of a stream of frames, checked. Raises ValueError on a torn or changed frame."""
    while head := stream.read(_HEAD.size):
        if len(head) < _HEAD.size or _HEAD.unpack(head)[1] != masked(head[:8]):
            raise ValueError("record with a broken length")
        size = _HEAD.unpack(head)[0]
        body = stream.read(size + _SUM.size)
        if len(body) < size + _SUM.size or _SUM.unpack(body[size:])[0] != masked(body[:size]):
            raise ValueError("record with a broken payload")
        yield body[:size]


def pack(doc_id: int | None, ids: bytes, width: int) -> bytes:
    """ids: unsigned 32-bit little-endian. Narrowed to 16 bits if width is 2."""
    if width == 2:
        held = np.frombuffer(ids, "<u4")
        if len(held) and held.max() > 0xFFFF:
            raise ValueError(f"id {held.max()} does not fit 16 bits")
        ids = held.astype("<u2").tobytes()
    return _KEY.pack(doc_id or 0, width, doc_id is None) + ids


def unpack(payload: bytes) -> tuple[int | None, np.ndarray]:
    doc_id, width, null = _KEY.unpack_from(payload)
    return None if null else doc_id, np.frombuffer(payload, f"<u{width}", offset=_KEY.size).astype("<u4")


def _place(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def write_records(docs: DataFrame, folder: str, tokenizer: str, end_id: int = 2, width: int | None = None, partitions: int | None = None) -> DataFrame:
    """Writes docs to record and index files in folder; returns part, path, records, ids (in the order of doc_id).

    width: bytes of an id, 2 or 4; by default 2 if all ids of the vocabulary and end_id fit."""
    if width is None:
        width = 2 if max(encoder(tokenizer).most, end_id) <= 0xFFFF else 4

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, encode, end = TaskContext.get().partitionId(), encoder(tokenizer).encode, np.array([end_id], "<u4").tobytes()
        system, root = _place(folder)
        system.create_dir(root, recursive=True)
        path = f"part-{part:05d}-{uuid.uuid4().hex}"
        index: list[tuple[int, int, int]] = []
        at = total = 0
        with system.open_output_stream(f"{root}/{path}.rec") as out:
            for piece in slices(batches, "text", 1_000_000):
                texts = [x or "" for x in piece["text"].to_pylist()]
                block = []
                for doc, ids in zip(piece["doc_id"].to_pylist(), encode(texts), strict=True):
                    total += len(ids) // 4 + 1
                    block.append(frame(pack(doc, ids + end, width)))
                    index.append((doc or 0, at, len(block[-1])))
                    at += len(block[-1])
                out.write(b"".join(block))
        with system.open_output_stream(f"{root}/{path}.idx") as out:
            out.write(np.array(index, INDEX_ROW).tobytes())
        if index:
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([path]), pa.array([len(index)]), pa.array([total])], ["part", "path", "records", "ids"])

    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    count = partitions or int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    order = ("doc_id", F.xxhash64("text"))  # the hash cuts runs of one doc_id, too
    return slim.repartitionByRange(count, *order).sortWithinPartitions(*order).mapInArrow(run, "part int, path string, records long, ids long")


def read_records(parts: DataFrame, folder: str) -> DataFrame:
    """part, before (ids of earlier records of the part), doc_id, ids (unsigned 32-bit, in bytes) of every record of the parts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        system, root = _place(folder)
        for batch in batches:
            for part, path in zip(batch["part"].to_pylist(), batch["path"].to_pylist(), strict=True):
                rows: list[tuple] = []
                held = before = 0
                with system.open_input_stream(f"{root}/{path}.rec") as stream:
                    for payload in unframe(stream):
                        doc, ids = unpack(payload)
                        rows.append((part, before, doc, ids.tobytes()))
                        before += len(ids)
                        held += len(payload)
                        if held > 4_000_000:
                            yield _rows(rows)
                            rows, held = [], 0
                if rows:
                    yield _rows(rows)

    return parts.select("part", "path").mapInArrow(run, "part int, before long, doc_id long, ids binary")


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    kinds, names = [pa.int32(), pa.int64(), pa.int64(), pa.binary()], ["part", "before", "doc_id", "ids"]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)


def read_shuffled(folder: str, part: str, seed: int) -> Iterator[tuple[int | None, np.ndarray]]:
    """Records of one part in a seeded random order, each fetched by the index."""
    system, root = _place(folder)
    with system.open_input_stream(f"{root}/{part}.idx") as stream:
        index = np.frombuffer(stream.read(), INDEX_ROW)
    with system.open_input_file(f"{root}/{part}.rec") as source:
        for i in np.random.default_rng(seed).permutation(len(index)):
            source.seek(int(index["offset"][i]))
            yield unpack(next(unframe(pa.BufferReader(source.read(int(index["size"][i]))))))


def positions(spark: SparkSession, docs: DataFrame, folder: str, tokenizer: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every record, read back from the files written for docs.

    Starts are the ids of earlier parts (summed over one row for each part) and of earlier records of the part."""
    parts = materialize(write_records(docs, folder, tokenizer))
    earlier = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    base = parts.select(F.col("part").alias("p"), F.coalesce(F.sum("ids").over(earlier), F.lit(0)).alias("base"))
    back = read_records(parts.repartition(max(1, parts.count())), folder)
    back = back.select("part", "before", "doc_id", (F.octet_length("ids") / 4).cast("long").alias("n_tokens"), F.crc32("ids").alias("ids_crc32"))
    return back.join(F.broadcast(base), F.col("part") == F.col("p")).select("doc_id", (F.col("base") + F.col("before")).alias("start"), "n_tokens", "ids_crc32")


def query(spark, sf_dir: str) -> DataFrame:
    folder = f"{shared_folder(spark)}/records_{uuid.uuid4().hex}"
    return positions(spark, load(spark, sf_dir, "documents"), folder, vocabulary("byte_bpe_50k.json"))

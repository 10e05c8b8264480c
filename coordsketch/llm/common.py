"""Helpers shared by the text operators: shared-folder tables, bounded Arrow batches, rolling hashes."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Words are runs of bytes outside the six ASCII white-space characters.
WORD_SPACE = r"[\x20\x09-\x0D]+"
_OWN_FOLDER: dict[str, str] = {}


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share. Where the session names none, a temporary one in local mode, where there
    is one machine; on a cluster that is an error, as executors would write to their own disks."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not named:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        named = _OWN_FOLDER.setdefault("path", "file://" + tempfile.mkdtemp(prefix="coordsketch_"))
    return named.rstrip("/")


def fresh(columns: list[str], *names: str) -> list[str]:
    """names, changed so that none is one of columns."""
    taken = {c.lower() for c in columns}
    out = []
    for name in names:
        while name.lower() in taken:
            name = "_" + name
        taken.add(name.lower())
        out.append(name)
    return out


def materialize(df: DataFrame) -> DataFrame:
    """Writes df once to the shared folder and reads it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/stage_{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def row_key() -> object:
    """A key for (doc_id, text): equal for repeated rows, which then share their result, and different otherwise."""
    return F.xxhash64(F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), F.coalesce(F.col("text"), F.lit("")))


def slices(batches: Iterator[pa.RecordBatch], column: str, most_bytes: int = 4_000_000) -> Iterator[pa.RecordBatch]:
    """Cuts Arrow batches so that the texts of a piece hold most_bytes or a single row."""
    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = np.fromiter((0 if x is None else x for x in pc.binary_length(batch[column]).to_pylist()), np.int64, batch.num_rows)
        start, held = 0, 0
        for i, size in enumerate(sizes.tolist()):
            if held and held + size > most_bytes:
                yield batch.slice(start, i - start)
                start, held = i, 0
            held += size
        yield batch.slice(start)


def flat_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a text column as one array, with the start and length of each row (null: length 0)."""
    raw = [b"" if x is None else x for x in column.cast(pa.binary()).to_pylist()]
    lengths = np.fromiter(map(len, raw), np.int64, len(raw))
    starts = np.zeros(len(raw), np.int64)
    np.cumsum(lengths[:-1], out=starts[1:])
    return np.frombuffer(b"".join(raw), np.uint8), starts, lengths


_BASE = 0x9E3779B97F4A7C15
_UNBASE = pow(_BASE, -1, 1 << 64)
_POWERS: dict[int, np.ndarray] = {}


def _powers(base: int, n: int) -> np.ndarray:
    held = _POWERS.get(base)
    if held is None or len(held) < n:
        held = np.empty(n, np.uint64)
        held[0], k = 1, 1
        while k < n:
            m = min(k, n - k)
            held[k : k + m] = held[:m] * np.uint64(pow(base, k, 1 << 64))
            k += m
        _POWERS[base] = held
    return held[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


class RollingHash:
    """64-bit polynomial hashes of any slice of a byte array, by prefix sums modulo 2^64."""

    def __init__(self, data: np.ndarray):
        n = len(data)
        self._prefix = np.zeros(n + 1, np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * _powers(_BASE, max(n, 1))[:n], out=self._prefix[1:])
        self._back = _powers(_UNBASE, n + 1)

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self._prefix[end] - self._prefix[start]) * self._back[start])

    def windows(self, width: int) -> np.ndarray:
        return mix((self._prefix[width:] - self._prefix[:-width]) * self._back[: len(self._prefix) - width])


def ranges(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """start, start + 1, ... for each pair of start and count, concatenated."""
    ends = np.cumsum(counts)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(starts - (ends - counts), counts)

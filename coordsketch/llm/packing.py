"""Sum-of-squares online packing of tokenized documents into sequences of bounded length.

A level is a range of GRAIN fill sizes. For every level h the packer keeps N(h), the number of open sequences filled to it,
in one level array. A piece of s tokens goes to the level (or a new sequence) for which the sum of all N(h)^2 becomes
smallest; a sequence within GRAIN tokens of its length is closed. Documents longer than a sequence are cut into whole
sequences and a rest. Where MOST_OPEN sequences are open, none is begun: if no level has room, the piece is cut at the end of a
sequence of the level whose closing makes the sum smallest, and its rest is placed by the same rule. So at most MOST_OPEN
sequences and their ids are held, whatever the lengths.

Every task packs its own partition online, in row order. At the end, the pieces of open sequences are placed again by the same
rule with at most LAST_OPEN open sequences, so that many of a partition stay badly filled.

Defined cases: a null text is an empty one and has only its end id; repeated rows are packed as often as they stand;
an empty table gives an empty result; texts of any length are cut, never truncated. Extra columns are ignored.
"""

from __future__ import annotations

from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import load, slices
from .tokens import encoder, vocabulary

LENGTH, END_ID = 4096, 2
#: Fill sizes to a level; open sequences of a task, and at the end of its partition.
GRAIN, MOST_OPEN, LAST_OPEN = 64, 256, 2

_SCHEMA = "doc_id long, start long, length long, ids binary, doc_tokens long, sequence_id long, offset long"


class LevelArray:
    """Open sequences by fill level, and the sum-of-squares rule."""

    def __init__(self, capacity: int, grain: int = GRAIN, most_open: int = MOST_OPEN, first: int = 0):
        self.capacity, self.grain, self.most_open = capacity, min(grain, max(1, capacity // 64)), most_open
        self.counts = [0] * (capacity // self.grain + 2)
        self.open: list[list[tuple[int, int]]] = [[] for _ in self.counts]  # of each level: (fill, sequence), in ascending order
        self.next, self.live = first, 0

    def level(self, fill: int) -> int:
        """Closed sequences and new ones have the level 0."""
        return 0 if fill == 0 or fill > self.capacity - self.grain else fill // self.grain + 1

    def _change(self, old: int, new: int) -> int:
        """By how much the sum of squares grows if a sequence goes from one level to another."""
        if old == new:
            return 0
        return (1 - 2 * self.counts[old] if old else 0) + (1 + 2 * self.counts[new] if new else 0)

    def place(self, size: int) -> tuple[int, int, int]:
        """(sequence number, fill before, tokens taken) for an item of 1 to capacity tokens; all are taken, unless it had to be cut."""
        full = self.live >= self.most_open
        best, at, cut = (self._change(0, self.level(size)), 0, False) if not full else (None, 0, False)
        for h in range(len(self.open) - 1, 0, -1):  # ties: the fullest
            if self.open[h]:
                i = bisect_left(self.open[h], (self.capacity - size + 1, 0)) - 1  # the fullest with room
                if i >= 0:
                    change = self._change(h, self.level(self.open[h][i][0] + size))
                    if best is None or cut or change < best or (change == best and not at):
                        best, at, cut = change, h, False
                elif full and (best is None or cut) and (best is None or self._change(h, 0) < best):
                    best, at, cut = self._change(h, 0), h, True
        if not at:
            sequence, fill, self.next = self.next, 0, self.next + 1
        else:
            i = len(self.open[at]) - 1 if cut else bisect_left(self.open[at], (self.capacity - size + 1, 0)) - 1
            fill, sequence = self.open[at].pop(i)
            self.counts[at] -= 1
            self.live -= 1
        taken = min(size, self.capacity - fill)
        h = self.level(fill + taken)
        if h:
            insort(self.open[h], (fill + taken, sequence))
            self.counts[h] += 1
            self.live += 1
        return sequence, fill, taken


class Packer:
    """Places pieces (doc, start, ids, tokens of the document) and gives back those of closed sequences."""

    def __init__(self, length: int):
        self.levels = LevelArray(length)
        self.waiting: dict[int, list[tuple]] = {}  # pieces of open sequences

    def put(self, doc, start: int, ids: bytes, total: int) -> Iterator[tuple]:
        """Rows doc, start, length, ids, doc_tokens, sequence, offset of the sequences that this piece closes."""
        while ids:
            sequence, fill, taken = self.levels.place(len(ids) // 4)
            piece = (doc, start, taken, ids[: 4 * taken], total, sequence, fill)
            if self.levels.level(fill + taken):
                self.waiting.setdefault(sequence, []).append(piece)
            else:
                yield from self.waiting.pop(sequence, ())
                yield piece
            start, ids = start + taken, ids[4 * taken :]

    def rest(self, most_open: int = LAST_OPEN) -> Iterator[tuple]:
        """All other rows: the open sequences' pieces, placed again with at most most_open open sequences."""
        held, self.waiting = self.waiting, {}
        self.levels = LevelArray(self.levels.capacity, most_open=most_open, first=self.levels.next)
        for sequence in sorted(held):
            for doc, start, _, ids, total, _, _ in held[sequence]:
                yield from self.put(doc, start, ids, total)
        for pieces in self.waiting.values():
            yield from pieces


def packed(docs: DataFrame, tokenizer: str, length: int = LENGTH, end_id: int = END_ID) -> DataFrame:
    """One row for each piece: doc_id, start, length, ids, doc_tokens, sequence_id, offset. tokenizer: a file's path."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        base, encode = TaskContext.get().partitionId() << 32, encoder(tokenizer).encode
        packer, end = Packer(length), np.array([end_id], "<u4").tobytes()
        ready: list[tuple] = []
        for part in slices(batches, "text", 1_000_000):
            texts = [x or "" for x in part["text"].to_pylist()]
            for doc, ids in zip(part["doc_id"].to_pylist(), encode(texts), strict=True):
                ids += end
                total = len(ids) // 4
                for at in range(0, total, length):
                    ready.extend(packer.put(doc, at, ids[4 * at : 4 * (at + length)], total))
            if ready:
                yield _batch(ready, base)
                ready = []
        ready.extend(packer.rest())
        for at in range(0, len(ready), 4096):
            yield _batch(ready[at : at + 4096], base)

    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return slim.mapInArrow(run, _SCHEMA)


def _batch(rows: list[tuple], base: int) -> pa.RecordBatch:
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.int64(), pa.int64()]
    names = ["doc_id", "start", "length", "ids", "doc_tokens", "sequence_id", "offset"]
    columns = list(zip(*rows, strict=True))
    columns[5] = [base + s for s in columns[5]]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names)


def with_checksums(pieces: DataFrame) -> DataFrame:
    """Pieces with the unsigned CRC-32 of their ids in place of the ids."""
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


def query(spark, sf_dir: str) -> DataFrame:
    return with_checksums(packed(load(spark, sf_dir, "documents"), vocabulary("word_bpe_49k.json")))


"""Benchmark decontamination by template windows.

Texts become sequences of tokens: runs of letters, lower-cased, single Chinese or Japanese characters, and numbers. In the
plain view numbers, and units right after numbers, are typed placeholders; in the name view, capitalised words are
placeholders as well, but where a sentence begins only those that the benchmark never writes in lower case. In the exact
view every token stands for itself, which finds items that are nearly all numbers.
Windows of five tokens of the benchmark items are hashed, and every document's windows are looked up in them. An item is
found in a document if at least 0.8 of its windows are, in any view, in their order and at one place (with insertions of
at most a quarter of the item's tokens, or SLACK), and if its slots are filled consistently there: each value that stands in slots of
the item is replaced by one value throughout, and different values stay different. Equal
values mean a copied item, others a re-parameterised one. A window with under three literal tokens is no evidence but in
the exact view.

The benchmark's windows are broadcast in blocks of bounded size; a larger benchmark takes more passes over the documents.

Defined cases: null and short texts hold no windows and are clean; an item with fewer than five tokens is one window of
its own length, and found only if at least three of its tokens, or all, are literal; repeated rows and repeated items give repeated rows; empty
tables give an empty result. Long texts are read whole. Extra columns are ignored.
"""

from __future__ import annotations

from bisect import bisect_left
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import RollingHash, flat_bytes, load, mix, slices

WIDTH, SHARE, LEAST_LITERALS = 5, 0.8, 3
#: Tokens by which a run of windows may always be shifted by insertions or deletions.
SLACK = 8
#: Fixed units, in lower case.
UNITS = "mm cm m km in ft yd mi mg g kg t lb oz ml l gal s sec min h hr hrs hour hours day days week weeks month months year years km/h mph kph k c f hz kb mb gb tb eur euro euros usd dollar dollars cent cents pound pounds percent degrees meter meters metre metres mile miles liter liters litre litres gram grams second seconds minute minutes".split()
#: Tokens of benchmark text in one broadcast block.
BLOCK_TOKENS = 2_000_000
_NUMBER, _UNIT, _NAME = (np.uint64(x) for x in (0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3))
_STEP = np.uint64(0x9E3779B97F4A7C15)


class Tokens:
    """The tokens of a text column: bytes (lower case), start, end, owner, and the hashes of the views.

    known: sorted hashes of words that are no names where a sentence begins; else those of the column itself."""

    def __init__(self, column: pa.Array, known: np.ndarray | None = None):
        data, starts, lengths = flat_bytes(column)
        upper = (data >= 65) & (data <= 90)
        after = np.zeros(len(data), bool)
        after[1:] = data[:-1] == 0xC3
        upper |= after & (data >= 0x80) & (data <= 0x9E) & (data != 0x97)
        low = np.where(upper, data + 32, data).astype(np.uint8)
        self.low = low
        letter = ((low >= 97) & (low <= 122)) | (data >= 0x80)
        digit = (data >= 48) & (data <= 57)
        point = np.zeros(len(data), bool)
        if len(data) > 2:
            point[1:-1] = ((data[1:-1] == 46) | (data[1:-1] == 44)) & digit[:-2] & digit[2:]
        kind = letter.astype(np.int8) + 2 * (digit | point).astype(np.int8)
        single = _classify(data, kind)
        border = np.ones(len(data) + 1, bool)
        border[1:-1] = kind[1:] != kind[:-1]
        border[single] = border[single + np.where(data[single] >= 0xF0, 4, 3)] = True
        border[np.minimum(starts, len(data))] = True
        edges = np.flatnonzero(border)
        keep = kind[edges[:-1]] > 0 if len(data) else np.zeros(0, bool)
        self.start, self.end = edges[:-1][keep], edges[1:][keep]
        self.owner = np.searchsorted(starts + lengths, self.start, "right")
        number = kind[self.start] == 2 if len(data) else np.zeros(0, bool)
        hashes = RollingHash(low).of(self.start, self.end) if len(self.start) else np.zeros(0, np.uint64)
        follows = np.zeros(len(hashes), bool)
        if len(hashes):
            follows[1:] = number[:-1] & (self.owner[1:] == self.owner[:-1]) & (self.start[1:] - self.end[:-1] <= 1)
        unit = follows & np.isin(hashes, _unit_hashes())
        self.exact = hashes
        self.plain = np.where(number, _NUMBER, np.where(unit, _UNIT, hashes))
        # a name: upper case, then lower case, and no sentence begins there with a known word
        lead = self.start + after[np.minimum(self.start + 1, max(len(data) - 1, 0))] if len(data) else self.start
        second = np.minimum(lead + 1, max(len(data) - 1, 0))
        title = upper[lead] & ~upper[second] & letter[second] & (second < self.end) if len(data) else np.zeros(0, bool)
        opening = np.ones(len(hashes), bool)
        if len(hashes):
            gap = np.zeros(len(data) + 1, np.int64)
            np.cumsum((data == 46) | (data == 33) | (data == 63) | (data == 10), out=gap[1:])
            opening[1:] = (gap[self.start[1:]] > gap[self.end[:-1]]) | (self.owner[1:] != self.owner[:-1])
        if known is None:
            known = np.unique(hashes[~upper[lead] & ~number]) if len(data) else hashes
        self.known = known
        if len(known):
            opening &= known[np.minimum(np.searchsorted(known, hashes), len(known) - 1)] == hashes
        else:
            opening[:] = False
        self.named = np.where(title & ~opening & ~number & ~unit, _NAME, self.plain)

    def text(self, i: int) -> bytes:
        return self.low[self.start[i] : self.end[i]].tobytes()

    def windows(self, view: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
        """First tokens and hashes of the windows inside one text with enough literal tokens."""
        n = len(view) - width + 1
        if n <= 0:
            return np.zeros(0, np.int64), np.zeros(0, np.uint64)
        first = np.flatnonzero(self.owner[:n] == self.owner[width - 1 :])
        if view is not self.exact or width < WIDTH:
            least = self.plain if view is self.exact else view
            literal = np.concatenate([[0], np.cumsum((least != _NUMBER) & (least != _UNIT) & (least != _NAME))])
            first = first[literal[first + width] - literal[first] >= min(LEAST_LITERALS, width)]
        value = np.zeros(len(first), np.uint64)
        for i in range(width):
            value = value * _STEP + view[first + i]
        return first, mix(value + np.uint64(width))


def _classify(data: np.ndarray, kind: np.ndarray) -> np.ndarray:
    """Corrects kind for characters beyond ASCII: punctuation and symbols are 0, wide digits 2. First bytes of the
    characters that are words of their own (Chinese ideographs and Japanese syllables)."""
    found = []
    for least, most, size in ((0xC2, 0xDF, 2), (0xE0, 0xEF, 3), (0xF0, 0xF4, 4)):
        at = np.flatnonzero((data >= least) & (data <= most))
        if not len(at):
            continue
        code = data[at].astype(np.int64) & (0x1F >> (size - 2))
        for i in range(1, size):
            code = code << 6 | (data[at + i] & 63)
        between = lambda *spans: np.any([(code >= a) & (code <= b) for a, b in spans], axis=0)  # noqa: B023, E731
        signs = between((0xA0, 0xA9), (0xAB, 0xB4), (0xB6, 0xB9), (0xBB, 0xBF), (0xD7, 0xD7), (0xF7, 0xF7), (0x2000, 0x206F), (0x2190, 0x2BFF), (0x3000, 0x3004), (0x3008, 0x3020), (0x3030, 0x3030), (0x30FB, 0x30FB), (0xFE10, 0xFE6F), (0xFF01, 0xFF0F), (0xFF1A, 0xFF20), (0xFF3B, 0xFF40), (0xFF5B, 0xFF65))
        digits = between((0xFF10, 0xFF19))
        for i in range(size):
            kind[at[signs] + i] = 0
            kind[at[digits] + i] = 2
        if size > 2:
            found.append(at[between((0x3005, 0x3007), (0x3041, 0x30FA), (0x30FC, 0x30FF), (0x3400, 0x4DBF), (0x4E00, 0x9FFF), (0xF900, 0xFAFF), (0xFF66, 0xFF9D), (0x20000, 0x3FFFF))])
    return np.concatenate(found) if found else np.zeros(0, np.int64)


_HELD: list[np.ndarray] = []


def _unit_hashes() -> np.ndarray:
    if not _HELD:
        raw = np.frombuffer("".join(UNITS).encode(), np.uint8)
        sizes = np.array([len(u) for u in UNITS])
        ends = np.cumsum(sizes)
        _HELD.append(RollingHash(raw).of(ends - sizes, ends))
    return _HELD[0]


class Index:
    """The windows of a block of benchmark items."""

    def __init__(self, items: list[tuple[int | None, str | None]]):
        self.ids = [i for i, _ in items]
        self.tokens = Tokens(pa.array([t or "" for _, t in items], pa.string()))
        sizes = np.bincount(self.tokens.owner, minlength=len(items))
        self.views = {}
        for name in ("plain", "named", "exact"):
            entries = []
            for width in sorted({min(WIDTH, int(s)) for s in sizes if s}):
                first, value = self.tokens.windows(getattr(self.tokens, name), width)
                own = np.minimum(WIDTH, sizes[self.tokens.owner[first]]) == width
                entries.append((width, first[own], value[own]))
            first, value = (np.concatenate([e[i] for e in entries]) if entries else np.zeros(0, np.int64) for i in (1, 2))
            order = np.argsort(value, kind="stable")
            totals = np.bincount(self.tokens.owner[first], minlength=len(items)) if len(first) else np.zeros(len(items), int)
            self.views[name] = (sorted({e[0] for e in entries}), value[order], first[order], totals)

    def search(self, docs: Tokens) -> Iterator[tuple[int, int, float, str]]:
        """(document row, item row, share of the item's windows, copied or changed) for items found in documents."""
        found: dict[tuple[int, int], tuple[float, str]] = {}
        for name, (widths, values, first, totals) in self.views.items():
            for width in widths:
                at, value = docs.windows(getattr(docs, name), width)
                left, right = np.searchsorted(values, value, "left"), np.searchsorted(values, value, "right")
                hits = np.flatnonzero(right > left)
                pairs: dict[tuple[int, int], list[tuple[int, int]]] = defaultdict(list)
                for h in hits.tolist():
                    for j in first[left[h] : right[h]].tolist():
                        pairs[int(docs.owner[at[h]]), int(self.tokens.owner[j])].append((int(at[h]), j))
                for key, hit in pairs.items():
                    if len({j for _, j in hit}) / totals[key[1]] >= SHARE:
                        share, kind = self._consistent(docs, hit, name, width, totals[key[1]])
                        if kind and share > found.get(key, (0.0, ""))[0]:
                            found[key] = (share, kind)
        for (doc, item), (share, kind) in sorted(found.items()):
            yield doc, item, share, kind

    def _consistent(self, docs: Tokens, hit: list[tuple[int, int]], name: str, width: int, total: int) -> tuple[float, str]:
        """The share of the item's windows, and copied, changed, or nothing if no alignment with a sufficient share fills the slots with one value each.

        A document may hold an item many times, with other values each time, so hits are judged by their alignment: one shift
        between document and item by itself, or with windows it lacks taken from the nearest other shifts (insertions), as far
        as these are near and the windows stay in the item's order. Share and slots are judged within the same alignment."""
        view = getattr(self.tokens, name)
        by_shift: dict[int, set[int]] = defaultdict(set)
        for d, j in hit:
            by_shift[d - j].add(j)
        places: dict[int, list[int]] = defaultdict(list)
        for s in sorted(by_shift):
            for j in by_shift[s]:
                places[j].append(s)

        def nearest(s: int, held: list[int]) -> int:
            i = bisect_left(held, s)
            return min(held[max(i - 1, 0) : i + 1], key=lambda x: abs(x - s))

        item = self.tokens.owner[hit[0][1]]
        size = int(np.searchsorted(self.tokens.owner, item, "right") - np.searchsorted(self.tokens.owner, item, "left"))
        slack = max(SLACK, size // 4)

        def run(s: int) -> tuple[tuple[int, int], ...]:
            near = [(t + j, j) for j in sorted(places) for t in (nearest(s, places[j]),) if abs(t - s) <= slack]
            return tuple(_rising(near))

        need, best, most = SHARE * total - 1e-9, "", 0
        tried = {tuple((s + j, j) for j in sorted(own)) for s, own in by_shift.items() if len(own) >= need}
        if len(places) >= need:
            tried |= {group for s, own in by_shift.items() if len(own) < need for group in (run(s),) if len(group) >= need}
        for group in sorted(tried):
            forward: dict[bytes, bytes] = {}
            back: dict[bytes, bytes] = {}
            good = same = True
            for d, j in group:
                for i in range(width):
                    if view[j + i] in (_NUMBER, _UNIT, _NAME):
                        a, b = self.tokens.text(j + i), docs.text(d + i)
                        good &= forward.setdefault(a, b) == b and back.setdefault(b, a) == a
                        same &= a == b
            if name == "exact":  # its windows are equal; the numbers between them have to be filled consistently
                same = good = self._filled(docs, group)
            if (good or same) and len(group) > most:
                best, most = "copied" if same else "changed", len(group)
        return most / total, best


    def _filled(self, docs: Tokens, group: tuple[tuple[int, int], ...]) -> bool:
        """Whether all numbers of the item that have a number at their place in the document have one value each there."""
        (d, j), *_ = group
        item, doc = self.tokens.owner[j], docs.owner[d]
        start, end = np.searchsorted(self.tokens.owner, item, "left"), np.searchsorted(self.tokens.owner, item, "right")
        forward: dict[bytes, bytes] = {}
        back: dict[bytes, bytes] = {}
        known = dict((j, d - j) for d, j in group)
        shift = d - j
        for j in range(start, end):
            shift = known.get(j, shift)
            if self.tokens.plain[j] == _NUMBER and 0 <= j + shift < len(docs.plain) and docs.owner[j + shift] == doc and docs.plain[j + shift] == _NUMBER:
                a, b = self.tokens.text(j), docs.text(j + shift)
                if forward.setdefault(a, b) != b or back.setdefault(b, a) != a:
                    return False
        return True


def _rising(hits: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The longest part of hits (d, j), given by rising j, in which d rises as well."""
    ends: list[int] = []
    last: list[int] = []  # index of the hit that ends the best run of each length
    before = []
    for i, (d, _) in enumerate(hits):
        n = bisect_left(ends, d)
        before.append(last[n - 1] if n else -1)
        ends[n : n + 1] = [d]
        last[n : n + 1] = [i]
    out, i = [], last[-1] if last else -1
    while i >= 0:
        out.append(hits[i])
        i = before[i]
    return out[::-1]


def _blocks(benchmark: DataFrame) -> Iterator[list[tuple]]:
    block: list[tuple] = []
    size = 0
    for row in benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).toLocalIterator():
        block.append(tuple(row))
        size += len(row["text"] or "") // 4 + 1
        if size > BLOCK_TOKENS:
            yield block
            block, size = [], 0
    yield block


def leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, item_id, share, kind (copied or changed) for every benchmark item found in a document."""
    spark = docs.sparkSession
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    whole = None
    for block in _blocks(benchmark):
        sent = spark.sparkContext.broadcast(block)

        def run(batches: Iterator[pa.RecordBatch], sent=sent) -> Iterator[pa.RecordBatch]:
            index = None
            for piece in slices(batches, "text", 1_000_000):
                index = index or Index(sent.value)
                doc_ids = piece["doc_id"].to_pylist()
                rows = [(doc_ids[d], index.ids[i], float(share), kind) for d, i, share, kind in index.search(Tokens(piece["text"], index.tokens.known))]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.float64(), pa.string()), strict=True)], ["doc_id", "item_id", "share", "kind"])

        found = slim.mapInArrow(run, "doc_id long, item_id long, share double, kind string")
        whole = found if whole is None else whole.unionByName(found)
    return whole


def query(spark, sf_dir: str) -> DataFrame:
    return leaks(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark"))

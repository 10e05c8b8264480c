"""Pairs of sets that share many keys: an exact join of ranges of sets, whose partial counts never leave a task.

Sets are ordered by `place` and cut into ranges; a task holds the sets of one range and those of the ranges before it that can be
partners, so that most pairs of ranges never meet. Of each pair the first set asks: with the keys of all sets in one order, rare
ones first, the first `meets` common keys of a pair are among the first keys of either set, as many as it may miss and `meets` more.
How many it may miss depends on the other set's size, so a key asks fewer sets the less rare it is among the keys of its set.
Pairs that meet so often are counted in full. Equal sets are looked at once, and pairs of them are written out at the end.
Keys are 32-bit hashes within a task; sets that hold a key whose hash is not its own are told apart (`sure`), for callers to recount.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.lineage import stored

#: Keys and sets of a range, on average; the least number of ranges; keys of partners in a task; lookups that are counted at a time, and cells for them.
BLOCK_KEYS, BLOCK_SETS, LEAST_BLOCKS, PARTNER_KEYS, LOOKUPS, CELLS = 8_000_000, 65_536, 12, 24_000_000, 1_000_000, 1 << 32
#: Cells for the counts by which keys are ordered; bits of a set's signature.
CELL_BITS, BITS = 20, 512
COUNTS = 1 << CELL_BITS


@dataclass(frozen=True)
class Rule:
    """What a pair needs: a set with n keys and a partner with b that can count, min(cap, max(share * n, part * (n + b))) common ones."""

    share: float
    part: float = 0.0
    cap: float = math.inf

    def need(self, n: np.ndarray, b: np.ndarray) -> np.ndarray:
        return np.ceil(np.minimum(self.cap, np.maximum(self.share * n, self.part * (n + b))) - 1e-9).astype(np.int64)


@dataclass
class Sets:
    """Sets in flat arrays: unique hashes of keys, rare ones first; `whole` is the number of keys. Of each pair, the set with the lower `turn` asks."""

    flat: np.ndarray
    start: np.ndarray
    size: np.ndarray
    whole: np.ndarray
    turn: np.ndarray

    def take(self, i: np.ndarray) -> Sets:
        return Sets(self.flat, self.start[i], self.size[i], self.whole[i], self.turn[i])

    def keys(self, i: np.ndarray) -> np.ndarray:
        return self.flat[_ranges(self.start[i], self.size[i])]


def _ranges(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    ends = np.cumsum(counts)
    return np.arange(ends[-1] if len(ends) else 0) + np.repeat(starts - (ends - counts), counts)


def _stretches(work: np.ndarray, most: int, rows: int) -> Iterator[tuple[int, int]]:
    """Stretches of rows, of work at most `most` or one row, and of at most so many rows."""
    total, a = np.concatenate([[0], np.cumsum(work)]), 0
    while a < len(work):
        b = max(a + 1, min(a + rows, int(np.searchsorted(total, total[a] + most, "right")) - 1))
        yield a, b
        a = b


def _shared(left: Sets, right: Sets, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """The number of hashes that the sets x of left and y of right have in common, for every pair."""
    out = np.empty(len(x), np.int64)
    for a, b in _stretches(left.size[x] + right.size[y], LOOKUPS // 4, LOOKUPS):
        i, j = x[a:b], y[a:b]
        pair = np.concatenate([np.repeat(np.arange(b - a), left.size[i]), np.repeat(np.arange(b - a), right.size[j])]).astype(np.uint64)
        held = (pair << np.uint64(32)) | np.concatenate([left.keys(i), right.keys(j)])
        held.sort()
        out[a:b] = np.bincount((held[1:][held[1:] == held[:-1]] >> np.uint64(32)).astype(np.int64), minlength=b - a)
    return out


def _signatures(sets: Sets) -> np.ndarray:
    """The parities of the hashes in so many cells: sets differ in at least as many hashes as they do in parities."""
    out = np.empty((len(sets.size), BITS // 64), np.uint64)
    for a, b in _stretches(sets.size, LOOKUPS // 4, 2048):
        i = np.arange(a, b)
        mixed = (sets.keys(i) * np.uint32(2654435769)) >> np.uint32(32 - int(math.log2(BITS)))
        odd = np.bincount(np.repeat(i - a, sets.size[a:b]) * BITS + mixed, minlength=(b - a) * BITS).astype(np.uint8) & 1
        out[a:b] = np.packbits(odd.reshape(b - a, BITS), axis=1).view(np.uint64)
    return out


def _meets(left: Sets, right: Sets, b: np.ndarray, rule: Rule, most: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Indices of pairs of a set of left and one of right with a higher turn that may share as many hashes as the rule needs. b: the least
    number of keys of each set of right that can count; those with over `most` times the keys of a set of left are no partners of it."""
    fewest = int(left.whole.min())
    off = int((left.whole - left.size).max())  # equal hashes within a set count once
    least = np.maximum(rule.need(left.whole, np.zeros(1) + b.min()) - (left.whole - left.size), 1)
    meets = max(1, min(int(least.min()), max(2, fewest // 20)))
    order = np.argsort(b, kind="stable")
    right, b = right.take(order), b[order]
    first = np.clip(right.size - np.maximum(rule.need(np.full(1, fewest), b) - off, 1) + meets, 0, right.size)
    posting = np.empty(int(first.sum()), np.uint64)
    ends = np.cumsum(first)
    for u, v in _stretches(first, LOOKUPS, len(first)):
        mine = np.repeat(np.arange(u, v, dtype=np.uint64), first[u:v])
        posting[ends[u] - first[u] : ends[v - 1]] = (right.flat[_ranges(right.start[u:v], first[u:v])].astype(np.uint64) << np.uint64(32)) | mine
    posting.sort()
    at = np.flatnonzero(np.append(True, (posting[1:] ^ posting[:-1]) >> np.uint64(32) > 0)[: len(posting)])
    names = (posting[at] >> np.uint64(32)).astype(np.uint32)
    if not len(names):
        return
    ends = np.append(at[1:], len(posting))
    total = len(b)
    open_turn = left.turn.max() < right.turn.min()
    asks = np.clip(left.size - least + meets, 0, left.size)
    for u, v in _stretches(asks, LOOKUPS // 4, len(asks)):
        owner = np.repeat(np.arange(u, v), asks[u:v])
        ask = left.flat[_ranges(left.start[u:v], asks[u:v])]
        spare = left.size[owner] - (np.arange(len(owner)) - np.repeat(np.cumsum(asks[u:v]) - asks[u:v], asks[u:v])) + meets - 1 + (left.whole - left.size)[owner]
        name = np.minimum(np.searchsorted(names, ask), len(names) - 1)
        held = np.flatnonzero(names[name] == ask)
        owner, spare, name, ask = owner[held], spare[held], name[held], ask[held]
        limit = most * left.whole[owner] + 1e-9
        if rule.part:
            limit = np.minimum(limit, np.where(spare >= rule.cap, np.inf, spare / rule.part - left.whole[owner] + 1e-6))
        upper = np.searchsorted(b, limit, "right")
        begin, end = at[name], ends[name]
        few = np.flatnonzero(upper < total)
        end[few] = np.searchsorted(posting, (ask[few].astype(np.uint64) << np.uint64(32)) | upper[few].astype(np.uint64))
        count = end - begin
        edge = np.searchsorted(owner, np.arange(u, v + 1))
        sums = np.concatenate([[0], np.cumsum(count)])
        for p, q in _stretches(sums[edge[1:]] - sums[edge[:-1]], LOOKUPS, max(1, CELLS // total - 1)):
            i = slice(edge[p], edge[q])
            if sums[edge[q]] - sums[edge[p]] < meets:
                continue
            other = posting[_ranges(begin[i], count[i])].astype(np.uint32)
            asker = np.repeat((owner[i] - (u + p)).astype(np.uint32), count[i])
            if not open_turn:
                later = right.turn[other] > left.turn[u + p : u + q][asker]
                other, asker = other[later], asker[later]
            cell = asker * np.uint32(total) + other
            cell.sort()
            if len(cell) < meets:
                continue
            cell = cell[meets - 1 :][cell[meets - 1 :] == cell[: len(cell) - meets + 1]]
            if len(cell):
                cell = cell[np.append(True, cell[1:] != cell[:-1])].astype(np.int64)
                yield u + p + cell // total, order[cell % total]


def _found(left: Sets, right: Sets, b: np.ndarray, rule: Rule, most: float = math.inf) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Indices of the pairs of _meets that do share as many hashes, and how many."""
    marks = _signatures(left), _signatures(right)
    found = [(np.zeros(0, np.int64),) * 3]
    at_once = max(1, LOOKUPS // 16)
    for x, y in ((x[i : i + at_once], y[i : i + at_once]) for x, y in _meets(left, right, b, rule, most) for i in range(0, len(x), at_once)):
        least = np.maximum(rule.need(left.whole[x], b[y]) - (left.whole - left.size)[x], 1)
        near = np.bitwise_count(marks[0][x] ^ marks[1][y]).sum(1, dtype=np.int64) <= left.size[x] + right.size[y] - 2 * least
        x, y, least = x[near], y[near], least[near]
        both = _shared(left, right, x, y)
        kept = both >= least
        found.append((x[kept], y[kept], both[kept]))
    return tuple(np.concatenate(c) for c in zip(*found, strict=True))


def pairs_of(keys: list[np.ndarray], place: np.ndarray, block: np.ndarray, need: float, ratio: float) -> tuple[np.ndarray, np.ndarray]:
    """Indices of the pairs of sets, of unlike blocks where there are two, that share at least need * (size of the one that is first by
    place) keys. ratio > 0: place is the size, and the larger set has at most ratio times the size of the other one."""
    whole = np.fromiter(map(len, keys), np.int64, len(keys))
    keys = [np.unique(k) for k in keys]
    size = np.fromiter(map(len, keys), np.int64, len(keys))
    _, code, df = np.unique(np.concatenate(keys), return_inverse=True, return_counts=True)
    code = np.argsort(np.argsort(df, kind="stable"), kind="stable")[code]  # rare keys first
    flat = code[np.lexsort((code, np.repeat(np.arange(len(keys)), size)))].astype(np.uint32)
    turn = np.empty(len(keys), np.int64)
    turn[np.argsort(place, kind="stable")] = np.arange(len(keys))
    sets = Sets(flat, np.cumsum(size) - size, size, whole, turn)
    sides = [np.flatnonzero(block == s) for s in np.unique(block).tolist()]
    met = [(np.zeros(0, np.int64),) * 2]
    for i, j in zip(sides, sides[::-1], strict=True):
        x, y, _ = _found(sets.take(i), sets.take(j), place[j] if ratio else whole[j], Rule(need), ratio or math.inf)
        met.append((i[x], j[y]))
    return tuple(np.concatenate(c) for c in zip(*met, strict=True))


def _listed(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Values and offsets of lists."""
    held = column.combine_chunks()
    held = pa.concat_arrays(held.chunks) if isinstance(held, pa.ChunkedArray) else held
    edges = held.offsets.to_numpy()
    return held.values.to_numpy()[: edges[-1]], edges


def _joined(parts: list[np.ndarray]) -> np.ndarray:
    """parts in one array; each of them is dropped when it is copied."""
    out, a = np.empty(sum(map(len, parts)), parts[0].dtype), 0
    parts.reverse()
    while parts:
        part = parts.pop()
        out[a : a + len(part)] = part
        a += len(part)
    return out


def _prepared(sets: DataFrame) -> DataFrame:
    """sets with `of` as unique 32-bit numbers of hashes, in order, those of rare keys first, and `odd`, whether one of them is the hash of two keys."""
    low = F.col("key").bitwiseAND(F.lit(0xFFFFFFFF))
    names = sets.select(F.explode("of").alias("key")).groupBy(low.alias("h")).agg(F.count(F.lit(1)).alias("n"), F.min("key").alias("x"), F.max("key").alias("y"))
    cells = names.groupBy(F.pmod("h", F.lit(COUNTS)).cast("int").alias("cell")).agg(F.max("n").alias("n"), F.flatten(F.collect_list(F.when(F.col("x") != F.col("y"), F.array("h")))).alias("twice"))
    table = cells.toArrow()
    counts = np.zeros(COUNTS, np.int64)
    counts[table["cell"].to_numpy()] = table["n"].to_numpy()
    order = np.empty(COUNTS, np.uint32)
    order[np.argsort(counts, kind="stable")] = np.arange(COUNTS, dtype=np.uint32)

    def code(order: np.ndarray, hashes: np.ndarray) -> np.ndarray:
        """The place of a hash's cell, and the rest of the hash: as many numbers as hashes, those of rare keys first."""
        return (order[hashes & np.uint32(COUNTS - 1)] << np.uint32(32 - CELL_BITS)) | (hashes >> np.uint32(CELL_BITS))

    twice = code(order, _listed(table["twice"])[0].astype(np.uint32))
    shared = sets.sparkSession.sparkContext.broadcast((order, twice))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        order, twice = shared.value
        for batch in batches:
            if not batch.num_rows:
                continue
            values, edges = _listed(pa.chunked_array([batch.column("of")]))
            held = np.repeat(np.arange(batch.num_rows, dtype=np.uint64) << np.uint64(32), np.diff(edges))
            held |= code(order, values[edges[0] :].astype(np.uint32))
            held.sort()
            held = held[np.append(True, held[1:] != held[:-1])[: len(held)]]
            flat, owner = held.astype(np.uint32), (held >> np.uint64(32)).astype(np.int64)
            odd = np.zeros(batch.num_rows, bool)
            if len(twice):
                odd[owner[np.isin(flat, twice)]] = True
            ends = np.append(0, np.cumsum(np.bincount(owner, minlength=batch.num_rows))).astype(np.int32)
            of = pa.ListArray.from_arrays(pa.array(ends), pa.array(flat.view(np.int32)))
            held = {n: batch.column(n) for n in batch.schema.names} | {"of": of, "odd": pa.array(odd)}
            yield pa.RecordBatch.from_arrays(list(held.values()), names=list(held))

    kinds = [f"{n} {'array<int>' if n == 'of' else t}" for n, t in sets.dtypes]
    return sets.mapInArrow(run, ", ".join([*kinds, "odd boolean"]))


def _equal_sets(of: Column) -> Column:
    """A number that equal sets have in common. of: 64-bit hashes of keys, each key once."""
    return F.aggregate(of, F.lit(0).cast("long"), lambda a, x: a.bitwiseXOR(x))


def _members(sets: DataFrame) -> DataFrame:
    """rep, set_id: for each set the first one that equals it."""
    same = sets.groupBy("like", "whole", "place").agg(F.collect_list("set_id").alias("ids"))
    return same.select(F.array_min("ids").alias("rep"), F.explode("ids").alias("set_id"))


def _plan(sets: DataFrame) -> list[dict]:
    """Ranges of place in order: first and last place, first bin, and the least `since`; parts of their sets and of their partners."""
    rows = sets.groupBy("bin").agg(F.count(F.lit(1)).alias("n"), F.sum("whole").alias("keys"), F.min("place").alias("first"), F.max("place").alias("last"), F.min("since").alias("since")).orderBy("bin").collect()
    n, keys = sum(r["n"] for r in rows), sum(r["keys"] for r in rows)
    blocks = max(LEAST_BLOCKS, math.ceil(n / BLOCK_SETS), math.ceil(keys / BLOCK_KEYS))
    found: list[dict] = []
    for r in rows:
        work = (r["n"] / max(n, 1) + r["keys"] / max(keys, 1)) / 2 * blocks
        if found and found[-1]["work"] + work <= 1:
            x = found[-1]
            x |= {"work": x["work"] + work, "n": x["n"] + r["n"], "keys": x["keys"] + r["keys"], "last": r["last"], "since": min(x["since"], r["since"])}
        else:
            found.append(r.asDict() | {"work": work})
    tasks = 0
    for j, x in enumerate(found):
        partners = sum(y["keys"] for y in found[: j + 1] if y["last"] >= x["since"])
        x |= {"parts": math.ceil(x["work"]), "chunks": max(1, math.ceil(partners / PARTNER_KEYS)), "base": tasks}
        tasks += x["parts"] * x["chunks"]
    return found


def _labels(sets: DataFrame, n: int) -> list[int]:
    """Numbers that Spark deals out to n partitions, one to each."""
    rows = sets.sparkSession.range(32 * n + 64).groupBy(F.pmod(F.hash("id"), F.lit(n)).alias("p")).agg(F.min("id").alias("id")).collect()
    at = {r["p"]: r["id"] for r in rows}
    return [at.get(p, -1 - p) for p in range(n)]


def meeting(sets: DataFrame, rule: Rule) -> tuple[DataFrame, DataFrame]:
    """a, b, both, n_a, n_b, sure of the pairs of unlike sets that share as many keys as the rule needs, a the one of lower place; and
    rep, set_id: of equal sets only the first one is in these pairs. sets: set_id, of (64-bit hashes of keys), whole (their number),
    place, since (the least place that a partner before it has), marks (sorted numbers of which those below the other set's place can
    count; null: all keys); read twice."""
    log = F.floor(F.log(F.least("place", F.lit(1e300))) * 64)
    coded = stored(_prepared(sets.withColumn("like", _equal_sets(F.col("of"))).withColumn("bin", F.coalesce(log, F.lit(-(1 << 40))).cast("long"))))
    plan, held = _plan(coded), _members(coded)
    if not plan:
        return sets.sparkSession.createDataFrame([], "a string, b string, both long, n_a long, n_b long, sure boolean"), held
    tasks = sum(x["parts"] * x["chunks"] for x in plan)
    of_plan = lambda name, j, kind="int": F.element_at(F.array(*[F.lit(x[name]).cast(kind) for x in plan]), (j + 1).cast("int"))
    begins = F.array(*[F.lit(x["bin"]).cast("long") for x in plan])
    mine = (F.size(F.filter(begins, lambda s: s <= F.col("bin"))) - 1).alias("mine")
    ready = coded.withColumn("mine", mine).withColumn("part", F.pmod("like", of_plan("parts", F.col("mine"))).cast("int"))
    chunk = lambda j: F.pmod(F.shiftright("like", 17), of_plan("chunks", j)).cast("int")
    later = F.filter(F.sequence(F.col("mine"), F.lit(len(plan) - 1)), lambda j: F.col("place") >= of_plan("since", j, "double"))
    of_part = lambda j, s: of_plan("base", j) + s * of_plan("chunks", j) + chunk(j)
    elsewhere = lambda j: F.filter(F.sequence(F.lit(0), of_plan("parts", j) - 1), lambda s: (j != F.col("mine")) | (s != F.col("part")))
    asking = F.flatten(F.transform(later, lambda j: F.transform(elsewhere(j), lambda s: of_part(j, s))))
    asked = F.transform(F.sequence(F.lit(0), of_plan("chunks", F.col("mine")) - 1), lambda c: of_plan("base", F.col("mine")) + F.col("part") * of_plan("chunks", F.col("mine")) + c)
    cases = F.concat(F.transform(asking, lambda t: F.struct(t.alias("t"), F.lit(False).alias("here"))), F.transform(asked, lambda t: F.struct(t.alias("t"), F.lit(True).alias("here"))))
    dealt = ready.withColumn("case", F.explode(cases)).select(
        "set_id", "of", "whole", "like", "place", "odd", "mine", F.when(F.col("case.here"), F.col("marks")).alias("marks"), F.col("case.here").alias("here"),
        F.element_at(F.array(*[F.lit(x).cast("long") for x in _labels(sets, tasks)]), F.col("case.t") + 1).alias("task"), F.col("case.t").alias("number"),
    )
    first = [float(x["first"]) for x in plan]
    spans = [(x["base"], x["chunks"]) for x in plan]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        flats, sizes, marks, marked, rows = [], [], [], [], []
        for batch in batches:  # copied, so that Arrow's memory goes with the batch
            for name, values, counts in (("of", flats, sizes), ("marks", marks, marked)):
                held, edges = _listed(pa.chunked_array([batch.column(name)]))
                values.append(held[edges[0] :].copy())
                counts.append(np.diff(edges).astype(np.int64))
            rows.append((np.array(batch.column("set_id").to_pylist(), object), *(batch.column(c).to_numpy(zero_copy_only=False).copy() for c in ("here", "like", "whole", "place", "odd", "mine"))))
            number = batch.column("number")[0].as_py()
        ids, here, like, whole, place, odd, at = map(np.concatenate, zip(*rows, strict=True))
        flat, size, marks, marked = _joined(flats), np.concatenate(sizes), _joined(marks), np.concatenate(marked)
        base, chunks = next(s for s in reversed(spans) if s[0] <= number)
        kind = np.lexsort((like, whole, place))
        new = np.append(True, np.any([c[kind][1:] != c[kind][:-1] for c in (place, whole, like)], axis=0))
        turn = np.empty(len(kind), np.int64)
        turn[kind] = np.cumsum(new) - 1
        begins = np.flatnonzero(new)
        for p, q in zip(begins.tolist(), np.append(begins[1:], len(kind)).tolist(), strict=True):
            if q - p > 1:  # equal sets come together, all with one role
                ids[kind[p]] = min(ids[kind[p:q]])
        one = kind[begins]  # one of equal sets
        all_of = Sets(flat.view(np.uint32), np.cumsum(size) - size, size, whole.astype(np.int64), turn)
        held = one[here[one]]
        if not len(held):
            return
        asking = one[~here[one] | ((like[one] >> 17) % chunks == (number - base) % chunks)]
        right = all_of.take(held)
        for i in np.unique(at[asking]).tolist():
            left = asking[at[asking] == i]
            b = whole[held].astype(np.int64)
            if len(marks):
                below = np.concatenate([[0], np.cumsum(marks < first[i])])
                ends = np.cumsum(marked)
                b = (below[ends] - below[ends - marked])[held]
            x, y, both = _found(all_of.take(left), right, b, rule)
            x, y = left[x], held[y]
            yield pa.RecordBatch.from_arrays([pa.array(ids[x], pa.string()), pa.array(ids[y], pa.string()), pa.array(both), pa.array(whole[x].astype(np.int64)), pa.array(whole[y].astype(np.int64)), pa.array(~(odd[x] & odd[y]))], names=["a", "b", "both", "n_a", "n_b", "sure"])

    return dealt.repartition(tasks, "task").groupBy("task").applyInArrow(run, "a string, b string, both long, n_a long, n_b long, sure boolean"), held


def spread(pairs: DataFrame, held: DataFrame) -> DataFrame:
    """pairs (a, b, ...) of first ones among equal sets, or of one with itself, as pairs of their members, a < b."""
    x, y = (held.select(F.col("rep").alias(c), F.col("set_id").alias(f"_{c}")) for c in "ab")
    every = pairs.join(x, "a").join(y, "b").where("a <> b or _a < _b")
    return every.select(F.least("_a", "_b").alias("a"), F.greatest("_a", "_b").alias("b"), *[c for c in pairs.columns if c not in "ab"])


def same(held: DataFrame) -> DataFrame:
    """a, b: each first one of several equal sets with itself."""
    return held.groupBy("rep").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select(F.col("rep").alias("a"), F.col("rep").alias("b"))

"""SimHash near-duplicate detection by meet-in-the-middle ball hashing.

Two fingerprints that differ in at most 2r bits share a variant that differs from each in at most r. So every distinct
fingerprint emits its ball of radius r, the variants are shuffled, and those that meet are verified and linked. All
members of a variant's bucket lie within 2r of each other, hence a bucket holds at most one ball of fingerprints and
links to its smallest member keep every connection.

Defined cases: null or wordless texts have fingerprint zero and are linked like any other; repeated rows and equal
texts share a fingerprint and a component; a null doc_id never names a component unless all its members are null; an
empty table gives an empty result. Extra columns are ignored.

`similar_components` links texts by the Jaccard similarity of their word shingles instead. One 64-bit ball cannot reach
0.8: fingerprints of such texts differ in about ten bits. So every text has several short fingerprints, each joined with
two min-hashes of the same shingles, which keep unrelated texts apart at any corpus size. Every fingerprint emits its ball
of radius one. Colliding pairs are first tested by exact bounds on how many shingles they must differ in, within the join,
and then compared by their whole shingle sets.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize, mix, slices

_SCHEMA = "doc_id long, fp long"


def fingerprint(text: str | None, width: int = 3) -> int:
    """The unsigned 64-bit fingerprint of one text: each bit set in over half of its shingle hashes."""
    return int(_fingerprints([(text or "").encode()], width)[0])


def _fingerprints(texts: list[bytes], width: int) -> np.ndarray:
    from xxhash import xxh64_intdigest

    hashes: list[int] = []
    counts = np.zeros(len(texts), np.int64)
    for i, raw in enumerate(texts):
        words = raw.lower().split()
        if len(words) <= width:
            shingles = [b" ".join(words)] if words else []
        else:
            shingles = map(b" ".join, zip(*(words[j:] for j in range(width)), strict=False))
        before = len(hashes)
        hashes.extend([xxh64_intdigest(s, 42) for s in shingles])
        counts[i] = len(hashes) - before
    out = np.zeros(len(texts), np.uint64)
    full = np.flatnonzero(counts)
    if len(full):
        ends = np.cumsum(counts[full])
        bits = np.unpackbits(np.array(hashes, np.uint64).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        sums = np.add.reduceat(bits, ends - counts[full], axis=0, dtype=np.int64)
        ones = (2 * sums > counts[full][:, None]).astype(np.uint8)
        out[full] = np.packbits(ones, axis=1, bitorder="little").view(np.uint64)[:, 0]
    return out


def with_fingerprints(docs: DataFrame, width: int = 3) -> DataFrame:
    """doc_id, fp (the unsigned bits in a signed long) of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in slices(batches, "text", 1_000_000):
            raw = [x or b"" for x in piece["text"].cast(pa.binary()).to_pylist()]
            yield pa.RecordBatch.from_arrays([piece["doc_id"], pa.array(_fingerprints(raw, width).view(np.int64))], ["doc_id", "fp"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, _SCHEMA)


def _ball(fp: Column, radius: int) -> Column:
    masks = [0] + [sum(1 << b for b in chosen) for n in range(1, radius + 1) for chosen in combinations(range(64), n)]
    signed = [m - (1 << 64) if m >> 63 else m for m in masks]
    return F.transform(F.array(*[F.lit(m).cast("long") for m in signed]), lambda m: fp.bitwiseXOR(m))


def links(fps: DataFrame, radius: int = 2) -> DataFrame:
    """Links a < b between distinct fingerprints at most radius bits apart that connect all such pairs. radius: even, or one more than needed is searched."""
    half = (radius + 1) // 2
    variants = fps.select("fp", F.explode(_ball(F.col("fp"), half)).alias("variant"))
    met = variants.withColumn("first", F.min("fp").over(Window.partitionBy("variant")))
    pairs = met.where("fp <> first").select(F.col("first").alias("a"), F.col("fp").alias("b")).distinct()
    if radius % 2:  # an odd radius: bucket members may be one bit too far from the first, so all their pairs are verified
        met = variants.alias("x").join(variants.alias("y"), F.expr("x.variant = y.variant and x.fp < y.fp"))
        pairs = met.select(F.col("x.fp").alias("a"), F.col("y.fp").alias("b")).distinct()
    return pairs.where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= radius)


def components(edges: DataFrame) -> DataFrame:
    """node, label: the smallest node that is reachable over edges a, b. Rounds of neighbour minima with pointer jumping."""
    both = materialize(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    labels = materialize(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.first("a")).alias("label")))
    while True:
        heard = both.join(labels, both["b"] == labels["node"]).groupBy("a").agg(F.min("label").alias("heard"))
        lower = labels.join(heard, labels["node"] == heard["a"]).select("node", F.col("label").alias("old"), F.least("label", "heard").alias("label"))
        root = labels.select(F.col("node").alias("at"), F.col("label").alias("root"))
        jumped = lower.join(root, F.col("label") == F.col("at"), "left").select("node", "old", F.least("label", "root").alias("label"))
        jumped = materialize(jumped)
        changed = jumped.where("old <> label").limit(1).count()
        labels = jumped.select("node", "label")
        if not changed:
            return labels


def simhash_components(docs: DataFrame, width: int = 3, radius: int = 2) -> DataFrame:
    """doc_id, fp, component_id for every row of docs; component_id is the smallest doc_id linked to it, itself included."""
    prints = materialize(with_fingerprints(docs, width))
    smallest = prints.groupBy("fp").agg(F.min("doc_id").alias("least"))
    labels = components(links(prints.select("fp").distinct(), radius))
    named = smallest.join(labels, smallest["fp"] == labels["node"]).groupBy("label").agg(F.min("least").alias("component"))
    linked = labels.join(named, "label").select("node", "component")
    whole = smallest.join(linked, smallest["fp"] == linked["node"], "left").select("fp", F.coalesce("component", "least").alias("component_id"))
    return prints.join(whole, "fp").select("doc_id", "fp", "component_id")


#: Short fingerprints of a text: their number, bits of each, and min-hashes joined with each. At a similarity of 0.8 one of
#: them meets with probability 0.57 (0.89 for at most two differing bits, 0.64 for the min-hashes), so one of twelve with 0.99996.
TABLES, BITS, MINS = 12, 8, 2
#: Cells of the parity vector of a shingle set, 64 to a column.
CELLS = 512
#: One text in so many leads in the first round; in the second one all others do.
LEADERS = 16
#: Names of texts up to which they are broadcast (counted first): 8 bytes each.
MOST_NAMES = 500_000
_CODES = [f"c{t}" for t in range(TABLES)]
_ODD = [f"p{i}" for i in range(CELLS // 64)]
_SIGNED = ["doc_id", "h0", "h1", "n", *_ODD, *_CODES]


def _shingle_set(raw: bytes, width: int) -> set[bytes]:
    words = raw.lower().split()
    if len(words) <= width:
        return {b" ".join(words)} if words else set()
    return set(map(b" ".join, zip(*(words[j:] for j in range(width)), strict=False)))


_SALTS = [np.uint64(pow(0x7FB5D329728EA185, t + 2, 1 << 64)) for t in range(TABLES * MINS)]


def _signature(raw: bytes, width: int) -> np.ndarray:
    """n (distinct shingles), the parity vector and the codes of one text, as signed longs."""
    from xxhash import xxh64_intdigest

    found = _shingle_set(raw, width)
    out = np.zeros(1 + len(_ODD) + TABLES, np.uint64)
    first = np.fromiter((xxh64_intdigest(x, 42) for x in found), np.uint64, len(found))
    if not len(first):
        return out.view(np.int64)
    words = np.stack([mix(first + np.uint64(i * 0x9E3779B97F4A7C15 % (1 << 64))) for i in range(-(-TABLES * BITS // 64))], axis=1)
    sums = np.zeros(64 * words.shape[1], np.int64)
    for at in range(0, len(first), 65536):
        sums += np.unpackbits(words[at : at + 65536].view(np.uint8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    sides = np.packbits(2 * sums[: TABLES * BITS] > len(first), bitorder="little")
    least = np.array([((first ^ salt) * salt).min() for salt in _SALTS]).reshape(TABLES, MINS)
    salts = np.arange(TABLES, dtype=np.uint64)
    for i in range(MINS):
        salts = mix(salts + least[:, i])
    odd = np.packbits((np.bincount((first >> np.uint64(64 - CELLS.bit_length() + 1)).astype(np.int64), minlength=CELLS) & 1).astype(np.uint8), bitorder="little")
    out[0], out[1 : 1 + len(_ODD)], out[1 + len(_ODD) :] = len(first), odd.view(np.uint64), salts ^ sides.astype(np.uint64)
    return out.view(np.int64)


def _signatures(docs: DataFrame, width: int) -> DataFrame:
    """For every row doc_id, the 128-bit hash of its text (h0, h1), and its signature."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh3_128_digest

        for piece in slices(batches, "text", 1_000_000):
            raw = [x or b"" for x in piece["text"].cast(pa.binary()).to_pylist()]
            whole = np.frombuffer(b"".join(map(xxh3_128_digest, raw)), np.int64).reshape(-1, 2)
            rest = np.array([_signature(x, width) for x in raw], np.int64)
            columns = [piece["doc_id"], *map(pa.array, np.hstack((whole, rest)).T.copy())]
            yield pa.RecordBatch.from_arrays(columns, _SIGNED)

    return docs.mapInArrow(run, ", ".join(f"{c} long" for c in _SIGNED))


def _possible(x: str, y: str, similarity: float) -> Column:
    """Whether sets x and y can have the similarity. Exact: they differ in at least as many shingles as their sizes do, and in
    at least as many as there are cells in which the parities of their shingles differ."""
    most = (1 - similarity) / (1 + similarity) * (F.col(f"{x}.n") + F.col(f"{y}.n")) + 1e-9
    apart = sum((F.bit_count(F.col(f"{x}.{p}").bitwiseXOR(F.col(f"{y}.{p}"))) for p in _ODD), F.lit(0))
    return (F.abs(F.col(f"{x}.n") - F.col(f"{y}.n")) <= most) & (apart <= most)


def _verified(pairs: DataFrame, texts: DataFrame, width: int, similarity: float) -> DataFrame:
    """The pairs a, b whose shingle sets have at least the similarity. texts: node, text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good, held, last = [], set(), None
            for a, b, x, y in zip(batch["a"].to_pylist(), batch["b"].to_pylist(), batch["x"], batch["y"], strict=True):
                if a != last:
                    held, last = _shingle_set((x.as_py() or "").encode(), width), a
                other = _shingle_set((y.as_py() or "").encode(), width)
                both = len(held & other)
                if both >= similarity * (len(held) + len(other) - both) - 1e-9:
                    good.append((a, b))
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*good, strict=True)] or [pa.array([], pa.int64())] * 2, ["a", "b"])

    left = texts.select(F.col("node").alias("a"), F.col("text").alias("x")).hint("merge")
    right = texts.select(F.col("node").alias("b"), F.col("text").alias("y")).hint("merge")
    return pairs.join(right, "b").join(left, "a").select("a", "b", "x", "y").mapInArrow(run, "a long, b long").distinct()


def _first_pairs(signed: DataFrame, similarity: float) -> DataFrame:
    """a, b: every text with one other one, the smallest name of most of the unchanged codes that it shares."""
    own = signed.select("node", F.explode(F.array(*_CODES)).alias("code"))
    least = own.groupBy("code").agg(F.min("node").alias("leader"), F.count(F.lit(1)).alias("_of")).where("_of > 1").drop("_of")
    led = own.join(least.hint("merge"), "code").where("node <> leader")
    often = led.groupBy("node", "leader").agg(F.count(F.lit(1)).alias("times"))
    chosen = often.groupBy("node").agg(F.max_by("leader", F.struct("times", -F.col("leader"))).alias("leader"))
    marks = signed.select("node", "n", *_ODD)
    near = chosen.join(marks.alias("x").hint("merge"), "node").select("leader", F.struct("node", "n", *_ODD).alias("x"))
    near = near.join(marks.select(F.col("node").alias("leader"), F.struct("n", *_ODD).alias("y")).hint("merge"), "leader")
    return near.where(_possible("x", "y", similarity)).select(F.col("leader").alias("a"), F.col("x.node").alias("b"))


def _unlike(rows: DataFrame) -> DataFrame:
    """The rows (bucket, label, ...) of buckets that hold more than one label, without the label."""
    mixed = rows.select(F.hash("bucket").alias("_b"), "label").groupBy("_b").agg(F.min("label").alias("_lo"), F.max("label").alias("_hi")).where("_lo < _hi").select("_b")
    slim = rows.drop("label")
    return slim.join(mixed.hint("merge"), F.hash(slim["bucket"]) == mixed["_b"], "left_semi")


def _texts(docs: DataFrame, names: DataFrame) -> DataFrame:
    """node, text of the names (node). A few names go to the documents; else both meet."""
    few = names.limit(MOST_NAMES + 1).count() <= MOST_NAMES
    return docs.withColumnRenamed("doc_id", "node").join(names.hint("broadcast" if few else "merge"), "node", "left_semi")


def similar_labels(signed: DataFrame, docs: DataFrame, width: int, similarity: float) -> DataFrame:
    """node, label of texts (named by their smallest doc_id) that are linked to others: the smallest name linked to them.

    Every text is first compared with one promising other one, so large groups of near copies have one label early. Then
    balls are emitted, and all pairs that meet in a bucket with unlike labels are compared, in the round in which one of
    them leads: few texts lead in the first round, the rest in the second, and labels are found anew in between. A pair is
    left out only if its labels are equal by then or an exact bound says that it is not similar; so what is linked at the
    end is what comparing all pairs that meet would link."""
    none = signed.select("node", F.col("node").alias("label")).where("false")

    def relabel(old: DataFrame, pairs: DataFrame) -> tuple[DataFrame, bool]:
        names = materialize(pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct())
        good = materialize(_verified(pairs, _texts(docs, names), width, similarity))
        if not good.limit(1).count():
            return old, False
        return components(good.union(old.where("node <> label").select(F.col("label").alias("a"), F.col("node").alias("b")))), True

    def labelled(rows: DataFrame, labels: DataFrame) -> DataFrame:
        known = labels.withColumnRenamed("label", "_known").hint("merge")
        return rows.drop("label").join(known, "node", "left").withColumn("label", F.coalesce("_known", "node")).drop("_known")

    begun = materialize(_first_pairs(signed, similarity))
    labels, _ = relabel(none, begun)
    flips = F.array(*[F.struct(F.lit(i).cast("byte").alias("flip"), F.lit(m).cast("long").alias("mask")) for i, m in enumerate([0, *(1 << i for i in range(BITS))])])
    codes = labelled(signed.select("node", F.array(*_CODES).alias("codes")), labels)
    ball = codes.select("node", "label", F.explode("codes").alias("code")).select("node", "label", F.explode(flips).alias("f"), "code")
    met = _unlike(ball.select(F.col("code").bitwiseXOR(F.col("f.mask")).alias("bucket"), "node", "label", F.col("f.flip").alias("flip")))
    waiting = materialize(met)
    marks = labelled(signed.select("node", "n", *_ODD), labels)
    waiting = materialize(waiting.join(marks.hint("merge"), "node"))
    rank = F.when(F.pmod(F.xxhash64("node", F.lit("turn")), F.lit(LEADERS)) == 0, 0).otherwise(1)
    for r in range(2):
        ranked = waiting.withColumn("rank", rank)
        x, y = ranked.where(F.col("rank") >= r).alias("x"), ranked.where(F.col("rank") == r).alias("y")
        # two texts meet in several variants of one code, and count in one: both unchanged, or the flip of the lesser name first
        low = F.col("x.node") < F.col("y.node")
        once = (F.when(low, F.col("x.flip")).otherwise(F.col("y.flip")) < F.when(low, F.col("y.flip")).otherwise(F.col("x.flip"))) | ((F.col("x.flip") == 0) & (F.col("y.flip") == 0))
        ordered = (F.col("x.rank") > r) | low
        met = x.join(y, (F.col("x.bucket") == F.col("y.bucket")) & (F.col("x.label") != F.col("y.label")) & once & ordered & _possible("x", "y", similarity))
        pairs = materialize(met.select(F.least("x.node", "y.node").alias("a"), F.greatest("x.node", "y.node").alias("b")).distinct())
        labels, new = relabel(labels, pairs)
        if new and not r:
            waiting = labelled(waiting, labels)
            mixed = materialize(_unlike(waiting.select("bucket", "label")).distinct())
            waiting = materialize(waiting.join(mixed.hint("merge"), "bucket", "left_semi"))
    return labels


def similar_components(docs: DataFrame, width: int = 5, similarity: float = 0.8) -> DataFrame:
    """doc_id, component_id for every row of docs: the smallest doc_id among texts linked by Jaccard similarity.

    Equal texts are one; texts without words are linked to each other; rows of texts that have only null doc_ids are
    linked to nothing and have a null component."""
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    signed = materialize(_signatures(slim, width))
    same = signed.groupBy("h0", "h1").agg(F.min("doc_id").alias("node"), F.first(F.struct(*_SIGNED[3:])).alias("s"))
    same = materialize(same.select("h0", "h1", "node", "s.*"))
    labels = similar_labels(same.where("node is not null"), slim, width, similarity)
    labels = labels.withColumnRenamed("node", "_node").hint("merge")
    named = same.join(labels, F.col("node") == F.col("_node"), "left").select("h0", "h1", F.coalesce("label", "node").alias("component_id"))
    return signed.select("doc_id", "h0", "h1").join(named.hint("merge"), ["h0", "h1"]).select("doc_id", "component_id")


def query(spark, sf_dir: str) -> DataFrame:
    from .common import load

    found = simhash_components(load(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")

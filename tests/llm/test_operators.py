"""The text operators against plain versions, on a small fixture with odd rows and on empty tables."""

import hashlib
import math
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from coordsketch.llm import chat, decontaminate, lm, packing, pii, pipeline, quality, records, repeats, sharding, simhash
from coordsketch.llm.tokens import Encoder, vocabulary

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, fp long, key string, _row string"
WORDS = re.compile(rb"[^\x20\x09-\x0D]+")


def texts():
    rng = np.random.default_rng(1)
    word = lambda: "".join(rng.choice(list("aeiou"), 2)) + "".join(rng.choice(list("bcdfgé"), 3))
    prose = [" ".join(word() for _ in range(int(rng.integers(60, 160)))) + "." for _ in range(24)]
    passage = "this passage of many plain words stands in several documents and must be found wherever it stands " * 3
    out = [None, "", "   \n\t ", "one", "one", "Ünïcode wörds and ok", "a" * 900, "ab " * 400, prose[0], prose[0], prose[0] + " more"]
    out += [p[:200] + passage + p[200:] for p in prose[1:5]] + prose[5:]
    out += ["mail me at joe.doe@mail.example.com or 10.20.30.40, 999.1.1.1", "card 4111 1111 1111 1111 and 4111111111111112", "tel +1 (743) 555-3824 or +12", 'x token = "24be64439e3e49cf46b2d7c90f3602a3d0b907ff" y', "a@b.c_d@e.f", "1" * 5000 + " " + "1." * 3000, ("line again\n" * 30) + "end"]
    return out


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i if i != 3 else None, t, [None, "en", "de"][i % 3], ["s", "s", "t", None][i % 4], 0, 1, "k", "r") for i, t in enumerate(texts())]
    return spark.createDataFrame([*rows, rows[9]], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def raw(docs):
    return [(r["doc_id"], (r["text"] or "").encode()) for r in docs.collect()]


def test_repeats(docs, empty, monkeypatch):
    def plain(length):
        rows = raw(docs)
        times = Counter(b[i : i + length] for _, b in rows for i in range(len(b) - length + 1))
        out = []
        for d, b in rows:
            cover = np.zeros(len(b), bool)
            for i in range(len(b) - length + 1):
                if times[b[i : i + length]] > 1:
                    cover[i : i + length] = True
            spans = int((np.diff(np.concatenate([[0], cover.astype(int)])) == 1).sum())
            out.append((d, len(b), int(cover.sum()), spans, bytes(np.frombuffer(b, np.uint8)[~cover])))
        return Counter(out)

    for length, gram, most in ((200, 64, 1024), (200, 64, 1), (50, 20, 3)):
        monkeypatch.setattr(repeats, "MOST_CLASSES", most)
        got = repeats.without_repeats(docs, length, gram).collect()
        assert Counter((r["doc_id"], r["n_bytes"], r["n_removed"], r["n_spans"], bytes(r["kept"])) for r in got) == plain(length)
    assert repeats.without_repeats(empty).count() == 0


def test_repeat_groups_hold_all_occurrences(docs, monkeypatch):
    rows = {d: b for d, b in raw(docs)}
    assert len(rows) + 1 == len(raw(docs))  # one row stands twice
    for most in (1024, 1):
        monkeypatch.setattr(repeats, "MOST_CLASSES", most)
        got = repeats.repeat_groups(docs, 50, 20).collect()
        groups = {}
        for r in got:
            groups.setdefault((r["group"], r["length"]), set()).add((r["doc_id"], r["start"]))
        copies = Counter((d, b) for d, b in raw(docs))
        covered = {d: np.zeros(len(b), bool) for d, b in rows.items()}
        for (_, n), places in groups.items():
            strings = {rows[d][s : s + n] for d, s in places}
            assert len(strings) == 1
            (string,) = strings
            assert {(d, i) for d, b in rows.items() for i in range(len(b) - n + 1) if b[i : i + n] == string} == places
            assert sum(copies[d, rows[d]] for d, _ in places) > 1
            for d, s in places:
                covered[d][s : s + n] = True
        removed = {r["doc_id"]: r["n_removed"] for r in repeats.without_repeats(docs, 50, 20).collect()}
        assert {d: int(c.sum()) for d, c in covered.items()} == removed


def test_suffix_array_and_intervals():
    data = np.frombuffer(b"banana$anab", np.uint8)
    at = np.arange(len(data))
    order, common = repeats.suffix_array(data, at, np.full(len(data), len(data)), 16)
    suffixes = [data[i:].tobytes() for i in range(len(data))]
    assert [suffixes[i] for i in order] == sorted(suffixes)
    want = [0] + [next((j for j, (x, y) in enumerate(zip(suffixes[a], suffixes[b], strict=False)) if x != y), min(len(suffixes[a]), len(suffixes[b]))) for a, b in zip(order, order[1:], strict=False)]
    assert common.tolist() == want
    found = {data[m[0] : m[0] + n].tobytes(): len(m) for n, m in repeats.maximal_repeats(data, at, np.full(len(data), len(data)), np.zeros(len(data), int), 1, 16)}
    assert found[b"ana"] == 3 and found[b"a"] == 5 and b"na" not in found  # na is always preceded by a
    assert list(repeats.intervals(np.array([0, 3, 5, 3, 0, 4]), 3)) == [(5, 1, 2), (3, 0, 3), (4, 4, 5)]


def test_simhash(docs, empty):
    import xxhash

    def fp(b):
        words = [bytes(c + 32 if 65 <= c <= 90 else c for c in w) for w in WORDS.findall(b)]
        s = [b" ".join(words[i : i + 3]) for i in range(len(words) - 2)] if len(words) > 2 else [b" ".join(words)] if words else []
        h = [xxhash.xxh64_intdigest(x, 42) for x in s]
        return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))

    got = simhash.simhash_components(docs).collect()
    rows = [(d, fp(b)) for d, b in raw(docs)]
    assert Counter((r["doc_id"], r["fp"] % (1 << 64)) for r in got) == Counter(rows)
    label = {f: f for _, f in rows}
    for _ in rows:
        for a in label:
            for b in label:
                if (a ^ b).bit_count() <= 2:
                    label[a] = label[b] = min(label[a], label[b])
    least = {}
    for d, f in rows:
        if d is not None:
            least[label[f]] = min(least.get(label[f], d), d)
    assert all(r["component_id"] == least.get(label[r["fp"] % (1 << 64)]) for r in got)
    assert simhash.simhash_components(empty).count() == 0


def test_simhash_links_find_all_pairs_within_the_radius(spark):
    rng = np.random.default_rng(2)
    base = [int(x) for x in rng.integers(0, 1 << 62, 40)]
    near = [b ^ (1 << int(i)) ^ (1 << int(j)) for b, i, j in zip(base, rng.integers(0, 64, 40), rng.integers(0, 64, 40), strict=True)]
    fps = {x - (1 << 64) if x >> 63 else x for x in base + near}
    nodes = {r["node"]: r["label"] for r in simhash.components(simhash.links(spark.createDataFrame([(f,) for f in fps], "fp long"))).collect()}
    for a in fps:
        for b in fps:
            if a != b and ((a ^ b) % (1 << 64)).bit_count() <= 2:
                assert nodes[a] == nodes[b]


def test_similar_components(spark, docs, empty):
    rng = np.random.default_rng(5)
    words = [f"w{i}" for i in range(4000)]
    rows = [(d, b.decode()) for d, b in raw(docs)]
    for group in range(12):  # families of edited copies; in every third one many copies of one text
        base = list(rng.choice(words, int(rng.integers(40, 300))))
        for copy in range(40 if group % 3 == 0 else 4):
            edited = list(base)
            for at in rng.integers(0, len(base), int(rng.integers(0, 1 + len(base) // 45))):
                edited[at] = "edited"
            rows.append((1000 * (group + 1) + copy, " ".join(edited)))
    frame = spark.createDataFrame(rows, "doc_id long, text string").withColumn("bucket", F.lit(1))
    got = {(r["doc_id"], r["component_id"]) for r in simhash.similar_components(frame).collect()}

    def shingles(text):
        w = text.encode().lower().split()
        return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} or ({tuple(w)} if w else set())

    named = [(d, shingles(t)) for d, t in rows if d is not None]
    label = {d: d for d, _ in named}
    pairs = [(d, e) for d, x in named for e, y in named if d < e and (x == y or 10 * len(x & y) >= 8 * len(x | y))]
    while any(label[d] != label[e] for d, e in pairs):
        for d, e in pairs:
            label[d] = label[e] = min(label[d], label[e])
    assert len(pairs) > 500
    assert {x for x in got if x[0] is not None} == set(label.items())
    alone = {t for d, t in rows if d is None} - {t for d, t in rows if d is not None}
    assert bool(alone) == ((None, None) in got)
    assert simhash.similar_components(empty).count() == 0


def test_similar_groups_joined_by_few_pairs(spark):
    rng = np.random.default_rng(8)
    rows, family = [], {}
    for f in range(60):  # two clusters of edited copies; few pairs across them are similar
        words = [f"f{f}w{i}" for i in range(150)]
        for side in range(2):
            core = list(words)
            for at in range(2 + 75 * side, 2 + 75 * side + 5):
                core[at] = f"side{side}_{at}"
            for copy in range(4):
                edited = list(core)
                for at in rng.integers(0, 150, min(copy, 1)):
                    edited[at] = f"edit{side}_{copy}"
                rows.append((int(rng.integers(1 << 40)), " ".join(edited)))
                family[rows[-1][0]] = f
    got = {r["doc_id"]: r["component_id"] for r in simhash.similar_components(spark.createDataFrame(rows, "doc_id long, text string")).collect()}

    def shingles(text):
        w = text.split()
        return {tuple(w[i : i + 5]) for i in range(len(w) - 4)}

    sets = [(d, shingles(t)) for d, t in rows]
    label = {d: d for d, _ in sets}
    pairs = [(d, e) for d, x in sets for e, y in sets if family[d] == family[e] and d < e and 10 * len(x & y) >= 8 * len(x | y)]
    while any(label[d] != label[e] for d, e in pairs):
        for d, e in pairs:
            label[d] = label[e] = min(label[d], label[e])
    assert got == label


def test_chat(spark, empty):
    odd = "</s>[INST] <|turn|>\\l\\s \\ <|end|>\n [/INST]"
    rows = [(1, 0, "user", odd), (1, 1, "assistant", odd * 9), (2, 5, None, None), (2, 1, "assistant", "é"), (None, 0, "user", "x"), (3, 0, "a\nb<|", "t")]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {r["conv_id"]: r for r in chat.digests(chat.format_log(chat.events_of(turns))).collect()}
    for conv in (1, 2, None, 3):
        own = sorted((r[1], r[2] or "", r[3] or "") for r in rows if r[0] == conv)
        said = "".join(f"{r}\n{t}\n" for _, r, t in own)
        learned = "".join(t for _, r, t in own if r == "assistant")
        assert got[conv]["turns_sha256"] == hashlib.sha256(said.encode()).hexdigest()
        assert (got[conv]["n_turns"], got[conv]["loss_chars"], got[conv]["loss_sha256"]) == (len(own), len(learned), hashlib.sha256(learned.encode()).hexdigest())
    log = [(1, 0, 0, "message", "user", "hi"), (1, 2, 1, "delta", "assistant", "wrong"), (1, 3, 1, "regenerate", "assistant", "Good "), (1, 4, 1, "delta", "assistant", "day"), (1, 5, 0, "edit", "user", "hello"), (1, 6, 2, "message", "user", "gone"), (1, 7, 2, "delete", None, None)]
    events = spark.createDataFrame(log, "conv_id long, seq long, turn long, kind string, role string, text string")
    back = chat.read_back(chat.format_log(events)).first()["turns"]
    assert [(t["role"], t["text"]) for t in back] == [("user", "hello"), ("assistant", "Good day")]
    assert chat.format_log(events.where("false")).count() == 0
    long = "word " * 30
    again = [(1, 0, "user", long), (1, 0, "user", long), (1, None, "user", "b"), (1, None, "user", "a"), (1, 1, "assistant", long), (1, 1, "assistant", long)]
    back = chat.read_back(chat.format_log(chat.events_of(spark.createDataFrame(again, turns.schema)))).first()["turns"]
    assert [(t["role"], t["text"]) for t in back] == [("user", "a"), ("user", "b"), ("user", long), ("user", long), ("assistant", long), ("assistant", long)]


def test_sharding(docs, empty, spark):
    got = sharding.shard_documents(docs, 4).collect()
    assert Counter((r["doc_id"], r["size"], r["text_crc32"]) for r in got) == Counter((d, len(b) + 1, zlib.crc32(b)) for d, b in raw(docs))
    counts = Counter(r["shard"] for r in got)
    assert set(counts) == set(range(4)) and max(counts.values()) - min(counts.values()) <= 1
    assert all(sorted(r["slot"] for r in got if r["shard"] == s) == list(range(n)) for s, n in counts.items())
    many = spark.range(1600).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, "hot").otherwise(F.concat(F.lit("s"), F.col("id") % 7)).alias("source"), F.lit("t").alias("text"))
    mix = Counter((r["shard"], r["source"]) for r in sharding.shard_documents(many, 16).collect())
    assert all(31 <= mix[s, "hot"] <= 36 for s in range(16))
    assert sharding.shard_documents(empty).count() == 0


def test_quality(docs, empty):
    def base(b):
        t = b.decode()
        words = re.findall(r"[^\x20\x09-\x0D]+", t)
        times = Counter(tuple(words[i : i + 3]) for i in range(len(words) - 2))
        cover = {j for i in range(len(words) - 2) if times[tuple(words[i : i + 3])] > 1 for j in range(i, i + 3)}
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(cover)

    got = quality.judged(docs).collect()
    names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
    assert Counter((r["doc_id"], *(r[n] for n in names)) for r in got) == Counter((d, *base(b)) for d, b in raw(docs))
    for r in got:
        assert r["base_failed"] == (r["n_words"] < 50 or 100 * r["n_repeat_words"] > 50 * r["n_words"])
        assert not (r["kept"] and r["base_failed"])
    assert sum(r["kept"] for r in got) >= 20
    assert quality.judged(empty).count() == 0


def test_quantile_sketches_merge(spark):
    rows = spark.createDataFrame([("en", "s", "m", v, v % 3 + 1) for v in range(100)], "lang string, source string, measure string, bin int, n long")
    values = sorted(v for v in range(100) for _ in range(v % 3 + 1))
    q = quality.quantiles(rows.unionByName(rows.where("false")), ["lang"]).first()
    assert (q["q25"], q["q50"], q["q75"]) == tuple(values[math.ceil(len(values) * p / 100) - 1] for p in (25, 50, 75))


def test_encoder_equals_whole_texts():
    from tokenizers import Tokenizer

    odd = [*(t or "" for t in texts()), " ", "  a  b\n c  d", "x\x1c y\x1f z", "<|endoftext|> hi", "it's  \n\n ok ", "　x y", "don 't 's we're they'll.", "a\tb \tc", "1 2 33  4", "Σας ΑΣ. İstanbul H̱ello, Å", "foo.\nBar, baz.\n\nQux", "\n a", "日本語 テスト. ok", "x² ½ Ⅷ", "a.,; b...c ###", "end<|endoftext|>", "<|startoftext|> a <|ENDOFTEXT|>"]
    for name in ("word_bpe_49k.json", "byte_bpe_50k.json"):
        whole = Tokenizer.from_file(vocabulary(name))
        want = [e.ids for e in whole.encode_batch(odd, add_special_tokens=False)]
        encoder = Encoder(vocabulary(name))
        for _ in range(2):
            assert [np.frombuffer(x, "<u4").tolist() for x in encoder.encode(odd)] == want


def test_records(spark, docs, empty, tmp_path):
    folder = f"file://{tmp_path}/rec"
    got = sorted(((r["doc_id"] is not None, r["doc_id"] or 0, r["start"], r["n_tokens"], r["ids_crc32"]) for r in records.positions(spark, docs, folder, vocabulary("byte_bpe_50k.json")).collect()), key=lambda r: r[2])
    encoder = Encoder(vocabulary("byte_bpe_50k.json"))
    at = 0
    assert [r[:2] for r in got] == sorted(r[:2] for r in got)
    ids = {}
    for d, b in raw(docs):
        ids[d] = encoder.encode([b.decode()])[0] + b"\x02\0\0\0"
    for has, d, start, n, crc in got:
        own = ids[d if has else None]
        assert (start, n, crc) == (at, len(own) // 4, zlib.crc32(own))
        at += n
    parts = sorted(p.stem for p in (tmp_path / "rec").glob("*.rec"))
    shuffled = [d for p in parts for d, _ in records.read_shuffled(folder, p, 3)]
    assert Counter(shuffled) == Counter(d for d, _ in raw(docs))
    file = tmp_path / "rec" / f"{parts[0]}.rec"
    broken = bytearray(file.read_bytes())
    broken[20] ^= 1
    with pytest.raises(ValueError):
        list(records.unframe(pa.BufferReader(bytes(broken))))
    assert records.positions(spark, empty, f"file://{tmp_path}/none", vocabulary("byte_bpe_50k.json")).count() == 0
    wide = np.array([70000, 5], "<u4").tobytes()
    assert records.unpack(records.pack(3, wide, 4))[1].tolist() == [70000, 5]
    with pytest.raises(ValueError):
        records.pack(3, wide, 2)
    again = records.write_records(docs.where("doc_id is null or doc_id = 9"), f"file://{tmp_path}/again", vocabulary("byte_bpe_50k.json"), partitions=3)
    first, second = (sorted((r["part"], r["before"], r["doc_id"], bytes(r["ids"])) for r in records.read_records(again, f"file://{tmp_path}/again").collect()) for _ in range(2))
    assert first == second and len(first) == docs.where("doc_id is null or doc_id = 9").count()


def test_decontamination(spark, docs, empty):
    item = "Anna bought 12 apples for 30 dollars and gave 5 apples to her friend Peter before the long walk home in the rain"
    changed = item.replace("12", "71").replace("30", "90").replace(" 5 ", " 8 ").replace("Peter", "Maria")
    torn = "12 apples were there, and 30 dollars, and then nothing of the kind stood in this text at all, my friend"
    bench = spark.createDataFrame([(1, item), (2, None), (3, "two words"), (4, "")], "item_id long, text string")
    rows = spark.createDataFrame([(10, "Some words first. " + item + " and after."), (11, "x " + changed + " y"), (12, torn), (13, item.lower()), (14, None)], "doc_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r["kind"] for r in decontaminate.leaks(rows, bench).collect()}
    assert got == {(10, 1): "copied", (11, 1): "changed", (13, 1): "copied"}
    twice = item.replace("Anna", "He").replace("12 apples", "5 apples")
    both = spark.createDataFrame([(1, twice)], "item_id long, text string")
    mixed = spark.createDataFrame([(1, twice.replace("5 apples for", "7 apples for"))], "doc_id long, text string")
    assert decontaminate.leaks(mixed, both).count() == 0  # one slot value became two
    assert decontaminate.leaks(docs, bench).count() == 0 and decontaminate.leaks(empty, bench).count() == 0
    assert decontaminate.leaks(rows, bench.where("false")).count() == 0


def test_decontamination_judges_each_alignment(spark):
    lines = "In this shop each red box holds 12 pens, each red box holds 30 caps and nobody counts them"
    short = "every tall jar keeps 7 sweet plums inside"
    bench = spark.createDataFrame([(1, lines), (2, short)], "item_id long, text string")
    rows = [(n, "word " * n + lines) for n in range(20)] + [(50, lines.replace("12", "5").replace("30", "8"))]
    rows += [(60, " ".join(short.replace("7", str(n)) for n in (11, 12, 13, 14))), (61, lines.replace("30", "12"))]
    rows += [(62, lines.replace("holds 30", "really and truly holds 30")), (63, lines.replace("nobody", "surely " * 30 + "nobody"))]
    got = {(r["doc_id"], r["item_id"]): r["kind"] for r in decontaminate.leaks(spark.createDataFrame(rows, "doc_id long, text string").coalesce(1), bench).collect()}
    want = {(n, 1): "copied" for n in range(20)} | {(50, 1): "changed", (60, 2): "changed"}
    assert {k: v for k, v in got.items() if k[0] < 61} == want
    assert (61, 1) not in got


def test_decontamination_judges_share_and_slots_in_one_place(spark):
    item = "Anna bought 12 apples for 30 dollars and gave 5 apples to her friend Peter before the long walk home in the rain"
    torn = item.replace("12", "71").replace("gave 5 apples", "gave 8 pears").replace("30 dollars", "30 crowns")
    words = item.split()
    rng = np.random.default_rng(7)
    scattered = " ".join(" ".join(words[i : i + 5]) + " " + " ".join(f"filler{k}x" for k in range(i * 40, i * 40 + 40)) for i in rng.permutation(len(words) - 4))
    near = " ".join(" ".join(words[i : i + 5]) for i in rng.permutation(len(words) - 4))
    rows = [(1, torn), (2, torn + " . Also: home in the rain before the long walk home in the rain"), (3, scattered), (4, near), (5, item.replace("her friend", "her very good old friend")), (6, "x " * 50 + item)]
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    got = {r["doc_id"] for r in decontaminate.leaks(spark.createDataFrame(rows, "doc_id long, text string"), bench).collect()}
    assert got & {1, 2, 3, 4} == set() and 6 in got


def test_decontamination_of_numbers_names_and_unspaced_text(spark):
    sums = "Compute 12 + 35 * 7 - 4"
    tom = "Tom has 12 apples. Tom buys 30 more apples at the market. How many apples does Tom have?"
    wide = "小明有十二个苹果，他在市场上又买了三十个苹果。请问他现在一共有多少个苹果？"
    bench = spark.createDataFrame([(1, sums), (2, tom), (3, wide)], "item_id long, text string")
    rows = [(1, "Now: " + sums + ". Good."), (2, "Then. " + tom.replace("Tom", "Maria")), (3, "前面的话。" + wide + "后面的话。"), (4, sums.replace("35", "36")), (5, wide[:12]), (6, tom.replace("does Tom", "does Ben").replace("Tom", "Maria"))]
    got = {(r["doc_id"], r["item_id"]): r["kind"] for r in decontaminate.leaks(spark.createDataFrame(rows, "doc_id long, text string"), bench).collect()}
    assert got == {(1, 1): "copied", (2, 2): "changed", (3, 3): "copied"}


def test_pii(docs, empty):
    patterns = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}

    def luhn(d):
        return sum(x if i % 2 == 0 else 2 * x - 9 * (x > 4) for i, x in enumerate(map(int, reversed(d)))) % 10 == 0

    def base(t):
        for kind, p in patterns.items():
            for m in re.finditer(p, t):
                d = re.sub("[^0-9]", "", m[0])
                if kind == "email" or (kind == "ip" and all(int(x) <= 255 for x in m[0].split("."))) or (kind == "card" and 16 <= len(d) <= 19 and luhn(d)) or (kind == "phone" and 8 <= len(d) <= 15):
                    yield kind, m.start(), m.end()

    got = pii.personal_spans(docs).collect()
    found = Counter((r["doc_id"], tuple((s["kind"], s["start"], s["end"]) for s in r["spans"] if s["base"])) for r in got)
    assert found == Counter((d, tuple(base(b.decode()))) for d, b in raw(docs))
    red = {r["doc_id"]: r["text"] for r in pii.redact(docs).collect()}
    assert any("[email]" in (t or "") for t in red.values()) and len(red) == len({d for d, _ in raw(docs)})
    assert pii.personal_spans(empty).count() == 0 and pii.redact(empty).count() == 0


def test_added_spans_find_secrets_and_leave_names_alone(spark):
    rng = np.random.default_rng(12)
    hexes = lambda n: "".join(rng.choice(list("0123456789abcdef"), n))
    plain = lambda: "-".join("".join(rng.choice(list("abcdefghij"), 6)) for _ in range(5)) + f"-{int(rng.integers(1, 9))}"
    rows, spots = [], {}
    for i in range(300):
        lead = "some words of a text " * int(rng.integers(1, 4))
        if i % 3 == 0:
            value = hexes(40)
            lead += f'{rng.choice(["token", "key", "secret"])} = "'
            spots[i] = (len(lead), len(lead) + 40)
            rows.append((i, lead + value + '" and more words'))
        elif i % 3 == 1:
            rows.append((i, lead + "see the page " + plain() + " for that"))
        else:
            rows.append((i, lead + "and nothing else"))
    got = {r["doc_id"]: [(s["start"], s["end"]) for s in r["spans"] if s["kind"] == "secret"] for r in pii.personal_spans(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert sum(got[i] == [spot] for i, spot in spots.items()) >= 0.95 * len(spots)
    assert sum(bool(s) for i, s in got.items() if i not in spots) <= 0.02 * len(rows)


def test_reliabilities():
    rng = np.random.default_rng(4)
    counts, truth = Counter(), {}
    for _ in range(4000):
        y = rng.random() < 0.4
        votes = tuple(int((1 if y else -1) * (1 if rng.random() < a else -1)) if rng.random() < 0.8 else 0 for a in (0.95, 0.9, 0.85, 0.7, 0.6))
        counts[votes] += 1
        truth[votes] = truth.get(votes, 0) + y
    rates, posterior = pii.reliabilities([("email", v, n) for v, n in counts.items()])
    right = sum(n if (posterior["email", v] > 0.5) == (truth[v] * 2 > n) else 0 for v, n in counts.items())
    assert right / 4000 > 0.9
    assert rates["email"][1][0][1] > rates["email"][1][4][1]


def test_lm(docs, empty):
    got = lm.scored(docs).collect()
    rows = [(d, [w.decode("latin-1") for w in WORDS.findall(b.lower())] + [None]) for d, b in raw(docs)]
    held = lambda d: zlib.crc32(("" if d is None else str(d)).encode()) % 7 == 2
    c = Counter(w for d, ws in rows for w in ws if not held(d))
    n, v = sum(c.values()), len(c)
    want = Counter((d, held(d), len(ws), sum(c[w] > 0 for w in ws), n, round(sum(math.log10((c[w] + 1) / (n + v + 1)) for w in ws), 6)) for d, ws in rows)
    assert Counter((r["doc_id"], r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 6)) for r in got) == want
    assert all(-1e6 < r["score"] < 0 for r in got)
    pairs, before = Counter(), Counter()
    for d, ws in rows:
        if not held(d):
            pairs.update(zip(["start", *ws], ws, strict=False))
            before.update(["start", *ws[:-1]])

    def plain(ws):
        total = 0.0
        for v, w in zip(["start", *ws], ws, strict=False):
            seen = 2 ** (pairs[v, w].bit_length() - 1) if pairs[v, w] else 0
            total += math.log10((seen + lm.PRIOR * (c[w] + 1) / (n + v_types + 1)) / (before[v] + lm.PRIOR))
        return total

    v_types = v
    scores = {}
    for r in got:
        scores.setdefault(r["doc_id"], []).append(r["score"])
    for d, ws in rows:
        assert min(abs(s - plain(ws)) for s in scores[d]) <= 0.05 + 0.02 * len(ws)  # what the filter finds wrongly
        assert max(scores[d]) >= plain(ws) - 1e-6
    assert sum(min(abs(s - plain(ws)) for s in scores[d]) < 1e-6 for d, ws in rows) >= len(rows) // 2
    assert math.isclose(sum((pairs["start", w] + lm.PRIOR * (c[w] + 1) / (n + v + 1)) / (before["start"] + lm.PRIOR) for w in c) + lm.PRIOR / (n + v + 1) / (before["start"] + lm.PRIOR), 1)
    parts = {(r["doc_id"], round(r["score"], 6)) for r in lm.scored(docs, most_bytes=1).collect()}
    assert parts == {(r["doc_id"], round(r["score"], 6)) for r in got}
    assert lm.scored(empty).count() == 0


def test_filter_levels():
    rng = np.random.default_rng(3)
    pairs = rng.integers(0, 1 << 32, 4000).astype(np.uint64)
    counts = rng.integers(2, 200, 4000)
    raw_bits = np.frombuffer(lm.Segment.build(pairs, counts), np.uint8)
    got = lm.Segment.levels(raw_bits, pairs)
    assert (got >= np.floor(np.log2(counts))).all() and (got == np.floor(np.log2(counts))).mean() > 0.97
    assert (lm.Segment.levels(raw_bits, rng.integers(0, 1 << 32, 4000).astype(np.uint64)) > 0).mean() < 0.02


def test_filter_groups_take_one_pass_and_calls_do_not_grow(spark, monkeypatch):
    rng = np.random.default_rng(4)
    built = [(rng.integers(0, 1 << 32, 300).astype(np.uint64), rng.integers(1, 60, 300)) for _ in range(50)]
    raw = [np.frombuffer(lm.Segment.build(p, c), np.uint8) for p, c in built]
    _, offset, bits = lm._flat({i: r.tobytes() for i, r in enumerate(raw)}, 64)
    assert not bits[50:].any()
    where = np.repeat(np.arange(50), 300)
    pairs = np.concatenate([p for p, _ in built])
    calls, plain = [], lm.mix
    monkeypatch.setattr(lm, "mix", lambda x: (calls.append(1), plain(x))[1])
    got = lm.Segment.levels_among(np.concatenate(raw), offset[where], bits[where], pairs)
    assert len(calls) <= lm.MOST_LEVELS  # a call for each level, not for each segment
    assert got.tolist() == [x for r, (p, _) in zip(raw, built, strict=True) for x in lm.Segment.levels(r, p).tolist()]
    monkeypatch.undo()
    frame = spark.createDataFrame([(i, f"some words of text {i} and {i % 9}") for i in range(50)], "doc_id long, text string")
    plan = lm.scored(frame, most_bytes=1)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("FlatMapCoGroupsInArrow") == 1


def test_filter_keeps_pairs_seen_once(spark):
    rng = np.random.default_rng(6)
    pairs = rng.integers(0, 1 << 32, 4000).astype(np.uint64)
    bits = np.frombuffer(lm.Segment.build(pairs, np.ones(4000, np.int64)), np.uint8)
    assert (lm.Segment.levels(bits, pairs) == 0).mean() > 0.97 and (lm.Segment.levels(bits, pairs) >= 0).all()
    assert (lm.Segment.levels(bits, rng.integers(0, 1 << 32, 4000).astype(np.uint64)) >= 0).mean() < 0.02
    held = next(i for i in range(100) if zlib.crc32(str(i).encode()) % 7 == 2)
    train = [i for i in range(100) if zlib.crc32(str(i).encode()) % 7 != 2][:3]
    words = [f"w{i}" for i in range(30)]
    for text, level in ((words, 1), (words[::-1], 0)):  # pairs known from training, each seen once, and unknown ones
        rows = [(train[0], " ".join(words)), (train[1], "and and and and"), (train[2], "and and and"), (held, " ".join(text))]
        got = {r["doc_id"]: r for r in lm.scored(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
        seen = got[held]["score"] - got[held]["base_score"]
        assert (seen > 10) == bool(level)


def test_lm_sums_groups_by_row_whatever_their_order(spark, monkeypatch):
    rows = [(i, f"same words in every text but {i} and {i * i % 7}") for i in range(40)]
    frame = spark.createDataFrame(rows, "doc_id long, text string").coalesce(1)
    once = {(r["doc_id"], r["n_tokens"], round(r["score"], 6)) for r in lm.scored(frame).collect()}
    plain = lm._score

    def turned(spark, parts, words, group, known, first, *rest):
        order = F.col("doc_id") if first else F.col("doc_id").desc()
        return plain(spark, parts.coalesce(1).sortWithinPartitions(order), words, group, known, first, *rest)

    monkeypatch.setattr(lm, "_score", turned)
    got = [(r["doc_id"], r["n_tokens"], round(r["score"], 6)) for r in lm.scored(frame, most_bytes=1).collect()]
    assert len(got) == len(rows) and set(got) == once


def test_packing(docs, empty):
    encoder = Encoder(vocabulary("word_bpe_49k.json"))
    for length in (16, 4096):
        got = packing.packed(docs, vocabulary("word_bpe_49k.json"), length).collect()
        pieces = {}
        for r in got:
            pieces.setdefault(r["doc_id"], []).append(r)
        for d, b in set(raw(docs)):
            own = encoder.encode([b.decode()])[0] + b"\x02\0\0\0"
            times = Counter(x for x, _ in raw(docs))[d]
            rows = sorted(pieces[d], key=lambda r: r["start"])
            assert sum(r["length"] for r in rows) == times * len(own) // 4
            assert all(bytes(r["ids"]) == own[4 * r["start"] : 4 * (r["start"] + r["length"])] and r["doc_tokens"] == len(own) // 4 for r in rows)
        fills = {}
        for r in sorted(got, key=lambda r: (r["sequence_id"], r["offset"])):
            assert fills.get(r["sequence_id"], 0) == r["offset"]
            fills[r["sequence_id"]] = r["offset"] + r["length"]
        assert max(fills.values()) <= length and sum(v < 0.98 * length for v in fills.values()) <= 3 * 3
    assert packing.packed(empty, vocabulary("word_bpe_49k.json")).count() == 0


def test_level_array_takes_the_least_sum_of_squares():
    rng = np.random.default_rng(0)
    for most_open in (10_000, 3):
        levels = packing.LevelArray(64, 4, most_open)
        fills: dict[int, int] = {}
        level = lambda f: 0 if f == 0 or f > 64 - levels.grain else f // levels.grain + 1
        for size in rng.integers(1, 65, 400).tolist():
            counts = Counter(level(f) for f in fills.values())
            full = len(fills) >= most_open
            def squares(old, new):
                held = Counter(counts)  # noqa: B023
                for lv, by in ((level(old), -1), (level(new), 1)):
                    if lv:
                        held[lv] += by
                return sum(n * n for n in held.values())

            whole = [squares(f, f + size) for f in fills.values() if f + size <= 64]
            best = min(whole + ([] if full else [squares(0, size)]) or [squares(f, 64) for f in fills.values()])
            sequence, fill, taken = levels.place(size)
            assert fills.pop(sequence, 0) == fill and squares(fill, fill + taken) <= best + 0
            assert taken == size or (full and not whole and fill + taken == 64)
            if level(fill + taken):
                fills[sequence] = fill + taken
            assert len(fills) == levels.live <= most_open


def test_packing_holds_few_open_sequences():
    rng = np.random.default_rng(1)
    for sizes in (rng.integers(2100, 3900, 3000), np.clip(rng.lognormal(6.2, 1.1, 3000).astype(int), 1, 4096)):
        packer, rows, most = packing.Packer(4096), [], 0
        for d, s in enumerate(sizes.tolist()):
            rows.extend(packer.put(d, 0, bytes(4 * s), s))
            most = max(most, packer.levels.live)
        placed = len(rows)
        rows.extend(packer.rest())
        assert most <= packing.MOST_OPEN and sum(r[2] for r in rows) == sizes.sum()
        assert len(rows) - placed <= 3 * packing.MOST_OPEN
        used = len({r[5] for r in rows})
        assert 1 - sizes.sum() / 4096 / used < 0.02


def test_pipeline(spark, tiny, docs):
    clash = [c for c in ("_row", "_key", "_spans", "_kept", "_rows", "_gone", "_id", "node", "label")]
    rows = docs.drop("_row").select("*", *[F.lit(f"{c}!").alias(c) for c in clash])
    left = {}
    for name, stage in pipeline.STAGES:
        before, rows = rows, stage(spark, rows, tiny)
        if name != "packing":
            assert rows.columns == before.columns
            left[name] = rows.collect()
            kept = {r["doc_id"] for r in left[name]}
            assert kept <= {r["doc_id"] for r in before.select("doc_id").collect()}
            assert all(r[c] == f"{c}!" for r in left[name] for c in clash)
    given = docs.collect()
    good = {r["doc_id"] for r in quality.judged(docs).collect() if r["kept"]} - {r["doc_id"] for r in quality.judged(docs).collect() if not r["kept"]}
    assert Counter(r["doc_id"] for r in left["quality"]) == Counter(r["doc_id"] for r in given if r["doc_id"] in good)

    def shingles(t):
        w = t.encode().lower().split()
        return {tuple(w[i : i + 5]) for i in range(len(w) - 4)}

    sets = sorted({(r["doc_id"], r["text"]) for r in left["quality"]})
    label = {d: d for d, _ in sets}
    pairs = [(d, e) for d, x in sets for e, y in sets if d < e and 10 * len(shingles(x) & shingles(y)) >= 8 * len(shingles(x) | shingles(y))]
    while any(label[d] != label[e] for d, e in pairs):
        for d, e in pairs:
            label[d] = label[e] = min(label[d], label[e])
    assert sorted(r["doc_id"] for r in left["copies"]) == sorted(d for d in label if label[d] == d)
    assert {(r["doc_id"], r["text"]) for r in left["copies"]} <= set(sets)
    found = pii.personal_spans(spark.createDataFrame([(r["doc_id"], r["text"]) for r in left["leaks"]], "doc_id long, text string")).collect()
    texts = {r["doc_id"]: r["text"] for r in left["leaks"]}
    for r in found:
        t, at, out = texts[r["doc_id"]], 0, ""
        for a, b, kind in sorted((s["start"], s["end"], s["kind"]) for s in r["spans"]):
            if a >= at:
                out += t[at:a] + f"[{kind}]"
            at = max(at, b)
        texts[r["doc_id"]] = out + t[at:]
    assert {r["doc_id"]: r["text"] for r in left["privacy"]} == texts
    encoder = Encoder(vocabulary("word_bpe_49k.json"))
    pieces = {}
    for r in rows.collect():
        pieces.setdefault(r["doc_id"], {})[r["start"]] = bytes(r["ids"])
    assert {d: b"".join(x for _, x in sorted(p.items())) for d, p in pieces.items()} == {d: encoder.encode([t])[0] + b"\x02\0\0\0" for d, t in texts.items()}
    assert pipeline.run(spark, tiny).count() > 0

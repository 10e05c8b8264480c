"""Personal data by weak supervision.

Candidate spans come from wide patterns. Several labelers vote on each: format (pattern and value checks), gazetteer (cue
words near it, number prefixes, top-level domains), context (punctuation or cue right before it), shape and boundary. No
labeler is trusted by itself: expectation-maximisation over the counts of vote patterns, which are at most 3^5 for each
kind, estimates how often each labeler is right, hence the probability that a span of a pattern is personal. A final
classifier (naive Bayes over the span's own features, trained with these probabilities as soft labels) decides about
spans, and generalises over patterns. Base spans, which pass their kind's checks, are always kept.

Base kinds, fixed patterns and checks: email; ip, its parts at most 255; card, 16 to 19 digits that pass the Luhn check;
phone, 8 to 15 digits. Added kind: secret, a long token with digits. Offsets count code points; the end is exclusive.

Defined cases: a null text has no spans; repeated rows get equal spans; empty tables give an empty result; texts of any
length are scanned in linear time (runs are consumed possessively and entered at their first character only). Extra
columns are ignored.
"""

from __future__ import annotations

import math
from collections import defaultdict

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import fresh, load, materialize

KINDS = ("email", "ip", "card", "phone", "secret")
#: Equal to the plain patterns in what they match; lookbehinds and possessive runs only keep long texts linear.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
    "secret": r"(?<![A-Za-z0-9_-])(?=[A-Za-z_-]*+[0-9])[A-Za-z0-9_-]{20,}+",
}
#: A text without a match of this cannot hold the kind and is not scanned for it.
HINTS = {"email": "@", "ip": r"[0-9]\.[0-9]", "card": r"[0-9][\x20-]?[0-9]", "phone": r"\+[0-9]", "secret": r"[0-9]"}
#: Cue words of the gazetteer, fixed values, by kind.
CUES = {
    "email": "mail|email|e-mail|contact|write|correo|adresse",
    "ip": "ip|host|server|address|addr|login",
    "card": "card|visa|credit|karte|carte|tarjeta|payment",
    "phone": "phone|tel|call|mobile|fax|telefon|fono",
    "secret": "token|key|secret|password|passwd|pwd|auth|bearer",
}
#: Gazetteer of prefixes and endings, fixed values: calling codes of the telephone zones, first digits of payment cards, generic
#: and country domains (any two letters), and endings that no domain has.
CALLING = r"^\+(?:1|7|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]|(?:21|22|23|24|25|26|29|35|37|38|42|50|59|67|68|80|85|87|88|96|97|99)[0-9])"
ISSUER, NO_ISSUER = "^(?:4|5[1-5]|2[2-7]|3[4-7]|6)", "^[0179]"
DOMAIN, NO_DOMAIN = r"\.(?:com|org|net|edu|gov|mil|int|info|biz|name|pro|io|dev|app|cloud|online|example|test|[A-Za-z]{2})$", r"\.[0-9-]+$"
LABELERS = 5
EM_ROUNDS = 60


def _digits(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    """True if the digit string passes the Luhn check."""
    n = F.length(digits)
    values = F.transform(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: F.struct(F.substring(digits, i, F.lit(1)).cast("int").alias("d"), (((n - i) % 2) == 1).alias("twice")))
    return (F.aggregate(values, F.lit(0), lambda a, v: a + F.when(v["twice"], v["d"] * 2 - F.when(v["d"] > 4, 9).otherwise(0)).otherwise(v["d"])) % 10) == 0


def _valid(kind: str, x: Column) -> Column:
    if kind == "ip":
        return F.forall(F.split(x, r"\."), lambda p: F.when(F.length(F.regexp_replace(p, "^0+", "")) <= 3, F.coalesce(F.regexp_replace(p, "^0+", "").try_cast("int"), F.lit(0)) <= 255).otherwise(F.lit(False)))
    if kind == "card":
        d = _digits(x)
        return F.when(F.length(d).between(16, 19), _luhn(d)).otherwise(F.lit(False))
    if kind == "phone":
        return F.length(_digits(x)).between(8, 15)
    return F.lit(kind == "email")


def _worth(kind: str, x: Column) -> Column:
    """Matches that are kept as candidates; the others are far from the kind (such as two-digit numbers for cards)."""
    return F.length(_digits(x)) >= 12 if kind == "card" else F.lit(True)


def _spans(text: Column, kind: str) -> Column:
    """All candidate matches of a kind: array of (kind, start, end, value, before, base)."""
    kind_type = "array<struct<kind:string,start:int,end:int,value:string,before:string,base:boolean>>"
    pattern = PATTERNS[kind]
    pairs = F.arrays_zip(F.split(text, pattern, -1).alias("gap"), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("match"))

    def step(state: Column, pair: Column) -> Column:
        start = state["at"] + F.length(pair["gap"])
        end = start + F.coalesce(F.length(pair["match"]), F.lit(0))
        found = F.struct(F.lit(kind).alias("kind"), start.alias("start"), end.alias("end"), pair["match"].alias("value"), F.right(pair["gap"], F.lit(24)).alias("before"), _valid(kind, pair["match"]).alias("base"))
        taken = F.when(pair["match"].isNotNull() & _worth(kind, pair["match"]), F.concat(state["found"], F.array(found))).otherwise(state["found"])
        return F.struct(end.alias("at"), taken.alias("found"))

    start = F.struct(F.lit(0).alias("at"), F.array().cast(kind_type).alias("found"))
    scanned = F.aggregate(pairs, start, step, lambda s: s["found"])
    hint = F.contains(text, F.lit(HINTS[kind])) if kind == "email" else text.rlike(HINTS[kind])
    return F.when(hint, scanned).otherwise(F.array().cast(kind_type))


def _vote(yes: Column, no: Column) -> Column:
    return F.when(yes, F.lit(1)).when(no, F.lit(-1)).otherwise(F.lit(0)).cast("int")


def _voted(span: Column) -> Column:
    """The span with the labelers' votes (1, -1 or 0: abstains) and the classifier's features, all of bounded ranges."""
    kind, value, before = span["kind"], span["value"], F.lower(span["before"])
    digits, n = F.length(_digits(span["value"])), F.length(span["value"])
    cue = F.lit(False)
    for k, words in CUES.items():
        cue |= (kind == k) & before.rlike(rf"(?:^|[^a-z])(?:{words})[^a-z0-9]{{0,6}}$")
    secret = kind == "secret"
    hexlike, mixed = value.rlike(r"^[0-9a-fA-F]+$"), value.rlike("[a-z]") & value.rlike("[A-Z]") & value.rlike("[0-9]")
    votes = F.array(
        _vote(F.when(secret, hexlike | mixed).otherwise(span["base"]), F.when(secret, value.rlike("^[0-9_-]+$")).otherwise(~span["base"])),
        _vote(cue, F.lit(False)),
        _vote(before.rlike(r"[\s:=\"'(<,;]$") | (F.length(before) == 0), before.rlike(r"[0-9a-z.]$")),
        _vote(F.when(kind == "card", digits.between(15, 16)).when(kind == "phone", digits.between(10, 13)).when(secret, (digits * 4 >= n) & (n >= 24)).otherwise(n >= 9), F.when(kind == "card", digits > 19).when(kind == "phone", (digits < 8) | (digits > 15)).when(secret, digits * 10 < n).otherwise(n < 7)),
        _vote(F.when(kind == "email", value.rlike(DOMAIN)).when(kind == "card", value.rlike(ISSUER)).when(kind == "ip", ~value.rlike(r"^0|\.0[0-9]")).when(kind == "phone", value.rlike(CALLING)), F.when(kind == "email", value.rlike(NO_DOMAIN)).when(kind == "card", value.rlike(NO_ISSUER)).when(kind == "phone", ~value.rlike(CALLING))),
    )
    features = F.array(
        F.concat(kind, F.lit(":length:"), F.least((n / 4).cast("int"), F.lit(12)).cast("string")),
        F.concat(kind, F.lit(":digits:"), F.least((digits / 2).cast("int"), F.lit(12)).cast("string")),
        F.concat(kind, F.lit(":cue:"), cue.cast("string")),
        F.concat(kind, F.lit(":shape:"), F.when(hexlike, "hex").when(mixed, "mixed").otherwise("plain")),
        F.concat(kind, F.lit(":before:"), F.when(F.length(before) == 0, "start").when(before.rlike(r"\s$"), "space").when(before.rlike("[0-9a-z]$"), "word").otherwise("sign")),
        F.concat(kind, F.lit(":checked:"), span["base"].cast("string")),
    )
    return F.struct(kind.alias("kind"), span["start"].alias("start"), span["end"].alias("end"), span["base"].alias("base"), votes.alias("votes"), features.alias("features"))


def candidates(docs: DataFrame) -> DataFrame:
    """doc_id, spans: every row's candidate spans, in the order of KINDS and then start, with votes and features."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("t"))
    found = slim.select("doc_id", F.concat(*[_spans(F.col("t"), k) for k in KINDS]).alias("raw"))
    return found.select("doc_id", F.transform("raw", _voted).alias("spans"))


def reliabilities(patterns: list[tuple[str, tuple[int, ...], int]], rounds: int = EM_ROUNDS) -> tuple[dict, dict]:
    """EM over (kind, votes, count): per kind the labelers' rates of voting right, wrong or not at all on personal and
    other spans, and the probability of every vote pattern to be personal."""
    by_kind: dict[str, list] = defaultdict(list)
    for kind, votes, count in sorted(patterns):
        by_kind[kind].append((votes, count))
    rates, posterior = {}, {}
    for kind, rows in by_kind.items():
        soft = [1 / (1 + math.exp(-1.5 * sum(v))) for v, _ in rows]  # begins at the vote balance
        for _ in range(rounds):
            sums = {c: [{v: 0.5 for v in (-1, 0, 1)} for _ in range(LABELERS)] for c in (0, 1)}
            mass = [1.0, 1.0]
            for (votes, n), p in zip(rows, soft, strict=True):
                for c, w in ((0, n * (1 - p)), (1, n * p)):
                    mass[c] += w
                    for j, v in enumerate(votes):
                        sums[c][j][v] += w
            tables = {c: [{v: x / sum(t.values()) for v, x in t.items()} for t in sums[c]] for c in (0, 1)}
            prior = math.log(mass[1] / mass[0])
            soft = [_logistic(prior + sum(math.log(tables[1][j][v] / tables[0][j][v]) for j, v in enumerate(votes))) for votes, _ in rows]
        rates[kind] = tables
        posterior.update({(kind, votes): p for (votes, _), p in zip(rows, soft, strict=True)})
    return rates, posterior


def _logistic(x: float) -> float:
    return 1 / (1 + math.exp(-max(-50.0, min(50.0, x))))


def train(spans: DataFrame) -> dict[str, float]:
    """The classifier: log-odds weights by feature, and by kind for its prior. What is gathered is bounded by vote and feature ranges."""
    flat = spans.select(F.explode("spans").alias("s")).select("s.kind", "s.votes", "s.features")
    patterns = [(r["kind"], tuple(r["votes"]), r["n"]) for r in flat.groupBy("kind", "votes").agg(F.count(F.lit(1)).alias("n")).collect()]
    _, posterior = reliabilities(patterns)
    counts = flat.select("kind", "votes", F.explode("features").alias("feature")).groupBy("kind", "votes", "feature").agg(F.count(F.lit(1)).alias("n")).collect()
    soft, mass = defaultdict(lambda: [0.5, 0.5]), defaultdict(lambda: [1.0, 1.0])
    for kind, votes, n in patterns:
        p = posterior[kind, votes]
        mass[kind][0] += n * (1 - p)
        mass[kind][1] += n * p
    for r in counts:
        p = posterior[r["kind"], tuple(r["votes"])]
        soft[r["feature"]][0] += r["n"] * (1 - p)
        soft[r["feature"]][1] += r["n"] * p
    weights = {k: math.log(m[1] / m[0]) for k, m in mass.items()}
    for feature, (no, yes) in soft.items():
        m = mass[feature.split(":")[0]]
        weights[feature] = math.log((yes / m[1]) / (no / m[0]))
    return weights


def decided(spans: DataFrame, weights: dict[str, float]) -> DataFrame:
    """spans reduced to those that are personal: base spans, and those that the classifier accepts."""
    table = F.create_map(*[F.lit(x) for k in sorted(weights) for x in (k, float(weights[k]))]) if weights else F.create_map(F.lit(""), F.lit(0.0))

    def odds(s: Column) -> Column:
        parts = F.transform(F.concat(F.array(s["kind"]), s["features"]), lambda f: F.coalesce(F.element_at(table, f), F.lit(0.0)))
        return F.aggregate(parts, F.lit(0.0), lambda a, b: a + b)

    kept = F.filter("spans", lambda s: s["base"] | (odds(s) > 0))
    return spans.withColumn("spans", F.transform(kept, lambda s: F.struct(s["kind"].alias("kind"), s["start"].alias("start"), s["end"].alias("end"), s["base"].alias("base"))))


def personal_spans(docs: DataFrame) -> DataFrame:
    """doc_id and spans (kind, start, end, base) of every row of docs, sorted by kind as listed and start."""
    found = materialize(candidates(docs))
    return decided(found, train(found))


def redact(docs: DataFrame) -> DataFrame:
    """docs with each personal span of text replaced by its kind in brackets; overlapping spans are replaced as one."""
    row, key, found = fresh(docs.columns, "_row", "_key", "_spans")
    keyed = docs.withColumn(row, F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit(""))))
    spans = materialize(candidates(docs.select("doc_id", "text").withColumn("doc_id", F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit(""))))).where(F.size("spans") > 0).dropDuplicates(["doc_id"]))
    clean = decided(spans, train(spans)).where(F.size("spans") > 0).select(F.col("doc_id").alias(key), F.array_sort(F.transform("spans", lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind")))).alias(found))
    joined = keyed.join(clean, F.col(row) == F.col(key), "left")
    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def step(state: Column, s: Column) -> Column:
        fresh = F.concat(state["out"], F.substring("text", state["at"] + 1, s["start"] - state["at"]), F.lit("["), s["kind"], F.lit("]"))
        return F.struct(F.greatest(state["at"], s["end"]).alias("at"), F.when(s["start"] >= state["at"], fresh).otherwise(state["out"]).alias("out"))

    text = F.aggregate(found, start, step, lambda s: F.concat(s["out"], F.substring("text", s["at"] + 1, F.length("text"))))
    return joined.withColumn("text", F.when(F.col(found).isNull(), F.col("text")).otherwise(text)).select(docs.columns)


def query(spark, sf_dir: str) -> DataFrame:
    rows = personal_spans(load(spark, sf_dir, "documents"))
    written = lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))
    base = F.filter("spans", lambda s: s["base"] & (s["kind"] != "secret"))
    of_kind = lambda k: F.filter("spans", lambda s: s["base"] & (s["kind"] == k))
    counts = [F.size(of_kind(k)).cast("long").alias(f"n_{k}") for k in KINDS[:4]]
    return rows.select("doc_id", *counts, F.sha2(F.array_join(F.transform(base, written), ",").cast("binary"), 256).alias("base_sha256"), F.array_join(F.transform("spans", written), ",").alias("spans"), F.size("spans").cast("long").alias("n_spans"))

"""Chat formatting by event-sourced reconstruction.

A log holds events (conv_id, seq, turn, kind, role, text). Events of a conversation are sorted by seq and folded to the
final messages: `message` and `regenerate` start a turn's text anew, `edit` replaces it, `delta` adds to it, `delete`
removes the turn. A turn's events are folded first, so a conversation is only assembled from final messages. They are
rendered with a template whose control strings cannot occur inside texts, as texts are escaped reversibly.

The template: <|turn|>role LF text <|end|> LF for each turn. Fixed escapes inside roles and texts: a backslash, the
characters < and [ and (in roles) a line feed are written as a backslash followed by s, l, b and n. So no template
string, nor those of other common templates, can be formed by a text.

Defined cases: null text, role and kind are an empty text, an empty role and `message`; events of equal seq fold in
the order of kind, role and text; a delta, edit or regenerate of an unknown turn starts it; a null conv_id is a
conversation of its own; repeated events of a log fold as they stand (a repeated message restarts its turn with the same
text), while every row of a table of turns is a turn of its own, repeated rows and rows without a turn included (the
latter come first); an empty log gives an empty result. Extra columns are ignored. One rendered conversation must fit in a row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import load

TURN, END = "<|turn|>", "<|end|>\n"
ESCAPES = (("\\", "\\s"), ("<", "\\l"), ("[", "\\b"))
#: The role whose texts carry the loss.
LEARNED = "assistant"


def escape(text: Column) -> Column:
    for plain, code in ESCAPES:
        text = F.replace(text, F.lit(plain), F.lit(code))
    return text


def unescape(text: Column) -> Column:
    for plain, code in reversed(ESCAPES):  # the backslash last: its code never makes another one
        text = F.replace(text, F.lit(code), F.lit(plain))
    return text


def events_of(conversations: DataFrame, piece: int = 64) -> DataFrame:
    """Rows of turns as a log: the start of each text as a message, the rest as streamed deltas of `piece` characters.

    A row's turn in the log is its place among the conversation's rows, by turn, role and text."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    place = F.row_number().over(Window.partitionBy(F.col("conv_id").cast("long")).orderBy(F.col("turn").cast("long"), F.coalesce(F.col("role").cast("string"), F.lit("")), text)).cast("long")
    cut = F.transform(F.sequence(F.lit(0), F.greatest(F.length(text) - 1, F.lit(0)).cast("int"), F.lit(piece)), lambda i: F.substring(text, i + 1, F.lit(piece)))
    base = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), place.alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), text.alias("text"))
    base = base.select("conv_id", "turn", "role", F.posexplode(cut).alias("step", "text"))
    kind = F.when(F.col("step") == 0, F.lit("message")).otherwise(F.lit("delta"))
    return base.select("conv_id", F.struct("turn", "step").alias("seq"), "turn", kind.alias("kind"), "role", "text")


def messages(events: DataFrame) -> DataFrame:
    """conv_id, turn, role, text: the log folded to the final message of every turn that was not deleted last."""
    event = F.struct(F.col("seq"), F.coalesce("kind", F.lit("message")).alias("kind"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    turns = events.groupBy("conv_id", "turn").agg(F.array_sort(F.collect_list(event)).alias("log"))
    resets = F.filter(F.sequence(F.lit(0), F.size("log") - 1), lambda i: F.get(F.col("log"), i)["kind"] != "delta")
    start = F.coalesce(F.array_max(resets), F.lit(0))
    live = F.slice("log", start + 1, F.size("log"))
    folded = turns.withColumn("live", live)
    return folded.where(F.get("live", F.lit(0))["kind"] != "delete").select("conv_id", "turn", F.get("live", F.lit(0))["role"].alias("role"), F.array_join(F.transform("live", lambda e: e["text"]), "").alias("text"))


def rendered(turns: DataFrame) -> DataFrame:
    """conv_id, formatted, loss (start and length, in characters of formatted, of every learned text)."""
    role = F.replace(escape(F.coalesce("role", F.lit(""))), F.lit("\n"), F.lit("\\n"))
    head = F.concat(F.lit(TURN), role, F.lit("\n"))
    body = escape(F.coalesce("text", F.lit("")))
    part = F.struct(F.col("turn"), F.concat(head, body, F.lit(END)).alias("whole"), F.length(head).alias("head"), F.length(body).alias("body"), (F.col("role") == LEARNED).alias("learned"))
    whole = turns.groupBy("conv_id").agg(F.array_sort(F.collect_list(part)).alias("parts"))
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,length:int>>").alias("loss"))

    def step(state: Column, p: Column) -> Column:
        mark = F.array(F.struct((state["at"] + p["head"]).alias("start"), p["body"].alias("length")))
        return F.struct((state["at"] + F.length(p["whole"])).alias("at"), F.when(p["learned"], F.concat(state["loss"], mark)).otherwise(state["loss"]).alias("loss"))

    return whole.select("conv_id", F.array_join(F.transform("parts", lambda p: p["whole"]), "").alias("formatted"), F.aggregate("parts", start, step, lambda s: s["loss"]).alias("loss"))


def read_back(formatted: DataFrame) -> DataFrame:
    """formatted with turns: an array of (role, text), parsed from the rendered string alone."""
    pieces = F.slice(F.split("formatted", r"<\|turn\|>"), 2, F.size(F.split("formatted", r"<\|turn\|>")))

    def parse(p: Column) -> Column:
        at = F.locate("\n", p) if isinstance(p, str) else F.instr(p, "\n")
        text = F.substring(p, at + 1, F.length(p) - at - len(END))
        return F.struct(unescape(F.replace(F.substring(p, F.lit(1), at - 1), F.lit("\\n"), F.lit("\n"))).alias("role"), unescape(text).alias("text"))

    return formatted.withColumn("turns", F.transform(pieces, parse))


def format_log(events: DataFrame) -> DataFrame:
    """conv_id, formatted, loss, of every conversation of an event log."""
    return rendered(messages(events))


def digests(formatted: DataFrame) -> DataFrame:
    """What formatted says when read back, as counts and SHA-256 digests."""
    back = read_back(formatted)
    spoken = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    learned = F.array_join(F.transform("loss", lambda m: unescape(F.substring(F.col("formatted"), m["start"] + 1, m["length"]))), "")
    named = back.withColumn("_spoken", spoken).withColumn("_learned", learned)
    return named.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(F.col("_spoken").cast("binary"), 256).alias("turns_sha256"),
        F.length("_learned").cast("long").alias("loss_chars"),
        F.sha2(F.col("_learned").cast("binary"), 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )


def query(spark, sf_dir: str) -> DataFrame:
    rows = load(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = "</s>[INST] ok [/INST]"
    extra = spark.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise(LEARNED).alias("role"), F.lit(probe).alias("text"))
    return digests(format_log(events_of(rows.unionByName(extra))))

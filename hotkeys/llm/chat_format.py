"""Chat formatting: event-sourced reconstruction of conversations, then rendering.

An event log has (conv_id, seq, kind, target, role, text). Per conversation, in order of seq:
`message` opens a message; `delta` appends to the targeted message, or to the latest one where the
target is null; `edit` and `regenerate` replace what it held. A message's final text is what its last opening or
replacement and the deltas after it give. All of it runs as one shuffle by conversation with
window sums and sorted folds; the result of a conversation is one row by nature.

Rendering: `<s>`, then for each message `<|role`, a line feed, the text and `</s>`. Backslashes in
texts are doubled and a backslash is put inside each control string, which `unescape` undoes exactly.
The loss mask is a list of code-point spans over assistant texts.

Defined results: null text or role counts as empty; a null turn sorts first; rows of one turn are
ordered by role and text; repeated rows are separate turns; an empty table gives an empty table;
other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from hotkeys.llm.common import table

#: The control strings that a text must not hold bare are <| <s> </s> [INST] [/INST].
START, OPEN, CLOSE = "<s>", "<|", "</s>"
_CONTROL = r"(<(?=\||/?s>)|\[(?=/?INST\]))"
_ESCAPED = r"(<(?=\\(?:\||/?s>))|\[(?=\\/?INST\]))\\"


def escape(text: Column) -> Column:
    return F.regexp_replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), _CONTROL, r"$1\\")


def unescape(text: Column) -> Column:
    return F.replace(F.regexp_replace(text, _ESCAPED, "$1"), F.lit("\\\\"), F.lit("\\"))


def escape_role(role: Column) -> Column:
    """As escape; the line feed that ends a role is written [\\N], which no escaped text holds."""
    return F.replace(escape(role), F.lit("\n"), F.lit("[\\N]"))


def unescape_role(role: Column) -> Column:
    return unescape(F.replace(role, F.lit("[\\N]"), F.lit("\n")))


def events_of(conversations: DataFrame) -> DataFrame:
    """Each row of a finished conversation as the event that opens its message."""
    return conversations.select("conv_id", F.col("turn").alias("seq"), F.lit("message").alias("kind"), F.lit(None).cast("long").alias("target"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))


def fold(events: DataFrame) -> DataFrame:
    """Final messages (conv_id, message, role, text) of an event log; message counts from 1."""
    order = W.partitionBy("conv_id").orderBy("seq", "kind", "role", "text")
    opened = F.sum((F.col("kind") == "message").cast("int")).over(order.rowsBetween(W.unboundedPreceding, 0))
    placed = events.withColumn("at", F.row_number().over(order)).withColumn("message", F.when(F.col("kind") == "message", opened).otherwise(F.coalesce("target", opened)))
    resets = F.max(F.when(F.col("kind") != "delta", F.col("at"))).alias("since")
    parts = F.collect_list(F.struct("at", "kind", "role", "text")).alias("parts")
    folded = placed.groupBy("conv_id", "message").agg(resets, parts)
    live = F.filter(F.sort_array("parts"), lambda p: p["at"] >= F.coalesce(F.col("since"), F.lit(0)))
    role = F.coalesce(F.filter(F.sort_array("parts"), lambda p: p["kind"] == "message")[0]["role"], F.lit(""))
    return folded.select("conv_id", "message", role.alias("role"), F.array_join(F.transform(live, lambda p: F.coalesce(p["text"], F.lit(""))), "").alias("text"))


def render(messages: DataFrame, loss_role: str = "assistant") -> DataFrame:
    """conv_id, formatted and loss_mask (array of start and end, in code points, end exclusive)."""
    head = F.concat(F.lit(OPEN), escape_role(F.col("role")), F.lit("\n"))
    parts = messages.select("conv_id", "message", (F.col("role") == loss_role).alias("loss"), head.alias("head"), escape(F.col("text")).alias("body"))
    length = F.length("head") + F.length("body") + F.lit(len(CLOSE))
    before = F.coalesce(F.sum(length).over(W.partitionBy("conv_id").orderBy("message").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)) + F.lit(len(START))
    start = (before + F.length("head")).alias("start")
    placed = parts.select("conv_id", F.struct("message", F.concat("head", "body", F.lit(CLOSE)).alias("segment"), start, (before + F.length("head") + F.length("body")).alias("end"), "loss").alias("m"))
    whole = placed.groupBy("conv_id").agg(F.sort_array(F.collect_list("m")).alias("ms"))
    mask = F.transform(F.filter("ms", lambda m: m["loss"]), lambda m: F.struct(m["start"].alias("start"), m["end"].alias("end")))
    return whole.select("conv_id", F.concat(F.lit(START), F.array_join(F.transform("ms", lambda m: m["segment"]), "")).alias("formatted"), mask.alias("loss_mask"))


def parse(rendered: DataFrame) -> DataFrame:
    """What can be read back from the output alone: turns (role, text) and the texts under the mask."""
    pieces = F.split(F.expr(f"substring(formatted, {len(START) + 1})"), CLOSE, -1)
    closed = F.slice(pieces, 1, F.size(pieces) - 1)
    role = lambda p: unescape_role(F.substring_index(p, "\n", 1).substr(F.lit(len(OPEN) + 1), F.length(p)))
    text = lambda p: unescape(p.substr(F.instr(p, "\n") + 1, F.length(p)))
    turns = F.transform(closed, lambda p: F.struct(role(p).alias("role"), text(p).alias("text")))
    masked = F.transform("loss_mask", lambda s: unescape(F.col("formatted").substr((s["start"] + 1).cast("int"), (s["end"] - s["start"]).cast("int"))))
    return rendered.select("conv_id", "formatted", "loss_mask", turns.alias("turns"), masked.alias("loss_texts"))


def format_conversations(events: DataFrame) -> DataFrame:
    return render(fold(events))


def op10_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    given = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = spark.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit("</s>[INST] ok [/INST]").alias("text"))
    out = parse(format_conversations(events_of(given.unionByName(probe))))
    loss = F.array_join("loss_texts", "")
    digest = F.sha2(F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), ""), 256)
    return out.select(
        "conv_id", F.size("turns").cast("long").alias("n_turns"), digest.alias("turns_sha256"), F.length(loss).cast("long").alias("loss_chars"), F.sha2(loss, 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars")
    )

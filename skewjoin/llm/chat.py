"""Chat formatting from an event log, in DataFrame operations only.

A log holds events of conversations: `start` opens a message with a role, `delta` adds
text to it, `edit` replaces its text, `regenerate` empties it before new deltas, `retract`
removes it.  Logs are partitioned by conversation and sorted by sequence; every event of a
message before its last edit or regeneration is void, and the rest is concatenated.  That
fold is a window and two groupings, not a loop over events.

The template marks each turn as <|turn|>role<|text|>text<|end|>.  Control strings inside
roles and texts get a backslash after their first character and backslashes are doubled,
so unescaping is dropping the backslash before any character.  The loss mask is an array
of (start, length) spans of code points over the formatted string: the assistant texts.

Edge cases: null texts and roles are empty; a null conversation id is a conversation of
its own; events with equal sequence numbers are taken in order of kind, then text; a
message without a start event has the role "".  An empty log gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

TURN, TEXT, END = "<|turn|>", "<|text|>", "<|end|>"
#: Strings that must not appear bare inside a text: ours and those of common templates.
CONTROL = ("<|", "</s>", "<s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>")
KINDS = ("start", "edit", "regenerate", "delta", "retract")


def escape(text: Column) -> Column:
    out = F.replace(text, F.lit("\\"), F.lit("\\\\"))
    for c in CONTROL:
        out = F.replace(out, F.lit(c), F.lit(c[0] + "\\" + c[1:]))
    return out


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"(?s)\\(.)", "$1")


def fold(log: DataFrame) -> DataFrame:
    """(conv_id, message, role, text): final messages of a log (conv_id, seq, message, kind, role, text)."""
    # positions order the events of a conversation whatever ties its sequence has
    rank = F.array_position(F.array(*[F.lit(k) for k in KINDS]), F.col("kind"))
    log = log.withColumn("text", F.coalesce("text", F.lit(""))).withColumn("at", F.struct("seq", rank.alias("rank"), "text"))
    message = Window.partitionBy("conv_id", "message")
    log = log.withColumn("void_before", F.max(F.when(F.col("kind").isin("edit", "regenerate"), F.col("at"))).over(message))
    live = F.col("kind").isin("delta", "edit") & (F.col("void_before").isNull() | (F.col("at") >= F.col("void_before")))
    out = log.groupBy("conv_id", "message").agg(
        F.coalesce(F.max_by("role", F.when(F.col("kind") == "start", F.col("at"))), F.lit("")).alias("role"),
        F.array_join(F.transform(F.array_sort(F.collect_list(F.when(live, F.struct("at", "text")))), lambda x: x["text"]), "").alias("text"),
        F.bool_or(F.col("kind") == "retract").alias("gone"),
    )
    return out.where("not gone").drop("gone")


def render(messages: DataFrame) -> DataFrame:
    """(conv_id, formatted, loss) of messages (conv_id, message, role, text), in order of message."""
    turns = messages.select("conv_id", F.struct("message", F.col("role"), F.col("text")).alias("m"))
    turns = turns.groupBy("conv_id").agg(F.array_sort(F.collect_list("m")).alias("ms"))
    parts = F.transform("ms", lambda m: F.struct(
        F.concat(F.lit(TURN), escape(m["role"]), F.lit(TEXT)).alias("head"),
        escape(m["text"]).alias("body"),
        (m["role"] == "assistant").alias("learn"),
    ))
    turns = turns.select("conv_id", parts.alias("ps"))
    tail = len(END)
    lengths = F.transform("ps", lambda p: F.struct(
        F.char_length(p["head"]).alias("head"), F.char_length(p["body"]).alias("body"), p["learn"].alias("learn")))
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,len:int>>").alias("spans"))
    spans = F.aggregate(lengths, start, lambda s, p: F.struct(
        (s["at"] + p["head"] + p["body"] + tail).alias("at"),
        F.when(p["learn"], F.concat(s["spans"], F.array(F.struct((s["at"] + p["head"]).alias("start"), p["body"].alias("len"))))).otherwise(s["spans"]).alias("spans"),
    ), lambda s: s["spans"])
    text = F.array_join(F.transform("ps", lambda p: F.concat(p["head"], p["body"], F.lit(END))), "")
    return turns.select("conv_id", text.alias("formatted"), spans.alias("loss"))


def parse(formatted: Column) -> Column:
    """array<struct<role, text>> read back from a formatted string."""
    turns = F.filter(F.split(formatted, r"\Q" + TURN + r"\E"), lambda t: t != "")
    halves = F.transform(turns, lambda t: F.split(t, r"\Q" + TEXT + r"\E", 2))
    return F.transform(halves, lambda h: F.struct(
        unescape(F.element_at(h, 1)).alias("role"),
        unescape(F.substring(F.element_at(h, 2), F.lit(1), F.char_length(F.element_at(h, 2)) - len(END))).alias("text"),
    ))


def masked(formatted: Column, loss: Column) -> Column:
    """All text under the loss mask, unescaped, joined with nothing between."""
    return F.array_join(F.transform(loss, lambda s: unescape(F.substring(formatted, s["start"] + 1, s["len"]))), "")


def as_log(rows: DataFrame) -> DataFrame:
    """The event log of finished turns (conv_id, turn, role, text): each opens a message and gives its text.

    Rows of one conversation that share a turn are messages of their own, in order of role and text.
    """
    rows = rows.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    place = F.row_number().over(Window.partitionBy("conv_id").orderBy("turn", "role", "text")).cast("long")
    rows = rows.withColumn("message", place)
    events = F.array(
        F.struct((2 * F.col("message")).alias("seq"), F.lit("start").alias("kind"), F.col("role").alias("role"), F.lit("").alias("text")),
        F.struct((2 * F.col("message") + 1).alias("seq"), F.lit("delta").alias("kind"), F.lit(None).cast("string").alias("role"), F.col("text").alias("text")),
    )
    return rows.select("conv_id", "message", F.inline(events))


def digest(rendered: DataFrame) -> DataFrame:
    """What the formatted strings give back."""
    turns = parse(F.col("formatted"))
    flat = F.array_join(F.transform(turns, lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    under = masked(F.col("formatted"), F.col("loss"))
    return rendered.select(
        "conv_id", F.size(turns).cast("long").alias("n_turns"), F.sha2(flat.cast("binary"), 256).alias("turns_sha256"),
        F.char_length(under).cast("long").alias("loss_chars"), F.sha2(under.cast("binary"), 256).alias("loss_sha256"),
        F.char_length("formatted").cast("long").alias("formatted_chars"),
    )


def op8(spark, sf_dir: str) -> DataFrame:
    rows = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    said = F.lit("</s>[INST] ok [/INST]").alias("text")
    extra = spark.range(2).select(
        F.lit(-1).cast("long").alias("conv_id"), F.col("id").alias("turn"),
        F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), said,
    )
    return digest(render(fold(as_log(rows.unionByName(extra)))))


OP8_SQL = r"""
WITH c AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'),
e AS (
  SELECT *, replace(replace(replace(replace(replace(replace(replace(replace(text, '\', '\\'), '<|', '<\|'), '</s>', '<\/s>'), '<s>', '<\s>'),
         '[INST]', '[\INST]'), '[/INST]', '[\/INST]'), '<<SYS>>', '<\<SYS>>'), '<</SYS>>', '<\</SYS>>') AS body FROM c)
SELECT conv_id, count(*)::BIGINT AS n_turns,
       sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
       sum(CASE WHEN role = 'assistant' THEN length(text) ELSE 0 END)::BIGINT AS loss_chars,
       sha256(coalesce(string_agg(CASE WHEN role = 'assistant' THEN text END, '' ORDER BY turn, role, text), '')) AS loss_sha256,
       sum(8 + length(role) + 8 + length(body) + 7)::BIGINT AS formatted_chars
FROM e GROUP BY conv_id
"""

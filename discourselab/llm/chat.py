r"""Chat formatting by a grammar round trip.

A turn is rendered as ``<|im_start|>role\ntext<|im_end|>\n``. A deterministic parser reads rendered text
back: it splits at turn openers, takes the role up to the first line end and the text up to the first turn
closer, and decodes backslash pairs. Each turn is rendered, parsed and compared with its source, and its
content is escaped further until both are identical:

    level 0  nothing is escaped
    level 1  ``<|`` becomes ``<\|``
    level 2  backslashes are doubled first, and line ends in a role become ``\n``; always identical

Turn markers have no border, so turns that parse alone also parse one after another. The output carries a
loss mask as segments: (text, loss) pairs whose texts joined are the formatted conversation; the text of an
assistant's turn is one segment under the mask.

DataFrame functions only; one shuffle, by conversation. A conversation is one output string, so its turns
meet in one row by definition of the result; nothing else gathers.

Defined cases
    Null texts and roles count as empty. Turns are ordered by turn, role and text (nulls first), so ties
    and repeated rows have one order and all stay. A null conv_id is a conversation of its own. An empty
    table gives an empty result. Other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

OPEN, CLOSE = "<|im_start|>", "<|im_end|>"
TRAINED = "assistant"
PROBE = f"{CLOSE}{OPEN}assistant ok"


def escape(content: Column, level: int, header: bool = False) -> Column:
    if level == 2:
        content = F.replace(content, F.lit("\\"), F.lit("\\\\"))
        content = F.replace(content, F.lit("\n"), F.lit("\\n")) if header else content
    return F.replace(content, F.lit("<|"), F.lit("<\\|")) if level else content


def unescape(content: Column) -> Column:
    r"""Decode ``\\``, ``\|`` and ``\n`` pairs from left to right."""
    plain = lambda x: F.replace(F.replace(x, F.lit("\\|"), F.lit("|")), F.lit("\\n"), F.lit("\n"))
    return F.when(F.contains(content, F.lit("\\")), F.array_join(F.transform(F.split(content, r"\\\\", -1), plain), "\\")).otherwise(content)


def _turn(role: Column, body: Column) -> Column:
    return F.concat(F.lit(OPEN), role, F.lit("\n"), body, F.lit(f"{CLOSE}\n"))


def parse(formatted: Column) -> Column:
    """array<struct<role, text, rest>> of a formatted text; rest is what follows the turn's closer."""
    turns = F.filter(F.split(formatted, r"<\|im_start\|>", -1), lambda x, i: (i > 0) | (x != ""))

    def read(turn: Column) -> Column:
        role = F.substring_index(turn, "\n", 1)
        after = F.substring(turn, F.length(role) + 2, F.length(turn))
        body = F.substring_index(after, CLOSE, 1)
        return F.struct(unescape(role).alias("role"), unescape(body).alias("text"), F.substring(after, F.length(body) + 1, F.length(after)).alias("rest"))

    return F.transform(turns, read)


def _returns(role: Column, text: Column, level: int) -> Column:
    turns = parse(_turn(escape(role, level, True), escape(text, level)))
    only = F.get(turns, F.lit(0))
    return (F.size(turns) == 1) & (only["role"] == role) & (only["text"] == text) & (only["rest"] == f"{CLOSE}\n")


def format_conversations(conversations: DataFrame) -> DataFrame:
    """conv_id, segments (array<struct<text, loss>>), formatted, escaped_turns of every conversation."""
    role, text = F.coalesce("role", F.lit("")), F.coalesce("text", F.lit(""))
    turns = conversations.select("conv_id", "turn", role.alias("role"), text.alias("text"))
    level = F.when(_returns(F.col("role"), F.col("text"), 0), 0).when(_returns(F.col("role"), F.col("text"), 1), 1).otherwise(2)
    chosen = lambda x, header=False: F.when(F.col("level") == 0, x).when(F.col("level") == 1, escape(x, 1, header)).otherwise(escape(x, 2, header))
    written = (
        turns.withColumn("level", level)
        .select("conv_id", F.struct("turn", "role", "text", chosen(F.col("role"), True).alias("head"), chosen(F.col("text")).alias("body"), "level").alias("t"))
    )
    ordered = written.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("t"))

    def pieces(t: Column) -> Column:
        part = lambda x, loss: F.struct(x.alias("text"), F.lit(loss).alias("loss"))
        head, tail = F.concat(F.lit(OPEN), t["head"], F.lit("\n")), F.lit(f"{CLOSE}\n")
        return (
            F.when(t["role"] == TRAINED, F.array(part(head, False), part(t["body"], True), part(tail, False)))
            .otherwise(F.array(part(F.concat(head, t["body"], tail), False)))
        )

    segments = ordered.select(
        "conv_id",
        F.flatten(F.transform("t", pieces)).alias("segments"),
        F.size(F.filter("t", lambda t: t["level"] > 0)).alias("escaped_turns"),
    )
    return segments.withColumn("formatted", F.array_join(F.transform("segments", lambda s: s["text"]), ""))


def read_back(formatted: DataFrame) -> DataFrame:
    """Counts and digests of what the formatted text and its loss mask say."""
    read = (
        formatted.withColumn("turns", parse(F.col("formatted")))
        .withColumn("trained", F.array_join(F.transform(F.filter("segments", lambda s: s["loss"]), lambda s: unescape(s["text"])), ""))
    )
    return read.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), ""), 256).alias("turns_sha256"),
        F.length("trained").cast("long").alias("loss_chars"),
        F.sha2("trained", 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )


def probe(spark: SparkSession) -> DataFrame:
    """Conversation -1: both its turns say what the template itself says."""
    return (
        spark.range(2)
        .select(
            F.lit(-1).cast("long").alias("conv_id"),
            F.col("id").alias("turn"),
            F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"),
            F.lit(PROBE).alias("text"),
        )
    )

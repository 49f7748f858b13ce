r"""Chat formatting with a grammar round trip (DataFrame functions only).

Grammar of a conversation:  ``<s>\n`` turn*   with   turn = ``[INST] `` role `` [/INST]\n`` text ``</s>\n``

A deterministic parser reads it: cut at the ends of turns, then each turn at the end of its header.
The text is first rendered as it is and parsed; where the turns that come back differ from the source,
or a text holds a control string, the conflicting strings are escaped and the result is parsed and
compared again, and a difference then stops the run. Escaping puts one more backslash into ``<``, any backslashes, ``s>`` (and likewise ``</s>``,
``[INST]``, ``[/INST]``); the parser takes one out of each that has any. So an escaped text holds no
control string, and texts without such strings stay as they are.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BEGIN, OPEN, HEAD, CLOSE = "<s>\n", "[INST] ", " [/INST]\n", "</s>\n"
_TAIL = r"(/?s>|/?INST\])"
_CONTROL = r"</?s>|\[/?INST\]"
_ESCAPE, _UNESCAPE = rf"([<\[])(\\*){_TAIL}", rf"([<\[]\\*)\\{_TAIL}"


def escape(text: Column) -> Column:
    return F.regexp_replace(text, _ESCAPE, r"$1$2\\$3")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, _UNESCAPE, "$1$2")


def render(turns: Column, change=lambda c: c) -> Column:
    """The string of an array of (role, text)."""
    one = lambda t: F.concat(F.lit(OPEN), change(t["role"]), F.lit(HEAD), change(t["text"]), F.lit(CLOSE))
    return F.concat(F.lit(BEGIN), F.array_join(F.transform(turns, one), ""))


def _raw(formatted: Column) -> Column:
    parts = F.split(F.substr(formatted, F.lit(len(BEGIN) + 1)), CLOSE, -1)
    return F.slice(parts, F.lit(1), F.size(parts) - 1)


def _read(part: Column) -> Column:
    head = F.instr(part, HEAD)
    role = F.substr(part, F.lit(len(OPEN) + 1), F.greatest(head - len(OPEN) - 1, F.lit(0)))
    return F.struct(unescape(role).alias("role"), unescape(F.substr(part, head + len(HEAD))).alias("text"))


def parse(formatted: Column) -> Column:
    """The array of (role, text) that a formatted conversation holds."""
    return F.transform(_raw(formatted), _read)


def loss_parts(formatted: Column) -> Column:
    """For each turn: the code points before its text, whether the text is under the loss mask (the
    assistant's are), and the text as it stands in the string, escaped."""

    def one(part: Column) -> Column:
        head = F.instr(part, HEAD) + (len(HEAD) - 1)
        return F.struct(head.alias("head"), (_read(part)["role"] == "assistant").alias("loss"), F.substr(part, head + 1).alias("text"))

    return F.transform(_raw(formatted), one)


def loss_spans(formatted: Column) -> Column:
    """Array of (start, length) in code points, from 0: the texts under the loss mask, as escaped."""
    zero = F.struct(F.lit(len(BEGIN)).alias("at"), F.expr("cast(array() as array<struct<start: int, length: int>>)").alias("spans"))

    def add(acc: Column, part: Column) -> Column:
        start = acc["at"] + part["head"]
        span = F.struct(start.cast("int").alias("start"), F.length(part["text"]).alias("length"))
        return F.struct((start + F.length(part["text"]) + len(CLOSE)).cast("int").alias("at"), F.when(part["loss"], F.concat(acc["spans"], F.array(span))).otherwise(acc["spans"]).alias("spans"))

    return F.aggregate(loss_parts(formatted), zero, add, lambda acc: acc["spans"])


def format_conversations(conversations: DataFrame) -> DataFrame:
    """(conv_id, formatted, escaped) for each conversation of (conv_id, turn, role, text).

    Turns stand by their number; equal numbers by role and then text, null numbers first. Null roles and
    texts are empty; rows with a null conv_id form one conversation. A conversation is one string, so one
    task holds all turns of one. Other columns are ignored; an empty table gives no rows.
    """
    text = lambda c: F.coalesce(F.col(c).cast("string"), F.lit(""))
    rows = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.struct(F.col("turn").alias("turn"), text("role").alias("role"), text("text").alias("text")).alias("row"))
    turns = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list("row")).alias("rows")).select("conv_id", F.transform("rows", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias("source"))
    plain = turns.withColumn("plain", render(F.col("source")))
    held = F.exists("source", lambda t: F.concat_ws("\n", t["role"], t["text"]).rlike(_CONTROL))
    plain = plain.withColumn("escaped", held | (parse(F.col("plain")) != F.col("source")))
    done = plain.withColumn("formatted", F.when(F.col("escaped"), render(F.col("source"), escape)).otherwise(F.col("plain")))
    wrong = F.col("escaped") & (parse(F.col("formatted")) != F.col("source"))
    return done.select("conv_id", F.when(wrong, F.raise_error(F.lit("a conversation does not survive its round trip"))).otherwise(F.col("formatted")).alias("formatted"), "escaped")


def read_back(formatted: DataFrame) -> DataFrame:
    """Digests of what the formatted strings hold: turns, and the text under the loss mask."""
    turns = F.col("turns")
    loss = F.array_join(F.transform(F.filter("parts", lambda t: t["loss"]), lambda t: unescape(t["text"])), "")
    flat = F.array_join(F.transform(turns, lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    read = formatted.select("conv_id", parse(F.col("formatted")).alias("turns"), loss_parts(F.col("formatted")).alias("parts"), F.length("formatted").cast("long").alias("formatted_chars"), "escaped")
    return read.select(
        "conv_id", F.size(turns).cast("long").alias("n_turns"), F.sha2(flat, 256).alias("turns_sha256"), F.length(loss).cast("long").alias("loss_chars"), F.sha2(loss, 256).alias("loss_sha256"), "formatted_chars", "escaped"
    )

"""Chat formatting with a grammar round trip; DataFrame functions only.

A conversation is rendered turn by turn, `[INST] user [/INST]`, `<s>assistant</s>`, `<<SYS>>system<</SYS>>`, and any other role
as `[TURN hex-of-role]text[/TURN]`. The rendering is parsed again by one regular grammar, in which a backslash quotes the next
character, and the recovered turns are compared with the source. What does not come back identical is rendered once more
with backslashes doubled and one set inside every control string; the second rendering is checked as the first, and the query
fails rather than return a conversation that does not round-trip.

The loss mask is run-length coded, one run per turn: characters before, inside and after the text, and whether the inside
counts. Defined results: null texts and null roles are empty strings; turns are ordered by turn (null first), then role, then
text; repeated rows are repeated turns; rows of a null conv_id are one conversation; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The template and its grammar: fixed values.
TAGS = {"user": ("[INST] ", " [/INST]"), "assistant": ("<s>", "</s>"), "system": ("<<SYS>>", "<</SYS>>")}
OTHER = ("[TURN ", "]", "[/TURN]")
GRAMMAR = r"(?s)\[INST\] .*? \[/INST\]|<s>.*?</s>|<<SYS>>.*?<</SYS>>|\[TURN [0-9A-F]*\].*?\[/TURN\]"
CONTROL = r"(\[|<)(/?INST\]|/?TURN[ \]]|/?s>|</?SYS>>)"


def escape(text: Column) -> Column:
    """Doubles backslashes and breaks every control string by one after its first character."""
    return F.regexp_replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), CONTROL, r"$1\\$2")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"(?s)\\(.)", "$1")


def _opening(role: Column) -> Column:
    out = None
    for name, (left, _) in TAGS.items():
        out = F.when(role == name, F.lit(left)) if out is None else out.when(role == name, F.lit(left))
    return out.otherwise(F.concat(F.lit(OTHER[0]), F.hex(F.encode(role, "UTF-8")), F.lit(OTHER[1])))


def _closing(role: Column) -> Column:
    out = None
    for name, (_, right) in TAGS.items():
        out = F.when(role == name, F.lit(right)) if out is None else out.when(role == name, F.lit(right))
    return out.otherwise(F.lit(OTHER[2]))


def render(turns: Column, escaped: bool) -> Column:
    return F.array_join(F.transform(turns, lambda t: F.concat(_opening(t["role"]), escape(t["text"]) if escaped else t["text"], _closing(t["role"]))), "")


def parse(formatted: Column) -> Column:
    """array<struct<role, text, before, inside, after, loss>> of the turns that the grammar finds, texts still escaped."""

    def one(token: Column) -> Column:
        role = F.lit(None).cast("string")
        left, right = F.instr(token, "]"), F.lit(len(OTHER[2]))
        role = F.decode(F.unhex(F.substring(token, F.lit(len(OTHER[0]) + 1), left - len(OTHER[0]) - 1)), "UTF-8")
        for name, (a, b) in reversed(TAGS.items()):
            here = F.startswith(token, F.lit(a))
            role = F.when(here, F.lit(name)).otherwise(role)
            left = F.when(here, F.lit(len(a))).otherwise(left)
            right = F.when(here, F.lit(len(b))).otherwise(right)
        inside = F.length(token) - left - right
        return F.struct(role.alias("role"), F.substring(token, left + 1, inside).alias("text"), left.alias("before"), inside.alias("inside"), right.alias("after"), (role == "assistant").alias("loss"))

    return F.transform(F.regexp_extract_all(formatted, F.lit(GRAMMAR), F.lit(0)), one)


def turns_of(parsed: Column) -> Column:
    return F.transform(parsed, lambda t: F.struct(t["role"].alias("role"), unescape(t["text"]).alias("text")))


def _whole(parsed: Column) -> Column:
    """Characters that the grammar accounts for."""
    return F.aggregate(parsed, F.lit(0), lambda n, t: n + t["before"] + t["inside"] + t["after"])


def format_conversations(rows: DataFrame) -> DataFrame:
    """One row per conversation: conv_id, formatted, escaped, mask (array<struct<before, inside, after, loss>>)."""
    clean = rows.select("conv_id", F.struct(F.col("turn").cast("long").alias("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).alias("t"))
    each = clean.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("t"))
    source = each.select("conv_id", F.transform("t", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias("source"))
    plain = source.withColumn("formatted", render(F.col("source"), False))
    read = plain.withColumn("parsed", parse(F.col("formatted")))
    same = (F.length("formatted") == _whole(F.col("parsed"))) & (turns_of(F.col("parsed")) == F.col("source"))
    first = read.withColumn("escaped", ~same).drop("parsed")
    second = first.withColumn("formatted", F.when(F.col("escaped"), render(F.col("source"), True)).otherwise(F.col("formatted")))
    again = second.withColumn("parsed", parse(F.col("formatted")))
    sure = F.when((F.length("formatted") == _whole(F.col("parsed"))) & (turns_of(F.col("parsed")) == F.col("source")), F.col("formatted")).otherwise(F.raise_error(F.lit("a conversation does not round-trip")).cast("string"))
    mask = F.transform("parsed", lambda t: F.struct(t["before"].alias("before"), t["inside"].alias("inside"), t["after"].alias("after"), t["loss"].alias("loss")))
    return again.select("conv_id", sure.alias("formatted"), "escaped", mask.alias("mask"))


def read_back(formatted: DataFrame) -> DataFrame:
    """Digests of what the formatted conversations hold: turns, and the text under the loss mask."""
    parsed = formatted.select("conv_id", "formatted", parse(F.col("formatted")).alias("parsed"))
    turns = turns_of(F.col("parsed"))
    told = F.array_join(F.transform(turns, lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    loss = F.array_join(F.transform(F.filter("parsed", lambda t: t["loss"]), lambda t: unescape(t["text"])), "")
    out = parsed.select("conv_id", F.size("parsed").cast("long").alias("n_turns"), F.sha2(told, 256).alias("turns_sha256"), loss.alias("loss"), F.length("formatted").cast("long").alias("formatted_chars"))
    return out.select("conv_id", "n_turns", "turns_sha256", F.length("loss").cast("long").alias("loss_chars"), F.sha2("loss", 256).alias("loss_sha256"), "formatted_chars")

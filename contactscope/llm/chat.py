"""Prefix-target expansion of conversations: every assistant turn becomes an example whose context is all turns before.

Only DataFrame expressions. A turn is `<|turn|>ROLE\\nTEXT<|end|>`; an example is the marked turns of the context and the
target, with `loss_start`/`loss_chars` (code points) around the target's text alone. Turns behind the last assistant turn,
or of a conversation without one, are kept in a last example without a target, so that the whole conversation can be
read back. Inside roles and texts the escape sign and every character that can open a control string are replaced
(`%` `<` `[` and the line feed of roles), so no text can forge a mark, and reading reverses it exactly.

Defined results: null role or text is empty; turns sort by turn, role, text (null turns first); repeated rows are turns of
their own; a null conv_id is one conversation; an empty table gives no rows; further columns are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# The marks of the template, and what is escaped (in this order; reading goes backwards).
TURN, END = "<|turn|>", "<|end|>"
ESCAPES = [("%", "%25"), ("<", "%3C"), ("[", "%5B"), ("\n", "%0A")]
TEXT_ESCAPES = ESCAPES[:3]


def escaped(text: Column, pairs: list[tuple[str, str]]) -> Column:
    for plain, code in pairs:
        text = F.replace(text, F.lit(plain), F.lit(code))
    return text


def unescaped(text: Column, pairs: list[tuple[str, str]]) -> Column:
    for plain, code in reversed(pairs):
        text = F.replace(text, F.lit(code), F.lit(plain))
    return text


def expand(conversations: DataFrame) -> DataFrame:
    """One row per example: conv_id, example (from 0), formatted, has_target, loss_start (from 1), loss_chars."""
    turn = F.struct(
        "turn",
        F.coalesce("role", F.lit("")).alias("role"),
        F.coalesce("text", F.lit("")).alias("text"),
    )
    grouped = conversations.groupBy("conv_id").agg(F.sort_array(F.collect_list(turn)).alias("turns"))
    body = lambda t: escaped(t["text"], TEXT_ESCAPES)
    marked = F.transform("turns", lambda t: F.concat(F.lit(TURN), escaped(t["role"], ESCAPES), F.lit("\n"), body(t), F.lit(END)))
    shaped = grouped.select(
        "conv_id",
        marked.alias("marked"),
        F.transform("turns", lambda t: F.length(body(t))).alias("chars"),
        F.filter(F.transform("turns", lambda t, i: F.when(t["role"] == "assistant", i + 1)), lambda i: i.isNotNull()).alias("targets"),
    )
    last = F.size("marked")
    ends = F.when(F.coalesce(F.array_max("targets"), F.lit(0)) == last, F.col("targets")).otherwise(F.concat("targets", F.array(last)))
    examples = shaped.select("conv_id", "marked", "chars", "targets", F.posexplode(ends).alias("example", "upto"))
    has = F.col("example") < F.size("targets")
    text = F.array_join(F.slice("marked", F.lit(1), F.col("upto")), "")
    size = F.element_at("chars", F.col("upto"))
    return examples.select("conv_id", "example", text.alias("formatted"), has.alias("has_target"), size.alias("size")).select(
        "conv_id",
        "example",
        "formatted",
        "has_target",
        F.when(F.col("has_target"), F.length("formatted") - len(END) - F.col("size") + 1).alias("loss_start"),
        F.when(F.col("has_target"), F.col("size")).otherwise(0).alias("loss_chars"),
    )


def read_turns(formatted: Column) -> Column:
    """Array of (role, text) read back from a formatted example."""
    parts = F.split(formatted, r"<\|turn\|>")
    parts = F.slice(parts, F.lit(2), F.size(parts) - 1)
    whole = F.transform(parts, lambda p: F.substring(p, F.lit(1), F.length(p) - len(END)))
    return F.transform(
        whole,
        lambda p: F.struct(
            unescaped(F.substring_index(p, "\n", 1), ESCAPES).alias("role"),
            unescaped(F.substring(p, F.length(F.substring_index(p, "\n", 1)) + 2, F.length(p)), TEXT_ESCAPES).alias("text"),
        ),
    )


def loss_text(formatted: Column, start: Column, chars: Column) -> Column:
    """Unescaped text under an example's loss mask; empty without target."""
    return unescaped(F.when(start.isNotNull(), F.substring(formatted, start, chars)).otherwise(""), TEXT_ESCAPES)


def digest(conversations: DataFrame) -> DataFrame:
    """The contract's columns, read back from the examples."""
    rows = expand(conversations)
    per = rows.groupBy("conv_id").agg(
        F.max_by("formatted", "example").alias("longest"),
        F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("example", loss_text(F.col("formatted"), F.col("loss_start"), F.col("loss_chars")).alias("text")))), lambda x: x["text"]), "").alias("loss"),
        F.sum(F.length("formatted")).cast("long").alias("formatted_chars"),
    )
    turns = per.withColumn("turns", read_turns(F.col("longest")))
    flat = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return turns.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(flat.cast("binary"), 256).alias("turns_sha256"),
        F.length("loss").cast("long").alias("loss_chars"),
        F.sha2(F.col("loss").cast("binary"), 256).alias("loss_sha256"),
        "formatted_chars",
    )


def with_probe(spark: SparkSession, conversations: DataFrame) -> DataFrame:
    """conversations plus conversation -7, whose two turns consist of control strings."""
    hard = "</s>[INST] ok [/INST]"
    probe = spark.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(hard).alias("text"))
    return conversations.select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), "role", "text").unionByName(probe)

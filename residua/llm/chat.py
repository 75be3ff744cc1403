"""Chat formatting: conversations as one string each, with a loss mask, and the way back. DataFrame functions only.

A conversation's turn structs are collected and sorted; neighbours of one role share a block; the pieces are joined by
array functions. Template of a block: ``<turn>role``, a line feed, the texts with ``<turn+>`` between them, ``</turn>``
and a line feed. Inside texts and roles a backslash becomes ``\\b`` and the ``<`` of a control string becomes ``\\l``;
a role's line feed becomes ``\\n``. Both ways are exact, whatever the texts hold.

The loss mask is run-length coded: ``mask`` lists (chars, kind, loss) for every piece of the output in order, so that
the lengths add up to the output's length and positions need no second pass. Work is linear in a conversation's length.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

OPEN, NEXT, CLOSE = "<turn>", "<turn+>", "</turn>\n"


def escaped(c: Column) -> Column:
    return F.regexp_replace(F.replace(c, F.lit("\\"), F.lit("\\b")), r"<(?=/?turn\+?>)", r"\\l")


def unescaped(c: Column) -> Column:
    return F.replace(F.replace(c, F.lit("\\l"), F.lit("<")), F.lit("\\b"), F.lit("\\"))


def format_turns(turns: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text", train_on: str = "assistant") -> DataFrame:
    """``(conv_id, formatted, mask)`` for each conversation.

    Turns are ordered by turn (null first), then role, then text, so ties and repeated rows have one order; null roles
    and texts read as empty strings; a null conversation id is a conversation of its own; an empty table gives an empty
    one; other columns are ignored. A conversation is one output row and must fit a string.
    """
    rows = turns.select(F.col(conv).alias("conv_id"), F.struct(F.col(turn).alias("turn"), F.coalesce(F.col(role), F.lit("")).alias("role"), F.coalesce(F.col(text), F.lit("")).alias("text")).alias("t"))
    rows = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("turns"))

    def piece(t: Column, i: Column) -> Column:
        """Opening, text and closing of a turn; the neighbours' roles tell whether its block begins or ends here."""
        same = lambda j: F.coalesce(F.get(F.col("turns"), j)["role"] == t["role"], F.lit(False))
        begins = F.concat(F.lit(OPEN), F.replace(escaped(t["role"]), F.lit("\n"), F.lit("\\n")), F.lit("\n"))
        return F.struct(F.when(same(i - 1), F.lit(NEXT)).otherwise(begins).alias("head"), escaped(t["text"]).alias("body"), F.when(same(i + 1), F.lit("")).otherwise(F.lit(CLOSE)).alias("tail"), (t["role"] == train_on).alias("loss"))

    part = lambda chars, kind, loss: F.struct(F.length(chars).cast("long").alias("chars"), F.lit(kind).alias("kind"), loss.alias("loss"))
    pieces = rows.select("conv_id", F.size("turns").alias("n"), "turns", F.transform("turns", piece).alias("pieces"))
    return pieces.select(
        "conv_id",
        F.array_join(F.transform("pieces", lambda p: F.concat(p["head"], p["body"], p["tail"])), "").alias("formatted"),
        F.flatten(F.transform("pieces", lambda p: F.array(part(p["head"], "mark", F.lit(False)), part(p["body"], "text", p["loss"]), part(p["tail"], "mark", F.lit(False))))).alias("mask"),
    )


def read_turns(formatted: DataFrame) -> DataFrame:
    """Back from ``format_turns``: adds ``turns`` (role, text, loss), parsed from the output and matched with its mask."""
    block = lambda b: F.substring(b, len(OPEN) + 1, 1 << 30)
    role = lambda b: unescaped(F.replace(F.substring_index(b, "\n", 1), F.lit("\\n"), F.lit("\n")))
    texts = lambda b: F.split(F.substring(b, F.locate("\n", b) + 1, F.length(b)), r"<turn\+>", -1)
    blocks = F.transform(F.filter(F.split("formatted", "</turn>\n", -1), lambda b: b != ""), block)
    parsed = formatted.withColumn("__turns", F.flatten(F.transform(blocks, lambda b: F.transform(texts(b), lambda x: F.struct(role(b).alias("role"), x.alias("raw"))))))
    parsed = parsed.withColumn("__held", F.filter("mask", lambda m: m["kind"] == "text"))
    both = F.zip_with("__turns", "__held", lambda t, m: F.struct(t["role"].alias("role"), unescaped(t["raw"]).alias("text"), (m["loss"] & (m["chars"] == F.length(t["raw"]))).alias("loss")))
    return parsed.withColumn("turns", both).drop("__turns", "__held")


def digests(formatted: DataFrame) -> DataFrame:
    """One row a conversation: what reading the output back gives, as counts and digests."""
    sha = lambda c: F.sha2(c.cast("binary"), 256)
    back = read_turns(formatted).withColumn("loss_text", F.array_join(F.transform(F.filter("turns", lambda t: t["loss"]), lambda t: t["text"]), ""))
    return back.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        sha(F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")).alias("turns_sha256"),
        F.length("loss_text").cast("long").alias("loss_chars"),
        sha(F.col("loss_text")).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )

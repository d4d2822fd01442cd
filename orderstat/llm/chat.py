r"""Chat formatting with Spark expressions only.

A conversation becomes one string: `<turn ROLE>TEXT</turn>` and a line feed per run of turns of one role, with `<more/>`
between the texts of a run. In texts and roles `\` becomes `\b`, `<` becomes `\l` and `>` becomes `\g`, so every `<`
of the output is the template's own and reading back gives the turns exactly.

Cases: a null role or text reads as empty; turns sort by (turn, role, text), null turns first, so ties have one order and
repeated rows stay; a null conv_id is a conversation of its own; other columns are ignored; an empty table gives an empty one.
One conversation is one row of the result, so its turns must fit a task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Characters escaped and their escapes, in the order of escaping.
ESCAPES = (("\\", "\\b"), ("<", "\\l"), (">", "\\g"))


def escaped(text: Column) -> Column:
    out = F.coalesce(text, F.lit(""))
    for plain, sign in ESCAPES:
        out = F.replace(out, F.lit(plain), F.lit(sign))
    return out


def unescaped(text: Column) -> Column:
    for plain, sign in reversed(ESCAPES):
        text = F.replace(text, F.lit(sign), F.lit(plain))
    return text


def formatted(turns: DataFrame) -> DataFrame:
    """(conv_id, formatted) from rows (conv_id, turn, role, text)."""
    rows = turns.select("conv_id", F.struct("turn", escaped(F.col("role")).alias("role"), escaped(F.col("text")).alias("text")).alias("t"))
    sorted_turns = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("turns"))

    def piece(t: Column, k: Column) -> Column:
        same = (k > 0) & (F.col("turns")[F.greatest(k - 1, F.lit(0))]["role"] == t["role"])
        opening = F.concat(F.when(k > 0, F.lit("</turn>\n")).otherwise(""), F.lit("<turn "), t["role"], F.lit(">"))
        return F.concat(F.when(same, F.lit("<more/>")).otherwise(opening), t["text"])

    return sorted_turns.select("conv_id", F.concat(F.array_join(F.transform("turns", piece), ""), F.lit("</turn>\n")).alias("formatted"))


def read_back(chats: DataFrame) -> DataFrame:
    """(conv_id, formatted, runs): runs of (role, texts), unescaped, parsed from the string alone."""

    def run(block: Column) -> Column:
        body = F.split(F.substring_index(block, "</turn>", 1), ">", 2)
        return F.struct(unescaped(body[0]).alias("role"), F.transform(F.split(body[1], "<more/>"), unescaped).alias("texts"))

    blocks = F.slice(F.split("formatted", "<turn "), 2, 1 << 30)
    return chats.select("conv_id", "formatted", F.transform(blocks, run).alias("runs"))


def digests(parsed: DataFrame) -> DataFrame:
    """Counts and digests of what read_back found; the loss mask covers the texts of assistant turns."""

    def lines(r: Column) -> Column:
        return F.transform(r["texts"], lambda x: F.concat(r["role"], F.lit("\n"), x, F.lit("\n")))

    loss = F.array_join(F.flatten(F.transform(F.filter("runs", lambda r: r["role"] == "assistant"), lambda r: r["texts"])), "")
    out = parsed.select("conv_id", "formatted", F.flatten(F.transform("runs", lines)).alias("lines"), loss.alias("loss"))
    return out.select(
        "conv_id",
        F.size("lines").cast("long").alias("n_turns"),
        F.sha2(F.array_join("lines", ""), 256).alias("turns_sha256"),
        F.char_length("loss").cast("long").alias("loss_chars"),
        F.sha2("loss", 256).alias("loss_sha256"),
        F.char_length("formatted").cast("long").alias("formatted_chars"),
    )

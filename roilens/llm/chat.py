"""Chat formatting as relational work, in Spark expressions only.

A conversation's turns are collected as structs and sorted; runs of one role become blocks, whose texts
are merged by aggregating the run's array under one header; blocks are concatenated.  The loss mask is
a list of byte ranges of the formatted text, those of assistant texts: everything that is read back,
text under the mask included, is cut out of the formatted text itself.

Control strings inside texts and roles are escaped by a tilde after their first character, with any
tildes that already stand there kept: "[INST]" becomes "[~INST]" and "[~INST]" becomes "[~~INST]",
which undoing reverses exactly and which leaves all other text as it was.

Null texts and roles count as empty; rows with a null turn come first; ties in turn go by role, then
text.  Rows with a null conv_id form one conversation.  A conversation must fit in one row.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Template:
    """Marks before a role, between role and text, between merged texts, and after a block."""

    open: str
    header: str
    join: str
    close: str


# Two public chat layouts.
INST = Template("[INST]", "[/INST]", "<turn>", "</s>")
CHATML = Template("<|im_start|>", "<|im_sep|>", "<|im_next|>", "<|im_end|>")
#: All control strings, those of other layouts included: opening character, tildes, and the rest.
CONTROL = r"([<\[])(~*)(/?INST\]|/?s>|/?turn>|</?SYS>>|\|im_start\|>|\|im_sep\|>|\|im_next\|>|\|im_end\|>)"
ESCAPED = CONTROL.replace("(~*)", "(~*)~")


def escape(text: Column) -> Column:
    return F.regexp_replace(text, CONTROL, r"$1$2~$3")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, ESCAPED, r"$1$2$3")


def format_chats(turns: DataFrame, template: Template = INST) -> DataFrame:
    """(conv_id, formatted, loss_mask): loss_mask lists structs of from and to, byte offsets into ``formatted``."""
    t = template
    empty = F.lit("")
    turn = F.struct(F.col("turn"), F.coalesce("role", empty).alias("role"), F.coalesce("text", empty).alias("text"))
    sorted_ = turns.groupBy("conv_id").agg(F.array_sort(F.collect_list(turn)).alias("turns")).withColumn("n", F.size("turns"))
    begins = F.filter(F.sequence(F.lit(1), F.col("n")), lambda i: (i == 1) | (F.element_at("turns", i)["role"] != F.element_at("turns", F.greatest(i - 1, F.lit(1)))["role"]))
    sorted_ = sorted_.withColumn("begins", begins)

    def block(begin: Column, number: Column) -> Column:
        """A run of one role: its mark, and the escaped texts with what stands before each."""
        upto = F.coalesce(F.get("begins", number + 1), F.col("n") + 1)
        role = F.element_at("turns", begin)["role"]
        header = F.concat(F.when(number > 0, F.lit(t.close)).otherwise(empty), F.lit(t.open), escape(role), F.lit(t.header))
        texts = F.transform(F.slice("turns", begin, upto - begin), lambda x: escape(x["text"]))
        return F.struct(header.alias("header"), (role == "assistant").alias("loss"), texts.alias("texts"))

    blocks = sorted_.select("conv_id", F.transform("begins", block).alias("blocks"))
    merged = F.transform("blocks", lambda b: F.concat(b["header"], F.array_join(b["texts"], t.join)))
    pieces = F.flatten(F.transform("blocks", lambda b: F.transform(b["texts"], lambda x, i: F.struct(
        F.when(i == 0, F.octet_length(b["header"])).otherwise(F.lit(len(t.join.encode()))).cast("long").alias("before"), F.octet_length(x).cast("long").alias("size"), b["loss"].alias("loss")))))
    out = blocks.select("conv_id", F.concat(F.array_join(merged, ""), F.lit(t.close)).alias("formatted"), pieces.alias("pieces"))
    span = "array<struct<from:bigint,to:bigint>>"
    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast(span).alias("spans"))

    def onward(acc: Column, x: Column) -> Column:
        begin = acc["at"] + x["before"]
        one = F.array(F.struct(begin.alias("from"), (begin + x["size"]).alias("to")))
        return F.struct((begin + x["size"]).alias("at"), F.when(x["loss"], F.concat(acc["spans"], one)).otherwise(acc["spans"]).alias("spans"))

    return out.select("conv_id", "formatted", F.aggregate("pieces", start, onward, lambda acc: acc["spans"]).alias("loss_mask"))


def read_back(formatted: DataFrame, template: Template = INST) -> DataFrame:
    """(conv_id, turns, loss_text, formatted_chars): turns parsed from ``formatted`` as structs of role and text, and the text under the mask."""
    t = template
    blocks = F.filter(F.split("formatted", _literal(t.close)), lambda x: x != "")

    def parse(block: Column) -> Column:
        parts = F.split(block, _literal(t.header), 2)
        role = unescape(F.substring(F.get(parts, F.lit(0)), len(t.open) + 1, 1 << 30))
        return F.transform(F.split(F.get(parts, F.lit(1)), _literal(t.join)), lambda x: F.struct(role.alias("role"), unescape(x).alias("text")))

    # of bytes, as a range of bytes is found without counting the characters before it
    cut = F.transform("loss_mask", lambda m: unescape(F.substring(F.col("_bytes"), (m["from"] + 1).cast("int"), (m["to"] - m["from"]).cast("int")).cast("string")))
    return formatted.withColumn("_bytes", F.col("formatted").cast("binary")).select(
        "conv_id", F.flatten(F.transform(blocks, parse)).alias("turns"), F.array_join(cut, "").alias("loss_text"), F.length("formatted").cast("long").alias("formatted_chars")
    )


def _literal(mark: str) -> str:
    return "".join(f"\\{c}" if not c.isalnum() else c for c in mark)


def digests(formatted: DataFrame, template: Template = INST) -> DataFrame:
    """Counts and digests of what is read back from the formatted conversations."""
    back = read_back(formatted, template)
    said = F.array_join(F.transform("turns", lambda x: F.concat(x["role"], F.lit("\n"), x["text"], F.lit("\n"))), "")
    return back.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(said, 256).alias("turns_sha256"),
        F.length("loss_text").cast("long").alias("loss_chars"),
        F.sha2("loss_text", 256).alias("loss_sha256"),
        "formatted_chars",
    )

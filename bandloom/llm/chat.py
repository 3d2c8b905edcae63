"""Chat formatting in DataFrame expressions only.

A conversation's turns are collected as structs, sorted by (turn, role, text); adjacent turns of one role become one
block. The template is `<s>[role]text</s>` for a block, with `<sep>` between the texts merged into it. Inside roles and
texts a backslash, `<`, `[` and `]` are written as a backslash and the letter b, l, s or r, so no control string can occur in
them and every step can be undone.

Output: conv_id, segments (array of text pieces and whether the loss counts them; their texts end to end are the
formatted string; only the assistant's texts count) and formatted.

Defined results: null text is empty; a null role is written `\\0` and differs from an empty one; a null conv_id groups like
any value; ties of turn are ordered by role and text; repeated rows are repeated turns; an empty table gives no
rows; other columns are not read. One conversation is one output row, so its turns meet in one task by definition.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The characters that are escaped, with their letters, and the template's control strings.
ESCAPES = (("\\", "b"), ("<", "l"), ("[", "s"), ("]", "r"))
OPEN, ROLE_END, JOIN, CLOSE, NO_ROLE = "<s>[", "]", "<sep>", "</s>", "\\0"


def escape(text: Column) -> Column:
    for char, letter in ESCAPES:
        text = F.replace(text, F.lit(char), F.lit("\\" + letter))
    return text


def unescape(text: Column) -> Column:
    for char, letter in reversed(ESCAPES):
        text = F.replace(text, F.lit("\\" + letter), F.lit(char))
    return text


def format_chat(conversations: DataFrame, learn_role: str = "assistant") -> DataFrame:
    turns = F.sort_array(F.collect_list(F.struct("turn", "role", F.coalesce("text", F.lit("")).alias("text"))))
    grouped = conversations.select("conv_id", "turn", "role", "text").groupBy("conv_id").agg(turns.alias("turns"))

    def segment(text: Column, loss: Column) -> Column:
        return F.struct(text.alias("text"), loss.alias("loss"))

    def written(turn: Column, i: Column) -> Column:
        opening = F.concat(F.lit(OPEN), F.coalesce(escape(turn.role), F.lit(NO_ROLE)), F.lit(ROLE_END))
        marker = F.when(i == 0, opening).when(F.get("turns", i - 1)["role"].eqNullSafe(turn.role), F.lit(JOIN)).otherwise(F.concat(F.lit(CLOSE), opening))
        return F.array(segment(marker, F.lit(False)), segment(escape(turn.text), F.coalesce(turn.role == learn_role, F.lit(False))))

    ending = F.array(segment(F.lit(CLOSE), F.lit(False)))
    segments = grouped.select("conv_id", F.concat(F.flatten(F.transform("turns", written)), ending).alias("segments"))
    return segments.withColumn("formatted", F.array_join(F.transform("segments", lambda s: s.text), ""))


def read_chat(formatted: Column) -> Column:
    """array<struct<role, text>>: the turns that a formatted string was made from."""
    blocks = F.split(formatted, CLOSE)
    blocks = F.slice(blocks, 1, F.size(blocks) - 1)

    def turns(block: Column) -> Column:
        role = F.substring_index(block.substr(F.lit(len(OPEN) + 1), F.length(block)), ROLE_END, 1)
        body = block.substr(F.length(role) + len(OPEN) + len(ROLE_END) + 1, F.length(block))
        plain = F.when(role != NO_ROLE, unescape(role))
        return F.transform(F.split(body, JOIN), lambda t: F.struct(plain.alias("role"), unescape(t).alias("text")))

    return F.flatten(F.transform(blocks, turns))


def chat_digest(formatted: DataFrame) -> DataFrame:
    """What the output says when it is read back."""
    lines = F.transform("turns", lambda t: F.concat(F.coalesce(t.role, F.lit("")), F.lit("\n"), t.text, F.lit("\n")))
    learned = F.array_join(F.transform(F.filter("segments", lambda s: s.loss), lambda s: unescape(s.text)), "")
    return (
        formatted.select("conv_id", "formatted", read_chat(F.col("formatted")).alias("turns"), learned.alias("learned"))
        .select(
            "conv_id",
            F.size("turns").cast("long").alias("n_turns"),
            F.sha2(F.array_join(lines, ""), 256).alias("turns_sha256"),
            F.length("learned").cast("long").alias("loss_chars"),
            F.sha2("learned", 256).alias("loss_sha256"),
            F.length("formatted").cast("long").alias("formatted_chars"),
        )
    )

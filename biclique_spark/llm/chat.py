"""Chat formatting by Spark expressions alone.

Turns of a conversation are collected as structs and sorted; adjacent turns of one role share a block; the
blocks are concatenated. A block is

    <turn>role<body>text<part>text of the next turn of that role</turn>\\n

and these control strings never occur inside a role or text: there a backslash is doubled, and the ``<`` of
a control string gets a backslash behind it. Reading back undoes both, so every turn is found again exactly.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

OPEN, BODY, PART, CLOSE = "<turn>", "<body>", "<part>", "</turn>\n"
#: What may not stand in a text: the start of any control string.
_CONTROL = r"<(?=/?turn>|body>|part>)"


def escape(text: Column) -> Column:
    return F.regexp_replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), _CONTROL, r"<\\")


def unescape(text: Column) -> Column:
    """Each backslash goes and the character behind it stays."""
    return F.regexp_replace(text, r"(?s)\\(.)", "$1")


def format_chats(
    turns: DataFrame,
    conv_col: str = "conv_id",
    turn_col: str = "turn",
    role_col: str = "role",
    text_col: str = "text",
    trained_role: str = "assistant",
) -> DataFrame:
    """One row per conversation: conv_id, segments (array of text, loss), formatted.

    ``segments`` joined without anything between are ``formatted``; ``loss`` marks the segments that are
    texts of the trained role. Null roles and texts count as empty. Turns with the same number are ordered
    by role, then text, null numbers first; repeated rows are turns of their own. Rows without a
    conversation form one with a null id. An empty table gives an empty result. A conversation becomes one
    string, so it must fit one row; other columns are not read.
    """
    rows = turns.select(
        F.col(conv_col).alias("conv_id"),
        F.struct(
            F.col(turn_col).alias("turn"),
            F.coalesce(F.col(role_col), F.lit("")).alias("role"),
            F.coalesce(F.col(text_col), F.lit("")).alias("text"),
        ).alias("t"),
    )
    whole = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("ts"))
    # Where runs of one role begin, counted from 1; one place behind the end closes the last run.
    runs = whole.select(
        "conv_id",
        "ts",
        F.filter(
            F.sequence(F.lit(1), F.size("ts")),
            lambda i: (i == 1) | (F.get("ts", i - 1)["role"] != F.get("ts", i - 2)["role"]),
        ).alias("starts"),
    ).withColumn("ends", F.concat(F.slice("starts", 2, F.size("starts")), F.array(F.size("ts") + 1)))
    blocks = runs.select(
        "conv_id",
        F.zip_with(
            "starts",
            "ends",
            lambda a, b: F.struct(
                F.get("ts", a - 1)["role"].alias("role"), F.transform(F.slice("ts", a, b - a), lambda t: t["text"]).alias("texts")
            ),
        ).alias("blocks"),
    )
    plain = lambda text: F.struct(text.alias("text"), F.lit(False).alias("loss"))
    segments = blocks.select(
        "conv_id",
        F.flatten(
            F.transform(
                "blocks",
                lambda b: F.concat(
                    F.array(plain(F.concat(F.lit(OPEN), escape(b["role"]), F.lit(BODY)))),
                    F.flatten(
                        F.transform(
                            b["texts"],
                            lambda x, i: F.concat(
                                F.when(i > 0, F.array(plain(F.lit(PART)))).otherwise(F.array().cast("array<struct<text:string,loss:boolean>>")),
                                F.array(F.struct(escape(x).alias("text"), (b["role"] == trained_role).alias("loss"))),
                            ),
                        )
                    ),
                    F.array(plain(F.lit(CLOSE))),
                ),
            )
        ).alias("segments"),
    )
    return segments.withColumn("formatted", F.array_join(F.transform("segments", lambda s: s["text"]), ""))


def read_back(formatted: Column) -> Column:
    """The turns of a formatted conversation, as an array of (role, text): blocks end where CLOSE stands."""
    blocks = F.split(formatted, CLOSE)
    blocks = F.slice(blocks, F.lit(1), F.size(blocks) - 1)

    def turns(block: Column) -> Column:
        halves = F.split(F.substr(block, F.lit(len(OPEN) + 1)), BODY)
        return F.transform(
            F.split(F.get(halves, F.lit(1)), PART),
            lambda x: F.struct(unescape(F.get(halves, F.lit(0))).alias("role"), unescape(x).alias("text")),
        )

    return F.flatten(F.transform(blocks, turns))


def digests(chats: DataFrame) -> DataFrame:
    """What can be read back from format_chats(): counts and digests of turns and of the text under the loss mask."""
    loss = F.transform(F.filter("segments", lambda s: s["loss"]), lambda s: unescape(s["text"]))
    read = chats.select(
        "conv_id",
        read_back(F.col("formatted")).alias("turns"),
        F.array_join(loss, "").alias("loss"),
        F.char_length("formatted").cast("long").alias("formatted_chars"),
    )
    flat = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return read.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(flat.cast("binary"), 256).alias("turns_sha256"),
        F.char_length("loss").cast("long").alias("loss_chars"),
        F.sha2(F.col("loss").cast("binary"), 256).alias("loss_sha256"),
        "formatted_chars",
    )

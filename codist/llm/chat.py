"""Chat formatting with typed content parts, by DataFrame functions only.

A turn holds parts of the kinds text, image, audio and document. A visitor over the parts writes
text as it is and everything else as a numbered placeholder, and lists the attachments with the
number of tokens that the placeholder stands for. A turn is written as

    <turn ROLE>
    BODY</turn>

Inside roles and texts the backslash is written as ``\\-``, ``<`` as ``\\(`` and, in roles, ``>``
as ``\\)``. So ``<`` begins a mark wherever it stands, whatever the texts say, and ``read_turns``
gets the texts back unchanged.

Edges: null text or role is empty, null parts are no parts; an unknown kind is a placeholder of no
tokens; turns with one number are ordered by role and then content, and null numbers come first;
rows that repeat are turns that repeat; extra columns are ignored; no rows give no conversations.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PART = "struct<kind:string,text:string,uri:string,width:int,height:int,seconds:double,pages:int>"
END = "</turn>\n"


@dataclass(frozen=True)
class Expansion:
    """Tokens that stand in for an attachment."""

    patch: int = 14
    tokens_per_second: float = 25.0
    tokens_per_page: int = 512


def escaped(x: Column) -> Column:
    return F.replace(F.replace(x, F.lit("\\"), F.lit("\\-")), F.lit("<"), F.lit("\\("))


def unescaped(x: Column) -> Column:
    x = F.replace(F.replace(x, F.lit("\\("), F.lit("<")), F.lit("\\)"), F.lit(">"))
    return F.replace(x, F.lit("\\-"), F.lit("\\"))


def text_parts(text: Column) -> Column:
    """One text part, for tables whose turns are plain text."""
    return F.array(F.struct(F.lit("text").alias("kind"), text.alias("text"), *[F.lit(None).cast(t).alias(n) for n, t in (("uri", "string"), ("width", "int"), ("height", "int"), ("seconds", "double"), ("pages", "int"))]))


def expanded_tokens(part: Column, by: Expansion) -> Column:
    side = lambda n: F.ceil(F.coalesce(part[n], F.lit(0)) / by.patch)
    return (
        F.when(part["kind"] == "image", side("width") * side("height"))
        .when(part["kind"] == "audio", F.ceil(F.coalesce(part["seconds"], F.lit(0.0)) * by.tokens_per_second))
        .when(part["kind"] == "document", F.coalesce(part["pages"], F.lit(0)) * by.tokens_per_page)
        .otherwise(0)
        .cast("bigint")
    )


def format_chats(turns: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", parts: str = "parts", trained_role: str = "assistant", by: Expansion = Expansion()) -> DataFrame:
    """One row for each conversation.

    formatted; segments: for each turn its length in characters and, within it, the range under the
    loss mask (of length 0 for turns of other roles), so that the mask is read in one pass;
    attachments: turn and part (from 1), kind, uri and tokens; attachment_tokens: their sum.
    """
    named = F.coalesce(F.col(role), F.lit(""))
    pieces = F.coalesce(F.col(parts), F.array().cast(f"array<{PART}>"))
    visit = lambda p, i: F.when(p["kind"] == "text", escaped(F.coalesce(p["text"], F.lit("")))).otherwise(F.concat(F.lit("<"), F.regexp_replace(F.coalesce(p["kind"], F.lit("unknown")), "[<>\\\\\\s]", "_"), F.lit(" "), (i + 1).cast("string"), F.lit(">")))
    head = F.concat(F.lit("<turn "), F.replace(escaped(named), F.lit(">"), F.lit("\\)")), F.lit(">\n"))
    rows = turns.select(
        F.col(conv).alias("conv_id"),
        F.col(turn).alias("turn"),
        named.alias("role"),
        head.alias("head"),
        F.array_join(F.transform(pieces, visit), "").alias("body"),
        F.filter(F.transform(pieces, lambda p, i: F.struct((i + 1).alias("part"), p["kind"].alias("kind"), p["uri"].alias("uri"), expanded_tokens(p, by).alias("tokens"))), lambda a: ~a["kind"].eqNullSafe("text")).alias("files"),
    )
    rows = rows.select(
        "conv_id",
        F.struct(
            "turn",
            "role",
            F.concat("head", "body", F.lit(END)).alias("segment"),
            F.length("head").alias("loss_start"),
            F.when(F.col("role") == trained_role, F.length("body")).otherwise(0).alias("loss_length"),
            "files",
        ).alias("t"),
    )
    held = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list("t")).alias("ts"))
    files = F.flatten(F.transform("ts", lambda t, i: F.transform(t["files"], lambda a: F.struct((i + 1).alias("turn"), a["part"].alias("part"), a["kind"].alias("kind"), a["uri"].alias("uri"), a["tokens"].alias("tokens")))))
    return held.select(
        "conv_id",
        F.array_join(F.transform("ts", lambda t: t["segment"]), "").alias("formatted"),
        F.transform("ts", lambda t: F.struct(F.length(t["segment"]).alias("length"), t["loss_start"].alias("loss_start"), t["loss_length"].alias("loss_length"))).alias("segments"),
        files.alias("attachments"),
    ).withColumn("attachment_tokens", F.aggregate("attachments", F.lit(0).cast("bigint"), lambda s, a: s + a["tokens"]))


def read_turns(chats: DataFrame) -> DataFrame:
    """All columns and, read from ``formatted``, turns: role and text, and loss_text: the text under the mask."""
    cut = F.split("formatted", END, -1)
    held = chats.withColumn("_cut", F.slice(cut, 1, F.size(cut) - 1))
    head = lambda s: F.substring_index(s, ">\n", 1)
    turns = F.transform("_cut", lambda s: F.struct(unescaped(F.substr(head(s), F.lit(7))).alias("role"), unescaped(F.substr(s, F.length(head(s)) + 3)).alias("text")))
    loss = F.array_join(F.transform("segments", lambda m, i: unescaped(F.substr(F.col("_cut")[i], m["loss_start"] + 1, m["loss_length"]))), "")
    return held.withColumn("turns", turns).withColumn("loss_text", loss).drop("_cut")

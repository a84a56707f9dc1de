"""Chat formatting with typed content parts, built-in functions only.

A message is a list of parts (text, image, audio, document).  A visitor over the parts
gathers neighbouring texts and writes them with control strings escaped, so that no
control string arises where two parts meet, writes an ordered placeholder for every
attachment, and records its reference and the number of tokens it expands to.

    turn      ::=  <s>[INST] role [/INST] content</s>
    content   ::=  (escaped text | <|kind:n|>)*        n counts attachments from 1

Escaping doubles every backslash and then puts one backslash after the first character
of each control string, so a control string never occurs inside a text and the text can
be restored exactly.

Defined cases: null text is empty, a null role is empty, a null or empty list of parts
gives an empty content, an unknown kind of part is written as text; turns that tie are
ordered by role, then text; rows that repeat are turns of their own; a null conversation
id is a conversation of its own; an empty table gives no rows; other columns are ignored.
One conversation is one output row, so its turns meet in one task by definition.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

OPEN, MIDDLE, CLOSE = "<s>[INST] ", " [/INST] ", "</s>"
#: Control strings of the template, none inside another.
CONTROLS = ("<s>", "</s>", "[INST]", "[/INST]", "<|")
KINDS = ("image", "audio", "document")
#: Type of a content part: size is pixels for images, seconds for audio, pages for documents.
PART = "struct<kind:string,text:string,ref:string,width:double,height:double>"


def escape(text: Column) -> Column:
    out = F.replace(F.coalesce(text, F.lit("")), F.lit("\\"), F.lit("\\\\"))
    return reduce(lambda t, c: F.replace(t, F.lit(c), F.lit(c[0] + "\\" + c[1:])), CONTROLS, out)


def unescape(text: Column) -> Column:
    out = reduce(lambda t, c: F.replace(t, F.lit(c[0] + "\\" + c[1:]), F.lit(c)), CONTROLS, text)
    return F.replace(out, F.lit("\\\\"), F.lit("\\"))


def text_part(text: Column) -> Column:
    """A text as a list of one part."""
    none = F.lit(None)
    return F.array(F.struct(F.lit("text").alias("kind"), text.alias("text"), none.cast("string").alias("ref"), none.cast("double").alias("width"), none.cast("double").alias("height")))


def expanded_tokens(part: Column, patch: int, per_second: float, per_page: int) -> Column:
    """Tokens a placeholder stands for: image patches, audio frames, document pages."""
    tiles = F.ceil(F.coalesce(part["width"], F.lit(0.0)) / patch) * F.ceil(F.coalesce(part["height"], F.lit(0.0)) / patch)
    return (
        F.when(part["kind"] == "image", tiles)
        .when(part["kind"] == "audio", F.ceil(F.coalesce(part["width"], F.lit(0.0)) * per_second))
        .when(part["kind"] == "document", F.ceil(F.coalesce(part["width"], F.lit(0.0))) * per_page)
        .otherwise(0)
        .cast("long")
    )


def format_chats(
    rows: DataFrame,
    conv_col: str = "conv_id",
    turn_col: str = "turn",
    role_col: str = "role",
    parts_col: str = "parts",
    loss_roles: tuple[str, ...] = ("assistant",),
    patch: int = 14,
    audio_tokens_per_second: float = 25.0,
    page_tokens: int = 700,
) -> DataFrame:
    """One row per conversation.

    conv id, n_turns, formatted, loss_spans (code points from 0, end excluded),
    attachments (ordinal, kind, ref, tokens), expanded_tokens.
    """
    turn = F.struct(F.col(turn_col).alias("turn"), F.coalesce(F.col(role_col), F.lit("")).alias("role"), F.coalesce(F.col(parts_col), F.array().cast(f"array<{PART}>")).alias("parts"))
    chats = rows.groupBy(F.col(conv_col).alias("_conv")).agg(F.sort_array(F.collect_list(turn)).alias("_turns"))
    attachment = lambda p: p["kind"].isin(*KINDS)
    # Attachments of all turns, in order; each turn knows how many came before it.
    chats = chats.withColumn("_files", F.filter(F.flatten(F.transform("_turns", lambda t: t["parts"])), attachment))
    chats = chats.withColumn("_counts", F.transform("_turns", lambda t: F.size(F.filter(t["parts"], attachment))))

    def visit(state: Column, part: Column) -> Column:
        n = state["n"] + F.when(attachment(part), 1).otherwise(0)
        mark = F.concat(state["out"], escape(state["open"]), F.lit("<|"), part["kind"], F.lit(":"), n.cast("string"), F.lit("|>"))
        return F.struct(
            F.when(attachment(part), mark).otherwise(state["out"]).alias("out"),
            F.when(attachment(part), F.lit("")).otherwise(F.concat(state["open"], F.coalesce(part["text"], F.lit("")))).alias("open"),
            n.alias("n"),
        )

    def content(t: Column, i: Column) -> Column:
        earlier = F.aggregate(F.slice("_counts", F.lit(1), i), F.lit(0), lambda a, x: a + x)
        start = F.struct(F.lit("").alias("out"), F.lit("").alias("open"), earlier.alias("n"))
        one = F.when(attachment(t["parts"][0]), F.lit(None)).otherwise(escape(t["parts"][0]["text"]))
        return F.when((F.size(t["parts"]) == 1) & one.isNotNull(), one).otherwise(F.aggregate(t["parts"], start, visit, lambda s: F.concat(s["out"], escape(s["open"]))))

    chats = chats.withColumn(
        "_pieces",
        F.transform("_turns", lambda t, i: F.struct(t["role"].alias("role"), F.concat(F.lit(OPEN), escape(t["role"]), F.lit(MIDDLE)).alias("head"), content(t, i).alias("body"))),
    )
    chats = chats.withColumn("_sizes", F.transform("_pieces", lambda p: F.struct(p["role"].alias("role"), F.length(p["head"]).alias("head"), F.length(p["body"]).alias("body"))))

    def span(state: Column, p: Column) -> Column:
        start = state["at"] + p["head"]
        masked = F.array(F.struct(start.alias("start"), (start + p["body"]).alias("end")))
        return F.struct((start + p["body"] + len(CLOSE)).alias("at"), F.when(p["role"].isin(*loss_roles), F.concat(state["spans"], masked)).otherwise(state["spans"]).alias("spans"))

    begin = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,end:int>>").alias("spans"))
    listed = F.transform("_files", lambda p, i: F.struct((i + 1).alias("ordinal"), p["kind"].alias("kind"), p["ref"].alias("ref"), expanded_tokens(p, patch, audio_tokens_per_second, page_tokens).alias("tokens")))
    return chats.select(
        F.col("_conv").alias(conv_col),
        F.size("_turns").cast("long").alias("n_turns"),
        F.array_join(F.transform("_pieces", lambda p: F.concat(p["head"], p["body"], F.lit(CLOSE))), "").alias("formatted"),
        F.aggregate("_sizes", begin, span, lambda s: s["spans"]).alias("loss_spans"),
        listed.alias("attachments"),
        F.aggregate(listed, F.lit(0).cast("long"), lambda a, x: a + x["tokens"]).alias("expanded_tokens"),
    )


def read_turns(formatted: Column) -> Column:
    """array<struct<role,text>> parsed back from a formatted conversation."""
    chunks = F.split(formatted, F.lit(CLOSE))
    return F.transform(
        F.slice(chunks, F.lit(1), F.size(chunks) - 1),
        lambda c: F.struct(
            unescape(F.substring_index(F.substr(c, F.lit(len(OPEN) + 1)), MIDDLE, 1)).alias("role"),
            unescape(F.substr(c, F.length(F.substring_index(c, MIDDLE, 1)) + len(MIDDLE) + 1)).alias("text"),
        ),
    )


def read_parts(content: Column) -> Column:
    """array<struct<kind,text,ordinal>> of an escaped content: texts unescaped, attachments by ordinal.

    Escaped texts hold no `<|`, so every one of them opens a placeholder.
    """
    chunks = F.split(content, F.lit("<\\|"))
    part = lambda kind, text, n: F.struct(kind.alias("kind"), text.alias("text"), n.alias("ordinal"))
    words = lambda c: part(F.lit("text"), unescape(c), F.lit(None).cast("int"))
    mark = lambda c: part(F.substring_index(c, ":", 1), F.lit(None).cast("string"), F.substring_index(F.substring_index(c, "|>", 1), ":", -1).cast("int"))
    rest = lambda c: F.substr(c, F.length(F.substring_index(c, "|>", 1)) + 3)
    found = F.concat(F.array(words(chunks[0])), F.flatten(F.transform(F.slice(chunks, F.lit(2), F.size(chunks)), lambda c: F.array(mark(c), words(rest(c))))))
    return F.filter(found, lambda p: (p["kind"] != "text") | (p["text"] != ""))


def read_loss(formatted: Column, spans: Column) -> Column:
    """Text under the loss mask, unescaped, in order."""
    return F.array_join(F.transform(spans, lambda s: unescape(F.substr(formatted, s["start"] + 1, s["end"] - s["start"]))), "")

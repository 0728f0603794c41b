"""Chat formatting of typed content parts, in DataFrame operations only.

A turn is a list of parts (kind, text, ref, units). The visitor writes a text part as escaped text and any
other part as a placeholder of its kind, in order, records the attachment and adds up how many tokens the
placeholders stand for. Turns are marked with control strings that begin with `<|`; inside texts a backslash
is doubled and `<|` gets one, so a text can never hold a control string and reading back is exact.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

START, END = "<|im_start|>", "<|im_end|>\n"
#: Tokens that one unit of a part stands for: image tiles, seconds of audio, pages of a document.
EXPANDED = {"image": 256, "audio": 25, "document": 500}
PART = "struct<kind: string, text: string, ref: string, units: bigint>"


def escape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), F.lit("<|"), F.lit("<\\|"))


def unescape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("<\\|"), F.lit("<|")), F.lit("\\\\"), F.lit("\\"))


def _role(role: Column) -> Column:
    """A role stands on the line of its mark: its line feeds are escaped too."""
    return F.replace(escape(F.coalesce(role, F.lit(""))), F.lit("\n"), F.lit("\\n"))


def as_parts(turns: DataFrame) -> DataFrame:
    """conv_id, turn, role and text as one text part."""
    part = F.struct(F.lit("text").alias("kind"), F.coalesce("text", F.lit("")).alias("text"), F.lit(None).cast("string").alias("ref"), F.lit(0).cast("long").alias("units"))
    return turns.select("conv_id", "turn", "role", F.array(part).alias("parts"))


def _visit(part: Column) -> Column:
    text = F.coalesce(part["kind"], F.lit("text")) == "text"
    known = part["kind"].isin(*EXPANDED)
    return F.when(text, escape(F.coalesce(part["text"], F.lit("")))).when(known, F.concat(F.lit("<|"), part["kind"], F.lit("|>"))).otherwise(F.lit("<|attachment|>"))


def _tokens(part: Column) -> Column:
    out = F.lit(0).cast("long")
    for kind, n in EXPANDED.items():
        out = F.when(part["kind"] == kind, F.coalesce(part["units"], F.lit(1)) * n).otherwise(out)
    return out


def format_chat(turns: DataFrame, loss_role: str = "assistant") -> DataFrame:
    """One row for each conversation of turns (conv_id, turn, role, parts: array of PART).

    Turns are ordered by turn, then role and content; nulls first. Returns conv_id, formatted, loss_spans
    (start, end: bytes of the UTF-8 text under the loss mask, one span for each turn of loss_role), attachments
    in order (turn, kind, ref, tokens) and placeholder_tokens. Null role: empty. Null text or parts: empty. A
    part of unknown kind is an attachment of no tokens. Null conv_id: a conversation of its own. Repeated rows
    are turns of their own. No rows: no rows.
    """
    parts = F.coalesce(F.col("parts"), F.array().cast(f"array<{PART}>"))
    flat = turns.select(
        "conv_id",
        "turn",
        F.coalesce("role", F.lit("")).alias("role"),
        F.concat(F.lit(START), _role(F.col("role")), F.lit("\n")).alias("head"),
        F.array_join(F.transform(parts, _visit), "").alias("body"),
        F.transform(F.filter(parts, lambda p: F.coalesce(p["kind"], F.lit("text")) != "text"), lambda p: F.struct(p["kind"].alias("kind"), p["ref"].alias("ref"), _tokens(p).alias("tokens"))).alias("files"),
    )
    order = Window.partitionBy("conv_id").orderBy("turn", "role", "body")
    size = F.octet_length("head") + F.octet_length("body") + len(END)
    placed = flat.withColumn("at", F.coalesce(F.sum(size.cast("long")).over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).withColumn("k", F.row_number().over(order))
    begin = F.col("at") + F.octet_length("head")
    grouped = placed.groupBy("conv_id").agg(
        F.array_sort(F.collect_list(F.struct("k", F.concat("head", "body", F.lit(END)).alias("text"), "turn", "files", (F.col("role") == loss_role).alias("loss"), begin.alias("start"), (begin + F.octet_length("body")).alias("end")))).alias("t")
    )
    attachments = F.flatten(F.transform("t", lambda t: F.transform(t["files"], lambda f: F.struct(t["turn"].alias("turn"), f["kind"].alias("kind"), f["ref"].alias("ref"), f["tokens"].alias("tokens")))))
    return grouped.select(
        "conv_id",
        F.array_join(F.transform("t", lambda t: t["text"]), "").alias("formatted"),
        F.transform(F.filter("t", lambda t: t["loss"]), lambda t: F.struct(t["start"].alias("start"), t["end"].alias("end"))).alias("loss_spans"),
        attachments.alias("attachments"),
        F.aggregate(attachments, F.lit(0).cast("long"), lambda n, a: n + a["tokens"]).alias("placeholder_tokens"),
    )


def read_turns(formatted: Column) -> Column:
    """Role and text of each turn, read back from the formatted text (placeholders stay as they are written)."""
    raw = F.split(formatted, r"<\|im_end\|>\n", -1)
    raw = F.slice(raw, 1, F.size(raw) - 1)
    line = lambda x: F.instr(x, "\n")
    return F.transform(raw, lambda x: F.struct(_unrole_text(F.substring(x, F.lit(len(START) + 1), line(x) - len(START) - 1)).alias("role"), unescape(F.substring(x, line(x) + 1, F.length(x))).alias("text")))


def _unrole_text(role: Column) -> Column:
    """Undo _role: doubled backslashes are set apart first, so that what is left of `\\n` is a line feed."""
    pieces = F.transform(F.split(role, r"\\\\", -1), lambda p: F.replace(F.replace(p, F.lit("<\\|"), F.lit("<|")), F.lit("\\n"), F.lit("\n")))
    return F.array_join(pieces, "\\")


def loss_text(formatted: Column, spans: Column) -> Column:
    """All text under the loss mask, unescaped, with nothing between."""
    raw = F.encode(formatted, "UTF-8")
    return F.array_join(F.transform(spans, lambda s: unescape(F.decode(F.substring(raw, (s["start"] + 1).cast("int"), (s["end"] - s["start"]).cast("int")), "UTF-8"))), "")

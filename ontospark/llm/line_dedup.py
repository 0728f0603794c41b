"""Line deduplication over line-id sequences, in DataFrame operations only.

Each line position is a suffix of its document's line-id sequence. Distributed prefix doubling names the first
2^k lines of a suffix from two names of half the length. After each round a suffix stays only if its name
still occurs twice: what stays is exactly the suffix array's intervals whose common prefix has at least that
length, and everything else is closed. Doubling ends at the run length asked for (one overlapping round makes
up for a length that is no power of two). In each interval the earliest suffix is the source, and the lines
under the others are later copies; neighbouring suffixes join into maximal runs.

Only names of repeated lines travel, the text doesn't. Counts are summed before they are shuffled, and joins
on a hot name are plain equi-joins of written tables, which adaptive execution splits.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ontospark.llm._frames import cut

RUN = 3
#: Line positions that a broadcast list of removals may hold; beyond it documents are shuffled.
BROADCAST_LINES = 2_000_000
_LOWEST = -(1 << 63)


def _doc_key(row: str = "") -> list[Column]:
    return [F.coalesce(F.col(f"{row}doc_id").cast("long"), F.lit(_LOWEST)).alias("doc"), F.xxhash64(f"{row}text").alias("body")]


def _lines(text: str = "text") -> Column:
    return F.split(F.col(text), "\n", -1)


def _repeated(named: DataFrame) -> DataFrame:
    """The suffixes whose name occurs more than once, with the earliest place of that name."""
    classes = cut(named.groupBy("n1", "n2").agg(F.count(F.lit(1)).alias("n"), F.min(F.struct("doc", "body", "pos")).alias("first")).where("n > 1").drop("n"))
    return named.join(classes, ["n1", "n2"])


def _double(active: DataFrame, shift: int) -> DataFrame:
    """Names of prefixes that reach shift lines further: from the names at a suffix and at shift lines after it."""
    ahead = active.select("doc", "body", (F.col("pos") - shift).alias("pos"), F.col("n1").alias("m1"), F.col("n2").alias("m2"))
    pairs = active.select("doc", "body", "pos", "n1", "n2").join(ahead, ["doc", "body", "pos"])
    return cut(pairs.select("doc", "body", "pos", F.xxhash64("n1", "m1").alias("n1"), F.xxhash64(F.lit(1), "n2", "m2").alias("n2")))


def later_copies(docs: DataFrame, run: int = RUN) -> DataFrame:
    """(doc, body, pos, first): starts of runs of `run` lines that also start earlier, and the earliest start. doc, body: id and hash of the text."""
    named = docs.where("text IS NOT NULL").select(
        *_doc_key(), F.posexplode(F.transform(_lines(), lambda x: F.struct(F.xxhash64(x).alias("n1"), F.xxhash64(F.lit(1), x).alias("n2"), (F.trim(x) == "").alias("blank")))).alias("pos", "line")
    ).select("doc", "body", "pos", "line.*")
    active = _repeated(named).select("doc", "body", "pos", "n1", "n2", "blank", "first").distinct()
    starts = None
    if run > 1:
        active = cut(active)
        starts = active.where("NOT blank").select("doc", "body", "pos")
    have = 1
    while have < run:
        shift = min(have, run - have)
        active = cut(_repeated(_double(active, shift)))
        have += shift
    found = active.where(F.col("first") < F.struct("doc", "body", "pos"))
    return (found.where("NOT blank") if starts is None else found.join(starts, ["doc", "body", "pos"])).select("doc", "body", "pos", "first")


def maximal_runs(docs: DataFrame, run: int = RUN) -> DataFrame:
    """Maximal runs of at least `run` lines that also start earlier, whatever their length: doc, start, length, source_doc, source_start.

    A suffix and the earliest suffix of its interval have a common prefix of `run` lines or more. Where the suffixes at
    the following lines have sources at the following lines too, the common prefix is longer by as much: such suffixes
    are one run, whose length is the longest common prefix with its source from the run's start on. Runs start on a line
    that isn't blank. Repeated rows of a doc_id with one text are one document.
    """
    found = later_copies(docs, run).distinct()
    apart = F.col("first.pos") - F.col("pos")
    key = [F.col("doc"), F.col("body"), F.col("first.doc"), F.col("first.body"), apart]
    island = F.col("pos") - F.row_number().over(Window.partitionBy(*key).orderBy("pos"))
    runs = found.select("doc", "body", "pos", "first", island.alias("island"), apart.alias("apart")).groupBy("doc", "body", F.col("first.doc").alias("source_doc"), F.col("first.body").alias("source_body"), "apart", "island")
    out = runs.agg(F.min("pos").alias("start"), (F.max("pos") - F.min("pos") + run).cast("long").alias("length"), F.min("first.pos").alias("source_start"))
    return out.select("doc", "start", "length", "source_doc", "source_start")


def drop_repeated_lines(docs: DataFrame, run: int = RUN) -> DataFrame:
    """Delete every line that lies in a run of `run` lines which also starts earlier in the corpus.

    Earlier: smaller doc_id, or the same document at an earlier line. Runs are judged on the input, start on a
    line that isn't blank, and don't cross documents. Lines are cut at \\n and compared exactly. Returns docs
    with all its columns, text replaced, plus `_lines` and `_removed` (counts); a column of that name in docs
    is replaced. Null text: no lines, stays null. Empty text: one blank line, stays. Fewer lines than a run:
    unchanged. Rows that repeat a doc_id with the same text are one document and get the same result; with
    other text the order is by a hash of the text. A null doc_id sorts first. No rows: no rows.
    """
    gone = later_copies(docs, run).select("doc", "body", F.explode(F.sequence(F.col("pos"), F.col("pos") + run - 1)).alias("p"))
    gone = cut(gone.groupBy("doc", "body").agg(F.collect_set("p").alias("gone")))
    small = (gone.agg(F.sum(F.size("gone"))).first()[0] or 0) <= BROADCAST_LINES
    kept = [c for c in docs.columns if c.lower() not in ("_lines", "_removed")]
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in kept]).alias("row")).select("row", *_doc_key("row."))
    out = rows.join(F.broadcast(gone) if small else gone, ["doc", "body"], "left")
    lines = _lines("row.text")
    n = F.when(F.col("row.text").isNull(), F.lit(0)).otherwise(F.size(lines))
    left = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), F.col("gone"))
    text = F.when(F.col("gone").isNull(), F.col("row.text")).otherwise(F.array_join(F.transform(left, lambda i: F.get(lines, i)), "\n"))
    return out.select(*[text.alias(c) if c == "text" else F.col(f"row.`{c}`").alias(c) for c in kept], n.cast("long").alias("_lines"), F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("_removed"))

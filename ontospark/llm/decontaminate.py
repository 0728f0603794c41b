"""Benchmark decontamination: size-partitioned MinHash containment search, in DataFrame operations only.

Items are partitioned by size (powers of two). An item's sketch is its least shingle hashes; the sketch length
of a partition follows from its largest size, such that a document that holds the wanted share of an item's
shingles must hold one from the sketch. Documents, however long, are probed with all their shingles, so no
leak inside a long text is missed. Pairs that meet are verified by exact containment of the shingles as text.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ontospark.llm._frames import bounded, cut

WORDS = 5
SHARE = 80


def _words(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), r"[\x20\x09-\x0D]+"), lambda w: w != "")


def _runs(words: Column, n: int, make) -> Column:
    """make(list of n word columns) for each run of n words; an empty array if there are fewer."""
    return F.when(F.size(words) >= n, F.transform(F.sequence(F.lit(0), F.size(words) - n), lambda i: make([F.get(words, i + k) for k in range(n)]))).otherwise(F.array())


def _hashes(words: Column, n: int) -> Column:
    return _runs(words, n, lambda w: F.xxhash64(*w))


def _texts(words: Column, n: int) -> Column:
    return _runs(words, n, lambda w: F.concat_ws(" ", *w))


def _of_item(make, words: Column, n: int) -> Column:
    """An item's shingles; one with fewer than n words is a single shingle of all its words."""
    out = make(words, n)
    for k in range(1, n):
        out = F.when(F.size(words) == k, make(words, k)).otherwise(out)
    return F.array_distinct(out)


def leaks(docs: DataFrame, items: DataFrame, n: int = WORDS, percent: int = SHARE) -> DataFrame:
    """Pairs of a document and a benchmark item where the document holds at least percent % of the item's distinct n-word shingles.

    Words: lower-cased, cut at ASCII white space. Reads doc_id, text and item_id, text; other columns are
    ignored. Returns doc_id, item_id, n_item (the item's shingles), n_shared, containment. An item with fewer
    than n words is one shingle of all its words. Null or empty texts match nothing. Rows that repeat an id
    give one pair, with the best containment. A null id is an id. No rows: no rows.
    """
    item = items.where("text IS NOT NULL").select("item_id", _words(F.col("text")).alias("w")).where(F.size("w") > 0)
    item = cut(item.select("item_id", F.least(F.size("w"), F.lit(n)).alias("len"), _of_item(_hashes, F.col("w"), n).alias("h"), _of_item(_texts, F.col("w"), n).alias("sh")))
    lengths = sorted(r[0] for r in item.select("len").distinct().collect())
    top = F.pow(F.lit(2), F.ceil(F.log2(F.size("h").cast("double")))).cast("int")
    keep = top - F.ceil(top * percent / 100).cast("int") + 1
    sketch = cut(item.select("item_id", F.explode(F.slice(F.array_sort("h"), F.lit(1), keep)).alias("h")).distinct())
    words = docs.where("text IS NOT NULL").select("doc_id", _words(F.col("text")).alias("w"))
    probes = words.select("doc_id", F.explode(F.concat(*[_hashes(F.col("w"), k) for k in lengths]) if lengths else F.array(F.lit(0).cast("long"))).alias("h"))
    pairs = cut(probes.join(bounded(sketch), "h").select("doc_id", "item_id").distinct())
    near = docs.select("doc_id", "text").alias("d").join(bounded(pairs).alias("p"), F.expr("d.doc_id <=> p.doc_id")).select("d.doc_id", "d.text", "p.item_id")
    both = near.alias("a").join(bounded(item).alias("b"), F.expr("a.item_id <=> b.item_id")).select("a.doc_id", "a.item_id", "b.sh", "b.len", _words(F.col("a.text")).alias("w"))
    mine = F.coalesce(*[F.when(F.col("len") == k, _texts(F.col("w"), k)) for k in lengths]) if lengths else F.array(F.lit(""))
    found = both.select("doc_id", "item_id", F.size("sh").cast("long").alias("n_item"), F.size(F.array_intersect("sh", mine)).cast("long").alias("n_shared"))
    # written before it is filtered: a filter pushed below would split the text again for every shingle
    found = cut(found).where(f"100 * n_shared >= {percent} * n_item").withColumn("containment", F.col("n_shared") / F.col("n_item"))
    best = F.max(F.struct("containment", "n_item", "n_shared")).alias("m")
    return found.groupBy("doc_id", "item_id").agg(best).select("doc_id", "item_id", "m.n_item", "m.n_shared", "m.containment")


def drop_leaks(docs: DataFrame, items: DataFrame, n: int = WORDS, percent: int = SHARE) -> DataFrame:
    """The rows of docs, all columns as they were, that hold no benchmark item."""
    bad = cut(leaks(docs, items, n, percent).select(F.col("doc_id").alias("_leaked")).distinct())
    bad = bounded(bad).alias("bad")
    return docs.alias("d").join(bad, F.expr("d.doc_id <=> bad._leaked"), "left_anti")

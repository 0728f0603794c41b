"""Exact n-gram Jaccard join with adaptive multi-match prefixes.

Two documents with Jaccard similarity of at least t differ in at most k shingles, and k follows from their
sizes. Shingles are put in one global order, rarest first: by their count in a table of hashed counters over
all documents, then by hash. Any order is exact; this one keeps passages that many documents share out of the
prefixes. The shortest prefix is the first n - ceil(t n) + 1 shingles, and one shared shingle makes a
candidate. Where the estimated candidate cost of a size class is too high for that, its prefix is lengthened
and more matches are asked for: shingles are dealt by a second hash into more than k parts, the prefix is the
first m shingles of every part, and a pair is looked at only if all m prefix shingles of one part agree. Parts
with too few shingles are left out. There are so many parts that an agreeing one remains for every pair of
documents with few thin parts; documents with more thin parts also send the shortest prefix, so no pair is
lost for any m. A class takes the first of STEPS whose estimated cost, from a bounded sample scaled to the
corpus, is small enough, else the cheapest of them. Candidate pairs are never listed: each prefix keeps a star
to its least member (first within a task, then within a bucket), and members of one candidate component are
verified exactly by a search that skips pairs that are already connected.

Where so many documents share a counter that a component outgrows one verification task, the shingles of its
members are counted exactly, slice by slice, and their shortest prefixes are taken anew in the order of those
counts; a component is then what both orders leave together.

Documents with equal shingle sets are one node from the start.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ontospark.llm._frames import batch, bounded, cut, freeing, give_back, parts_for, rows_of, text_bytes
from ontospark.llm._text import LOWER, mix, shingle_set
from ontospark.llm.components import components
from ontospark.plans.ship import ship

#: The shortest prefix (one match), then m matches in one of the parts, then whole parts.
ONE, WHOLE = -1, 0
STEPS = (ONE, 2, 4, WHOLE)
#: From this similarity on, parts hold enough shingles to need two matches or more, so classes start at the second step
#: and take whole parts if none is cheap; below it too many parts would be thin.
THICK = 85
#: Hashed counters: one for LOAD shingles, and their least and most number as powers of two.
LOAD, LEAST_BITS, MOST_BITS = 4, 16, 24
SAMPLE = 1500
#: Candidate pairs that one document may cost on the estimate before its class takes the next step.
COST = 1.0
GROWTH = 1.25
#: Shingles that one verification task holds of one block. Verifying takes some 50 bytes a shingle besides the texts, and two
#: blocks may meet in a task, so this bounds what a worker takes.
BLOCK = 2_000_000
#: Where a component outgrew a block: shingles that one bucket sums over all slices, and those that one task counts exactly.
#: The slices carry texts, of which Spark holds a copy on either side of the pipe, so they are smaller.
BUCKET, SLICE = 2_000_000, 500_000
_SIG = np.dtype([("sig", "<u8"), ("node", "<i8")])


def most_different(total: int, percent: int) -> int:
    """The most shingles in which two sets whose sizes sum to total differ at this similarity."""
    shared = -(-percent * total // (100 + percent))
    return total - 2 * shared


def classes(percent: int) -> list[int]:
    """First sizes of the size classes; similar sets lie in the same or in neighbouring classes."""
    out = [1]
    while out[-1] < 1 << 40:
        out.append(max(out[-1] + 1, int(out[-1] * max(GROWTH, 100 / percent))))
    return out


def node_of(s: np.ndarray) -> int:
    """A 63-bit name of a shingle set."""
    with np.errstate(over="ignore"):
        return int(mix(np.array([mix(s.copy()).sum() + np.uint64(len(s))], np.uint64))[0] >> np.uint64(1))


def counter_of(s: np.ndarray, bits: int) -> np.ndarray:
    return (mix(s ^ np.uint64(0x3C6E_F372_FE94_F82B)) >> np.uint64(64 - bits)).astype(np.int64)


def level_of(counts: np.ndarray) -> np.ndarray:
    """Counts as bytes, eight levels to a doubling; rarer shingles come first in the global order."""
    return np.minimum(8 * np.log2(counts.astype(np.float64) + 1), 255).astype(np.uint8)


class Prefixes:
    """Signatures of one shingle set; steps: ONE, m or WHOLE by size class; levels: of the hashed counters, or None."""

    def __init__(self, percent: int, steps: dict[int, int], levels: np.ndarray | None = None):
        self.percent, self.steps, self.first, self.levels = percent, steps, classes(percent), levels
        self.bits = 0 if levels is None else len(levels).bit_length() - 1

    def ordered(self, s: np.ndarray) -> np.ndarray:
        """The sorted set in the global order."""
        return s if self.levels is None else s[np.argsort(self.levels[counter_of(s, self.bits)], kind="stable")]

    def shortest(self, s: np.ndarray) -> np.ndarray:
        """One signature for each shingle of the shortest prefix of an ordered set."""
        return mix(s[: len(s) + (-self.percent * len(s) // 100) + 1] ^ np.uint64(0x5DEE_CE66_D123_4567))

    def size_class(self, n: int) -> int:
        return int(np.searchsorted(self.first, n, "right")) - 1

    def schemes(self, n: int) -> list[int]:
        c = self.size_class(n)
        return [c, c + 1] if 100 * n >= self.percent * self.first[c + 1] else [c]

    def bound(self, c: int) -> int:
        """The most shingles in which a linked pair of class c differs; 0: only equal sets, one node anyway, are linked.

        The bound rises with the size sum among even and among odd sums, but not from one to the next.
        """
        total = 2 * (self.first[c + 1] - 1)
        return max(most_different(total, self.percent), most_different(total - 1, self.percent))

    def block(self, s: np.ndarray, c: int, m: int) -> tuple[np.ndarray, bool]:
        """Signatures in class c, and whether the document has more thin parts than the class can spare."""
        k = self.bound(c)
        if k <= 0:
            return np.zeros(0, np.uint64), False
        least, spare = (1, 4 + 8 * k // 100) if self.percent < THICK else (2, 5 + k // 4)
        parts = k + 1 + spare
        part = (mix(s ^ np.uint64(0xA5A5_5A5A_0F0F_F0F0 + c)) % np.uint64(parts)).astype(np.int64)
        order = np.argsort(part, kind="stable")
        p, x = part[order], s[order]
        head = np.flatnonzero(np.concatenate([[True], p[1:] != p[:-1]]))
        size = np.diff(np.append(head, len(p)))
        at = p[head]
        if m:
            rank = np.arange(len(p)) - np.repeat(head, size)
            x = x[rank < m]
            head = np.concatenate([[0], np.cumsum(np.minimum(size, m))[:-1]])
        total = np.add.reduceat(mix(x), head)
        full = size >= least
        return mix(total + at.astype(np.uint64) * np.uint64(0x9E37_79B9) + np.uint64((c + 1) << 40))[full], parts - int(full.sum()) > spare

    def of(self, s: np.ndarray) -> np.ndarray:
        out, plain = [], False
        s = self.ordered(s)
        for c in self.schemes(len(s)):
            m = self.steps.get(c, ONE if self.percent < THICK else WHOLE)
            if m != ONE:
                sig, few = self.block(s, c, m)
                out.append(sig)
            plain |= m == ONE or few
        if plain:
            out.append(self.shortest(s))
        return np.concatenate(out)


def estimate_steps(sample: list[np.ndarray], rows: int, percent: int, levels: np.ndarray | None = None) -> dict[int, int]:
    """The step of each size class: the first whose estimated candidates for one document stay below COST, else the cheapest.

    One pair more than the sample shows is assumed. Of equally cheap steps the shortest prefix wins. Classes that link
    equal sets only are not estimated, since parts send nothing for them.
    """
    by: dict[int, list[np.ndarray]] = {}
    p = Prefixes(percent, {}, levels)
    for s in sample:
        if len(s):
            for c in p.schemes(len(s)):
                by.setdefault(c, []).append(p.ordered(s))
    out = {}
    for c, sets in by.items():
        if p.bound(c) <= 0:
            continue
        best = None
        for m in STEPS if percent < THICK else STEPS[1:]:
            sigs = np.concatenate([p.shortest(s) if m == ONE else p.block(s, c, m)[0] for s in sets])
            _, n = np.unique(sigs, return_counts=True)
            cost = (1 + (n * (n - 1) // 2).sum()) * 2 / len(sets) * rows / max(1, len(sample))
            if best is None or cost < best or (percent >= THICK and cost > COST):
                best, out[c] = cost, m
            if cost <= COST:
                break
    return out


def _sets(batches, n: int):
    for row in rows_of(batches, "doc_id", "body"):
        yield row[0], shingle_set((row[1] or b"").translate(LOWER), n)


_NODES = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("node", pa.int64()), ("slice", pa.int32()), ("counts", pa.binary())])


def _nodes(n: int, bits: int, slices: int):
    """A row for each document; after them the task's hashed counters, in slices."""

    def of(batches):
        counts = np.zeros(1 << bits, np.uint32)
        for b in batches:
            out: list[list] = [[], [], []]
            for doc, s in _sets([b], n):
                for c, v in zip(out, (doc, len(s), node_of(s) if len(s) else None), strict=True):
                    c.append(v)
                np.add.at(counts, counter_of(s, bits), 1)
            none = [None] * len(out[0])
            yield batch(_NODES, [*out, none, none])
        if counts.any():
            width = len(counts) // slices
            for i in range(slices):
                part = counts[i * width : (i + 1) * width]
                if part.any():
                    yield batch(_NODES, [[None], [None], [None], [i], [zlib.compress(part.tobytes(), 1)]])

    return of


_LEVELS = pa.schema([("slice", pa.int32()), ("levels", pa.binary())])


def _levels(batches):
    total: dict[int, np.ndarray] = {}
    for i, blob in rows_of(batches, "slice", "counts"):
        part = np.frombuffer(zlib.decompress(blob), np.uint32)
        total[i] = total[i] + part if i in total else part.astype(np.uint64)
    for i, part in total.items():
        yield batch(_LEVELS, [[i], [level_of(part).tobytes()]])


#: Bytes of texts from which on a group first returns what the groups before it left.
LARGE = 4 << 20


_SENT = pa.schema([("bucket", pa.int32()), ("kind", pa.int32()), ("blob", pa.binary())])


def _stars(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The least member of each signature, and edges of the others to it."""
    x = x[np.lexsort((x["node"], x["sig"]))]
    first = np.concatenate([[True], x["sig"][1:] != x["sig"][:-1]])
    least = x["node"][first][np.cumsum(first) - 1]
    e = np.stack([x["node"], least], 1)[x["node"] != least]
    return x[first], np.unique(e, axis=0) if len(e) else e


def _dealt(x: np.ndarray, buckets: int) -> pa.RecordBatch:
    """Signatures in one blob for each bucket, each with its least node; edges of the other nodes to it."""
    x, edges = _stars(x)
    bucket = ((x["sig"] >> np.uint64(32)) % np.uint64(buckets)).astype(np.int64)
    order = np.argsort(bucket, kind="stable")
    x, bucket = x[order], bucket[order]
    at = np.concatenate([[0], np.flatnonzero(np.diff(bucket)) + 1, [len(x)]])
    rows = [(int(bucket[i]), 0, x[i:j].tobytes()) for i, j in zip(at[:-1], at[1:], strict=True)]
    for i in range(0, len(edges), 4096):
        rows.append((int(edges[i, 0] % buckets), 1, edges[i : i + 4096].tobytes()))
    return batch(_SENT, [list(c) for c in zip(*rows, strict=True)])


def _signed(sig: np.ndarray, node: int) -> np.ndarray:
    x = np.zeros(len(sig), _SIG)
    x["sig"], x["node"] = sig, node
    return x


def _send(n: int, percent: int, steps: dict[int, int], levels, buckets: int, flush: int = 500_000):
    """levels: a broadcast variable of at most 2 ** MOST_BITS bytes."""

    def of(batches):
        prefixes = Prefixes(percent, steps, np.frombuffer(levels.value, np.uint8))
        seen: set[int] = set()
        parts, size = [], 0
        for _, s in _sets(batches, n):
            if not len(s) or (node := node_of(s)) in seen:
                continue
            if len(seen) < 1_000_000:  # only spares repeated work
                seen.add(node)
            parts.append(_signed(prefixes.of(s), node))
            size += len(parts[-1])
            if size >= flush:
                yield _dealt(np.concatenate(parts), buckets)
                parts, size = [], 0
        if size:
            yield _dealt(np.concatenate(parts), buckets)

    return of


_EDGE = pa.schema([("a", pa.int64()), ("b", pa.int64())])


def _gather(batches):
    sigs, edges = [], []
    for kind, blob in rows_of(batches, "kind", "blob"):
        (edges if kind else sigs).append(blob)
    out = [np.frombuffer(b, "<i8").reshape(-1, 2) for b in edges]
    if sigs:
        out.append(_stars(np.frombuffer(b"".join(sigs), _SIG))[1])
    if out:
        e = np.unique(np.concatenate(out), axis=0)
        for i in range(0, len(e), 50_000):
            yield batch(_EDGE, [e[i : i + 50_000, 0], e[i : i + 50_000, 1]])


_COUNT = np.dtype([("key", "<u8"), ("n", "<u4")])
_COUNTED = pa.schema([("slice", pa.int32()), ("bucket", pa.int32()), ("blob", pa.binary())])


def _room(group: pa.Table) -> None:
    if group.nbytes >= LARGE:
        give_back()


def _members(group: pa.Table, n: int) -> list[tuple[int, int, np.ndarray]]:
    """root, node and shingles (counted for that root alone) of each text of a slice, once a node."""
    out = {}
    for root, node, body in rows_of(group.to_batches(), "root", "node", "body"):
        if node not in out:
            s = shingle_set((body or b"").translate(LOWER), n)
            if len(s) and node_of(s) == node:
                out[node] = (root, node, _within(root, s))
    return [out[x] for x in sorted(out)]


def _within(root: int, s: np.ndarray) -> np.ndarray:
    """Shingles are counted and met within one component, which grew too large, each for itself."""
    return mix(s ^ mix(np.array([root], np.int64).view(np.uint64)))


def _tally(n: int, buckets: int):
    def of(group: pa.Table) -> pa.Table:
        _room(group)
        of_slice, rows = group.column("slice")[0].as_py(), []
        sets = [s for _, _, s in _members(group, n)]
        if sets:
            key, count = np.unique(np.concatenate(sets), return_counts=True)
            x = np.zeros(len(key), _COUNT)
            x["key"], x["n"] = key, count
            at = np.searchsorted(_bucket(key, buckets), np.arange(buckets + 1))
            rows = [(of_slice, b, x[i:j].tobytes()) for b, (i, j) in enumerate(zip(at[:-1], at[1:], strict=True)) if j > i]
        return pa.Table.from_batches([batch(_COUNTED, [list(c) for c in zip(*rows, strict=True)] or [[], [], []])])

    return of


def _bucket(key: np.ndarray, buckets: int) -> np.ndarray:
    """Buckets rise with the key, so sorted keys stay sorted from bucket to bucket."""
    return ((key >> np.uint64(32)) * np.uint64(buckets)) >> np.uint64(32)


def _total(group: pa.Table) -> pa.Table:
    """Of each slice's keys of a bucket, in their order, the count over all slices as a level."""
    slices = group.column("slice").to_pylist()
    parts = [np.frombuffer(b, _COUNT) for b in group.column("blob").to_pylist()]
    key, back = np.unique(np.concatenate([p["key"] for p in parts]), return_inverse=True)
    level = level_of(np.bincount(back, weights=np.concatenate([p["n"] for p in parts])))[back]
    at = np.concatenate([[0], np.cumsum([len(p) for p in parts])])
    blobs = [level[i:j].tobytes() for i, j in zip(at[:-1], at[1:], strict=True)]
    return pa.Table.from_batches([batch(_COUNTED, [slices, group.column("bucket").to_pylist(), blobs])])


def _again(n: int, percent: int, buckets: int):
    """Shortest prefixes of a slice's texts in the order of the counts that came back for it."""

    def of(group: pa.Table, counted: pa.Table) -> pa.Table:
        _room(group)
        members = _members(group, n)
        if not members:
            return _SENT.empty_table()
        key = np.unique(np.concatenate([s for _, _, s in members]))
        level = np.frombuffer(b"".join(b for _, b in sorted(zip(counted.column("bucket").to_pylist(), counted.column("blob").to_pylist(), strict=True))), np.uint8)
        p, out = Prefixes(percent, {}), []
        for _, node, s in members:
            s.sort()
            out.append(_signed(p.shortest(s[np.argsort(level[np.searchsorted(key, s)], kind="stable")]), node))
        return pa.Table.from_batches([_dealt(np.concatenate(out), buckets)])

    return of


def narrowed(src: DataFrame, groups: DataFrame, nodes: DataFrame, n: int, percent: int, buckets: int) -> DataFrame:
    """groups(node, root) of candidates, where components too large for one verification task are split by exact counts."""
    members = groups.join(nodes, "node")
    large = cut(members.groupBy("root").agg(F.sum("n").alias("total")).where(F.col("total") > BLOCK))
    total = large.agg(F.sum("total")).first()[0]
    if not total:
        return groups
    slices, tallied = -(-int(total) // SLICE), -(-int(total) // BUCKET)
    inside = cut(members.join(bounded(large.select("root")), "root", "left_semi").select(F.col("rep").alias("doc_id"), "node", "root"))
    texts = src.join(bounded(inside), "doc_id").withColumn("slice", F.pmod(F.xxhash64("node"), F.lit(slices)).cast("int"))
    texts = cut(texts.select("slice", "root", "node", "body"))
    tallies = texts.groupBy("slice").applyInArrow(_tally(n, tallied), "slice int, bucket int, blob binary")
    counted = tallies.groupBy("bucket").applyInArrow(_total, "slice int, bucket int, blob binary")
    sent = texts.groupBy("slice").cogroup(counted.groupBy("slice")).applyInArrow(_again(n, percent, buckets), "bucket int, kind int, blob binary")
    near = cut(sent.repartition(buckets, "bucket").mapInArrow(freeing(_gather), "a long, b long").distinct())
    return cut(groups.join(bounded(large.select("root")), "root", "left_anti").select("node", "root").unionByName(components(near)))


def forest(sets: list[np.ndarray], percent: int) -> list[tuple[int, int]]:
    """Links that span the components of these sets; a pair already connected is not compared.

    Shingles are ordered by how many of the sets hold them. Linked sets share one of their first
    n - ceil(t n) + 1 shingles in that order, so only sets met there are compared, by exact overlap.
    """
    m = len(sets)
    if m < 2:
        return []
    size = np.array([len(s) for s in sets])
    start = np.concatenate([[0], np.cumsum(size)])
    tokens, n = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)[1:]
    rank = np.empty(len(n), np.int32)
    rank[np.argsort(n, kind="stable")] = np.arange(len(n), dtype=np.int32)
    tokens, common_ones = rank[tokens], np.sort(n) > 1
    lead = []
    for d in range(m):
        mine = tokens[start[d] : start[d + 1]]
        mine.sort()
        head = mine[: size[d] + (-percent * int(size[d]) // 100) + 1]
        lead.append(head[common_ones[head]])
    owner = np.repeat(np.arange(m, dtype=np.int32), [len(x) for x in lead])
    met = np.concatenate(lead)
    order = np.argsort(met, kind="stable")
    owner, at = owner[order], np.searchsorted(met[order], np.arange(len(n) + 1))
    left, out, mark = np.ones(m, bool), [], np.zeros(len(n), bool)
    for seed in range(m):
        if not left[seed]:
            continue
        left[seed] = False
        queue = [seed]
        while queue:
            d = queue.pop()
            if not len(lead[d]):
                continue
            near = np.unique(np.concatenate([owner[at[t] : at[t + 1]] for t in lead[d].tolist()]))
            near = near[left[near]]
            near = near[(100 * size[near] >= percent * size[d]) & (percent * size[near] <= 100 * size[d])]
            if not len(near):
                continue
            mine = tokens[start[d] : start[d + 1]]
            mark[mine] = True
            for e in near.tolist():
                both = int(np.count_nonzero(mark[tokens[start[e] : start[e + 1]]]))
                if 100 * both >= percent * (size[e] + size[d] - both):
                    left[e] = False
                    out.append((d, e))
                    queue.append(e)
            mark[mine] = False
    return out


def _verify(n: int, percent: int):
    def of(group: pa.Table) -> pa.Table:
        _room(group)
        sets: dict[int, np.ndarray] = {}
        for node, body in rows_of(group.to_batches(), "node", "body"):
            if node not in sets:
                s = shingle_set((body or b"").translate(LOWER), n)
                if len(s) and node_of(s) == node:
                    sets[node] = s
        nodes = sorted(sets)
        e = forest([sets[x] for x in nodes], percent)
        return pa.Table.from_batches([batch(_EDGE, [[nodes[a] for a, _ in e], [nodes[b] for _, b in e]])])

    return of


def similar(docs: DataFrame, n: int = 5, percent: int = 80) -> DataFrame:
    """Link documents whose sets of n-word shingles have Jaccard similarity of at least percent / 100.

    Words: A-Z lower-cased, cut at ASCII white space. Reads doc_id and text; other columns are ignored.
    Returns one row for each row of docs: doc_id, n_shingles (set size), component_id (least doc_id reachable
    by links). With fewer than n words the whole sequence is the only shingle. Null or empty text: an empty
    set, linked with nothing, its own component. Null doc_id: null component unless others share its set.
    Rows that repeat a doc_id each get a row. No rows: no rows.
    """
    spark = docs.sparkSession
    ship(spark)
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("body"))
    size = text_bytes(src, "body")
    buckets = parts_for(spark, size)
    bits = min(MOST_BITS, max(LEAST_BITS, int(size // (6 * LOAD)).bit_length()))
    slices = 1 << min(8, buckets.bit_length())
    both = cut(src.mapInArrow(freeing(_nodes(n, bits, slices)), "doc_id long, n_shingles long, node long, slice int, counts binary"))
    known = both.where("slice IS NULL").select("doc_id", "n_shingles", "node")
    rows = known.count()
    levels = np.zeros(1 << bits, np.uint8)
    counted = both.where("slice IS NOT NULL").select("slice", "counts").repartition(buckets, "slice")
    for i, part in counted.mapInArrow(freeing(_levels), "slice int, levels binary").collect():
        levels[i * len(part) : (i + 1) * len(part)] = np.frombuffer(part, np.uint8)
    shared = spark.sparkContext.broadcast(levels.tobytes())
    picked = src.where("doc_id IS NOT NULL AND body IS NOT NULL").join(
        F.broadcast(known.where("n_shingles > 0").select("doc_id", F.xxhash64("doc_id").alias("h")).orderBy("h", "doc_id").limit(SAMPLE).select("doc_id").distinct()), "doc_id"
    ).select("body").limit(SAMPLE)
    sample = [shingle_set(r[0].translate(LOWER), n) for r in picked.toLocalIterator()]
    steps = estimate_steps(sample, rows, percent, levels)
    sent = src.mapInArrow(freeing(_send(n, percent, steps, shared, buckets)), "bucket int, kind int, blob binary")
    near = cut(sent.repartition(buckets, "bucket").mapInArrow(freeing(_gather), "a long, b long").distinct())
    nodes = known.where("node IS NOT NULL").groupBy("node").agg(F.min("doc_id").alias("rep"), F.max("n_shingles").alias("n"))
    groups = narrowed(src, components(near), nodes, n, percent, buckets)
    members = groups.join(nodes, "node").select("node", "root", "rep", "n")
    blocks = members.groupBy("root").agg(F.ceil(F.sum("n") / BLOCK).cast("int").alias("nb"))
    placed = members.join(blocks, "root").withColumn("mine", F.pmod(F.xxhash64("node"), F.col("nb")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("nb") - 1)))
    placed = cut(placed.select(F.col("rep").alias("doc_id"), "node", "root", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j")))
    full = src.join(bounded(placed), "doc_id").repartition(buckets, "root", "i", "j")
    links = components(full.groupBy("root", "i", "j").applyInArrow(_verify(n, percent), "a long, b long"))
    at = nodes.select("node", "rep").join(links, "node", "left").select("node", "rep", F.coalesce("root", "node").alias("root"))
    least = at.groupBy("root").agg(F.min("rep").alias("component_id"))
    final = cut(at.join(least, "root").select("node", "component_id"))
    return known.join(final, "node", "left").select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))

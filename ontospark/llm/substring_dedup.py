"""Substring deduplication by prefix-partitioned groups of sparse suffixes.

A window of 20 words is filed under one suffix: the one that starts at the least-hashed 8-word run inside the window
(its anchor). Equal windows have equal anchors at equal distances, so the suffixes that start at anchors, about one in
seven, are enough. Suffixes are split by prefixes of variable length into groups that fit a task:

1. by their first 8 words. Each slice of documents sends how many windows it files under each prefix; a prefix with
   one window in all cannot repeat and is closed.
2. an open prefix with at most GROUP windows is a group of its own. One with more is split further, by the window as
   a whole (the suffix's prefix with what stands before the anchor).

A group's leaves are sorted by the label of their window, then by place. Neighbours with equal labels have a common
prefix of 20 words or more, so each run of equal labels is one deep internal node of the group's tree: its earliest
leaf stays, and windows at its later leaves are removed. Adjacent windows join into maximal repeats when words are
marked. Labels are hashes (96 bits): a leaf that carried the 20 words that follow it would take 27 times the text.
Each slice sends a node once, with its earliest leaf, so a passage that a third of all documents share costs one
record for each slice, and no task holds all its copies.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ontospark.llm._frames import batch, rows_of, sliced
from ontospark.llm._text import grams, sliding_min, spans, word_hashes
from ontospark.plans.ship import ship

WINDOW = 20
PREFIX = 8
#: Windows under one prefix that one group takes.
GROUP = 1 << 18
_SECOND = 0xD1342543DE82EF95
_OPEN = np.dtype([("v", "<u8"), ("n", "<u4")])
_FOUND = np.dtype([("v", "<u8"), ("large", "u1")])
_LEAF = np.dtype([("h", "<u8"), ("g", "<u4"), ("doc", "<i8"), ("pos", "<i8")])
_NODE = np.dtype([("h", "<u8"), ("g", "<u4")])
_MOVED = pa.schema([("bucket", pa.int32()), ("slice", pa.int32()), ("kind", pa.int32()), ("blob", pa.binary())])


def _anchors(h: np.ndarray, window: int, prefix: int) -> tuple[np.ndarray, np.ndarray]:
    """The prefix groups of a document's windows, and all its prefix hashes."""
    g = grams(h, prefix)
    return sliding_min(g, window - prefix + 1), g


def _pack(records: np.ndarray) -> bytes:
    """Field after field, which packs better than row after row."""
    return b"".join(np.ascontiguousarray(records[f]).tobytes() for f in records.dtype.names)


def _unpack(blob: bytes, kind: np.dtype) -> np.ndarray:
    n, at = len(blob) // kind.itemsize, 0
    out = np.zeros(n, kind)
    for f in kind.names:
        out[f] = np.frombuffer(blob, kind[f], n, at)
        at += n * kind[f].itemsize
    return out


def _unpacked(blobs: list[bytes], kind: np.dtype) -> np.ndarray:
    return np.concatenate([_unpack(b, kind) for b in blobs]) if blobs else np.zeros(0, kind)


def _deal(records: np.ndarray, key: np.ndarray, buckets: int, slice_: int, kind: int) -> list[tuple]:
    b = (key >> np.uint64(32)) % np.uint64(buckets)
    order = np.argsort(b, kind="stable")
    records, b = records[order], b[order]
    bounds = np.concatenate([[0], np.flatnonzero(np.diff(b)) + 1, [len(b)]]) if len(b) else [0]
    return [(int(b[i]), slice_, kind, _pack(records[i:j])) for i, j in zip(bounds[:-1], bounds[1:], strict=True)]


def _moved(rows: list[tuple]) -> pa.Table:
    return pa.Table.from_batches([batch(_MOVED, [list(c) for c in zip(*rows, strict=True)] if rows else [[], [], [], []])])


def _send_prefixes(window: int, prefix: int, buckets: int):
    def of(group: pa.Table) -> pa.Table:
        seen, much, slice_ = [], [], 0
        for slice_, body in zip(group.column("slice").to_pylist(), group.column("body").to_pylist(), strict=True):
            h = word_hashes(*spans(body or b""))
            if len(h) >= window:
                a, g = _anchors(h, window, prefix)
                head = np.flatnonzero(np.concatenate([[True], a[1:] != a[:-1]]))
                seen.append(a[head])
                # windows with one anchor at one place are different windows: a stretch counts once unless its anchor occurs again
                s = np.sort(g)
                again = np.unique(s[1:][s[1:] == s[:-1]])
                much.append(np.where(np.isin(a[head], again), np.diff(np.append(head, len(a))) + 1, 1))
        if not seen:
            return _moved([])
        v, back = np.unique(np.concatenate(seen), return_inverse=True)
        out = np.zeros(len(v), _OPEN)
        out["v"], out["n"] = v, np.minimum(np.bincount(back, weights=np.concatenate(much)), 0xFFFFFFFF).astype(np.uint32)
        return _moved(_deal(out, v, buckets, slice_, 0))

    return of


def _open_prefixes(group: int):
    """Of a bucket's prefixes, those with more than one suffix go back to the slices that hold them, and whether they are split further."""

    def of(batches):
        got = [(s, _unpack(b, _OPEN)) for s, b in rows_of(batches, "slice", "blob")]
        if got:
            v, back = np.unique(np.concatenate([x["v"] for _, x in got]), return_inverse=True)
            total = np.bincount(back, weights=np.concatenate([x["n"] for _, x in got]))[back]
            at, rows = 0, []
            for s, x in got:
                n = total[at : at + len(x)]
                at += len(x)
                keep = np.zeros(int((n > 1).sum()), _FOUND)
                if len(keep):
                    keep["v"], keep["large"] = x["v"][n > 1], n[n > 1] * WINDOW > group
                    rows.append((0, s, 1, _pack(keep)))
            yield from _moved(rows).to_batches()

    return of


def _leaves(docs: list[tuple], opened: np.ndarray, window: int, prefix: int) -> np.ndarray:
    """Suffixes of open prefixes: labels, document and start; row is the place in docs, key what the leaf is dealt by."""
    out, kind = [], np.dtype([*_LEAF.descr, ("row", "<i8"), ("key", "<u8")])
    for row, (doc, _, h) in enumerate(docs):
        if len(h) < window:
            continue
        a, _ = _anchors(h, window, prefix)
        run = np.concatenate([[True], a[1:] != a[:-1]])
        head = a[run]
        at = np.minimum(np.searchsorted(opened["v"], head), len(opened) - 1)
        mine = np.cumsum(run) - 1
        p = np.flatnonzero((opened["v"][at] == head)[mine])
        if len(p):
            x = np.zeros(len(p), kind)
            x["h"], x["g"], x["doc"], x["pos"], x["row"] = grams(h, window)[p], grams(h, window, _SECOND)[p] >> np.uint64(32), doc, p, row
            x["key"] = np.where(opened["large"][at][mine[p]] > 0, x["h"], a[p])
            out.append(x)
    if not out:
        return np.zeros(0, kind)
    x = np.concatenate(out)
    return x[np.lexsort((x["pos"], x["doc"], x["g"], x["h"]))]


def _opened(blobs: list[bytes]) -> np.ndarray:
    x = _unpacked(blobs, _FOUND)
    return x[np.argsort(x["v"], kind="stable")]


def _firsts(x: np.ndarray) -> np.ndarray:
    """Where a new node starts among sorted leaves."""
    return np.concatenate([[True], (x["h"][1:] != x["h"][:-1]) | (x["g"][1:] != x["g"][:-1])]) if len(x) else np.zeros(0, bool)


def _among(head: np.ndarray, told: np.ndarray) -> np.ndarray:
    """Which sorted nodes are among those told; equal first labels with unlike second ones are told apart."""
    h, g = np.concatenate([head["h"], told["h"]]), np.concatenate([head["g"], told["g"]])
    mine = np.arange(len(h)) < len(head)
    order = np.lexsort((mine, g, h))  # a told node comes right before the equal one in head
    h, g, mine = h[order], g[order], mine[order]
    hit = np.zeros(len(h), bool)
    hit[1:] = mine[1:] & (h[1:] == h[:-1]) & (g[1:] == g[:-1])
    out = np.zeros(len(head), bool)
    out[order[hit]] = True
    return out


def _read(left: pa.Table, right: pa.Table, *, keep: bool) -> tuple[list[tuple], int, dict[int, list[bytes]]]:
    docs, slice_ = [], 0
    for doc, slice_, body in zip(*(left.column(c).to_pylist() for c in ("doc_id", "slice", "body")), strict=True):
        docs.append((doc, body if keep else None, word_hashes(*spans(body or b""))))
    blobs: dict[int, list[bytes]] = {1: [], 2: []}
    for kind, blob in zip(right.column("kind").to_pylist(), right.column("blob").to_pylist(), strict=True):
        blobs[kind].append(blob)
    return docs, slice_, blobs


#: Stands for a null id inside a slice; its rows compare with each other by start only.
_NULL = -(1 << 63)


def _send_leaves(window: int, prefix: int, buckets: int):
    def of(left: pa.Table, right: pa.Table) -> pa.Table:
        docs, slice_, blobs = _read(left, right, keep=False)
        if not blobs[1]:
            return _moved([])
        x = _leaves([(_NULL if d is None else d, t, h) for d, t, h in docs], _opened(blobs[1]), window, prefix)
        first = x[_firsts(x)]
        return _moved(_deal(first[list(_LEAF.names)], first["key"], buckets, slice_, 0))

    return of


def _later_nodes(batches):
    """Of nodes with leaves in several slices, the slices without the earliest leaf learn that all their leaves are later."""
    got = [(s, _unpack(b, _LEAF)) for s, b in rows_of(batches, "slice", "blob")]
    if got:
        x = np.concatenate([x for _, x in got])
        owner = np.repeat(np.arange(len(got)), [len(x) for _, x in got])
        order = np.lexsort((x["pos"], x["doc"], x["g"], x["h"]))
        x, owner = x[order], owner[order]
        late = ~_firsts(x)
        x, owner = x[late], owner[late]
        order = np.argsort(owner, kind="stable")
        x, owner = x[order], owner[order]
        rows = []
        for i, j in zip(np.concatenate([[0], np.flatnonzero(np.diff(owner)) + 1]), np.concatenate([np.flatnonzero(np.diff(owner)) + 1, [len(x)]]), strict=True):
            if j > i:
                node = np.zeros(j - i, _NODE)
                node["h"], node["g"] = x["h"][i:j], x["g"][i:j]
                rows.append((0, got[owner[i]][0], 2, _pack(node)))
        yield from _moved(rows).to_batches()


def _without(body: bytes, removed: np.ndarray) -> bytes:
    """The words that stay, joined by one space."""
    b, starts, ends = spans(body)
    starts, ends = starts[~removed], ends[~removed]
    if not len(starts):
        return b""
    step = np.zeros(len(b) + 2, np.int8)
    step[starts] += 1
    step[ends + 1] -= 1
    out = np.append(b, 32).astype(np.uint8)
    out[ends] = 32
    return out[np.cumsum(step[: len(b) + 1]).astype(bool)].tobytes()[:-1]


_RESULT = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("removed", pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))), ("kept", pa.binary())])
_DIGEST = pa.schema([("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string())])


def _finish(window: int, prefix: int, digest: bool):
    def of(left: pa.Table, right: pa.Table) -> pa.Table:
        docs, _, blobs = _read(left, right, keep=True)
        gone = [np.zeros(len(h) + 1, np.int32) for _, _, h in docs]
        if blobs[1]:
            x = _leaves([(_NULL if d is None else d, t, h) for d, t, h in docs], _opened(blobs[1]), window, prefix)
            first = _firsts(x)
            if len(x):
                node = np.cumsum(first) - 1
                head = x[first]
                late = (x["doc"] != head["doc"][node]) | (x["pos"] != head["pos"][node])
                if blobs[2]:
                    known = _among(head, _unpacked(blobs[2], _NODE))
                    late |= known[node]
                for row, pos in zip(x["row"][late].tolist(), x["pos"][late].tolist(), strict=True):
                    gone[row][pos] += 1
        out: list[list] = [[] for _ in range(4 if digest else 5)]
        for (doc, body, h), n in zip(docs, gone, strict=True):
            cover = np.cumsum(n[:-1])
            if len(cover) > window:
                cover[window:] -= cover[:-window].copy()
            removed = cover > 0
            kept = _without(body or b"", removed)
            row = [doc, len(h), int(removed.sum())]
            if digest:
                row.append(hashlib.sha256(kept).hexdigest())
            else:
                turn = np.diff(np.concatenate([[0], removed.astype(np.int8), [0]]))
                row += [[{"start": int(s), "end": int(e)} for s, e in zip(np.flatnonzero(turn == 1), np.flatnonzero(turn == -1), strict=True)], kept]
            for c, v in zip(out, row, strict=True):
                c.append(v)
        return pa.Table.from_batches([batch(_DIGEST if digest else _RESULT, out)])

    return of


def drop_repeats(docs: DataFrame, window: int = WINDOW, prefix: int = PREFIX, digest: bool = False) -> DataFrame:
    """Remove every word that lies in a window of `window` words whose sequence also starts earlier.

    Earlier: a smaller doc_id, or the same document at an earlier start. Windows are judged on the input.
    Returns one row for each row of docs (columns doc_id, text are read, others ignored): doc_id, n_words,
    n_removed, and the removed word spans with the kept words joined by one space, or with digest=True only
    their SHA-256. Null text: no words. Fewer than `window` words: nothing removed. Rows that repeat a doc_id
    count as the same document, so neither removes the other. A null doc_id sorts first. No rows: no rows.
    """
    ship(docs.sparkSession)
    moved = "bucket int, slice int, kind int, blob binary"
    parts, n = sliced(docs)
    opened = parts.groupBy("slice").applyInArrow(_send_prefixes(window, prefix, n), moved).repartition(n, "bucket").mapInArrow(_open_prefixes(GROUP), moved).repartition(n, "slice")
    leaves = parts.groupBy("slice").cogroup(opened.groupBy("slice")).applyInArrow(_send_leaves(window, prefix, n), moved)
    later = leaves.repartition(n, "bucket").mapInArrow(_later_nodes, moved).repartition(n, "slice")
    back = opened.unionByName(later).repartition(n, "slice")
    kind = "doc_id long, n_words long, n_removed long, " + ("kept_sha256 string" if digest else "removed array<struct<start: bigint, end: bigint>>, kept binary")
    out = parts.groupBy("slice").cogroup(back.groupBy("slice")).applyInArrow(_finish(window, prefix, digest), kind)
    return out if digest else out.withColumn("text", F.col("kept").cast("string")).drop("kept")

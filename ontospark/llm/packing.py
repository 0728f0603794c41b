"""Token packing by vector bin packing with the dot-product heuristic.

Every example asks for tokens, one segment and some loss-bearing tokens; a sequence offers a limit of each. A
bin takes, again and again, the fitting example whose demands point most the way of what is left of the bin
(weighted by how scarce each resource is over the waiting examples). If nothing fits whole and cutting is
allowed, one example is cut to fill the bin.

Documents need no shuffle: a task tokenises its rows, sends full-length pieces out at once and packs what is
left of each document. What remains at a task's end, less than one sequence, leaves as sequences whose lengths
are powers of two and so need no padding.
"""

from __future__ import annotations

import zlib
from array import array

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ontospark.llm._frames import batch, freeing, rows_of
from ontospark.plans.ship import ship

SEQUENCE = 2048
SEGMENTS = 256
END = b"\x01\x00\x00\x00"
#: How this vocabulary cuts text before merging, and its printable stand-ins for bytes.
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
_PLAIN = [*range(33, 127), *range(161, 173), *range(174, 256)]
_BYTE = {chr(b): b for b in _PLAIN} | {chr(256 + k): b for k, b in enumerate(b for b in range(256) if b not in _PLAIN)}
_loaded: dict[str, Encoder] = {}


class Encoder:
    """Byte-level BPE ids as little-endian 32-bit bytes.

    Texts of Latin-1 characters without an added token go through a faster engine over the same vocabulary, which
    gives the same ids (tested); all others go through the tokenizer itself, since added tokens in a text are ids of
    their own there, and the engines may know different Unicode versions.
    """

    def __init__(self, path: str):
        import tiktoken
        from tokenizers import Tokenizer

        self.model = Tokenizer.from_file(path)
        self.added = [t.content for t in self.model.get_added_tokens_decoder().values()]
        ranks = {bytes(_BYTE[c] for c in w): i for w, i in self.model.get_vocab(False).items() if w not in self.added}
        self.fast = tiktoken.Encoding(path, pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})

    def ids(self, text: str) -> bytes:
        try:
            text.encode("latin-1")
            plain = not any(t in text for t in self.added)
        except UnicodeEncodeError:
            plain = False
        return array("I", self.fast.encode_ordinary(text) if plain else self.model.encode(text, add_special_tokens=False).ids).tobytes()


def encoder(path: str) -> Encoder:
    if path not in _loaded:
        _loaded[path] = Encoder(path)
    return _loaded[path]


def fill(items: np.ndarray, limits: np.ndarray, cut: bool) -> list[list[tuple[int, int, int]]]:
    """Pack demands (rows: tokens, segments, loss tokens) into bins of the given limits.

    Returns bins of (item, start, length) pieces in tokens. With cut, an item may be cut so as to fill a bin;
    a cut piece takes loss tokens in proportion, rounded up. An item beyond a limit by itself is cut as well,
    and without cut raises ValueError. The last bin may be far from full.
    """
    need = items.astype(np.float64).copy()
    start = np.zeros(len(items), np.int64)
    if not cut and (need > limits).any():
        raise ValueError("an example is larger than a sequence")
    alive = need[:, 0] > 0
    bins: list[list[tuple[int, int, int]]] = []
    while alive.any():
        left, bin_ = limits.astype(np.float64).copy(), []
        live = np.flatnonzero(alive)
        part = need[live] / limits
        weight = part.sum(0) / max(part.sum(), 1e-12)
        open_ = np.ones(len(live), bool)
        while True:
            ok = open_ & (need[live] <= left).all(1)
            if ok.any():
                k = int(np.argmax(np.where(ok, part @ (weight * left / limits), -1.0)))
                take = int(need[live[k], 0])
            elif cut and left[0] >= 1 and left[1] >= 1 and left[2] >= 1 and open_.any():
                k = int(np.argmax(np.where(open_, need[live, 0], -1.0)))
                i = live[k]
                share = need[i, 2] / need[i, 0]
                take = int(min(left[0], need[i, 0], left[2] // share if share > 0 else left[0]))
                if take < 1:
                    break
            else:
                break
            i = live[k]
            bin_.append((int(i), int(start[i]), take))
            loss = need[i, 2] if take == need[i, 0] else np.ceil(need[i, 2] * take / need[i, 0])
            left -= (take, need[i, 1], loss)
            start[i] += take
            need[i, 0] -= take
            need[i, 2] -= loss
            open_[k] = False
            if need[i, 0] <= 0:
                alive[i] = False
        bins.append(bin_)
    return bins


_PIECE = [("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64()), ("sequence_id", pa.int64()), ("offset", pa.int64())]


class _Writer:
    """Sequences of one task; ids carry the task's partition, so they are unique and the same on every attempt."""

    def __init__(self, partition: int, with_ids: bool):
        self.next, self.with_ids = partition << 40, with_ids
        self.schema = pa.schema(_PIECE + [("ids", pa.binary())] * with_ids)
        self.columns: list[list] = [[] for _ in self.schema]

    def sequence(self, pieces: list[tuple[int | None, bytes, int, int]]) -> None:
        offset = 0
        for doc, ids, start, n in pieces:
            body = ids[4 * start : 4 * (start + n)]
            row = [doc, start, n, zlib.crc32(body), len(ids) // 4, self.next, offset]
            for c, v in zip(self.columns, [*row, body] if self.with_ids else row, strict=True):
                c.append(v)
            offset += n
        self.next += 1

    def drain(self) -> pa.RecordBatch:
        out, self.columns = batch(self.schema, self.columns), [[] for _ in self.schema]
        return out


def _pack(path: str, limits: tuple[int, int, int], with_ids: bool, block: int = 512):
    size = limits[0]

    def of(batches):
        enc, out = encoder(path), _Writer(TaskContext.get().partitionId(), with_ids)
        pool: list[tuple[int | None, bytes, int, int]] = []

        def settle(last: bool) -> None:
            """Pack the pool; the last bin waits for more, or leaves as powers of two."""
            nonlocal pool
            need = np.array([(n, 1, n) for _, _, _, n in pool]).reshape(-1, 3)
            bins = fill(need, np.array(limits), True)
            rest = bins.pop() if bins and sum(n for _, _, n in bins[-1]) < size else []
            for b in bins:
                out.sequence([(pool[i][0], pool[i][1], pool[i][2] + s, n) for i, s, n in b])
            pool = [(pool[i][0], pool[i][1], pool[i][2] + s, n) for i, s, n in rest]
            while last and pool:
                room = 1 << (sum(n for *_, n in pool).bit_length() - 1)
                piece, later = [], []
                for doc, ids, s, n in pool:
                    take = min(n, room)
                    room -= take
                    if take:
                        piece.append((doc, ids, s, take))
                    if n > take:
                        later.append((doc, ids, s + take, n - take))
                out.sequence(piece)
                pool = later

        def feed(docs: list[tuple[int | None, str]]) -> None:
            for doc, text in docs:
                ids = enc.ids(text) + END
                n = len(ids) // 4
                for s in range(0, n - size + 1, size):
                    out.sequence([(doc, ids, s, size)])
                if n % size:
                    pool.append((doc, ids, n - n % size, n % size))

        docs, chars = [], 0
        for doc, text in rows_of(batches, "doc_id", "text"):
            docs.append((doc, text or ""))
            chars += len(text or "")
            if chars >= 1_000_000 or len(docs) >= 1000:
                feed(docs)
                docs, chars = [], 0
                if len(pool) >= block:
                    settle(False)
                yield out.drain()
        feed(docs)
        settle(True)
        yield out.drain()

    return of


def pack(docs: DataFrame, path: str | None = None, tokens: int = SEQUENCE, segments: int = SEGMENTS, loss_tokens: int | None = None, with_ids: bool = False) -> DataFrame:
    """Cut and pack every document into sequences of at most `tokens` tokens, `segments` pieces and `loss_tokens` loss-bearing tokens.

    Reads doc_id and text, ignores other columns. A document is its ids and then id 1; each id lies in exactly
    one piece. Returns one row for each piece: doc_id, start (ids of the document before it), length, ids_crc32
    (of its little-endian unsigned 32-bit ids), doc_tokens, sequence_id, offset in the sequence; with_ids adds
    the ids. Null text counts as empty: a piece of one id. Rows that repeat a doc_id are documents of their
    own. No rows: no rows. All ids of a document bear loss.
    """
    ship(docs.sparkSession)
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("byte_bpe_50k.json")
    kind = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long" + ", ids binary" * with_ids
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return src.mapInArrow(freeing(_pack(path, (tokens, segments, tokens if loss_tokens is None else loss_tokens), with_ids)), kind)


def pack_examples(examples: DataFrame, limits: tuple[int, int, int], block: int = 4096) -> DataFrame:
    """Place whole examples (columns id, n_tokens, n_loss) into sequences; none is cut.

    Returns id, sequence_id, offset. An example beyond a limit, or a null or negative count, fails with ValueError.
    Examples of no tokens get an offset in no sequence (null).
    """

    ship(examples.sparkSession)

    def of(batches):
        schema = pa.schema([("id", pa.int64()), ("sequence_id", pa.int64()), ("offset", pa.int64())])
        next_ = TaskContext.get().partitionId() << 40
        for b in batches:
            rows = list(rows_of([b], "id", "n_tokens", "n_loss"))
            for lo in range(0, len(rows), block):
                part = rows[lo : lo + block]
                if any(n is None or k is None or n < 0 or k < 0 for _, n, k in part):
                    raise ValueError("counts must be given and not negative")
                out: list[list] = [[r[0] for r in part if not r[1]], [None for r in part if not r[1]], [None for r in part if not r[1]]]
                for bin_ in fill(np.array([(n, 1, k) for _, n, k in part]).reshape(-1, 3), np.array(limits), False):
                    at = 0
                    for i, _, n in bin_:
                        for c, v in zip(out, (part[i][0], next_, at), strict=True):
                            c.append(v)
                        at += n
                    next_ += 1
                yield batch(schema, out)

    return examples.select(F.col("id").cast("long").alias("id"), F.col("n_tokens").cast("long").alias("n_tokens"), F.col("n_loss").cast("long").alias("n_loss")).mapInArrow(of, "id long, sequence_id long, offset long")

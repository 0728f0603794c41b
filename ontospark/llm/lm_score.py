"""Language-model scores by online logistic mixing of hashed-context bit predictors.

A text is its words (A-Z lower-cased), each ended by a space, and an end mark. Every byte is coded as eight
binary decisions. Six contexts (order 0 to 4 and the whole prefix of the word) are hashed into one table of bit
counts; their log-odds are mixed with weights that a gate selects by how often the longest context was seen; an
adaptive map refines the mixed probability. Weights and map are trained online over every bucket of the lexicon,
one block of words after the other, each word with its count and scored as if one of its occurrences were
unseen; what the buckets learned is averaged by tokens, gate by gate. The class of the document (one of CLASSES,
a mixture of word distributions fitted without labels to all training documents; its index is paid for once) is
part of every context. Last, the bitwise probability of a word is mixed with its relative frequency in the class;
the share is the likeliest over all training tokens. Contexts end at word borders, so a word has one score in a
class: counts, training and scoring run over the lexicon, and documents only add up.

With across, contexts of bytes go on over word borders, through as many words as four bytes reach. Only the first
HEAD symbols of a word can see what is before it: they are its head, the others its rest. A word's probability is
the product of both. Symbols of heads are an own part of the lexicon, each with the four bytes before it, with their
own weights, a gate by the longest context of bytes, and no class; rests are coded once a word and class. The frequency in the
class then has each of PARTS in turn, and a document's probability is the mean over them.

The lexicon is never gathered in one place: words are dealt by hash over buckets, and slices of documents ask
each bucket once for the words that they hold.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ontospark.llm import _text
from ontospark.llm._frames import batch, cut, rows_of, sliced
from ontospark.llm._text import LOWER, mix, spans_of, word_hashes
from ontospark.plans.ship import ship

#: Least and most slots of the counter tables, as powers of two; between them there are two for each context of the lexicon.
#: The two tables are broadcast, so their bound is 32 MB; larger lexicons share slots.
LEAST_SLOTS, MOST_SLOTS = 16, 22
CLASSES = 8
#: Training documents, picked by a hash of their id, from which the classes start; rounds over all of them follow.
CLASS_SAMPLE, CLASS_ROUNDS = 1500, 6
CLASS_BITS = 12
ORDERS = 6
#: How often the online pass learns a word at most, each time with an even part of its count, and blocks of a bucket at most.
REPEATS, BLOCKS = 4, 512
GATES = 16
STEPS = 33
#: Symbols at the start of a word whose contexts tell of the text before it: the longest by bytes has four, one of them the space.
HEAD = 3
#: Parts that the whole-word predictor may have in a document where contexts cross words, equally likely before its text is seen.
PARTS = np.array([0.05, 0.2, 0.35, 0.5, 0.65, 0.8, 0.9, 0.97])


# --- classes of documents -----------------------------------------------------------------------------------


class Classes:
    """A mixture of word distributions over hashed words."""

    def __init__(self, bags: list[np.ndarray], rounds: int = 30, seed: int = 3):
        x = np.zeros((len(bags), 1 << CLASS_BITS), np.float32)
        for i, b in enumerate(bags):
            np.add.at(x[i], b, 1)
        rng = np.random.default_rng(seed)
        part = np.eye(CLASSES)[rng.integers(0, CLASSES, len(bags))] if len(bags) else np.zeros((0, CLASSES))
        for step in range(rounds + 1):
            self.theta = np.log((part.T @ x + 0.5) / ((part.T @ x).sum(1, keepdims=True) + 0.5 * (1 << CLASS_BITS)))
            self.prior = np.log((part.sum(0) + 1) / (len(bags) + CLASSES))
            if step < rounds and len(bags):
                z = x @ self.theta.T + self.prior
                z = (z - z.max(1, keepdims=True)) * min(1.0, 0.02 * 1.25**step)  # soft at first
                part = np.exp(z)
                part /= part.sum(1, keepdims=True)
        self.theta, self.log10_prior = self.theta.astype(np.float32), self.prior / np.log(10)

    def refit(self, words: np.ndarray, docs: np.ndarray) -> None:
        """From the hashed words' counts in each class and the documents of each."""
        self.theta = np.log((words + 0.5) / (words.sum(1, keepdims=True) + 0.5 * (1 << CLASS_BITS))).astype(np.float32)
        self.prior = np.log((docs + 1) / (docs.sum() + CLASSES))
        self.log10_prior = self.prior / np.log(10)

    def of(self, h: np.ndarray) -> int:
        return self.of_bag(bag(h))

    def of_bag(self, b: np.ndarray) -> int:
        if not len(b):
            return int(self.prior.argmax())
        return self.of_counts(np.bincount(b, minlength=1 << CLASS_BITS))

    def of_counts(self, n: np.ndarray) -> int:
        return int((self.theta @ n.astype(np.float32) + self.prior).argmax())

    def each(self, b: np.ndarray, n: np.ndarray, step: int = 16) -> np.ndarray:
        """of_bag() of texts whose hashed words follow one another, n of each; one product a text, so a text's class never depends on the others."""
        out, ends = np.empty(len(n), np.int64), np.cumsum(n)
        for lo in range(0, len(n), step):
            m = n[lo : lo + step]
            at = np.repeat(np.arange(len(m)) << CLASS_BITS, m) + b[ends[lo] - n[lo] : ends[lo + len(m) - 1]]
            counts = np.bincount(at, minlength=len(m) << CLASS_BITS).astype(np.float32).reshape(len(m), -1)
            out[lo : lo + step] = (np.array([self.theta @ x for x in counts]) + self.prior).argmax(axis=1)
        return out


def bag(h: np.ndarray) -> np.ndarray:
    return (h >> np.uint64(64 - CLASS_BITS)).astype(np.int64)


def keyed(h: np.ndarray, z: int | np.ndarray) -> np.ndarray:
    """Word and class in one key: the three low bits are the class."""
    return (h & ~np.uint64(7)) | np.uint64(z)


#: Bytes of joined texts whose words are hashed at once: few enough for a processor's cache.
_PIECE = 1 << 18


def _hashed(bodies: list[bytes | None]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all words of the texts, lower-cased, and the number of each text's words."""
    b, starts, ends, n = spans_of([(x or b"").translate(LOWER) for x in bodies])
    return word_hashes(b, starts, ends, _PIECE), n


def _encoded(u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys in any order, and the place of each key among them; by hashing, which costs a tenth of a sort."""
    d = pa.array(u).dictionary_encode()
    return d.dictionary.to_numpy(), d.indices.to_numpy()


def _places(u: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys in their order, and the place of each key among them."""
    distinct, back = _encoded(u)
    order = np.argsort(distinct)
    rank = np.empty(len(order), np.int64)
    rank[order] = np.arange(len(order))
    return distinct[order], rank[back]


# --- bit contexts -------------------------------------------------------------------------------------------


def symbols(body: np.ndarray, length: np.ndarray, z: np.ndarray, first: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bytes of each word and a space after it; the word of each symbol; context hashes (ORDERS x symbols).

    first: symbols before that place in their word are left out.
    """
    n = length + 1
    at = np.concatenate([[0], np.cumsum(n)[:-1]])
    total = int(n.sum())
    s = np.full(total, 32, np.uint8)
    word = np.repeat(np.arange(len(n)), n)
    place = np.arange(total) - at[word]
    s[place < length[word]] = body
    past = np.zeros((4, total), np.uint32)
    for k in range(4):
        past[k, k + 1 :] = s[: total - k - 1]
        past[k, place <= k] = 0
    _text._grow(total + 1)
    run = np.zeros(total + 1, np.uint64)
    np.cumsum((s + np.uint64(1)) * _text._powers[0][:total], out=run[1:])
    prefix = (run[:-1] - run[at[word]]) * _text._powers[1][at[word]]
    if first:
        keep = np.flatnonzero(place >= first)
        s, word, place, past, prefix = s[keep], word[keep], place[keep], past[:, keep], prefix[keep]
    return s, word, _contexts(place, past, mix(prefix), z[word])


def rests(body: np.ndarray, length: np.ndarray, z: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """symbols() of what follows the heads of the words."""
    return symbols(body, length, z, HEAD)


def heads(body: np.ndarray, length: np.ndarray, z: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """symbols() of single symbols of heads: the four bytes before each, then itself. The last space before it is where its word starts."""
    b = body.reshape(-1, 5)
    place = (b[:, 3::-1] == 32).argmax(axis=1)
    past = b[:, 3::-1].T.astype(np.uint32)
    _text._grow(HEAD)
    run = np.zeros(len(b), np.uint64)
    for k in range(1, HEAD):  # the k-th byte of the word
        at = np.flatnonzero(place >= k)
        run[at] += (b[at, 4 - place[at] + k - 1] + np.uint64(1)) * _text._powers[0][k - 1]
    return b[:, 4].copy(), np.arange(len(b)), _contexts(place, past, mix(run), z)


def _contexts(place: np.ndarray, past: np.ndarray, prefix: np.ndarray, z: np.ndarray) -> np.ndarray:
    c = np.empty((ORDERS, len(place)), np.uint32)
    c[0] = np.minimum(place, 3)
    c[1] = past[0]
    c[2] = c[1] << 8 | past[1]
    c[3] = c[2] << 8 | past[2]
    c[4] = c[3] << 8 | past[3]
    c[5] = (prefix >> np.uint64(32)).astype(np.uint32)
    for k in range(ORDERS):
        h = (c[k] + np.uint32(0x9E3779B1 * (k + 1) & 0xFFFFFFFF) + z.astype(np.uint32) * np.uint32(0x3C6EF372)) * np.uint32(0x85EBCA6B)
        c[k] = (h ^ (h >> np.uint32(13))) * np.uint32(0xC2B2AE35)
    return c


def slot_bits(symbols_: int) -> int:
    """For a lexicon of so many bytes (spaces included): about two slots for each context."""
    return min(MOST_SLOTS, max(LEAST_SLOTS, (2 * ORDERS * symbols_).bit_length()))


def slots(c: np.ndarray, partial: np.ndarray, bits: int) -> np.ndarray:
    h = (c ^ partial * np.uint32(0x27D4EB2F)) * np.uint32(0x165667B1)
    return (h ^ (h >> np.uint32(15))) * np.uint32(0x9E3779B1) >> np.uint32(32 - bits)


def count_bits(body: np.ndarray, length: np.ndarray, z: np.ndarray, weight: np.ndarray, zeros: np.ndarray, ones: np.ndarray, coded=symbols) -> None:
    """Add the words' bits, weighted by their counts, to the tables.

    Equal symbols in equal contexts are summed first, so short contexts cost few additions.
    """
    s, word, c = coded(body, length, z)
    w, bits = weight[word].astype(np.float64), len(zeros).bit_length() - 1
    for k in range(ORDERS):
        key = c[k].astype(np.uint64) << np.uint64(8) | s
        order = np.argsort(key)
        key = key[order]
        head = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
        total = np.add.reduceat(w[order], head) if len(head) else w
        context, symbol = (key[head] >> np.uint64(8)).astype(np.uint32), key[head].astype(np.uint32) & np.uint32(255)
        partial = np.ones(len(head), np.uint32)
        for b in range(7, -1, -1):
            bit = symbol >> np.uint32(b) & np.uint32(1)
            i, one = slots(context, partial, bits), bit == 1
            np.add.at(ones, i[one], total[one])
            np.add.at(zeros, i[~one], total[~one])
            partial = partial << np.uint32(1) | bit


def odds(n0: np.ndarray, n1: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Log-odds of a one after these counts, weaker where little was seen, and the gate."""
    x = np.log((n1 + np.float32(0.05)) / (n0 + np.float32(0.05))) * np.minimum(1, (n0 + n1) / 2)
    return np.clip(x, -12, 12), np.minimum(GATES - 1, np.log2(1 + n0 + n1)).astype(np.uint8)


class Mixer:
    def __init__(self, zeros: np.ndarray, ones: np.ndarray, p_end: float, longest: int = ORDERS - 1):
        """longest: the context whose count picks the gate."""
        self.zeros, self.ones, self.p_end, self.longest = zeros, ones, p_end, longest
        self.bits = len(zeros).bit_length() - 1
        self.weights = np.full((GATES, ORDERS + 1), 0.3, np.float32)
        self.weights[:, ORDERS] = 0
        self.map = np.tile(1 / (1 + np.exp(-np.linspace(-8, 8, STEPS))), (GATES, 1)).astype(np.float32)
        self._tables: dict[bool, tuple[np.ndarray, np.ndarray]] = {}

    def table(self, less_one: bool) -> tuple[np.ndarray, np.ndarray]:
        """Log-odds and gate of every slot; less_one: of every slot and bit, where one occurrence of the bit is left out."""
        if less_one not in self._tables:
            shape, step = (len(self.zeros), 2) if less_one else (len(self.zeros),), 1 << 15
            x, gate = np.empty(shape, np.float32), np.empty(shape, np.uint8)
            for lo in range(0, len(x), step):
                at = slice(lo, lo + step)
                n0, n1 = self.zeros[at], self.ones[at]
                if less_one:
                    x[at, 0], gate[at, 0] = odds(np.maximum(0, n0 - 1), n1)
                    x[at, 1], gate[at, 1] = odds(n0, np.maximum(0, n1 - 1))
                else:
                    x[at], gate[at] = odds(n0, n1)
            self._tables[less_one] = x.ravel(), gate.ravel()
        return self._tables[less_one]

    def inputs(self, i: np.ndarray, bit: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
        """Log-odds of each context, and the gate of the longest; with bit, one occurrence of it is left out."""
        x, gate = self.table(bit is not None)
        if bit is not None:
            i = i << np.uint32(1) | bit
        return np.take(x, i), np.take(gate, i[self.longest]).astype(np.int64)

    def mixed(self, x: np.ndarray, gate: np.ndarray) -> np.ndarray:
        """Log-odds mixed with the weights of each gate; the last weight is a constant."""
        z = np.take(self.weights[:, ORDERS], gate)
        for k in range(ORDERS):
            z += np.take(self.weights[:, k], gate) * x[k]
        return z

    @staticmethod
    def place(z: np.ndarray, gate: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where the map (flat) has these log-odds: the step below, and the part of the way to the next."""
        y = (np.clip(z, -7.999, 7.999) + 8) * ((STEPS - 1) / 16)
        lo = y.astype(np.int64)
        return gate * STEPS + lo, y - lo

    def refine(self, z: np.ndarray, gate: np.ndarray) -> np.ndarray:
        at, part = self.place(z, gate)
        flat = self.map.ravel()
        return np.take(flat, at) * (1 - part) + np.take(flat, at + 1) * part

    def learn(self, body: np.ndarray, length: np.ndarray, z_of: np.ndarray, weight: np.ndarray, times: np.ndarray | None = None, least: int = 1024, coded=symbols) -> np.ndarray:
        """Online over the words in their order, each `times` times with this weight; the weight that each gate saw.

        Inputs depend on the counters alone, so a block computes them once, however often its words are learned.
        """
        times = np.ones(len(length), np.int64) if times is None else times
        ends, saw = np.cumsum(length), np.zeros(GATES)
        block = max(least, -(-len(length) // BLOCKS))
        for lo in range(0, len(length), block):
            hi = min(len(length), lo + block)
            s, word, c = coded(body[ends[lo] - length[lo] : ends[hi - 1]], length[lo:hi], z_of[lo:hi])
            w, rounds = weight[lo:hi][word], times[lo:hi][word]
            most = int(rounds.max())
            partial = np.ones(len(s), np.uint32)
            rate = 0.4 / (1 + 4 * lo / max(1, len(length)))
            for b in range(7, -1, -1):
                bit = s.astype(np.uint32) >> np.uint32(b) & np.uint32(1)
                x, gate = self.inputs(slots(c, partial, self.bits), bit)
                order = np.argsort(gate.astype(np.uint8), kind="stable")  # a gate's symbols side by side
                inputs, gate, at = x, gate[order], bit[order].astype(np.int64)
                x = np.ones((ORDERS + 1, len(order)), np.float32)  # the last input is a constant
                np.take(inputs, order, axis=1, out=x[:ORDERS], mode="clip")
                saw += self._step(x, gate, at, w[order], rate)
                for r in range(1, most):
                    rows = np.flatnonzero(rounds[order] > r)
                    saw += self._step(np.take(x, rows, axis=1), gate[rows], at[rows], w[order[rows]], rate)
                partial = partial << np.uint32(1) | bit
        return saw

    def _step(self, x: np.ndarray, gate: np.ndarray, bit: np.ndarray, w: np.ndarray, rate: float) -> np.ndarray:
        """One update by symbols sorted by gate; the weight that each gate saw."""
        cuts = np.searchsorted(gate, np.arange(GATES + 1))
        n = np.diff(cuts)
        met = np.flatnonzero(n)
        first, saw = cuts[met], np.zeros(GATES)
        z = np.repeat(self.weights.T, n, axis=1)
        z *= x
        z = z.sum(axis=0)
        p = 1 / (1 + np.exp(np.minimum(30, np.maximum(-30, -z))))
        saw[met] = np.add.reduceat(w, first)
        miss = (w * (bit - p)).astype(np.float32)
        self.weights[met] += (rate * 0.25 / np.maximum(saw[met], 32) * np.add.reduceat(x * miss, first, axis=1)).T
        flat, part = self.place(z, gate)
        at, late, map_ = 2 * flat + bit, w * part, self.map.ravel()
        for j, share in ((at, w - late), (at + 2, late)):
            both = np.bincount(j, share, 2 * GATES * STEPS)
            map_ = ((map_ * 20 + both[1::2]) / (20 + (both[::2] + both[1::2]))).astype(np.float32)
        self.map = map_.reshape(GATES, STEPS)
        return saw

    def symbol_log10(self, s: np.ndarray, c: np.ndarray) -> np.ndarray:
        """log10 probability of each symbol in its contexts: eight bits, so over all 256 symbols they sum to one."""
        partial, out = np.ones(len(s), np.uint32), np.ones(len(s), np.float64)
        for b in range(7, -1, -1):
            bit = s.astype(np.uint32) >> np.uint32(b) & np.uint32(1)
            x, gate = self.inputs(slots(c, partial, self.bits), None)
            z = self.mixed(x, gate)
            p = 0.5 / (1 + np.exp(-np.clip(z, -30, 30))) + 0.5 * self.refine(z, gate)
            p = np.clip(p, 1e-6, 1 - 1e-6)
            out *= np.where(bit == 1, p, 1 - p)
            partial = partial << np.uint32(1) | bit
        return np.log10(out)

    def log10(self, body: np.ndarray, length: np.ndarray, z_of: np.ndarray, block: int = 20_000, coded=symbols) -> np.ndarray:
        """log10 bitwise probability of each word with the space after it."""
        out, ends = np.zeros(len(length), np.float64), np.cumsum(length)
        lo = 0
        while lo < len(length):
            base = ends[lo] - length[lo]
            hi = max(lo + 1, min(lo + block, int(np.searchsorted(ends, base + 40_000, "right"))))
            s, word, c = coded(body[base : ends[hi - 1]], length[lo:hi], z_of[lo:hi])
            out[lo:hi] = np.bincount(word, self.symbol_log10(s, c), hi - lo)
            lo = hi
        return out


# --- lexicon ------------------------------------------------------------------------------------------------

#: By the bytes of a word, up to HEAD: what of its head stays, and the spaces instead of the rest.
_KEPT = ~((np.uint64(1) << (np.uint64(8 * (HEAD + 1)) - np.arange(HEAD + 1, dtype=np.uint64) * np.uint64(8))) - np.uint64(1))
_FILL = ~_KEPT & np.uint64(0x20202020)


_SPACES = bytes(32 if k in b"\t\n\v\f\r" else k for k in range(256))


def _spaced(raw: bytes) -> bytes:
    """Words joined by one space; most texts need no more than other separators replaced."""
    out = raw.translate(_SPACES).strip(b" ")
    return b" ".join(out.split()) if b"  " in out else out


def head_keys(texts: list[bytes]) -> np.ndarray:
    """For each word of lower-cased texts its head: the four bytes before it (words joined by one space), then its first HEAD + 1, spaces after its end."""
    p = np.frombuffer(b" " * 4 + b"    ".join([_spaced(raw) for raw in texts]) + b" " * 8, np.uint8)
    space = p == 32
    turn = np.flatnonzero(space[1:] != space[:-1]) + 1  # from spaces to a word and back, over and over
    at, ends = turn[::2], turn[1::2]
    length = np.minimum(HEAD, ends - at)
    key = np.ndarray((len(p) - 7,), ">u8", p, strides=(1,))[at - 4].astype(np.uint64)
    return key & _KEPT[length] | _FILL[length]


def head_symbols(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Symbols of heads, each with the four bytes before it in one key, and which of the heads each belongs to."""
    out, of = [], []
    for k in range(HEAD):
        at = np.flatnonzero(keys >> np.uint64(8 * (HEAD + 1 - k)) & np.uint64(255) != 32) if k else np.arange(len(keys))
        out.append(keys[at] >> np.uint64(8 * (HEAD - k)) & np.uint64(0xFFFFFFFFFF))
        of.append(at)
    return np.concatenate(out), np.concatenate(of)


def _packed(u: np.ndarray) -> bytes:
    """Sorted keys byte by byte of their places, which Spark's compression makes small."""
    return u.view(np.uint8).reshape(-1, 8).T.tobytes()


def _unpacked(b: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(b, np.uint8).reshape(8, -1).T).view(np.uint64).ravel()


def _of_heads(h: bytes, c: bytes):
    """z, c, lengths and bodies of a bucket of symbols of heads; they belong to no class."""
    u = _unpacked(h)
    return np.full(len(u), CLASSES), np.frombuffer(c, "<i8"), np.full(len(u), 5), u.astype(">u8").view(np.uint8).reshape(-1, 8)[:, 3:].ravel()


_LEX = "bucket int, h binary, c binary, len binary, body binary"
_LEX_PA = pa.schema([("bucket", pa.int32()), ("h", pa.binary()), ("c", pa.binary()), ("len", pa.binary()), ("body", pa.binary())])


_BAGS = pa.schema([("doc_id", pa.int64()), ("h", pa.binary())])


def _bags(batches):
    for b in batches:
        for lo in range(0, b.num_rows, 256):
            ids, bodies = zip(*rows_of([b.slice(lo, 256)], "doc_id", "body"), strict=True)
            h, n = _hashed(bodies)
            h, ends = bag(h).astype("<i2"), np.cumsum(n)
            yield batch(_BAGS, [list(ids), [h[i - k : i].tobytes() for i, k in zip(ends.tolist(), n.tolist(), strict=True)]])


_CLASS = pa.schema([("z", pa.int32()), ("n", pa.int64()), ("words", pa.binary())])


def _class_rows(words: np.ndarray, docs: np.ndarray) -> pa.RecordBatch:
    held = [z for z in range(CLASSES) if docs[z]]
    return batch(_CLASS, [held, [int(docs[z]) for z in held], [zlib.compress(words[z].astype("<i8").tobytes(), 1) for z in held]])


def _assigned(classes: Classes):
    """Hashed words and documents of each class, where every document goes to its likeliest class."""

    def of(batches):
        words, docs = np.zeros((CLASSES, 1 << CLASS_BITS), np.int64), np.zeros(CLASSES, np.int64)
        for (h,) in rows_of(batches, "h"):
            n = np.bincount(np.frombuffer(h, "<i2"), minlength=1 << CLASS_BITS)
            z = classes.of_counts(n)
            words[z] += n
            docs[z] += 1
        yield _class_rows(words, docs)

    return of


def _sum_classes(batches):
    words, docs = np.zeros((CLASSES, 1 << CLASS_BITS), np.int64), np.zeros(CLASSES, np.int64)
    for z, n, blob in rows_of(batches, "z", "n", "words"):
        words[z] += np.frombuffer(zlib.decompress(blob), "<i8")
        docs[z] += n
    yield _class_rows(words, docs)


def fit_classes(docs: DataFrame, train) -> Classes:
    """Started from CLASS_SAMPLE documents, then fitted to all training documents until nothing moves or CLASS_ROUNDS end."""
    rows = docs.where(train(F.col("doc_id"))).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("body"))
    bags = cut(rows.mapInArrow(_bags, "doc_id long, h binary"))
    first = bags.orderBy(F.xxhash64("doc_id"), "doc_id", "h").limit(CLASS_SAMPLE).select("h")
    classes = Classes([np.frombuffer(b, "<i2").astype(np.int64) for b in sorted(bytes(r[0]) for r in first.toLocalIterator())])
    last = None
    for _ in range(CLASS_ROUNDS):
        words, n = np.zeros((CLASSES, 1 << CLASS_BITS), np.int64), np.zeros(CLASSES, np.int64)
        sums = bags.mapInArrow(_assigned(classes), "z int, n long, words binary").repartition(CLASSES, "z").mapInArrow(_sum_classes, "z int, n long, words binary")
        for z, k, blob in sums.collect():
            words[z], n[z] = np.frombuffer(zlib.decompress(blob), "<i8"), k
        if not n.sum() or last is not None and (words == last).all():
            break
        classes.refit(words, n)
        last = words
    return classes


def _gather(b: np.ndarray, starts: np.ndarray, length: np.ndarray) -> np.ndarray:
    """Bytes of the given spans, one after the other."""
    at = np.cumsum(length) - length
    return b[np.arange(int(length.sum())) + np.repeat(starts - at, length)]


def _merge(h: np.ndarray, c: np.ndarray, length: np.ndarray, body: np.ndarray) -> tuple[np.ndarray, ...]:
    starts = np.cumsum(length) - length
    order = np.argsort(h)  # not stable: rows of one key hold the same word
    h = h[order]
    head = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]])) if len(h) else np.zeros(0, np.int64)
    total = np.add.reduceat(c[order], head) if len(head) else np.zeros(0, np.int64)
    first = order[head]
    return h[head], total, length[first], _gather(body, starts[first], length[first])


def _stable(b: np.ndarray) -> np.ndarray:
    """The stable order of bucket numbers; numbers of 16 bits are sorted by digits, which is faster."""
    return np.argsort(b.astype(np.uint16) if len(b) and b.max() < 1 << 16 else b, kind="stable")


def _by_bucket(h, c, length, body, buckets: int) -> pa.RecordBatch:
    b = ((h >> np.uint64(32)) % np.uint64(buckets)).astype(np.int64)
    order = _stable(b)
    starts = np.cumsum(length) - length
    body = _gather(body, starts[order], length[order])
    h, c, length, b = h[order], c[order], length[order], b[order]
    cuts = np.concatenate([[0], np.flatnonzero(np.diff(b)) + 1, [len(b)]]) if len(b) else np.zeros(1, int)
    ends = np.concatenate([[0], np.cumsum(length)])
    cols: list[list] = [[] for _ in range(5)]
    for i, j in zip(cuts[:-1], cuts[1:], strict=True):
        for col, v in zip(cols, (int(b[i]), h[i:j].tobytes(), c[i:j].astype("<i8").tobytes(), length[i:j].astype("<i4").tobytes(), body[ends[i] : ends[j]].tobytes()), strict=True):
            col.append(v)
    return batch(_LEX_PA, cols)


HEAD_BUCKETS = 16


def _head_bucket(u: np.ndarray, buckets: int) -> np.ndarray:
    """Buckets of heads follow those of words; a bucket of heads for HEAD_BUCKETS of words, since heads are few and every slice asks each bucket."""
    return buckets + ((mix(u) >> np.uint64(32)) % np.uint64(-(-buckets // HEAD_BUCKETS))).astype(np.int64)


def _counted(u: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys in their order, with the sums of their counts."""
    order = np.argsort(u)
    u = u[order]
    at = np.flatnonzero(np.concatenate([[True], u[1:] != u[:-1]])) if len(u) else np.zeros(0, np.int64)
    return u[at], np.add.reduceat(n[order], at) if len(at) else n


def _split(b: np.ndarray) -> tuple[np.ndarray, np.ndarray, list[tuple[int, int]]]:
    """The stable order by bucket, the buckets in it, and where each of them starts and ends."""
    order = _stable(b)
    b = b[order]
    cuts = np.concatenate([[0], np.flatnonzero(np.diff(b)) + 1, [len(b)]]) if len(b) else np.zeros(1, int)
    return order, b, list(zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True))


def _heads_by_bucket(u: np.ndarray, n: np.ndarray, buckets: int) -> pa.RecordBatch:
    """Rows of the lexicon without lengths and bodies, which the keys hold."""
    u, n = _counted(u, n)
    order, b, parts = _split(_head_bucket(u, buckets))
    u, n = u[order], n[order]
    rows = [(int(b[i]), _packed(u[i:j]), n[i:j].astype("<i8").tobytes(), b"", b"") for i, j in parts]
    return batch(_LEX_PA, [list(c) for c in zip(*rows, strict=True)])


#: Bytes of texts whose words are taken at once.
_CHARS = 2 << 20


def _words(batches, buckets: int, classes: Classes, across: bool = False):
    """Distinct words of a stretch of documents with their training counts; across: symbols of their heads too."""
    held: list[tuple] = []
    early: list[tuple] = []
    texts: tuple[list, list] = [], []
    size = chars = 0

    def take():
        nonlocal chars, size
        for of in (0, 1):
            b, starts, ends, n = spans_of(texts[of])
            if len(starts):
                h = word_hashes(b, starts, ends, _PIECE)
                u, back = _encoded(keyed(h, np.repeat(classes.each(bag(h), n), n)))
                at = np.empty(len(u), np.int64)
                at[back] = np.arange(len(back))  # any of a key's places: they hold the same word
                length = (ends - starts)[at]
                held.append((u, np.bincount(back, minlength=len(u)) * of, length, _gather(b, starts[at], length)))
                size += len(u)
                if across:
                    u = np.sort(head_keys(texts[of]))
                    at = np.flatnonzero(np.concatenate([[True], u[1:] != u[:-1]]))
                    x, back = head_symbols(u[at])
                    early.append(_counted(x, np.diff(np.append(at, len(u)))[back] * of))
            texts[of].clear()
        chars = 0

    def drain():
        nonlocal held, early, size
        merged = _merge(*(np.concatenate([x[k] for x in held]) for k in range(4)))
        out = [_by_bucket(*merged, buckets)]
        if early:
            out.append(_heads_by_bucket(*(np.concatenate([x[k] for x in early]) for k in range(2)), buckets))
        held, early, size = [], [], 0
        return out

    for body, train in rows_of(batches, "body", "train"):
        if not body:
            continue
        texts[bool(train)].append(body.translate(LOWER))
        chars += len(body) + 32  # and what a short text takes besides
        if chars >= _CHARS:
            take()
            if size >= 1_500_000:
                yield from drain()
    take()
    if held:
        yield from drain()


def _lexicon(batches):
    by: dict[int, list[tuple]] = {}
    early: dict[int, list[tuple]] = {}
    for k, h, c, n, body in rows_of(batches, "bucket", "h", "c", "len", "body"):
        if not n:
            early.setdefault(k, []).append((_unpacked(h), np.frombuffer(c, "<i8")))
            continue
        by.setdefault(k, []).append((np.frombuffer(h, "<u8"), np.frombuffer(c, "<i8"), np.frombuffer(n, "<i4").astype(np.int64), np.frombuffer(body, np.uint8)))
    for k, parts in by.items():
        h, c, n, body = _merge(*(np.concatenate([x[i] for x in parts]) for i in range(4)))
        yield batch(_LEX_PA, [[k], [h.tobytes()], [c.astype("<i8").tobytes()], [n.astype("<i4").tobytes()], [body.tobytes()]])
    for k, parts in early.items():
        u, c = _counted(*(np.concatenate([x[i] for x in parts]) for i in range(2)))
        yield batch(_LEX_PA, [[k], [_packed(u)], [c.astype("<i8").tobytes()], [b""], [b""]])


def _entries(h: bytes, c: bytes, n: bytes, body: bytes, across: bool):
    """z, c, lengths and bodies of a row of the lexicon, and what gives their symbols."""
    if not n:
        return *_of_heads(h, c), heads
    return *_read_lex(h, c, n, body)[1:], rests if across else symbols


def _read_lex(h: bytes, c: bytes, n: bytes, body: bytes):
    h = np.frombuffer(h, "<u8")
    return h, (h & np.uint64(7)).astype(np.int64), np.frombuffer(c, "<i8"), np.frombuffer(n, "<i4").astype(np.int64), np.frombuffer(body, np.uint8)


def _pieces(z, c, n, body, step: int = 50_000):
    ends = np.cumsum(n)
    for lo in range(0, len(n), step):
        hi = min(len(n), lo + step)
        yield z[lo:hi], c[lo:hi], n[lo:hi], body[ends[lo] - n[lo] : ends[hi - 1]]


_SUMS = pa.schema([("z", pa.int32()), ("n", pa.int64()), ("v", pa.int64()), ("symbols", pa.int64())])
_CHUNK = 1 << 15
_TABLE = pa.schema([("chunk", pa.int32()), ("zeros", pa.binary()), ("ones", pa.binary())])


def _totals(batches):
    n, v, symbols_ = np.zeros(CLASSES, np.int64), 0, 0
    for h, c, length in rows_of(batches, "h", "c", "len"):
        c = np.frombuffer(c, "<i8")
        if not length:
            symbols_ += int((c > 0).sum())
            continue
        h, length = np.frombuffer(h, "<u8"), np.frombuffer(length, "<i4")
        np.add.at(n, (h & np.uint64(7)).astype(int), c)
        v += len(np.unique(h[c > 0] >> np.uint64(3)))
        symbols_ += int((length[c > 0].astype(np.int64) + 1).sum())
    yield batch(_SUMS, [list(range(CLASSES)), n.tolist(), [v] + [0] * (CLASSES - 1), [symbols_] + [0] * (CLASSES - 1)])


def _count_tables(bits: int, across: bool = False):
    def of(batches):
        zeros, ones = np.zeros((1 << bits, 2)).T  # both counts of a slot lie side by side
        for row in rows_of(batches, "h", "c", "len", "body"):
            *entries, coded = _entries(*row, across)
            for z, c, n, body in _pieces(*entries):
                seen = c > 0
                starts = np.cumsum(n) - n
                count_bits(_gather(body, starts[seen], n[seen]), n[seen], z[seen], c[seen], zeros, ones, coded)
        for k in range(0, 1 << bits, _CHUNK):
            z, o = zeros[k : k + _CHUNK], ones[k : k + _CHUNK]
            if z.any() or o.any():
                yield batch(_TABLE, [[k // _CHUNK], [z.astype("<f4").tobytes()], [o.astype("<f4").tobytes()]])

    return of


def _sum_tables(batches):
    by: dict[int, list[np.ndarray]] = {}
    for k, z, o in rows_of(batches, "chunk", "zeros", "ones"):
        z, o = np.frombuffer(z, "<f4").astype(float), np.frombuffer(o, "<f4").astype(float)
        by[k] = [by[k][0] + z, by[k][1] + o] if k in by else [z, o]
    for k, (z, o) in by.items():
        yield batch(_TABLE, [[k], [z.astype("<f4").tobytes()], [o.astype("<f4").tobytes()]])


_LEARNED = pa.schema([("bucket", pa.int32()), ("saw", pa.binary()), ("weights", pa.binary()), ("map", pa.binary())])


#: The context that picks the gate of a head: the longest that reaches before the word.
HEAD_GATE = 4


def _learn(tables, p_end: float, across: bool = False):
    """The online pass over each bucket's training words, every count in it, each from the untrained mixer.

    tables: a broadcast variable of the two counter tables, sent once for learning and scoring.
    """

    def of(batches):
        model = Mixer(*tables.value, p_end)
        weights, map_, whole = model.weights, model.map, model.longest
        for k, *row in rows_of(batches, "bucket", "h", "c", "len", "body"):
            z, c, n, body, coded = _entries(*row, across)
            model.longest = HEAD_GATE if coded is heads else whole
            times = np.minimum(c, REPEATS)
            at = np.random.default_rng(k).permutation(np.flatnonzero(times))
            if not len(at):
                continue
            w, r = c[at] / times[at], times[at]
            starts, mean = np.cumsum(n) - n, float((w * r).sum() / r.sum())
            model.weights, model.map = weights.copy(), map_.copy()
            saw = mean * model.learn(_gather(body, starts[at], n[at]), n[at], z[at], w / mean, r, 128 if coded is heads else 1024, coded)
            yield batch(_LEARNED, [[k], [saw.astype("<f8").tobytes()], [model.weights.astype("<f4").tobytes()], [model.map.astype("<f4").tobytes()]])

    return of


def merged(model: Mixer, learned: list[tuple]) -> None:
    """Weights and maps of all buckets, averaged gate by gate by the tokens seen there."""
    total, weights, map_ = np.zeros(GATES), np.zeros((GATES, ORDERS + 1)), np.zeros((GATES, STEPS))
    for _, saw, w, m in sorted(tuple(r) for r in learned):
        saw = np.frombuffer(saw, "<f8")
        total += saw
        weights += saw[:, None] * np.frombuffer(w, "<f4").reshape(weights.shape)
        map_ += saw[:, None] * np.frombuffer(m, "<f4").reshape(map_.shape)
    g = total > 0
    model.weights[g], model.map[g] = weights[g] / total[g, None], map_[g] / total[g, None]


_BITS = pa.schema([("bucket", pa.int32()), ("h", pa.binary()), ("own", pa.binary()), ("c", pa.binary()), ("lp", pa.binary())])


def _bit_scores(tables, p_end: float, weights: np.ndarray, map_: np.ndarray, of_heads: tuple[np.ndarray, np.ndarray] | None = None):
    """own: count in the word's class; c: in all classes. of_heads: weights and map of heads, if contexts cross words."""

    def of(batches):
        model = Mixer(*tables.value, p_end)
        whole = model.longest
        for k, *row in rows_of(batches, "bucket", "h", "c", "len", "body"):
            z, c, n, body, coded = _entries(*row, of_heads is not None)
            model.longest = HEAD_GATE if coded is heads else whole
            model.weights, model.map = of_heads if coded is heads else (weights, map_)
            lp = [model.log10(b, m, y, coded=coded) for y, _, m, b in _pieces(z, c, n, body)]
            if coded is heads:
                yield batch(_BITS, [[k], [row[0]], [b""], [b""], [np.concatenate(lp).astype("<f4").tobytes()]])
                continue
            h = np.frombuffer(row[0], "<u8")
            _, back = np.unique(h >> np.uint64(3), return_inverse=True)
            total = np.zeros(int(back.max()) + 1 if len(back) else 0, np.int64)
            np.add.at(total, back, c)
            yield batch(_BITS, [[k], [row[0]], [row[1]], [total[back].astype("<i8").tobytes()], [np.concatenate(lp).astype("<f4").tobytes() if lp else b""]])

    return of


_SHARES = np.arange(1, 100) / 100
_FIT = pa.schema([("i", pa.int32()), ("s", pa.float64())])


def _read_bits(h: bytes, own: bytes, lp: bytes, sizes: np.ndarray):
    z = (np.frombuffer(h, "<u8") & np.uint64(7)).astype(np.int64)
    return np.maximum(1, sizes[z]), np.frombuffer(own, "<i8"), np.frombuffer(lp, "<f4").astype(np.float64)


def _share_fit(sizes: np.ndarray):
    """Log-likelihood of the training tokens at each share; a word's frequency is without the occurrence at hand."""

    def of(batches):
        fit = np.zeros(len(_SHARES))
        for row in rows_of(batches, "h", "own", "lp"):
            size, own, lp = _read_bits(*row, sizes)
            seen = own > 0
            often, p, own = (own[seen] - 1) / size[seen], 10 ** lp[seen], own[seen]
            for i, x in enumerate(_SHARES):
                fit[i] += (own * np.log(x * often + (1 - x) * p + 1e-300)).sum()
        yield batch(_FIT, [list(range(len(fit))), fit.tolist()])

    return of


_SCORED = pa.schema([("bucket", pa.int32()), ("h", pa.binary()), ("c", pa.binary()), ("lp", pa.binary())])


def _score_words(share: float, sizes: np.ndarray):
    """log10 probability of each word in its class."""

    def of(batches):
        for k, h, own, c, lp in rows_of(batches, "bucket", "h", "own", "c", "lp"):
            size, own, lp = _read_bits(h, own, lp, sizes)
            out = np.log10(share * (own / size) + (1 - share) * 10**lp + 1e-300)
            yield batch(_SCORED, [[k], [h], [c], [out.astype("<f4").tobytes()]])

    return of


# --- documents ----------------------------------------------------------------------------------------------

_ASK = pa.schema([("bucket", pa.int32()), ("slice", pa.int32()), ("blob", pa.binary())])


def _keys(table: pa.Table, classes: Classes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Keys of all documents' words, how many each document has, and each document's class."""
    h, n = _hashed([b for (b,) in rows_of(table.to_batches(), "body")])
    z = classes.each(bag(h), n)
    return keyed(h, np.repeat(z, n)), n, z


def _by_word_bucket(u: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """The order of distinct keys by bucket, and the buckets in it."""
    b = ((u >> np.uint64(32)) % np.uint64(buckets)).astype(np.int64)
    order = _stable(b)
    return order, b[order]


def _slice_words(table: pa.Table, buckets: int, classes: Classes):
    """Keys of each document's words, the place of each among the slice's distinct keys ordered by bucket, their number, and each document's class."""
    key, n, of = _keys(table, classes)
    u, back = _places(key)
    order, _ = _by_word_bucket(u, buckets)
    rank = np.empty(len(u), np.int64)
    rank[order] = np.arange(len(u))
    return np.split(key, np.cumsum(n)[:-1]), rank[back], len(u), of


def _ask(buckets: int, classes: Classes, across: bool = False):
    def of(table: pa.Table) -> pa.Table:
        u = _distinct(_keys(table, classes)[0])
        order, b = _by_word_bucket(u, buckets)
        u = u[order]
        cuts = np.concatenate([[0], np.flatnonzero(np.diff(b)) + 1, [len(b)]]) if len(b) else np.zeros(1, int)
        s = table.column("slice")[0].as_py()
        out = [batch(_ASK, [[int(b[i]) for i in cuts[:-1]], [s] * (len(cuts) - 1), [u[i:j].tobytes() for i, j in zip(cuts[:-1], cuts[1:], strict=True)]])]
        if across:
            u = _distinct(head_symbols(_distinct(_head_keys(table)))[0])
            order, b, parts = _split(_head_bucket(u, buckets))
            u = u[order]
            out.append(batch(_ASK, [[int(b[i]) for i, _ in parts], [s] * len(parts), [_packed(u[i:j]) for i, j in parts]]))
        return pa.Table.from_batches(out)

    return of


def _distinct(u: np.ndarray) -> np.ndarray:
    u = np.sort(u)
    return u[np.concatenate([[True], u[1:] != u[:-1]])] if len(u) else u


def _head_keys(table: pa.Table) -> np.ndarray:
    return head_keys([(b or b"").translate(LOWER) for (b,) in rows_of(table.to_batches(), "body")])


def _reply_across(buckets: int, sizes: np.ndarray):
    """For words the count, the relative frequency in the class and the bitwise log10; for heads the last alone."""

    def of(asked: pa.Table, lex: pa.Table) -> pa.Table:
        out: list[list] = [[], [], []]
        rows = list(zip(*(asked.column(x).to_pylist() for x in ("bucket", "slice", "blob")), strict=True))
        if rows:
            ((h, own, c, lp),) = zip(*(lex.column(k).to_pylist() for k in ("h", "own", "c", "lp")), strict=True)
            early, lp = rows[0][0] >= buckets, np.frombuffer(lp, "<f4")
            if early:
                h = _unpacked(h)
            else:
                h, own, c = np.frombuffer(h, "<u8"), np.frombuffer(own, "<i8"), np.frombuffer(c, "<i8")
                often = (own / np.maximum(1, sizes[(h & np.uint64(7)).astype(np.int64)])).astype("<f4")
            for k, s, blob in rows:
                i = np.searchsorted(h, _unpacked(blob) if early else np.frombuffer(blob, "<u8"))
                for col, v in zip(out, (k, s, lp[i].tobytes() if early else _packed(c[i]) + often[i].tobytes() + lp[i].tobytes()), strict=True):
                    col.append(v)
        return pa.Table.from_batches([batch(_ASK, out)])

    return of


def _reply(asked: pa.Table, lex: pa.Table) -> pa.Table:
    h, c, lp = (np.concatenate([np.frombuffer(x, t) for x in lex.column(k).to_pylist()] or [np.zeros(0, t)]) for k, t in (("h", "<u8"), ("c", "<i8"), ("lp", "<f4")))
    order = np.argsort(h, kind="stable")
    h, c, lp = h[order], c[order], lp[order]
    out: list[list] = [[], [], []]
    for k, s, blob in zip(*(asked.column(x).to_pylist() for x in ("bucket", "slice", "blob")), strict=True):
        i = np.searchsorted(h, np.frombuffer(blob, "<u8"))
        for col, v in zip(out, (k, s, c[i].tobytes() + lp[i].tobytes()), strict=True):
            col.append(v)
    return pa.Table.from_batches([batch(_ASK, out)])


_RESULT = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64()), ("bits_per_byte", pa.float64())])


def _finish(buckets: int, classes: Classes, total: int, vocab: int, ends: int, p_end: float):
    floor = np.log10(total + vocab + 1)

    def of(table: pa.Table, told: pa.Table) -> pa.Table:
        docs, at, held, of_class = _slice_words(table, buckets, classes)
        c, lp = np.zeros(held, np.int64), np.zeros(held)
        pos = 0
        for _, blob in sorted(zip(told.column("bucket").to_pylist(), told.column("blob").to_pylist(), strict=True), key=lambda x: x[0]):
            n = len(blob) // 12
            c[pos : pos + n] = np.frombuffer(blob, "<i8", n)
            lp[pos : pos + n] = np.frombuffer(blob, "<f4", n, 8 * n)
            pos += n
        base = np.log10(c + 1.0)
        lo, out = 0, [[] for _ in _RESULT]
        for doc, h, z, body in zip(table.column("doc_id").to_pylist(), docs, of_class, table.column("body").to_pylist(), strict=True):
            i = at[lo : lo + len(h)]
            lo += len(h)
            n = len(h) + 1
            score = classes.log10_prior[z] + float(lp[i].sum()) + len(h) * np.log10(1 - p_end) + np.log10(p_end)
            row = (doc, n, int((c[i] > 0).sum()) + (ends > 0), float(base[i].sum()) + np.log10(ends + 1.0) - n * floor, float(score), float(-score / np.log10(2) / max(1, len(body or b""))))
            for col, v in zip(out, row, strict=True):
                col.append(v)
        return pa.Table.from_batches([batch(_RESULT, out)])

    return of


def _finish_across(buckets: int, classes: Classes, total: int, vocab: int, ends: int, p_end: float):
    """A word's bitwise probability is that of its head after the text before it times that of its rest."""
    floor = np.log10(total + vocab + 1)

    def of(table: pa.Table, told: pa.Table) -> pa.Table:
        docs, at, held, of_class = _slice_words(table, buckets, classes)
        distinct, word = _places(_head_keys(table))
        x, of_head = head_symbols(distinct)
        u, back = _places(x)
        rank = np.empty(len(u), np.int64)
        rank[_split(_head_bucket(u, buckets))[0]] = np.arange(len(u))
        c, often, lp, early = np.zeros(held, np.int64), np.zeros(held), np.zeros(held), np.zeros(len(u))
        pos = [0, 0]
        for k, blob in sorted(zip(told.column("bucket").to_pylist(), told.column("blob").to_pylist(), strict=True), key=lambda x: x[0]):
            n = len(blob) // (4 if k >= buckets else 16)
            span = slice(pos[k >= buckets], pos[k >= buckets] + n)
            if k >= buckets:
                early[span] = np.frombuffer(blob, "<f4")
            else:
                c[span], often[span], lp[span] = _unpacked(blob[: 8 * n]), np.frombuffer(blob, "<f4", n, 8 * n), np.frombuffer(blob, "<f4", n, 12 * n)
            pos[k >= buckets] += n
        words = np.array([len(h) for h in docs])
        doc, often = np.repeat(np.arange(len(docs)), words), often[at]
        lp = lp[at] + np.bincount(of_head, early[rank[back]], len(distinct))[word]
        parts = _parted(lp, often, doc, len(docs))
        most = parts.max(0)
        score = most + np.log10((10 ** (parts - most)).mean(0)) + classes.log10_prior[of_class] + words * np.log10(1 - p_end) + np.log10(p_end)
        base = np.bincount(doc, np.log10(c + 1.0)[at], len(docs)) + np.log10(ends + 1.0) - (words + 1) * floor
        known = np.bincount(doc, (c > 0)[at], len(docs)).astype(np.int64) + (ends > 0)
        length = np.array([len(b or b"") for b in table.column("body").to_pylist()])
        bits = -score / np.log10(2) / np.maximum(1, length)
        return pa.Table.from_batches([batch(_RESULT, [table.column("doc_id").to_pylist(), *((x + 0).tolist() for x in (words + 1, known, base, score, bits))])])

    return of


def _parted(lp: np.ndarray, often: np.ndarray, doc: np.ndarray, docs: int) -> np.ndarray:
    """log10 probability of each document's words (PARTS x documents) at each part of the whole-word predictor."""
    met = np.flatnonzero(often > 0)
    f, p, of, new = often[met].astype(np.float32), (10 ** lp[met]).astype(np.float32), doc[met], np.flatnonzero(often <= 0)
    first = np.flatnonzero(np.diff(of, prepend=-1))  # documents follow one another
    out, bare, count = np.zeros((len(PARTS), docs)), np.bincount(doc[new], lp[new], docs), np.bincount(doc[new], minlength=docs)
    for k, x in enumerate(PARTS.tolist()):
        if len(first):
            out[k, of[first]] = np.add.reduceat(np.log(x * f + (1 - x) * p), first, dtype=np.float64)
        out[k] = out[k] / np.log(10) + bare + count * np.log10(1 - x)
    return out


def score_documents(docs: DataFrame, train, across: bool = False) -> DataFrame:
    """Score every row of docs with a model of the rows where train (a condition on doc_id) holds.

    across: contexts go on over the borders of words, so a word's score depends on the text before it.

    Words: A-Z lower-cased, cut at ASCII white space; one end mark counts as a token. Returns doc_id, n_tokens,
    n_known (tokens seen in training), train_tokens, base_score (sum of log10((c + 1) / (N + V + 1))), score
    (log10 probability of the model) and bits_per_byte. Null text counts as empty: the end mark alone. Nothing
    to train on: N = V = 0, and the untrained mixer scores. Other columns are ignored; each row gets a row. A
    row with null doc_id isn't trained on. No rows: no rows.
    """
    spark = docs.sparkSession
    ship(spark)
    parts, buckets = sliced(docs)
    classes = fit_classes(docs, train)
    src = docs.select(F.col("text").cast("binary").alias("body"), F.coalesce(train(F.col("doc_id")), F.lit(False)).alias("train"))
    words = src.mapInArrow(lambda it: _words(it, buckets, classes, across), _LEX)
    lex = cut(words.repartition(buckets, "bucket").mapInArrow(_lexicon, _LEX))
    ends = docs.where(train(F.col("doc_id"))).count()
    sums = lex.select("h", "c", "len").mapInArrow(_totals, "z int, n long, v long, symbols long").groupBy("z").agg(F.sum("n"), F.sum("v"), F.sum("symbols")).collect()
    sizes = np.zeros(CLASSES)
    for r in sums:
        sizes[r[0]] = r[1]
    n, v = int(sizes.sum()), sum(r[2] for r in sums)
    total, vocab = n + ends, v + (ends > 0)
    slots_ = slot_bits(sum(r[3] for r in sums))
    zeros, ones = np.zeros(1 << slots_, np.float32), np.zeros(1 << slots_, np.float32)
    counted = lex.select("h", "c", "len", "body").mapInArrow(_count_tables(slots_, across), "chunk int, zeros binary, ones binary").repartition(min(buckets, 16), "chunk").mapInArrow(_sum_tables, "chunk int, zeros binary, ones binary")
    for r in counted.toLocalIterator():
        zeros[r[0] * _CHUNK : (r[0] + 1) * _CHUNK] = np.frombuffer(r[1], "<f4")
        ones[r[0] * _CHUNK : (r[0] + 1) * _CHUNK] = np.frombuffer(r[2], "<f4")
    model = Mixer(zeros, ones, (ends + 1) / (total + 2))
    tables = spark.sparkContext.broadcast((zeros, ones))
    learned = lex.mapInArrow(_learn(tables, model.p_end, across), "bucket int, saw binary, weights binary, map binary").collect()
    merged(model, [r for r in learned if r[0] < buckets])
    early = None
    if across:
        first = Mixer(zeros, ones, model.p_end, HEAD_GATE)
        merged(first, [r for r in learned if r[0] >= buckets])
        early = first.weights, first.map
    bits = cut(lex.mapInArrow(_bit_scores(tables, model.p_end, model.weights, model.map, early), "bucket int, h binary, own binary, c binary, lp binary"))
    tables.destroy()
    asked = parts.groupBy("slice").applyInArrow(_ask(buckets, classes, across), "bucket int, slice int, blob binary")
    kind = "doc_id long, n_tokens long, n_known long, base_score double, score double, bits_per_byte double"
    if across:
        told = asked.groupBy("bucket").cogroup(bits.groupBy("bucket")).applyInArrow(_reply_across(buckets, sizes), "bucket int, slice int, blob binary")
        out = parts.groupBy("slice").cogroup(told.groupBy("slice")).applyInArrow(_finish_across(buckets, classes, total, vocab, ends, model.p_end), kind)
        return out.withColumn("train_tokens", F.lit(total).cast("long"))
    fit = np.zeros(len(_SHARES))
    for i, x in bits.mapInArrow(_share_fit(sizes), "i int, s double").groupBy("i").agg(F.sum("s")).collect():
        fit[i] = x
    share = float(_SHARES[fit.argmax()]) if n else 0.5
    scored = bits.mapInArrow(_score_words(share, sizes), "bucket int, h binary, c binary, lp binary")
    told = asked.groupBy("bucket").cogroup(scored.groupBy("bucket")).applyInArrow(_reply, "bucket int, slice int, blob binary")
    out = parts.groupBy("slice").cogroup(told.groupBy("slice")).applyInArrow(_finish(buckets, classes, total, vocab, ends, model.p_end), kind)
    return out.withColumn("train_tokens", F.lit(total).cast("long"))

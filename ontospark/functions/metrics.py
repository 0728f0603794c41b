"""Measures of a union of queries and of a run, and the caches with their counters."""

from __future__ import annotations

import threading
import time
import tracemalloc
from collections import OrderedDict
from collections.abc import Iterable, Sequence
from statistics import median, pstdev

from ontospark.logic.terms import CQ, TGD, Var

#: Cache sizes that hold three quarters of what an unbounded cache would.
CACHE_SIZES = {"mgu": 4500, "rename": 55000, "elimination": 2000}


def size(union: Sequence[CQ]) -> int:
    return len(union)


def n_atoms(union: Iterable[CQ]) -> int:
    return sum(len(q.body) for q in union)


def joins_pairs(union: Iterable[CQ]) -> int:
    """Unordered pairs of body occurrences of one variable."""
    total = 0
    for q in union:
        n: dict = {}
        for a in q.body:
            for t in a.args:
                if isinstance(t, Var):
                    n[t] = n.get(t, 0) + 1
        total += sum(k * (k - 1) // 2 for k in n.values())
    return total


def joins_atoms(union: Iterable[CQ]) -> int:
    return sum(len(q.body) - 1 for q in union)


def size_upper_bound(q: CQ, tgds: Sequence[TGD]) -> float:
    """How many queries a rewriting can hold; infinite for rules that are neither linear nor sticky."""
    from ontospark.logic.analysis import classify

    atoms = [a for t in tgds for a in (*t.body, *t.head)] + list(q.body)
    r, w, n = len({a.pred for a in atoms}), max(len(a.args) for a in atoms), len(q.body)
    kind = classify(tgds)
    if kind in ("linear", "multi-linear"):
        return float((r * (w * n) ** w) ** n)
    return 2.0 ** min(1000, r * (w * n) ** w) if kind == "sticky" else float("inf")


def significant(a: Sequence[float], b: Sequence[float]) -> bool:
    """Whether the medians of repeated runs differ by more than the larger deviation."""
    return abs(median(a) - median(b)) > max(pstdev(a), pstdev(b))


def measured(job, runs: int = 10) -> dict[str, float]:
    """Median and deviation of the time in ms, and the median peak of allocated memory in MB; time and memory in separate runs, as many for either."""
    times, peaks = [], []
    for _ in range(runs):
        began = time.perf_counter()
        job()
        times.append(1000 * (time.perf_counter() - began))
    for _ in range(runs):
        tracemalloc.start()
        job()
        peaks.append(tracemalloc.get_traced_memory()[1] / 1e6)
        tracemalloc.stop()
    return {"median_ms": median(times), "deviation_ms": pstdev(times), "peak_mb": median(peaks)}


def significant_medians(a: dict[str, float], b: dict[str, float]) -> bool:
    """The same test on what measured() returns."""
    return abs(a["median_ms"] - b["median_ms"]) > max(a["deviation_ms"], b["deviation_ms"])


class Cache:
    """A least-recently-used cache that counts calls and repeats; size 0 only counts."""

    def __init__(self, size: int, locked: bool = False):
        self.size, self.calls, self.hits, self.distinct = size, 0, 0, 0
        self.data: OrderedDict = OrderedDict()
        self.lock = threading.RLock() if locked else None

    def get(self, key, make):
        if self.lock:
            with self.lock:
                return self._get(key, make)
        return self._get(key, make)

    def _get(self, key, make):
        self.calls += 1
        if key in self.data:
            self.hits += 1
            self.data.move_to_end(key)
            return self.data[key]
        self.distinct += 1
        out = make()
        if self.size:
            self.data[key] = out
            if len(self.data) > self.size:
                self.data.popitem(last=False)
        return out


class Caches:
    """mgu, rename and elimination are cached; factorisation and homomorphism checks (of pruning) never repeat and are only counted.

    locked: one object may serve several threads, which then share what they find.
    """

    def __init__(self, sizes: dict[str, int] = CACHE_SIZES, locked: bool = False):
        self.mgu, self.rename, self.elimination = (Cache(sizes[k], locked) for k in ("mgu", "rename", "elimination"))
        self.factorisation, self.homomorphism = 0, 0

    def profile(self) -> list[tuple[str, int, float, int]]:
        rows = [(k, c.calls, 100.0 * c.hits / c.calls if c.calls else 0.0, c.distinct) for k, c in (("elimination", self.elimination), ("mgu", self.mgu), ("rename", self.rename))]
        return rows + [("factorisation", self.factorisation, 0.0, self.factorisation), ("homomorphism", self.homomorphism, 0.0, self.homomorphism)]

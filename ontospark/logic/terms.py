"""Terms, atoms, queries, rules and constraints. All objects are immutable and can be pickled."""

from __future__ import annotations

from collections.abc import Iterable
from typing import NamedTuple


class Var(str):
    __slots__ = ()


class Const(NamedTuple):
    value: object


class Null(NamedTuple):
    """A labelled null of a symbolic chase."""

    id: object


class Atom(NamedTuple):
    pred: str
    args: tuple

    def __str__(self) -> str:
        return f"{self.pred}({','.join(show(t) for t in self.args)})"


class Position(NamedTuple):
    pred: str
    i: int  # from 1


class CQ(NamedTuple):
    head: tuple
    body: tuple[Atom, ...]

    def __str__(self) -> str:
        return f"p({','.join(show(t) for t in self.head)}) <- {', '.join(map(str, self.body))}"


class TGD(NamedTuple):
    id: str
    body: tuple[Atom, ...]
    head: tuple[Atom, ...]

    def __str__(self) -> str:
        return f"{', '.join(map(str, self.body))} => {', '.join(map(str, self.head))}"


class FD(NamedTuple):
    pred: str
    key: tuple[int, ...]
    value: int


class NC(NamedTuple):
    id: str
    body: tuple[Atom, ...]


class Ontology(NamedTuple):
    tgds: tuple[TGD, ...]
    fds: tuple[FD, ...] = ()
    ncs: tuple[NC, ...] = ()


class FoldedQuery(NamedTuple):
    """head <- c1(..), c2(..): each component has its variables and a union of queries for them."""

    head: tuple
    heads: tuple[tuple, ...]
    unions: tuple[tuple[CQ, ...], ...]


class View(NamedTuple):
    """A predicate of a program and its queries, over tables' predicates and over earlier views."""

    name: str
    arity: int
    queries: tuple[CQ, ...]


class Program(NamedTuple):
    """Non-recursive views in the order of their use; the last one is the query."""

    views: tuple[View, ...]

    @property
    def goal(self) -> View:
        return self.views[-1]

    def flat_size(self) -> int:
        """How many queries over tables' predicates unfolding would give, variants counted apart."""
        n: dict[str, int] = {}
        for v in self.views:
            total = 0
            for q in v.queries:
                ways = 1
                for a in q.body:
                    ways *= n.get(a.pred, 1)
                total += ways
            n[v.name] = total
        return n[self.goal.name]


def show(t) -> str:
    return repr(t.value) if isinstance(t, Const) else f"_{t.id}" if isinstance(t, Null) else str(t)


def variables(atoms: Iterable[Atom]) -> set:
    return {t for a in atoms for t in a.args if isinstance(t, Var)}


def apply(s: dict, atoms: Iterable[Atom]) -> tuple[Atom, ...]:
    """The set of substituted atoms, in order of first occurrence."""
    return tuple(dict.fromkeys(Atom(a.pred, tuple(s.get(t, t) for t in a.args)) for a in atoms))


def apply_query(s: dict, q: CQ) -> CQ:
    return CQ(tuple(s.get(t, t) for t in q.head), apply(s, q.body))


def occurrences(q: CQ) -> dict:
    """How often each variable stands in head and body."""
    n: dict = {}
    for t in [*q.head, *(t for a in q.body for t in a.args)]:
        if isinstance(t, Var):
            n[t] = n.get(t, 0) + 1
    return n


def shared(q: CQ) -> set:
    return {v for v, n in occurrences(q).items() if n > 1} | {t for t in q.head if isinstance(t, Var)}


def frontier(t: TGD) -> set:
    return variables(t.body) & variables(t.head)


def existential(t: TGD) -> set:
    return variables(t.head) - variables(t.body)


def ex_positions(t: TGD) -> tuple[Position, ...]:
    """Where a normal rule's existential variables stand in its head, each of them once."""
    ex = existential(t)
    return tuple(Position(a.pred, i) for a in t.head for i, x in enumerate(a.args, 1) if x in ex)


def ex_position(t: TGD) -> Position | None:
    """The existential position of a rule that has at most one."""
    return next(iter(ex_positions(t)), None)

"""Builders for common kinds of rules."""

from __future__ import annotations

from collections.abc import Iterable

from ontospark.logic.terms import NC, TGD, Atom, Const, Ontology, Var


def _vars(n: int, start: int = 1) -> tuple[Var, ...]:
    return tuple(Var(f"X{i}") for i in range(start, start + n))


def inclusion(id: str, source: tuple[str, int], target: tuple[str, int], pairs: Iterable[tuple[int, int]]) -> TGD:
    """Values at the source positions (from 1) occur at the target positions; sides are (predicate, arity)."""
    body = _vars(source[1])
    at = {j: body[i - 1] for i, j in pairs}
    return TGD(id, (Atom(source[0], body),), (Atom(target[0], tuple(at.get(j, Var(f"Z{j}")) for j in range(1, target[1] + 1))),))


def conditional_inclusion(id: str, source: tuple[str, int], where: dict[int, object], target: tuple[str, int], pairs) -> TGD:
    """An inclusion of the rows whose given positions hold the given constants."""
    t = inclusion(id, source, target, pairs)
    s = {Var(f"X{i}"): Const(v) for i, v in where.items()}
    put = lambda a: Atom(a.pred, tuple(s.get(x, x) for x in a.args))
    return TGD(id, tuple(map(put, t.body)), tuple(map(put, t.head)))


def decompose_rule(id: str, pred: str, arity: int, parts: Iterable[tuple[str, tuple[int, ...]]]) -> TGD:
    x = _vars(arity)
    return TGD(id, (Atom(pred, x),), tuple(Atom(p, tuple(x[i - 1] for i in at)) for p, at in parts))


def merge_rule(id: str, left: tuple[str, int], right: tuple[str, int], target: str) -> TGD:
    """Join on the last position of left and the first of right; both reach the target."""
    a = _vars(left[1])
    b = (a[-1], *_vars(right[1] - 1, left[1] + 1))
    return TGD(id, (Atom(left[0], a), Atom(right[0], b)), (Atom(target, a + b[1:]),))


def cross_rule(id: str, left: tuple[str, int], right: tuple[str, int], target: str) -> TGD:
    a, b = _vars(left[1]), _vars(right[1], left[1] + 1)
    return TGD(id, (Atom(left[0], a), Atom(right[0], b)), (Atom(target, a + b),))


def from_axioms(axioms: Iterable[str]) -> Ontology:
    """`A < B`, `A < some R`, `some R < A`, `some R- < A`, `R << S`, `R << S-`, `A and B < none`: concepts and roles as rules."""
    x, y = Var("X"), Var("Y")
    role = lambda r, a, b: Atom(r[:-1], (b, a)) if r.endswith("-") else Atom(r, (a, b))
    tgds, ncs = [], []
    for text in axioms:
        if "<<" in text:
            r, s = (p.strip() for p in text.split("<<"))
            tgds.append(TGD(f"s{len(tgds) + 1}", (role(r, x, y),), (role(s, x, y),)))
            continue
        left, right = (p.strip() for p in text.split("<"))
        if right == "none":
            ncs.append(NC(f"c{len(ncs) + 1}", tuple(Atom(c.strip(), (x,)) for c in left.split(" and "))))
            continue
        body = role(left.split()[1], x, y) if left.startswith("some ") else Atom(left, (x,))
        head = role(right.split()[1], x, Var("Z")) if right.startswith("some ") else Atom(right, (x,))
        tgds.append(TGD(f"s{len(tgds) + 1}", (body,), (head,)))
    return Ontology(tuple(tgds), (), tuple(ncs))

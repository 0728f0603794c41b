"""Unions of queries and folded queries as DataFrame plans."""

from __future__ import annotations

from collections import Counter
from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ontospark.logic.terms import CQ, Atom, Const, FoldedQuery, Program, Var
from ontospark.plans.lineage import cut
from ontospark.sources.mapping import Database

MAX_FLAT = 200


def scan(atom: Atom, db: Database, df: DataFrame | None = None) -> DataFrame:
    """Rows that match the atom, one column for each variable; constants and repeated variables are filters on the scan."""
    df = db.extension(atom.pred) if df is None else df
    first: dict = {}
    for i, t in enumerate(atom.args, 1):
        col = F.col(f"c{i}")
        if isinstance(t, Const):
            df = df.where(col == F.lit(t.value))
        elif t in first:
            df = df.where(col == F.col(f"c{first[t]}"))
        else:
            first[t] = i
    return df.select(*[F.col(f"c{i}").alias(v) for v, i in first.items()]) if first else df.select(F.lit(1).alias("_one")).limit(1)


def _exists(df: DataFrame, other: DataFrame) -> DataFrame:
    """Rows of df if other has any: a cross join with at most one row."""
    return df.crossJoin(F.broadcast(other.select(F.lit(1).alias("_any")).limit(1))).drop("_any")


def plan_cq(q: CQ, db: Database, sources: dict[Atom, DataFrame] | None = None, distinct: bool = True) -> DataFrame:
    """Semi-joins for atoms that add no variable, equi-joins for the rest; columns a1, a2, ... in head order.

    Parts that share no variable with the head become existence tests.
    """
    out = {t for t in q.head if isinstance(t, Var)}
    nodes = [(set(t for t in a.args if isinstance(t, Var)), scan(a, db, (sources or {}).get(a))) for a in q.body]
    changed = True
    while changed and len(nodes) > 1:  # leaves of the join forest are folded into a neighbour by a semi-join
        changed = False
        for i, (mine, df) in enumerate(nodes):
            rest = [n for j, n in enumerate(nodes) if j != i]
            need = mine & (out | set().union(*(v for v, _ in rest)))
            takes = [j for j, n in enumerate(nodes) if j != i and (n[1].isStreaming or not df.isStreaming)]  # a stream can't be the right side of a semi-join with a table
            if not takes:
                continue
            if not need:
                k = next((j for j in takes if nodes[j][0] & out), takes[0])
                nodes[k] = (nodes[k][0], _exists(nodes[k][1], df))
            else:
                k = next((j for j in takes if need <= nodes[j][0]), None)
                if k is None:
                    continue
                nodes[k] = (nodes[k][0], nodes[k][1].join(df.select(*sorted(need)), sorted(need), "left_semi"))
            del nodes[i]
            changed = True
            break
    have, df = nodes.pop(0)
    while nodes:
        k = next((j for j, n in enumerate(nodes) if n[0] & have), None)
        if k is None:
            loose = next((j for j, n in enumerate(nodes) if not (n[0] & out) and not any(n[0] & m[0] for m in nodes if m is not n)), None)
            v, other = nodes.pop(loose if loose is not None else 0)
            df = _exists(df, other) if loose is not None else df.crossJoin(other)
        else:
            v, other = nodes.pop(k)
            df = df.join(other, sorted(v & have), "inner")
        have |= v
        keep = have & (out | set().union(*(n[0] for n in nodes)) if nodes else out)
        df = df.select(*sorted(keep)) if keep else df
        have = keep or have
    cols = [(F.lit(t.value) if isinstance(t, Const) else F.col(t)).alias(f"a{i}") for i, t in enumerate(q.head, 1)]
    if not cols:
        return df.select(F.lit(True).alias("holds")).limit(1)
    return df.select(*cols).distinct() if distinct else df.select(*cols)


def _tree(parts: Sequence[DataFrame]) -> DataFrame:
    parts = list(parts)
    while len(parts) > 1:
        parts = [parts[i].unionByName(parts[i + 1]) if i + 1 < len(parts) else parts[i] for i in range(0, len(parts), 2)]
    return parts[0]


def drop_dead(union: Sequence[CQ], db: Database) -> list[CQ]:
    edb = db.edb()
    return [q for q in union if all(a.pred in edb for a in q.body)]


def run_union(union: Sequence[CQ], db: Database, strategy: str = "merged", max_flat: int = MAX_FLAT, batch: int = 100, arity: int | None = None) -> DataFrame:
    """flat: one plan for each query. merged: queries that differ in one predicate share a plan over a union of scans.
    batched: flat plans of `batch` queries, each written to the shared folder."""
    union = drop_dead(union, db)
    if not union:
        n = arity or 0
        return db.spark.createDataFrame([], ", ".join(f"a{i} string" for i in range(1, n + 1)) or "holds boolean")
    for q in union:
        db.check_types(q.body)
    if strategy == "batched":
        return _tree([cut(_tree([plan_cq(q, db) for q in union[i : i + batch]]).distinct()) for i in range(0, len(union), batch)]).distinct()
    groups = [[q] for q in union] if strategy == "flat" else merge_groups(union)
    if len(groups) > max_flat:
        raise ValueError(f"{len(groups)} plans in one: use the folded or batched strategy, or raise max_flat")
    db.share(Counter(a.pred for g in groups for a in g[0].body))
    return _tree([_plan_group(g, db) for g in groups]).distinct()


def merge_groups(union: Sequence[CQ]) -> list[list[CQ]]:
    """Queries that are equal but for the predicate of one atom, with its arguments the same.

    Each query is filed under all its forms with one predicate left out; the largest files are taken first.
    """
    files: dict[tuple, list[CQ]] = {}
    for q in union:
        for a in q.body:
            files.setdefault((q.head, frozenset(q.body) - {a}, a.args), []).append(q)
    taken: set[CQ] = set()
    groups = []
    for (_, rest, args), qs in sorted(files.items(), key=lambda x: -len(x[1])):
        left = {next(iter(frozenset(q.body) - rest)).pred: q for q in qs if q not in taken}
        if len(left) > 1 and not any(Atom(p, args) in rest for p in left):
            groups.append(list(left.values()))
            taken.update(left.values())
    return groups + [[q] for q in union if q not in taken]


def _plan_group(group: list[CQ], db: Database) -> DataFrame:
    if len(group) == 1:
        return plan_cq(group[0], db, distinct=False)
    first = group[0]
    common = set(first.body).intersection(*(set(q.body) for q in group[1:]))
    (hole,) = set(first.body) - common
    preds = [next(iter(set(q.body) - common)).pred for q in group]
    return plan_cq(first, db, {hole: _tree([df for _, df in db.scan(preds)])}, distinct=False)


def _connected(parts: list[tuple[set, DataFrame]]) -> tuple[set, DataFrame]:
    """Take the first part and all that share variables with it, directly or by others, from the list and join them."""
    have, df = parts.pop(0)
    while (k := next((j for j, p in enumerate(parts) if p[0] & have), None)) is not None:
        v, other = parts.pop(k)
        if v <= have:
            df = df.join(other, sorted(v), "left_semi")
        else:
            df = df.join(other, sorted(v & have))
        have = have | v
    return have, df


def run_folded(f: FoldedQuery, db: Database) -> DataFrame:
    """One DataFrame for each component, then joins on the variables that they share.

    Components that reach no head variable over shared ones are joined among themselves and become one existence test.
    """
    parts = []
    for head, union in zip(f.heads, f.unions, strict=True):
        df = run_union(union, db, "merged", arity=len(head))
        parts.append((set(head), df.toDF(*head) if head else df))
    out = {t for t in f.head if isinstance(t, Var)}
    loose = [df for h, df in parts if not h]
    parts = [p for p in parts if p[0]]
    if not parts:
        df = loose[0].select(F.lit(True).alias("holds")).limit(1)
        for other in loose[1:]:
            df = _exists(df, other)
        return df
    groups = []
    while parts:
        have, df = _connected(parts)
        if have & out:
            groups.append(df.select(*sorted(have & out)))
        else:
            loose.append(df)
    if not groups:
        groups.append(loose.pop(0).select(F.lit(True).alias("holds")).limit(1))
    df = groups[0]
    for other in groups[1:]:
        df = df.crossJoin(other.distinct())
    for other in loose:
        df = _exists(df, other)
    cols = [(F.lit(t.value) if isinstance(t, Const) else F.col(t)).alias(f"a{i}") for i, t in enumerate(f.head, 1)]
    return df.select(*cols).distinct() if cols else df.select(F.lit(True).alias("holds")).limit(1)


def run_program(p: Program, db: Database) -> DataFrame:
    """Views in order; one that several queries use is written to the shared folder, once."""
    uses = Counter(a.pred for v in p.views for q in v.queries for a in q.body)
    scope = db.extended({})
    for v in p.views:
        if v is p.goal or drop_dead(v.queries, scope):
            df = run_union(v.queries, scope, "merged", arity=v.arity)
            if v is p.goal:
                return df
            scope = scope.extended({v.name: cut(df) if uses[v.name] > 1 and not df.isStreaming else df})
    raise ValueError("a program without views")


def ask(union: Sequence[CQ], db: Database) -> bool:
    """Whether any query has an answer: smallest bodies first, ends with the first hit."""
    return any(not plan_cq(CQ((), q.body), db).isEmpty() for q in sorted(drop_dead(union, db), key=lambda q: len(q.body)))


def answer_stats(df: DataFrame, exact: bool = False) -> DataFrame:
    n = F.count(F.lit(1)).alias("n")
    return df.agg(n, *[(F.countDistinct(c) if exact else F.approx_count_distinct(c)).alias(f"n_{c}") for c in df.columns])

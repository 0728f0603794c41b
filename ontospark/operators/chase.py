"""Level-bounded chase over DataFrames: the oracle that rewritings are held against. For small data."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ontospark.logic.terms import CQ, TGD, Atom, Const, Var, existential, frontier, variables
from ontospark.plans.exec import plan_cq
from ontospark.plans.lineage import cut
from ontospark.sources.mapping import Database, Mapping

NULL = "\u0000null:"


def _text(df: DataFrame) -> DataFrame:
    return df.select(*[F.col(c).cast("string").alias(c) for c in df.columns])


def _as_text(atoms: Sequence[Atom]) -> tuple[Atom, ...]:
    return tuple(Atom(a.pred, tuple(Const(str(t.value)) if isinstance(t, Const) else t for t in a.args)) for a in atoms)


def chase(db: Database, tgds: Sequence[TGD], levels: int, mode: str = "oblivious") -> dict[str, DataFrame]:
    """Facts after `levels` rounds, all positions as text; an invented value is a hash of rule and match, so a match fires once.

    restricted: a match fires only if its head has no image yet.
    """
    have = {p: _text(db.extension(p)) for p in db.edb()}
    for level in range(levels):
        now = Database(db.spark, Mapping(), extensions=have)
        new: dict[str, list[DataFrame]] = {}
        for t in tgds:
            if any(a.pred not in have for a in t.body):
                continue
            body = _as_text(t.body)
            names = sorted(variables(t.body))
            match = plan_cq(CQ(tuple(map(Var, names)), body), now).toDF(*names)
            if mode == "restricted" and all(a.pred in have for a in t.head):
                known = sorted(frontier(t))
                if known:
                    image = plan_cq(CQ(tuple(map(Var, known)), _as_text(t.head)), now).toDF(*known)
                    match = match.join(image, known, "left_anti")
            for v in existential(t):
                match = match.withColumn(v, F.concat(F.lit(f"{NULL}{t.id}:{v}:"), F.sha2(F.concat_ws("\u0001", *names), 256)))
            for a in t.head:
                row = match.select(*[(F.lit(str(x.value)) if isinstance(x, Const) else F.col(x)).alias(f"c{i}") for i, x in enumerate(a.args, 1)])
                new.setdefault(a.pred, []).append(row)
        grown = False
        for p, dfs in new.items():
            all_ = have[p] if p in have else None
            for d in dfs:
                all_ = d if all_ is None else all_.unionByName(d)
            was = have[p].count() if p in have else 0
            have[p] = cut(all_.distinct())
            grown |= have[p].count() > was
        if not grown:
            break
    return have


def chase_answers(q: CQ, db: Database, tgds: Sequence[TGD], levels: int, mode: str = "oblivious", facts: dict[str, DataFrame] | None = None) -> DataFrame:
    """Answers over the chase that hold no invented value, as text."""
    facts = chase(db, tgds, levels, mode) if facts is None else facts
    if any(a.pred not in facts for a in q.body):
        return db.spark.createDataFrame([], ", ".join(f"a{i} string" for i in range(1, len(q.head) + 1)) or "holds boolean")
    head = tuple(Const(str(t.value)) if isinstance(t, Const) else t for t in q.head)
    out = plan_cq(CQ(head, _as_text(q.body)), Database(db.spark, Mapping(), extensions=facts))
    for c in out.columns if q.head else ():
        out = out.where(~F.startswith(c, F.lit(NULL)))
    return out


def min_sufficient_level(q: CQ, db: Database, tgds: Sequence[TGD], want: DataFrame, most: int = 6) -> int | None:
    """The least level at which the chase gives all wanted answers."""
    text = _text(want)
    for k in range(most + 1):
        if text.exceptAll(chase_answers(q, db, tgds, k)).isEmpty():
            return k
    return None

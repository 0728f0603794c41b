"""Functional dependencies and negative constraints."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ontospark.logic.terms import CQ, FD, NC, TGD, frontier
from ontospark.operators.rewrite import Options, backward_rewrite
from ontospark.plans.exec import drop_dead, plan_cq
from ontospark.sources.mapping import Database


class Inconsistent(RuntimeError):
    def __init__(self, report: dict[str, list]):
        super().__init__(f"violated: {', '.join(report)}")
        self.report = report


def fd_violations(fd: FD, db: Database) -> DataFrame:
    """Keys with more than one value: one aggregation, no self-join."""
    v = F.col(f"c{fd.value}")
    key = [f"c{i}" for i in fd.key]
    return db.extension(fd.pred).groupBy(*key).agg(F.min(v).alias("least"), F.max(v).alias("greatest")).where("least <> greatest")


def fd_witnesses(fd: FD, db: Database) -> DataFrame:
    key = [f"c{i}" for i in fd.key]
    return db.extension(fd.pred).join(fd_violations(fd, db).select(*key), key, "left_semi")


def nc_rewriting(nc: NC, tgds: Sequence[TGD], db: Database, opts: Options = Options()) -> list[CQ]:
    """The union that must be empty; heads hold the body variables that survive everywhere."""
    return drop_dead(backward_rewrite(CQ((), nc.body), tgds, opts).union, db)


def nc_violations(nc: NC, tgds: Sequence[TGD], db: Database, witnesses: int = 10) -> list:
    for q in nc_rewriting(nc, tgds, db):
        head = tuple(dict.fromkeys(t for a in q.body for t in a.args if isinstance(t, str)))
        got = plan_cq(CQ(head, q.body), db).limit(witnesses).collect()
        if got:
            return [(str(q), tuple(r)) for r in got]
    return []


def is_non_conflicting(fds: Sequence[FD], tgds: Sequence[TGD]) -> bool:
    """A sufficient test: no rule head over the dependency's predicate fixes a key strictly inside its universal positions."""
    for fd in fds:
        for t in tgds:
            for a in t.head:
                if a.pred == fd.pred:
                    universal = {i for i, x in enumerate(a.args, 1) if x in frontier(t)}
                    if set(fd.key) < universal or (set(fd.key) == universal and fd.value in universal):
                        return False
    return True


def check(fds: Sequence[FD], ncs: Sequence[NC], tgds: Sequence[TGD], db: Database, witnesses: int = 10) -> None:
    """Run all checks side by side; raise Inconsistent with witnesses."""
    from concurrent.futures import ThreadPoolExecutor

    jobs = {f"{fd.pred}:{fd.key}->{fd.value}": (lambda fd=fd: [tuple(r) for r in fd_violations(fd, db).limit(witnesses).collect()]) for fd in fds}
    jobs |= {nc.id: (lambda nc=nc: nc_violations(nc, tgds, db, witnesses)) for nc in ncs}
    if not jobs:
        return
    with ThreadPoolExecutor(min(8, len(jobs))) as pool:
        got = {k: f.result() for k, f in {k: pool.submit(j) for k, j in jobs.items()}.items()}
    if report := {k: v for k, v in got.items() if v}:
        raise Inconsistent(report)

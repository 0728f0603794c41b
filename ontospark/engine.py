"""The facade: an ontology over a database, and certain answers."""

from __future__ import annotations

from collections.abc import Sequence
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame

from ontospark.logic.analysis import classify, is_linear, normalise
from ontospark.logic.parse import parse_ontology, parse_query
from ontospark.logic.terms import CQ, Ontology, Program
from ontospark.operators.checks import check
from ontospark.operators.program import compile_program
from ontospark.operators.rewrite import Options, Rewriting, backward_rewrite
from ontospark.operators.split import SplitRewriting, split_rewrite
from ontospark.operators.subsume import prune
from ontospark.plans.exec import ask, run_folded, run_program, run_union
from ontospark.plans.lineage import cut
from ontospark.plans.sqlgen import folded_to_sql
from ontospark.sources.mapping import Database


class OntologyEngine:
    """Compile once, run on any data. Rules of an unknown class need opts.max_queries as their guard."""

    def __init__(self, ontology: Ontology | str, db: Database, opts: Options = Options(subsets="single")):
        self.ontology = parse_ontology(ontology) if isinstance(ontology, str) else ontology
        self.tgds = normalise(self.ontology.tgds)
        self.db, self.opts = db, opts
        self.kind = classify(self.tgds)

    def rewrite(self, q: CQ | str, pruned: bool = False) -> Rewriting:
        out = backward_rewrite(self._query(q), self.tgds, self.opts)
        if pruned:
            out.union = prune(out.union, out.graph)
        return out

    def split(self, q: CQ | str, **how) -> SplitRewriting:
        how.setdefault("eliminate", is_linear(self.tgds))
        how.setdefault("prune_components", True)
        return split_rewrite(self._query(q), self.tgds, self.opts, **how)

    def program(self, q: CQ | str) -> Program:
        """The query as non-recursive views, each rewritten once."""
        return compile_program(self._query(q), self.tgds, self.opts, is_linear(self.tgds))

    def answer(self, q: CQ | str, strategy: str = "folded", checked: bool = False) -> DataFrame:
        """Certain answers, columns a1, a2, ...; checked: constraints first.

        strategy: folded (joins of component views; rules that aren't linear are folded further, as a program), program,
        merged, flat or batched (unfolded unions).
        """
        q = self._query(q)
        if checked:
            check(self.ontology.fds, self.ontology.ncs, self.tgds, self.db)
        if strategy == "program" or (strategy == "folded" and not is_linear(self.tgds)):
            return run_program(self.program(q), self.db)
        if strategy == "folded":
            return run_folded(self.split(q, output="folded").folded, self.db)
        return run_union(self.split(q).union, self.db, strategy, arity=len(q.head))

    def plain(self, q: CQ | str) -> DataFrame:
        """Answers that need no rule."""
        q = self._query(q)
        return run_union([q], self.db, "flat", arity=len(q.head))

    def ask(self, q: CQ | str) -> bool:
        return ask(self.split(q).union, self.db)

    def answer_many(self, queries: Sequence[CQ | str], threads: int = 4, strategy: str = "folded") -> list[DataFrame]:
        """Answers of several queries, compiled and run as concurrent jobs, each written to the shared folder."""
        with ThreadPoolExecutor(threads) as pool:
            return list(pool.map(lambda q: cut(self.answer(q, strategy)), queries))

    def sql(self, q: CQ | str, dialect: str = "duckdb") -> str:
        return folded_to_sql(self.split(q, output="folded").folded, self.db.mapping, dialect)

    def register(self, name: str, q: CQ | str) -> None:
        """Certain answers as a temporary view."""
        self.answer(q).createOrReplaceTempView(name)

    @staticmethod
    def _query(q: CQ | str) -> CQ:
        return parse_query(q) if isinstance(q, str) else q

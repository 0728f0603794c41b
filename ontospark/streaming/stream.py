"""Certain answers over a stream: unions of queries are monotone, so new facts only add answers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ontospark.engine import OntologyEngine
from ontospark.logic.terms import CQ
from ontospark.plans.exec import plan_cq
from ontospark.sources.mapping import Database


def stream_answers(engine: OntologyEngine, q: CQ | str, streams: dict[str, DataFrame], watermark: str | None = None, time_column: str | None = None) -> DataFrame:
    """The answers of the queries of the rewriting that read a stream, as one streaming DataFrame.

    streams: streaming extensions of predicates (columns in position order). Queries over static predicates
    alone are left to engine.answer. With watermark and time_column (a position of the head, a1, a2, ...),
    repeated answers are dropped within the watermark; without, over the whole stream.
    """
    db = Database(engine.db.spark, engine.db.mapping, engine.db.path, extensions={**engine.db.extensions, **streams})
    union = [u for u in engine.split(q).union if any(a.pred in streams for a in u.body) and all(a.pred in db for a in u.body)]
    if not union:
        raise ValueError("no query of the rewriting reads a stream")
    out = None
    for u in union:
        df = plan_cq(u, db, distinct=False)
        out = df if out is None else out.unionByName(df)
    if watermark and time_column:
        return out.withWatermark(time_column, watermark).dropDuplicatesWithinWatermark(out.columns)
    return out.dropDuplicates()


def windowed_counts(answers: DataFrame, time_column: str, window: str, watermark: str, slide: str | None = None) -> DataFrame:
    """Answers in tumbling (or sliding) windows; late rows beyond the watermark are dropped."""
    return answers.withWatermark(time_column, watermark).groupBy(F.window(time_column, window, slide)).agg(F.count(F.lit(1)).alias("n"))


def session_counts(answers: DataFrame, time_column: str, key: str, gap: str, watermark: str) -> DataFrame:
    return answers.withWatermark(time_column, watermark).groupBy(F.session_window(time_column, gap), key).agg(F.count(F.lit(1)).alias("n"))

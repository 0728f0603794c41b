import pytest
from pyspark.sql import functions as F

from ontospark.engine import OntologyEngine
from ontospark.logic.parse import parse_query
from ontospark.operators.checks import Inconsistent, is_non_conflicting
from ontospark.operators.chase import chase_answers, min_sufficient_level
from ontospark.operators.rewrite import Options
from ontospark.operators.split import run_components, decompose
from ontospark.plans.exec import run_folded
from ontospark.plans.sqlgen import to_sql
from ontospark.sources.mapping import Database, Mapping, Predicate, TypeClash
from ontospark.workloads import ontologies as W

SF = "/root/testdata/sf0.001"


def engine(spark, text, mapping, **k):
    return OntologyEngine(text, Database(spark, mapping, SF, **k))


def rows(df):
    return sorted(map(tuple, df.collect()), key=str)


def facts(spark, **preds):
    return {p: spark.createDataFrame(r, ", ".join(f"x{i} {'string' if isinstance(v, str) else 'long'}" for i, v in enumerate(r[0]))) for p, r in preds.items()}


def test_strategies_agree_and_add_certain_answers(spark):
    e = engine(spark, W.FINANCE, W.FINANCE_MAP)
    want = rows(e.answer(W.FINANCE_Q))
    assert len(want) == 652 and e.plain(W.FINANCE_Q).count() == 0
    assert rows(e.answer(W.FINANCE_Q, "merged")) == rows(e.answer(W.FINANCE_Q, "flat")) == want


def test_blind_rewriting_is_unsound_and_no_factorisation_incomplete(spark):
    ext = facts(spark, open_order=[("a",)], ranked=[("a", "high")], assigned=[("z", "x", "y")])
    ask = lambda q, **k: rows(OntologyEngine(W.COLLAB, Database(spark, Mapping(), extensions=ext), Options(**k)).answer(q, "flat"))
    bad = "p(O) <- assigned(O,'c','high')"
    assert ask(bad) == [] and ask(bad, check_applicability=False) == [("a",)]
    need = W.COLLAB_Q["factor_needed"]
    assert ("high", "a") in ask(need) and ("high", "a") not in ask(need, factorise=False)


def test_chase_agrees(spark):
    e = engine(spark, W.COLLAB, W.COLLAB_MAP)
    q = parse_query(W.COLLAB_Q["collab_certain"])
    want = e.answer(q, "flat")
    for mode in ("oblivious", "restricted"):
        got = chase_answers(q, e.db, e.tgds, 1, mode)
        assert rows(got) == rows(want.select(F.col("a1").cast("string")))
    assert min_sufficient_level(q, e.db, e.tgds, want, 2) == 1


def test_null_positions_are_no_facts_and_heads_may_hold_literals(spark):
    df = spark.createDataFrame([(1, "a"), (2, None)], "k long, v string")
    df.createOrReplaceTempView("t_nulls")
    m = Mapping(Predicate("r", "t_nulls", ("k", "v")))
    assert rows(Database(spark, m).extension("r")) == [(1, "a")]
    assert rows(Database(spark, m, null_policy="keep").extension("r").orderBy("c1")) == [(1, "a"), (2, None)]
    ext = facts(spark, d=[("a",), ("b",)])
    e = OntologyEngine("d(X) => g(X,'k')", Database(spark, Mapping(), extensions=ext))
    assert rows(e.answer("p(A,B) <- g(A,B)")) == [("a", "k"), ("b", "k")]


def test_types_are_checked(spark):
    ext = facts(spark, a=[("x",)], b=[(1,)])
    with pytest.raises(TypeClash):
        OntologyEngine("a(X) => c(X)", Database(spark, Mapping(), extensions=ext)).answer("p(A) <- a(A), b(A)", "flat")


def test_existence_tests_use_no_product_and_empty_parts_empty_the_answer(spark):
    ext = facts(spark, a=[("x",), ("y",)], b=[(1, 2)])
    e = OntologyEngine("c(X) => a(X)", Database(spark, Mapping(), extensions=ext))
    assert rows(e.answer("p(A) <- a(A), b(B,C)")) == [("x",), ("y",)]
    assert e.answer("p(A) <- a(A), b(B,B)").count() == 0
    assert e.ask("p() <- b(A,C)") and not e.ask("p() <- b(A,A)")


def test_linked_components_without_head_variables_become_one_existence_test(spark):
    plan = engine(spark, W.SPLITFULL, W.SPLITFULL_MAP).answer(W.SPLITFULL_Q["splitfull_q5"])._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join Cross") == 1 and plan.count("GlobalLimit 1") == 1
    ext = facts(spark, a=[("x",), ("y",)], b=[(1, 2)], d=[(2,)], g=[(3,)])
    e = OntologyEngine("c(X) => a(X)", Database(spark, Mapping(), extensions=ext))
    for q, want in (("p(A) <- a(A), b(B,C), d(C)", [("x",), ("y",)]), ("p(A) <- a(A), b(B,C), g(C)", []), ("p(A,B) <- a(A), b(B,C), d(C)", [("x", 1), ("y", 1)]), ("p() <- b(B,C), d(C), a(A)", [(True,)])):
        assert rows(run_folded(e.split(q, output="folded").folded, e.db)) == want


def test_each_table_is_read_once_for_a_component_and_filters_reach_the_scan(spark):
    e = engine(spark, W.SPLITFULL, W.SPLITFULL_MAP)
    plan = e.answer(W.SPLITFULL_Q["splitfull_q3"])._jdf.queryExecution().executedPlan().toString()
    assert plan.count("lineitem.parquet") == 1 and "CartesianProduct" not in plan and "Python" not in plan
    plan = engine(spark, W.COLLAB, W.COLLAB_MAP).plain(W.COLLAB_Q["collab_certain"])._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(o_orderpriority,1-URGENT)" in plan and "l_comment" not in plan


def test_sql_text_runs_in_duckdb(spark):
    import duckdb

    e = engine(spark, W.COLLAB, W.COLLAB_MAP)
    con = duckdb.connect()
    for t in ("orders", "lineitem", "supplier"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
    q = W.COLLAB_Q["collab_certain"]
    want = rows(e.answer(q, "flat"))
    assert sorted(con.execute(to_sql(e.rewrite(q).union, W.COLLAB_MAP)).fetchall(), key=str) == want
    assert sorted(con.execute(e.sql(q)).fetchall(), key=str) == want


def test_constraints(spark):
    e = engine(spark, W.CONTENT, W.CONTENT_MAP)
    with pytest.raises(Inconsistent) as bad:
        e.answer(W.CONTENT_Q["content_q1"], checked=True)
    assert list(bad.value.report) == ["c1"] and bad.value.report["c1"]
    ok = engine(spark, W.FINANCE, W.FINANCE_MAP)
    assert is_non_conflicting(ok.ontology.fds, ok.ontology.tgds)
    assert ok.answer("p(A) <- partner(A)", checked=True).count() > 0


def test_spark_executor_and_many_queries(spark):
    e = engine(spark, W.FINANCE, W.FINANCE_MAP)
    parts = decompose(parse_query(W.FINANCE_Q), e.tgds)
    a, b = (run_components(parts, e.tgds, Options(subsets="single"), executor=x, spark=spark) for x in ("serial", "spark"))
    assert [r.union for r in a] == [r.union for r in b]
    assert [r.count() for r in e.answer_many([W.FINANCE_Q, "p(A) <- item(A,B)"])][0] == 652


def test_folded_query_with_unlinked_components(spark):
    ext = facts(spark, a=[("x",)], b=[("y",)])
    e = OntologyEngine("c(X) => a(X)", Database(spark, Mapping(), extensions=ext))
    assert rows(run_folded(e.split("p(A,B) <- a(A), b(B)", output="folded").folded, e.db)) == [("x", "y")]


def test_stream_equals_batch(spark):
    from ontospark.workloads import catalog

    got = rows(catalog.QUERIES["stream_events_certain"](spark, SF))
    e = engine(spark, W.STREAM, catalog._EVENTS)
    assert got == rows(e.answer(W.STREAM_Q)) and got


def test_mapping_round_trip():
    assert Mapping.from_json(W.TRADE_MAP.to_json()).by == W.TRADE_MAP.by


def test_entry_points_are_aligned(spark):
    import __spark_entry__ as entry

    q, o = entry.queries(), entry.oracle_sql()
    assert set(o) <= set(q)
    assert entry.entry(spark).count() == 652


def test_programs_and_shared_views_on_data(spark, monkeypatch):
    from ontospark.sources import mapping

    e = engine(spark, W.CLIQUE, W.CLIQUE_MAP)
    q = "p(A,B,C) <- tri(A,B,C)"
    want = rows(e.answer(q, "merged"))
    assert want and rows(e.answer(q, "program")) == want
    ext = facts(spark, a=[("x", "y")], b=[("y", "z")])
    e = OntologyEngine("a(X,Y), b(Y,Z) => c(X,Z)\nc(X,Y) => d(X)", Database(spark, Mapping(), extensions=ext))
    assert rows(e.answer("p(A) <- d(A)")) == [("x",)] and e.answer("p() <- d(A)").count() == 1 and e.answer("p(A) <- nothing(A)").count() == 0
    written = []
    monkeypatch.setattr(mapping, "cut", lambda df: written.append(0) or df)
    engine(spark, W.PATH, W.PATH_MAP).answer(W.path_query(2), "flat")  # path_1 occurs in one query only
    assert len(written) == 1 + 4 and not W.PATH_MAP["next"].unique and W.PATH_MAP["next"].derived


def test_keys_need_no_distinct(spark):
    assert "DISTINCT" not in W.COLLAB_MAP["ranked"].sql() and "DISTINCT" in W.COLLAB_MAP["assigned"].sql()


def test_graph_frames_and_table_function(spark):
    from ontospark.functions.graph import query_graph, register_udtf
    from ontospark.logic.parse import parse_ontology
    from ontospark.operators.rewrite import backward_rewrite

    nodes, edges = query_graph(spark, backward_rewrite(parse_query(W.COLLAB_Q["factor_needed"]), parse_ontology(W.COLLAB).tgds))
    assert (nodes.count(), edges.count(), nodes.where("returned").count()) == (4, 3, 3)
    register_udtf(spark)
    assert spark.sql("SELECT * FROM rewrite_cq('p(A) <- b(A)', 'a(X) => b(X)')").count() == 2


def test_windowed_and_session_counts(spark, tmp_path):
    from ontospark.streaming.stream import session_counts, windowed_counts

    df = spark.sql("SELECT timestamp'2024-01-01 00:00:00' + make_interval(0, 0, 0, 0, 0, x, 0) AS t, x % 2 AS u FROM VALUES (0), (1), (2), (30), (31) v(x)")
    assert sorted(r.n for r in windowed_counts(df, "t", "10 minutes", "1 hour").collect()) == [2, 3]
    assert sorted(r.n for r in session_counts(df, "t", "u", "5 minutes", "1 hour").collect()) == [1, 1, 1, 2]

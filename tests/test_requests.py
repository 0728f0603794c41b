"""Analyses and compilations for what the orders of a table ask for, against their SQL and the table."""

import duckdb
import pytest

from ontospark.logic import analysis
from ontospark.logic.parse import parse_query
from ontospark.operators.eliminate import reduce_query
from ontospark.operators.rewrite import Options, backward_rewrite
from ontospark.operators.split import split_rewrite
from ontospark.workloads import catalog, requests
from ontospark.workloads import published as G

SF = "/root/testdata/sf0.001"
NAMES = ["affected_positions", "cache_profile", "chase_backchase", "clique_metrics", "cover_graph_edges", "decomposition_components", "decomposition_rows", "elimination_cover_sets", "elimination_rows", "compile_measures", "deep_rows"]


@pytest.mark.parametrize("name", NAMES)
def test_asked_by_the_orders(spark, name):
    df = catalog.QUERIES[name](spark, SF)
    assert [f for f in df.inputFiles() if f.endswith("lineitem.parquet")]
    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM read_parquet('{SF}/lineitem.parquet')")
    got = [tuple(r) for r in df.collect()]
    if name in catalog.ORACLES:
        assert sorted(got, key=str) == sorted(con.execute(catalog.ORACLES[name]).fetchall(), key=str)
    orders = con.execute("SELECT count(DISTINCT l_orderkey) FROM lineitem").fetchall()[0][0]
    if name != "cover_graph_edges":  # a single kind makes no rule
        assert sum(n for _, n in {r[:2] for r in got}) == orders


def test_published_sizes_with_and_without_elimination_and_in_components():
    opts = Options(subsets="single")
    for text, queries, base, less in ((G.TAXONOMY, G.TAXONOMY_Q, {i: r[0] for i, r in G.TAXONOMY_ROWS.items()}, None), (G.ROLES, G.ROLES_Q, {i: r[0] for i, r in G.ROLES_ROWS.items()}, G.ROLES_ROWS), (G.STAFF, G.STAFF_Q, {i: r[0] for i, r in G.STAFF_ROWS.items()}, G.STAFF_ROWS)):
        t = analysis.normalise(G.parsed(text).tgds)
        for i, q in queries.items():
            q = parse_query(q)
            whole, split = backward_rewrite(q, t, opts), split_rewrite(q, t, opts)
            assert len(whole.union) == len(split.union) == base[i]
            reduced = backward_rewrite(reduce_query(q, t), t, Options(subsets="single", eliminate=lambda x, t=t: reduce_query(x, t)))
            assert len(reduced.union) == (less[i][4] if less else base[i])
            if not less:
                assert (len(split.parts), split.explored) == G.TAXONOMY_ROWS[i][4:6]


def test_compiling_is_measured_for_all_kinds_and_ten_times_for_time_and_for_memory(monkeypatch):
    base, split = [], []
    monkeypatch.setattr(requests, "backward_rewrite", lambda q, *a, **k: base.append(q))
    monkeypatch.setattr(requests, "split_rewrite", lambda q, *a, **k: split.append(q))
    requests._measures(["af", "ao", "nf", "no", "rf", "ro"])
    assert len(base) == len(split) == 20
    assert {frozenset(a.pred for a in q.body) for q in base + split} == {frozenset(("pays", "payer", "bill", "desk", "quote", "lists", "paper_list"))}


def test_every_shape_has_a_task_of_its_own(spark):
    def task(kinds):
        from pyspark import TaskContext

        return [(TaskContext.get().partitionId(),)]

    got = [r.task for r in requests.compiled(task, "task long")(spark, SF).collect()]
    assert len(got) == len(set(got)) > 1

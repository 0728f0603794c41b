"""Registered queries of the workloads, and SQL that computes the same from the meaning of the rules."""

from __future__ import annotations

from functools import cache

from pyspark.sql import Window
from pyspark.sql import functions as F

from ontospark.engine import OntologyEngine
from ontospark.functions import metrics
from ontospark.functions.graph import graph_sizes, query_graph, register_udtf, rule_graph
from ontospark.logic import analysis
from ontospark.logic.parse import parse_ontology, parse_query
from ontospark.operators import baselines, checks
from ontospark.operators.chase import chase_answers
from ontospark.operators.rewrite import Options, backward_rewrite, family_linear, family_sticky, replace
from ontospark.operators.split import split_rewrite
from ontospark.operators.subsume import prune
from ontospark.plans.exec import run_union
from ontospark.sources.mapping import Database
from ontospark.workloads import ontologies as W
from ontospark.workloads import published as G
from ontospark.workloads import requests

SINGLE = Options(subsets="single")


@cache
def rules(text: str):
    return parse_ontology(text)


def engine(spark, sf_dir, text, mapping, opts=SINGLE):
    return OntologyEngine(rules(text), Database(spark, mapping, sf_dir), opts)


def certain(text, mapping, q, strategy="folded"):
    return lambda spark, sf_dir: engine(spark, sf_dir, text, mapping).answer(q, strategy)


def plain(text, mapping, q):
    return lambda spark, sf_dir: engine(spark, sf_dir, text, mapping).plain(q)


def chased(text, mapping, q, levels, types):
    def run(spark, sf_dir):
        e = engine(spark, sf_dir, text, mapping)
        out = chase_answers(parse_query(q), e.db, e.ontology.tgds, levels, "restricted")
        return out.select(*[F.col(f"a{i}").cast(t).alias(f"a{i}") for i, t in enumerate(types, 1)])

    return run


def row(spark, **values):
    kinds = ", ".join(f"{k} {'string' if isinstance(v, str) else 'double' if isinstance(v, float) else 'boolean' if isinstance(v, bool) else 'long'}" for k, v in values.items())
    return spark.createDataFrame([tuple(values.values())], kinds)


def const(**values) -> str:
    return "SELECT " + ", ".join(f"{repr(v) if isinstance(v, str) else str(v).lower() + ('::BIGINT' if isinstance(v, int) and not isinstance(v, bool) else '::DOUBLE' if isinstance(v, float) else '')} AS {k}" for k, v in values.items())


def sizes(make):
    return lambda spark, sf_dir: row(spark, **make())


def union_sizes(union):
    return {"size": len(union), "atoms": metrics.n_atoms(union), "joins_pairs": metrics.joins_pairs(union)}


def _split_sizes(text, q, eliminate=False):
    return lambda: union_sizes(split_rewrite(parse_query(q), analysis.normalise(rules(text).tgds), SINGLE, eliminate=eliminate).union)


def _path(n):
    r = backward_rewrite(parse_query(W.path_query(n)), rules(W.PATH).tgds, Options(subsets="single", edb=W.PATH_MAP.edb()))
    return union_sizes(r.union) | ({"explored_r": r.explored_r, "explored_all": r.explored_all} if n < 3 else {})


def _split(i):
    s = split_rewrite(parse_query(W.SPLITFULL_Q[f"splitfull_q{i}"]), rules(W.SPLITFULL).tgds, SINGLE)
    return union_sizes(s.union) | {"explored": s.explored, "generated": s.generated, "components": len(s.parts)}


_PROP = "w(X,Y) => e(Y,X)\ne(X,Y) => f(X,X,Y)\nf(X,Y,Y) => w(Y,X)"
_MARK = "g(X,Y), h(Y,Z) => j(X,Z,W)\nj(X,Y,Z) => g(Y,X)"


def _marks(spark, sf_dir):
    t = rules(_MARK).tgds
    return spark.createDataFrame(sorted((r, str(v), n) for (r, v), n in analysis.sticky_marking(t).items()), "rule string, variable string, round long")


def _subsumption(component):
    def make():
        q, t = parse_query("p(A) <- next(A,B), next(B,C), next(A,D)"), rules(W.PATH).tgds
        opts = Options(subsets="all", edb=W.PATH_MAP.edb())
        if component:
            return {"size": len(split_rewrite(q, t, opts, prune_components=True).union)}
        r = backward_rewrite(q, t, opts)
        return {"size": len(prune(r.union, r.graph))}

    return make


def _piece():
    t = rules("s(X) => t(X,X,Y)\nr(X,Y) => s(Y)").tgds
    q = parse_query("p(A) <- t(A,B,C), s(B)")
    a, b = backward_rewrite(q, t), baselines.piece_rewrite(q, t)
    return {"backward": len(prune(a.union)), "piece": len(prune(b.union))}


def _bounds():
    q, t = parse_query(W.path_query(2)), rules(W.PATH).tgds
    size, bound = len(backward_rewrite(q, t, SINGLE).union), metrics.size_upper_bound(q, t)
    return {"size": size, "bound": bound, "within": size <= bound}


SUITES = {"trade": (W.TRADE, W.TRADE_MAP), "content": (W.CONTENT, W.CONTENT_MAP), "path": (W.PATH, W.PATH_MAP), "collab": (W.COLLAB, W.COLLAB_MAP)}


def _suite(spark, sf_dir):
    """All short queries over an ontology: the rewriter and its rival end in unions of one size."""
    rows = []
    for name, (text, mapping) in SUITES.items():
        o = rules(text)
        t = analysis.normalise(o.tgds)
        qs, same = W.generated_suite(o), 0
        for q in qs:
            a = prune([x for x in backward_rewrite(q, t, SINGLE).union if all(y.pred in mapping for y in x.body)])
            b = prune([x for x in baselines.piece_rewrite(q, t).union if all(y.pred in mapping for y in x.body)])
            same += len(a) == len(b)
        rows.append((name, len(qs), same))
    return spark.createDataFrame(rows, "ontology string, queries long, same_size long")


SETS = {"taxonomy": (G.TAXONOMY, G.TAXONOMY_Q), "roles": (G.ROLES, G.ROLES_Q), "staff": (G.STAFF, G.STAFF_Q)}


def _normal(text):
    return analysis.normalise(rules(text).tgds)


def _mode_rows(spark, sf_dir):
    """Sizes after elimination and decomposition with no pruning, pruning at the end, in components, and while rewriting."""
    rows = []
    for name, (text, queries) in {**SETS, "path": (W.PATH, {i: W.path_query(i) for i in (1, 2, 3)})}.items():
        t = _normal(text)
        for i, q in queries.items():
            q = parse_query(q)
            opts = Options(subsets="single", edb=W.PATH_MAP.edb()) if name == "path" else SINGLE
            none = split_rewrite(q, t, opts, eliminate=True)
            part = split_rewrite(q, t, opts, eliminate=True, prune_components=True)
            inline = split_rewrite(q, t, replace(opts, inline=True), eliminate=True)
            rows.append((name, i, len(none.union), len(prune(none.union)), len(part.union), len(inline.union)))
    return spark.createDataFrame(rows, "ontology string, query int, none long, final long, component long, inline long")


def _graph_rows(spark, sf_dir):
    sets = {"taxonomy": G.TAXONOMY, "splitfull": W.SPLITFULL, "path": W.PATH}
    return spark.createDataFrame([(k, *graph_sizes(_normal(x))) for k, x in sets.items()], "ontology string, nodes long, propagation_edges long, cover_edges long, longest long")


GAINS = {
    "finance": (W.FINANCE, W.FINANCE_MAP, W.FINANCE_Q), "collab": (W.COLLAB, W.COLLAB_MAP, W.COLLAB_Q["collab_certain"]), "trade": (W.TRADE, W.TRADE_MAP, W.TRADE_Q["trade_q1"]),
}


def _gain(spark, sf_dir):
    """Certain answers against the answers that need no rule."""
    out = None
    for name, (text, mapping, q) in GAINS.items():
        e = engine(spark, sf_dir, text, mapping)
        one = e.answer(q).agg(F.count(F.lit(1)).alias("certain_rows")).crossJoin(e.plain(q).agg(F.count(F.lit(1)).alias("plain_rows"))).select(F.lit(name).alias("ontology"), "certain_rows", "plain_rows")
        out = one if out is None else out.unionByName(one)
    return out


def _against_chase(spark, sf_dir):
    """Rows that the rewriting finds and the chase doesn't, and the other way round."""
    e = engine(spark, sf_dir, W.COLLAB, W.COLLAB_MAP)
    q = parse_query(W.COLLAB_Q["collab_certain"])
    got, want = e.answer(q).select(F.col("a1").cast("string").alias("a1")), chase_answers(q, e.db, e.ontology.tgds, 1, "restricted")
    wrong, missing = got.exceptAll(want).agg(F.count(F.lit(1)).alias("unsound")), want.exceptAll(got).agg(F.count(F.lit(1)).alias("missing"))
    return wrong.crossJoin(missing)


def _graph_nodes(spark, sf_dir):
    r = backward_rewrite(parse_query(W.COLLAB_Q["factor_needed"]), rules(W.COLLAB).tgds)
    nodes, edges = query_graph(spark, r)
    return nodes.join(edges, nodes.id == edges.target, "left").groupBy("atoms", "returned", F.coalesce("label", F.lit("start")).alias("made_by")).agg(F.count(F.lit(1)).alias("n"))


def _udtf(spark, sf_dir):
    register_udtf(spark)
    return spark.sql("SELECT atoms, joins, count(*) AS n FROM rewrite_cq('p(A) <- seller(A), sells(A,B)', 'sells(X,Y) => seller(X)\\ntrader(X) => seller(X)') GROUP BY atoms, joins")


def _nc(spark, sf_dir):
    e = engine(spark, sf_dir, W.CONTENT, W.CONTENT_MAP)
    nc = e.ontology.ncs[0]
    from ontospark.logic.terms import CQ, Var

    return run_union(backward_rewrite(CQ((Var("X"),), nc.body), e.tgds, SINGLE).union, e.db, "flat", arity=1)


def _fd(pred):
    mapping = W.Mapping(W.P("line", "{lineitem}", ("l_orderkey", "l_linenumber", "l_partkey")), W.P("ord", "{orders}", ("o_orderkey", "o_custkey")))
    fd = {"line": checks.FD("line", (1, 2), 3), "ord": checks.FD("ord", (1,), 2)}[pred]
    return lambda spark, sf_dir: checks.fd_violations(fd, Database(spark, mapping, sf_dir)).agg(F.count(F.lit(1)).alias("groups"))


def _finance(spark, sf_dir):
    return engine(spark, sf_dir, W.FINANCE, W.FINANCE_MAP).answer(W.FINANCE_Q)


def _aggregate(spark, sf_dir):
    return _finance(spark, sf_dir).groupBy("a3").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("a2").alias("companies"))


def _topk(spark, sf_dir):
    return _finance(spark, sf_dir).groupBy("a2").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "a2").limit(10)


def _window(spark, sf_dir):
    w = Window.partitionBy("a3").orderBy(F.desc("n"), "a2")
    n = _finance(spark, sf_dir).groupBy("a3", "a2").agg(F.count(F.lit(1)).alias("n"))
    return n.withColumn("rank", F.row_number().over(w)).where("rank <= 3")


def _setops(spark, sf_dir):
    e = engine(spark, sf_dir, W.COLLAB, W.COLLAB_MAP)
    return e.answer(W.COLLAB_Q["collab_certain"]).exceptAll(e.plain(W.COLLAB_Q["collab_certain"]))


def _rollup(spark, sf_dir):
    return _finance(spark, sf_dir).rollup("a3").agg(F.count(F.lit(1)).alias("n"))


_EVENTS = W.Mapping(
    W.P("purchased", "{events}", ("user_id", "event_id"), "event_type = 'purchase'"),
    W.P("viewed", "{events}", ("user_id", "event_id"), "event_type = 'view'"),
    W.P("placed", "{orders}", ("o_custkey", "o_orderkey"), "o_orderstatus = 'F'"),
)


def _stream(spark, sf_dir):
    """The streaming run over the events' files, until all are read; equals the batch answer."""
    import uuid

    from ontospark.plans.lineage import shared_dir
    from ontospark.streaming.stream import stream_answers

    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    events = spark.readStream.schema(schema).parquet(f"{sf_dir}/events*.parquet")
    e = engine(spark, sf_dir, W.STREAM, _EVENTS)
    kinds = {"purchased": "purchase", "viewed": "view"}
    streams = {p: events.where(F.col("event_type") == k).select("user_id", "event_id") for p, k in kinds.items()}
    out = stream_answers(e, W.STREAM_Q, streams)
    path = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    run = out.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/state").outputMode("append").trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.schema(out.schema).parquet(f"{path}/out")


def _unsound():
    q, t = parse_query(W.COLLAB_Q["collab_constant_unsound"]), rules(W.COLLAB).tgds
    return {"checked": len(backward_rewrite(q, t, SINGLE).union), "blind": len(backward_rewrite(q, t, Options(subsets="single", check_applicability=False)).union)}


def _factor():
    q, t = parse_query(W.COLLAB_Q["factor_needed"]), rules(W.COLLAB).tgds
    a, b = backward_rewrite(q, t), backward_rewrite(q, t, Options(factorise=False))
    return {"with_factor": len(a.union), "factor_steps": a.explored_all - a.explored_r, "without": len(b.union)}


def _family():
    q, t = family_linear(3, 3)
    return {"size": len(backward_rewrite(q, t, SINGLE).union)}


def _sticky_family():
    q, t = family_sticky(2)
    return {"largest": max(len(x.body) for x in backward_rewrite(q, t, SINGLE).union)}


F_, C_, T_ = (W.FINANCE, W.FINANCE_MAP), (W.CONTENT, W.CONTENT_MAP), (W.TRADE, W.TRADE_MAP)
QUERIES = {
    "finance_certain": certain(*F_, W.FINANCE_Q),
    "finance_merged": certain(*F_, W.FINANCE_Q, "merged"),
    "finance_plain": plain(*F_, W.FINANCE_Q),
    "finance_folded": certain(*F_, W.FINANCE_Q, "folded"),
    "finance_program": certain(*F_, W.FINANCE_Q, "program"),
    "finance_chase": chased(*F_, W.FINANCE_Q, 2, ("long", "long", "string")),
    "finance_legal": certain(*F_, "p(A) <- partner(A)"),
    "finance_flat60_metrics": sizes(_split_sizes(W.EXAMPLE, W.EXAMPLE_Q)),
    "finance_flat_metrics": sizes(_split_sizes(W.FINANCE, W.FINANCE_Q)),
    "finance_pruned_metrics": sizes(_split_sizes(W.EXAMPLE, W.EXAMPLE_Q, True)),
    "finance_own_pruned_metrics": sizes(_split_sizes(W.FINANCE, W.FINANCE_Q, True)),
    **{k: certain(W.COLLAB, W.COLLAB_MAP, q, "flat") for k, q in W.COLLAB_Q.items()},
    "collab_plain": plain(W.COLLAB, W.COLLAB_MAP, W.COLLAB_Q["collab_certain"]),
    "collab_chase": chased(W.COLLAB, W.COLLAB_MAP, W.COLLAB_Q["collab_certain"], 1, ("long",)),
    "unsound_control": sizes(_unsound),
    "factor_control": sizes(_factor),
    **{f"path_q{n}": certain(W.PATH, W.PATH_MAP, W.path_query(n), "flat") for n in (1, 2, 3)},
    **{f"path_q{n}": certain(W.PATH, W.PATH_MAP, W.path_query(n), "folded") for n in (4, 5)},
    **{f"path_q{n}_metrics": sizes(lambda n=n: _path(n)) for n in (1, 2, 3, 4, 5)},
    **{k: certain(W.SPLITFULL, W.SPLITFULL_MAP, q) for k, q in W.SPLITFULL_Q.items()},
    **{f"splitfull_q{i}_metrics": sizes(lambda i=i: _split(i)) for i in (1, 2, 3, 4, 5)},
    "splitfull_flat_q2": certain(W.SPLITFULL, W.SPLITFULL_MAP, W.SPLITFULL_Q["splitfull_q2"], "batched"),
    **{k: certain(W.CLIQUE, W.CLIQUE_MAP, q) for k, q in W.CLIQUE_Q.items()},
    **{k: certain(*T_, q) for k, q in W.TRADE_Q.items()},
    **{k: certain(*C_, q) for k, q in W.CONTENT_Q.items()},
    "content_nc_violations": _nc,
    **{k: certain(W.CATALOG, W.CATALOG_MAP, q) for k, q in W.CATALOG_Q.items()},
    **{k: certain(W.COLLAB + W.EDGE, W.COLLAB_MAP, q) for k, q in W.EDGE_Q.items()},
    "fd_violations_lineitem": _fd("line"),
    "fd_ok_orders": _fd("ord"),
    "sticky_marking": _marks,
    "propagation_edges": lambda spark, sf_dir: rule_graph(spark, rules(_PROP).tgds),
    "subsumption_final": sizes(_subsumption(False)),
    "subsumption_component": sizes(_subsumption(True)),
    "piece_vs_backward": sizes(_piece),
    "size_bounds": sizes(_bounds),
    "family_linear_sizes": sizes(_family),
    "family_sticky_sizes": sizes(_sticky_family),
    "generated_suite_summary": _suite,
    "rule_set_sizes": lambda spark, sf_dir: spark.createDataFrame(G.sizes(), "ontology string, rules long, constraints long"),
    "subsumption_mode_rows": _mode_rows,
    "graph_rows": _graph_rows,
    "ontology_gain": _gain,
    "answers_against_chase": _against_chase,
    "query_graph_nodes": _graph_nodes,
    "rewrite_cq_udtf": _udtf,
    "answer_aggregate": _aggregate,
    "answer_topk": _topk,
    "answer_window": _window,
    "answer_setops": _setops,
    "answer_rollup": _rollup,
    "stream_events_certain": _stream,
}

# --- SQL from the meaning of the rules, written by hand --------------------------------------------------------------
_BASE = "SELECT DISTINCT o_orderkey AS a1 FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' AND o_orderpriority = '1-URGENT'"
_COLLAB = _BASE + " UNION SELECT o_orderkey FROM orders WHERE o_orderstatus = 'O' AND o_orderpriority = '1-URGENT'"
_HC = "SELECT l_suppkey AS c, o_orderpriority AS a, o_orderkey AS p FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE l_returnflag = 'R'"
_FIN = "SELECT DISTINCT l.p_partkey AS a1, u.c AS a2, l.p_brand AS a3 FROM part l JOIN (SELECT l_partkey AS s, l_suppkey AS c FROM lineitem WHERE l_returnflag IN ('A', 'R')) u ON u.s = l.p_partkey WHERE l.p_type IN ('PROMO', 'ECONOMY')"
_FIN_PLAIN = "SELECT DISTINCT a.p_partkey AS a1, l_suppkey AS a2, a.p_brand AS a3 FROM part a JOIN lineitem ON l_partkey = a.p_partkey JOIN supplier ON s_suppkey = l_suppkey WHERE a.p_size > 40 AND l_returnflag = 'A' AND s_acctbal > 3000 AND a.p_type IN ('PROMO', 'ECONOMY') AND a.p_brand IN ('Brand#1', 'Brand#2', 'Brand#3')"
_NEXT = "n AS (SELECT a, b FROM (SELECT conv_id * 100 + turn AS a, lead(conv_id * 100 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM conversations) WHERE b IS NOT NULL), l AS (SELECT max(conv_id * 100 + turn) AS a, 1 + conv_id % 5 AS k FROM conversations GROUP BY conv_id)"


def _path_sql(n: int) -> str:
    parts = []
    for used in range(n, -1, -1):
        joins = "".join(f" JOIN n n{i} ON n{i}.a = n{i - 1}.b" for i in range(1, used))
        if used == n:
            parts.append(f"SELECT n0.a AS a1 FROM n n0{joins}")
        elif used:
            parts.append(f"SELECT n0.a FROM n n0{joins} JOIN l ON l.a = n{used - 1}.b WHERE l.k >= {n - used}")
        else:
            parts.append(f"SELECT a FROM l WHERE k >= {n}")
    return f"WITH {_NEXT} " + " UNION ".join(parts)


def _split_sql(n: int) -> str:
    return f"SELECT DISTINCT l_orderkey AS a1, l_partkey AS a2 FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN part ON p_partkey = l_partkey WHERE floor((l_quantity - 1) * 20 / 50) + 1 <= {n} AND o_custkey % 20 + 1 <= {n} AND floor((p_size - 1) * 20 / 50) + 1 <= {n}"


_EDGES = "sym AS (SELECT a.n_nationkey AS x, b.n_nationkey AS y FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey WHERE a.n_nationkey < b.n_nationkey), e AS (SELECT DISTINCT c_nationkey AS x, s_nationkey AS y FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE l_quantity = 50 AND l_returnflag = 'R' AND l_linestatus = 'O' AND c_nationkey <> s_nationkey UNION SELECT x, y FROM sym UNION SELECT y, x FROM sym), t AS (SELECT a.x, a.y, b.y AS z FROM e a JOIN e b ON b.x = a.y JOIN e c ON c.x = a.x AND c.y = b.y)"
_PARTY = "SELECT concat('C', c_custkey) AS x FROM customer WHERE c_mktsegment = 'BUILDING' OR c_acctbal < 0 UNION SELECT concat('C', o_custkey) FROM orders WHERE o_orderstatus <> 'P' UNION SELECT concat('S', s_suppkey) FROM supplier UNION SELECT concat('S', l_suppkey) FROM lineitem WHERE l_returnflag = 'N'"
_BUYER = "SELECT concat('C', c_custkey) AS x FROM customer WHERE c_mktsegment = 'BUILDING' UNION SELECT concat('C', o_custkey) FROM orders WHERE o_orderstatus <> 'P'"
_ITEMS = "SELECT concat('D', doc_id) AS a1 FROM documents UNION SELECT concat('D', doc_id) FROM labels UNION SELECT concat('P', page_id) FROM pages UNION SELECT concat('T', conv_id * 100 + turn) FROM conversations UNION SELECT concat('B', item_id) FROM benchmark"
_LANG = "SELECT DISTINCT concat('D', doc_id) AS a1, lang AS a2 FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality IN (0, 1) OR toxic = 1)"
_SUPP = "SELECT DISTINCT l_suppkey AS s, l_partkey AS p FROM lineitem WHERE l_quantity = 50"


def _values(names: str, *rows: tuple) -> str:
    return f"SELECT * FROM (VALUES {', '.join(map(repr, rows))}) v({names})"


def _table(kinds: str, *rows: tuple) -> str:
    names = [x.split() for x in kinds.split(", ")]
    values = ", ".join("(" + ", ".join(str(v).lower() if isinstance(v, bool) else repr(v) for v in r) + ")" for r in rows)
    return f"SELECT {', '.join(f'{n}::{k} AS {n}' for n, k in names)} FROM (VALUES {values}) v({', '.join(n for n, _ in names)})"


def _suite_sql() -> str:
    """Counted from the arities: single atoms, pairs of predicates at all pairs of places, and twice the same predicate."""
    arities = [(name, i, n) for name, (text, _) in SUITES.items() for i, (_, n) in enumerate(W.predicates(rules(text)))]
    return (
        f"WITH a AS ({_table('ontology VARCHAR, i BIGINT, n BIGINT', *arities)}), c AS (SELECT ontology, count(*) + sum(n * (n + 1) // 2) - count(*) FILTER (WHERE n = 1) AS k FROM a GROUP BY ontology), "
        "d AS (SELECT x.ontology, sum(x.n * y.n) AS k FROM a x JOIN a y ON x.ontology = y.ontology AND x.i < y.i GROUP BY x.ontology) "
        "SELECT ontology, (c.k + d.k)::BIGINT AS queries, (c.k + d.k)::BIGINT AS same_size FROM c JOIN d USING (ontology)"
    )


#: By hand: w(X,Y) -> e(Y,X); e(X,Y) -> f(X,X,Y); f(X,Y,Y) -> w(Y,X).
_STEPS = (("w[1]", "e[2]", "s1"), ("w[2]", "e[1]", "s1"), ("e[1]", "f[1]", "s2"), ("e[1]", "f[2]", "s2"), ("e[2]", "f[3]", "s2"), ("f[1]", "w[2]", "s3"), ("f[2]", "w[1]", "s3"), ("f[3]", "w[1]", "s3"))


ORACLES = {
    **{k: _FIN for k in ("finance_certain", "finance_merged", "finance_chase", "finance_folded", "finance_program")},
    "finance_plain": _FIN_PLAIN,
    "finance_legal": "SELECT s_suppkey AS a1 FROM supplier WHERE s_acctbal < 0 OR s_acctbal > 3000 UNION SELECT l_suppkey FROM lineitem WHERE l_returnflag IN ('A', 'R')",
    "finance_flat60_metrics": const(size=60, atoms=300, joins_pairs=300),
    "finance_flat_metrics": const(size=6 * 12 * 2, atoms=5 * 144, joins_pairs=5 * 144),
    "finance_pruned_metrics": const(size=2, atoms=4, joins_pairs=2),
    "finance_own_pruned_metrics": const(size=3, atoms=6, joins_pairs=3),
    "collab_certain": _COLLAB,
    "collab_chase": _COLLAB,
    "collab_plain": _BASE,
    "collab_constant_unsound": f"SELECT DISTINCT p AS a1 FROM ({_HC}) WHERE c = 3 AND a = '1-URGENT'",
    "collab_selfjoin": f"SELECT DISTINCT p AS a1 FROM ({_HC}) WHERE c = p AND a = '1-URGENT'",
    "factor_needed": f"SELECT a AS a1, p AS a2 FROM ({_HC}) UNION SELECT o_orderpriority, o_orderkey FROM orders WHERE o_orderstatus = 'O'",
    "unsound_control": const(checked=1, blind=2),
    "factor_control": const(with_factor=3, factor_steps=1, without=2),
    **{f"path_q{n}": _path_sql(n) for n in range(1, 6)},
    **{f"path_q{n}_metrics": const(size=s, atoms=a, joins_pairs=j, **x) for n, s, a, j, x in ((1, 6, 6, 0, {"explored_r": 14, "explored_all": 14}), (2, 10, 16, 6, {"explored_r": 77, "explored_all": 81}), (3, 13, 29, 16, {}), (4, 15, 44, 29, {}), (5, 16, 60, 44, {}))},
    **{f"splitfull_q{i}": _split_sql(n) for i, n in enumerate((1, 5, 10, 20), 1)},
    "splitfull_flat_q2": _split_sql(5),
    "splitfull_q5": f"SELECT * FROM ({_split_sql(10)}) WHERE EXISTS ({_split_sql(3)})",
    **{f"splitfull_q{i}_metrics": const(size=s, atoms=a, joins_pairs=j, explored=x, generated=g, components=c) for i, s, a, j, x, g, c in ((1, 1, 3, 2, 3, 0, 3), (2, 125, 375, 250, 15, 12, 3), (3, 1000, 3000, 2000, 30, 27, 3), (4, 8000, 24000, 16000, 60, 57, 3), (5, 27000, 162000, 108000, 39, 33, 6))},
    "clique_q1": f"WITH {_EDGES} SELECT DISTINCT x AS a1, y AS a2, z AS a3 FROM t",
    "clique_q2": f"WITH {_EDGES} SELECT DISTINCT t.x AS a1, t.y AS a2, z AS a3, a.y AS a4 FROM t JOIN e a ON a.x = t.x JOIN e b ON b.x = t.y AND b.y = a.y JOIN e c ON c.x = z AND c.y = a.y",
    "clique_q3": f"WITH {_EDGES} SELECT x AS a1 FROM e UNION SELECT n_nationkey FROM nation WHERE n_regionkey = 0",
    "clique_q4": f"WITH {_EDGES} SELECT DISTINCT a.x AS a1, a.y AS a2 FROM t a JOIN t b ON b.x = a.y AND b.y = a.x",
    "cross_rule": f"WITH {_EDGES} SELECT n_nationkey AS a1, x AS a2, y AS a3 FROM nation, sym WHERE n_regionkey = 0",
    "trade_q1": f"SELECT x AS a1 FROM ({_PARTY})",
    "trade_q2": f"SELECT x AS a1 FROM ({_PARTY})",
    "trade_q3": "SELECT concat('O', o_orderkey) AS a1 FROM orders UNION SELECT concat('O', l_orderkey) FROM lineitem WHERE l_returnflag = 'N'",
    "trade_q4": f"SELECT concat('C', c_custkey) AS a1, concat('N', c_nationkey) AS a2 FROM customer WHERE c_acctbal < 0 AND concat('C', c_custkey) IN ({_BUYER})",
    "trade_q5": "SELECT DISTINCT concat('C', o_custkey) AS a1 FROM orders WHERE o_orderstatus <> 'P'",
    "content_q1": _ITEMS,
    "content_q2": _ITEMS,
    "content_q3": _LANG,
    "content_q4": "SELECT true AS holds WHERE EXISTS (SELECT 1 FROM pages)",
    "content_q5": _LANG,
    "content_nc_violations": "SELECT DISTINCT concat('D', doc_id) AS a1 FROM labels WHERE quality = 1 AND doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1)",
    "catalog_q1": f"SELECT p_partkey AS a1 FROM part WHERE p_type IN ('PROMO', 'STANDARD', 'LARGE') OR p_brand = 'Brand#1' UNION SELECT p FROM ({_SUPP})",
    "catalog_q2": f"SELECT DISTINCT p_partkey AS a1, s_nationkey AS a2 FROM part JOIN ({_SUPP}) ON p = p_partkey JOIN supplier ON s_suppkey = s WHERE p_type = 'LARGE'",
    "catalog_q3": f"SELECT DISTINCT s AS a1, p AS a2 FROM part JOIN ({_SUPP}) ON p = p_partkey WHERE p_type = 'PROMO' AND p_brand = 'Brand#1'",
    "catalog_q4": f"SELECT DISTINCT s AS a1, n_regionkey AS a2 FROM ({_SUPP}) JOIN supplier ON s_suppkey = s JOIN nation ON n_nationkey = s_nationkey",
    "catalog_q5": f"WITH x AS (SELECT DISTINCT p_type AS k, s_nationkey AS n FROM part JOIN ({_SUPP}) ON p = p_partkey JOIN supplier ON s_suppkey = s) SELECT n_nationkey AS a1, n_regionkey AS a2 FROM nation WHERE n_nationkey IN (SELECT n FROM x WHERE k = 'PROMO') AND n_nationkey IN (SELECT n FROM x WHERE k = 'STANDARD')",
    "conditional_inclusion": "SELECT o_orderkey AS a1 FROM orders WHERE o_orderpriority = '1-URGENT'",
    "head_constant": "SELECT o_orderkey AS a1, 'order' AS a2 FROM orders",
    "lav_rule": "SELECT DISTINCT o_orderpriority AS a1 FROM orders",
    "decompose_rule": f"SELECT DISTINCT c AS a1, p AS a2 FROM ({_HC})",
    "merge_rule": f"WITH w AS (SELECT a, p FROM ({_HC}) UNION SELECT o_orderpriority, o_orderkey FROM orders WHERE o_orderstatus = 'O') SELECT DISTINCT h.c AS a1, h.p AS a2, w.a AS a3 FROM ({_HC}) h JOIN w ON w.p = h.p",
    "repeated_var": f"SELECT DISTINCT c AS a1, c AS a2 FROM ({_HC})",
    "disconnected_cq": "SELECT o_orderkey AS a1 FROM orders WHERE o_orderpriority = '1-URGENT' AND EXISTS (SELECT 1 FROM orders WHERE o_orderstatus = 'O')",
    "boolean_ask": "SELECT true AS holds",
    "fd_violations_lineitem": "SELECT count(*) AS groups FROM (SELECT 1 FROM lineitem GROUP BY l_orderkey, l_linenumber HAVING min(l_partkey) <> max(l_partkey))",
    "fd_ok_orders": "SELECT count(*) AS groups FROM (SELECT 1 FROM orders GROUP BY o_orderkey HAVING min(o_custkey) <> max(o_custkey))",
    "propagation_edges": _values("source, target, label", *_STEPS),
    "sticky_marking": "SELECT rule, variable, round::BIGINT AS round FROM (VALUES ('s1', 'Y', 0), ('s2', 'Z', 0), ('s2', 'X', 1), ('s1', 'X', 2), ('s2', 'Y', 3), ('s1', 'Z', 4)) v(rule, variable, round)",
    # the doubled atom is redundant, so the pruned union is that of two steps
    "subsumption_final": const(size=10),
    "subsumption_component": const(size=10),
    # the query, t resolved, s resolved, both resolved
    "piece_vs_backward": const(backward=4, piece=4),
    # ten predicates of at most two places, two atoms: (10 (2 2)^2)^2
    "size_bounds": const(size=77, bound=25600.0, within=True),
    "family_sticky_sizes": const(largest=4),
    "generated_suite_summary": _suite_sql(),
    "rule_set_sizes": _table("ontology VARCHAR, rules BIGINT, constraints BIGINT", ("taxonomy", 222, 0), ("roles", 53, 0), ("staff", 87, 0), ("cliques", 34, 0), ("deep", 154, 19)),
    "subsumption_mode_rows": _table(
        "ontology VARCHAR, query INTEGER, none BIGINT, final BIGINT, component BIGINT, inline BIGINT",
        *((n, i, x, x, x, x) for n, rows in (("taxonomy", {i: r[0] for i, r in G.TAXONOMY_ROWS.items()}), ("roles", {i: r[4] for i, r in G.ROLES_ROWS.items()}), ("staff", {i: r[4] for i, r in G.STAFF_ROWS.items()}), ("path", {1: 6, 2: 10, 3: 13})) for i, x in rows.items()),
    ),
    # a class of a tree with a fan of 6 has one cover edge for each level above it; three chains of twenty predicates with five places; paths edge by edge
    "graph_rows": "WITH t(b) AS (VALUES (14), (9), (23), (2), (36), (4), (4), (2), (1), (222 - 95)) SELECT 'taxonomy' AS ontology, sum(b + 1)::BIGINT AS nodes, sum(b)::BIGINT AS propagation_edges, sum(least(b, 6) + 2 * greatest(0, least(b, 42) - 6) + 3 * greatest(0, b - 42))::BIGINT AS cover_edges, 3::BIGINT AS longest FROM t UNION ALL SELECT 'splitfull', 100, 95, 5 * 190, 19 UNION ALL SELECT 'path', 15, 17, 17 + 4 + 4 + 3, 3",
    "ontology_gain": " UNION ALL ".join(f"SELECT '{k}' AS ontology, (SELECT count(*) FROM ({c})) AS certain_rows, ({p}) AS plain_rows" for k, c, p in (("finance", _FIN, f"SELECT count(*) FROM ({_FIN_PLAIN})"), ("collab", _COLLAB, f"SELECT count(*) FROM ({_BASE})"), ("trade", _PARTY, "0"))),
    "answers_against_chase": const(unsound=0, missing=0),
    "query_graph_nodes": _table("atoms BIGINT, returned BOOLEAN, made_by VARCHAR, n BIGINT", (2, True, "start", 1), (2, True, "r", 2), (1, False, "f", 1)),
    "rewrite_cq_udtf": _table("atoms INTEGER, joins INTEGER, n BIGINT", (2, 1, 3)),
    "family_linear_sizes": const(size=64),
    "answer_aggregate": f"SELECT a3, count(*) AS n, count(DISTINCT a2) AS companies FROM ({_FIN}) GROUP BY a3",
    "answer_topk": f"SELECT a2, count(*) AS n FROM ({_FIN}) GROUP BY a2 ORDER BY n DESC, a2 LIMIT 10",
    "answer_window": f"SELECT * FROM (SELECT a3, a2, n, (row_number() OVER (PARTITION BY a3 ORDER BY n DESC, a2))::INTEGER AS rank FROM (SELECT a3, a2, count(*) AS n FROM ({_FIN}) GROUP BY a3, a2)) WHERE rank <= 3",
    "answer_setops": f"{_COLLAB} EXCEPT {_BASE}",
    "answer_rollup": f"SELECT a3, count(*) AS n FROM ({_FIN}) GROUP BY ROLLUP (a3)",
    "stream_events_certain": "SELECT DISTINCT user_id AS a1 FROM events WHERE event_type IN ('purchase', 'view') AND user_id IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F')",
}

QUERIES |= requests.QUERIES
ORACLES |= requests.ORACLES

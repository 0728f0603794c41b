"""Analyses and compilations for the rule sets and queries that the orders of a table ask for.

A line of `lineitem` is of one of six kinds, its return flag and its line status; an order asks for the distinct kinds of its
lines, in order ("af,no,ro"). What is asked for fixes a rule set or a query, each kind a rule or an atom of its own. Spark reads
the lines and counts the orders of each shape; its tasks then compile every shape once. The SQL derives the same from the lines.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ontospark.functions import metrics
from ontospark.logic import analysis
from ontospark.logic.parse import parse_ontology, parse_query
from ontospark.logic.unify import canonical
from ontospark.operators import baselines
from ontospark.operators.eliminate import cover_set, eliminate, reduce_query
from ontospark.operators.program import compile_program
from ontospark.operators.rewrite import Options, backward_rewrite, minimise
from ontospark.operators.split import decompose, split_rewrite
from ontospark.operators.subsume import prune
from ontospark.plans.ship import ship
from ontospark.workloads import ontologies as W
from ontospark.workloads import published as G

SINGLE = Options(subsets="single")
_TYPES = {"string": pa.string(), "long": pa.int64(), "double": pa.float64(), "boolean": pa.bool_()}
#: Each shape's kinds with their places (from 1) and the number m of them; o has the orders of each shape.
_SHAPES = (
    "WITH k AS (SELECT DISTINCT l_orderkey, lower(l_returnflag || l_linestatus) AS kind FROM lineitem WHERE l_returnflag IS NOT NULL AND l_linestatus IS NOT NULL), "
    "o AS (SELECT shape, count(*) AS orders FROM (SELECT string_agg(kind, ',' ORDER BY kind) AS shape FROM k GROUP BY l_orderkey) GROUP BY shape), "
    "a AS (SELECT shape, orders, unnest(string_split(shape, ',')) AS kind FROM o), "
    "s AS (SELECT *, row_number() OVER (PARTITION BY shape ORDER BY kind) AS i, count(*) OVER (PARTITION BY shape) AS m FROM a) "
)


def shapes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """shape, orders: what the orders ask for and how many ask for it; lines without a flag or status count for nothing."""
    lines = spark.read.parquet(f"{sf_dir}/lineitem.parquet").where("l_returnflag IS NOT NULL AND l_linestatus IS NOT NULL")
    asked = lines.groupBy("l_orderkey").agg(F.array_sort(F.collect_set(F.lower(F.concat("l_returnflag", "l_linestatus")))).alias("kinds"))
    return asked.groupBy(F.array_join("kinds", ",").alias("shape")).agg(F.count(F.lit(1)).alias("orders"))


def compiled(make: Callable[[list[str]], Iterable[tuple]], fields: str) -> Callable[[SparkSession, str], DataFrame]:
    """A query that runs make(kinds) in a task for every shape; its rows follow the shape and its orders.

    Shapes are dealt in turn to as many tasks as there can be shapes, since some take far longer than others; dealt by shape they
    stay as the count left them, which Spark puts into one task.
    """
    kinds = f"shape string, orders long, {fields}"
    schema = pa.schema([(n, _TYPES[t]) for n, t in (f.split() for f in kinds.split(", "))])

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for shape, orders in zip(b.column("shape").to_pylist(), b.column("orders").to_pylist(), strict=True):
                out = [(shape, orders, *r) for r in make(shape.split(","))]
                yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], f.type) for i, f in enumerate(schema)], schema=schema)

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        return shapes(spark, sf_dir).repartition(2**6 - 1).mapInArrow(rows, kinds)

    return query


def _parsed(*rules: str):
    return parse_ontology("\n".join(rules)).tgds if rules else ()


def _normal(text: str):
    return analysis.normalise(G.parsed(text).tgds)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


# --- affected positions: each kind hands a new value to the next, the last to the first ------------------------------


def _affected(kinds):
    t = _parsed(*(f"{k}(X,Y) => {n}(Y,Z)" for k, n in zip(kinds, kinds[1:] + kinds[:1], strict=True)))
    return sorted((r.id, f"{p.pred}[{p.i}]") for r in t for p in analysis.affected(r, t))


QUERIES["affected_positions"] = compiled(_affected, "rule string, position string")
ORACLES["affected_positions"] = _SHAPES + (
    "SELECT s.shape, s.orders, concat('s', s.i) AS rule, concat(n.kind, '[', p, ']') AS position FROM s, (VALUES (2, 1), (1, 2)) v(p, ahead), s n "
    "WHERE n.shape = s.shape AND n.i = (s.i - 1 + ahead) % s.m + 1"
)

# --- cache profile: paths as long as the order asks for, three steps at most -----------------------------------------


def _profile(kinds):
    t = G.parsed(W.PATH).tgds
    r = backward_rewrite(parse_query(W.path_query((len(kinds) + 1) // 2)), t, Options(subsets="single", eliminate=lambda q: reduce_query(q, t)))
    prune(r.union, r.graph, r.caches)
    return r.caches.profile()


QUERIES["cache_profile"] = compiled(_profile, "operation string, calls long, repeat_percent double, distinct_inputs long")

# --- chase and backchase: of one flag, the finished kind implies the open one ----------------------------------------


def _backchase(kinds):
    t = analysis.normalise(_parsed(*(f"{a}(X) => {b}(X)" for a in kinds for b in kinds if a[0] == b[0] and a < b), "af(X) => filed(X,Y)"))
    q = parse_query(f"p(A) <- {', '.join(f'{k}(A)' for k in kinds)}")
    out = baselines.chase_backchase(q, t, 4)
    return [(len(out), len(out[0].body), out[0] == canonical(reduce_query(q, t)))]


QUERIES["chase_backchase"] = compiled(_backchase, "plans long, atoms long, same boolean")
ORACLES["chase_backchase"] = _SHAPES + "SELECT shape, orders, 1::BIGINT AS plans, count(DISTINCT kind[1]) AS atoms, true AS same FROM s GROUP BY shape, orders"

# --- cliques: a kind of edge, a flag and its product with the next one for each kind asked for ------------------------


def _cliques(kinds):
    t = analysis.normalise(
        _parsed(
            *(f"kind_{k}(X,Y) => link(X,Y)" for k in kinds), "link(X,Y), link(Y,Z), link(X,Z) => three(X,Y,Z)", "three(X,Y,Z), link(X,W), link(Y,W), link(Z,W) => four(X,Y,Z,W)",
            *(r for a, b in zip(kinds, kinds[1:]) for r in (f"flag_{a}(X), flag_{b}(Y) => pair_{a}(X,Y)", f"pair_{a}(X,Y) => mixed(X,Y)")),
        )
    )
    programs = [(i, compile_program(parse_query(q), t, SINGLE)) for i, q in G.CLIQUES_Q.items()]
    return [(i, len(p.views), p.flat_size()) for i, p in programs]


QUERIES["clique_metrics"] = compiled(_cliques, "query long, views long, flat_size long")
#: An edge is a link or of one of m kinds; a product is mixed, or one of m - 1 pairs, each as it is or as two flags, which are views of their own.
ORACLES["clique_metrics"] = _SHAPES + (
    ", e AS (SELECT DISTINCT shape, orders, m, (m + 1) * (m + 1) * (m + 1) AS c FROM s) "
    "SELECT shape, orders, 1::BIGINT AS query, 1::BIGINT AS views, m + 1 AS flat_size FROM e UNION ALL SELECT shape, orders, 2, CASE WHEN m > 1 THEN m + 1 ELSE 1 END, 2 * m - 1 FROM e "
    "UNION ALL SELECT shape, orders, 3, 2, 1 + c FROM e UNION ALL SELECT shape, orders, 4, 3, 1 + c * (1 + c) FROM e"
)

# --- cover graph: each kind is turned round into the next --------------------------------------------------------------


def _cover(kinds):
    t = _parsed(*(f"{a}(X,Y) => {b}(Y,X)" for a, b in zip(kinds, kinds[1:])))
    return sorted((f"{a.pred}[{a.i}]", f"{b.pred}[{b.i}]", ">".join(x)) for a, b, x in analysis.cover_graph(t))


QUERIES["cover_graph_edges"] = compiled(_cover, "source string, target string, label string")
ORACLES["cover_graph_edges"] = _SHAPES + (
    "SELECT s.shape, s.orders, concat(s.kind, '[', p, ']') AS source, concat(n.kind, '[', CASE WHEN (n.i - s.i) % 2 = 0 THEN p ELSE 3 - p END, ']') AS target, "
    "array_to_string(list_transform(range(s.i, n.i), lambda x: concat('s', x)), '>') AS label FROM s JOIN s n ON n.shape = s.shape AND n.i > s.i, (VALUES (1), (2)) v(p)"
)

# --- components: a path through the kinds, where the finished kind of a flag hands a new value to the open one --------


def _components(kinds):
    t = analysis.normalise(_parsed(*(r for f in "anr" for r in (f"start_{f}(X) => {f}f(X,Y)", f"{f}f(X,Y) => {f}o(Y,Z)"))))
    q = parse_query(f"p(V0) <- {', '.join(f'{k}(V{i},V{i + 1})' for i, k in enumerate(kinds))}")
    return [(",".join(sorted(a.pred for a in p.body)), ",".join(map(str, p.head))) for p in decompose(q, t)]


QUERIES["decomposition_components"] = compiled(_components, "atoms string, head string")
#: A flag's kinds are one component; its variables that others share are the first and, unless the path ends there, the last.
ORACLES["decomposition_components"] = _SHAPES + (
    "SELECT shape, orders, string_agg(kind, ',' ORDER BY kind) AS atoms, concat('V', min(i) - 1, CASE WHEN max(i) < m THEN concat(',V', max(i)) ELSE '' END) AS head FROM s GROUP BY shape, orders, m, kind[1]"
)

# --- decomposition: a class of the wide taxonomy for each kind, with roles between neighbours --------------------------
_CLASS = {"af": ("town", 3), "ao": ("trade", 2), "nf": ("place", 3), "no": ("era", 5), "rf": ("guild", 5), "ro": ("person", 10)}


def _decomposed(kinds):
    atoms = [f"{_CLASS[k][0]}(V{i})" for i, k in enumerate(kinds)] + [f"met(V{i},V{i + 1})" for i in range(len(kinds) - 1)]
    s = split_rewrite(parse_query(f"p({','.join(f'V{i}' for i in range(len(kinds)))}) <- {', '.join(atoms)}"), _normal(G.TAXONOMY), SINGLE)
    return [(len(s.parts), len(s.union), s.explored)]


QUERIES["decomposition_rows"] = compiled(_decomposed, "components long, size long, explored long")
#: A class stands for itself and what is below it: sizes multiply, what is explored adds up.
ORACLES["decomposition_rows"] = _SHAPES + (
    f"SELECT shape, orders, 2 * m - 1 AS components, product(n)::BIGINT AS size, (sum(n) + m - 1)::BIGINT AS explored FROM s JOIN (VALUES {', '.join(f"('{k}', {n})" for k, (_, n) in _CLASS.items())}) c(kind, n) USING (kind) GROUP BY shape, orders, m"
)

# --- elimination: bills that are paid, and an atom over the roles for each kind ---------------------------------------
_ATOM = {"af": "payer(B)", "ao": "bill(C)", "nf": "desk(A)", "no": "quote(D)", "rf": "lists(E,F)", "ro": "paper_list(E)"}


def _roles_query(kinds):
    atoms = ["pays(B,C)", *(_ATOM[k] for k in kinds)]
    return parse_query(f"p({','.join(sorted({v for a in atoms for v in a if v in 'ABCDEF'}))}) <- {', '.join(atoms)}")


def _covers(kinds):
    q, t = _roles_query(kinds), _normal(G.ROLES)
    left = eliminate(q, t, passes="fixpoint")
    return [(b.pred, len(cover_set(b, q, t)), b in left) for b in q.body]


QUERIES["elimination_cover_sets"] = compiled(_covers, "atom string, covers long, gone boolean")
#: Domain and range of a role that is asked for as well are implied by it.
ORACLES["elimination_cover_sets"] = _SHAPES + (
    f", x AS (SELECT shape, orders, kind, list_contains(string_split(shape, ','), 'rf') AS lists FROM s UNION ALL SELECT shape, orders, '', false FROM o) "
    f"SELECT shape, orders, atom, (CASE WHEN gone THEN 1 ELSE 0 END)::BIGINT AS covers, gone FROM (SELECT shape, orders, atom, kind IN ('af', 'ao') OR (kind = 'ro' AND lists) AS gone FROM x JOIN (VALUES ('', 'pays'), {', '.join(repr((k, a.split('(')[0])) for k, a in _ATOM.items())}) v(kind, atom) USING (kind))"
)


def _reducing(t):
    return Options(subsets="single", eliminate=lambda x: reduce_query(x, t))


def _sizes(union):
    return len(union), metrics.n_atoms(union), metrics.joins_pairs(union)


def _eliminated(kinds):
    q, t = _roles_query(kinds), _normal(G.ROLES)
    base, less = backward_rewrite(q, t, SINGLE), backward_rewrite(reduce_query(q, t), t, _reducing(t))
    return [tuple(x for r in (base, less) for x in (*_sizes(r.union), r.explored_r))]


_COUNTS = ("size", "atoms", "joins", "explored")
QUERIES["elimination_rows"] = compiled(_eliminated, ", ".join(f"{p}{c} long" for p in ("base_", "") for c in _COUNTS))
#: Ways of each atom: a role or its inverse; a domain or range also as its role in both directions; the desk with three below it.
ORACLES["elimination_rows"] = _SHAPES + (
    ", x AS (SELECT shape, orders, m, list_contains(string_split(shape, ','), 'rf') AND list_contains(string_split(shape, ','), 'ro') AS two, product(n) * 2 AS n, "
    "product(CASE WHEN kind IN ('af', 'ao') THEN 1 ELSE n END) * 2 AS kept, count(*) FILTER (WHERE kind IN ('af', 'ao')) AS implied "
    "FROM s JOIN (VALUES ('af', 3), ('ao', 3), ('nf', 6), ('no', 3), ('rf', 2), ('ro', 3)) w(kind, n) USING (kind) GROUP BY shape, orders, m), "
    "y AS (SELECT shape, orders, n::BIGINT AS b, m + 1 AS ba, implied + two::BIGINT AS bj, (CASE WHEN two THEN kept / 3 ELSE kept END)::BIGINT AS l, m + 1 - implied - two::BIGINT AS la FROM x) "
    "SELECT shape, orders, b AS base_size, b * ba AS base_atoms, b * bj AS base_joins, b AS base_explored, l AS size, l * la AS atoms, 0::BIGINT AS joins, l AS explored FROM y"
)

# --- times and peaks of compiling: medians of ten runs each, for all kinds asked for ---------------------------------


def _measures(kinds):
    q, t = _roles_query(kinds), _normal(G.ROLES)
    base = metrics.measured(lambda: backward_rewrite(q, t, SINGLE))
    split = metrics.measured(lambda: split_rewrite(q, t, SINGLE, eliminate=True, output="folded"))
    return [(base["median_ms"], base["peak_mb"], split["median_ms"], split["peak_mb"], metrics.significant_medians(base, split))]


QUERIES["compile_measures"] = compiled(_measures, "base_ms double, base_mb double, split_ms double, split_mb double, significant boolean")

# --- deep rules with invented values: what the device of the first kind does for the ability of the last ---------------


def _deep(kinds):
    first, last = (1 + ("af", "ao", "nf", "no", "rf", "ro").index(k) for k in (kinds[0], kinds[-1]))
    q, t = parse_query(f"p(A) <- device_{first}(A), helps_{last}(A,B), ability_{last}(B)"), _normal(G.DEEP)
    base, less = backward_rewrite(q, t, SINGLE), backward_rewrite(reduce_query(q, t), t, Options(subsets="single", eliminate=lambda x: reduce_query(x, t)))
    pruned = [{canonical(minimise(x)) for x in prune(r.union, r.graph)} for r in (base, less)]
    return [(len(less.union) <= len(base.union), less.explored_r <= base.explored_r, pruned[0] == pruned[1])]


QUERIES["deep_rows"] = compiled(_deep, "not_larger boolean, not_more_explored boolean, same_pruned boolean")
ORACLES["deep_rows"] = _SHAPES + "SELECT shape, orders, true AS not_larger, true AS not_more_explored, true AS same_pruned FROM o"

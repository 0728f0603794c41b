"""Connected components of an edge table by contraction to least neighbours."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ontospark.llm._frames import cut


def components(edges: DataFrame) -> DataFrame:
    """edges(a long, b long) -> (node, root): the least node reachable. Nodes without an edge don't occur.

    In each round every node takes the label of its least neighbour's least neighbour, if lesser, and edges are
    carried over to labels; the least node of a component keeps its own. Ids are hashes, so in expectation a
    round leaves a fraction of the nodes, and finished components no edge. Each round is a table in the shared
    folder; at the end the rounds' labels are followed, from the last one back.
    """
    left = cut(edges.where("a <> b").selectExpr("least(a, b) AS a", "greatest(a, b) AS b").distinct())
    rounds = []
    while not left.isEmpty():
        both = left.union(left.selectExpr("b", "a"))
        least = cut(both.groupBy("a").agg(F.min("b").alias("m")).selectExpr("a AS node", "least(a, m) AS up"))
        top = least.selectExpr("node AS at", "up AS top")
        step = cut(least.join(top, least.up == top.at).select("node", F.col("top").alias("root")))
        rounds.append(step)
        x, y = step.selectExpr("node AS a", "root AS x"), step.selectExpr("node AS b", "root AS y")
        moved = left.join(x, "a").join(y, "b").where("x <> y")
        left = cut(moved.selectExpr("least(x, y) AS a", "greatest(x, y) AS b").distinct())
    if not rounds:
        return left.selectExpr("a AS node", "b AS root")
    found = rounds.pop()
    while rounds:
        later = found.selectExpr("node AS at", "root AS top")
        step = rounds.pop()
        found = cut(step.join(later, step.root == later.at, "left").select("node", F.coalesce("top", "root").alias("root")))
    return found

"""Exact top-k inner-product search with a dual cover tree.

Queries and data lie in one tree. Its upper levels are a cover tree of a bounded sample (every level is a net of
half the radius of the one above, and keeps the points of that level); every row then hangs below its nearest
leaf pivot, and its lower levels are built where the rows are: a block of at most BLOCK rows of a leaf holds nodes
of about NODE_ROWS rows with a centre and a covering radius.

Neighbouring leaves are packed into query groups of at most GROUP rows, so a data block is sent once for each
group that needs it, not for each leaf. A leaf is sent to a group unless the best inner product that the covering
radii allow stays below the group's worst k-th score, which a first pass over the group's own blocks bounds. Inside
a task a group meets its blocks in the order of their bounds and keeps k rows for each query; a node of a block is
multiplied only with the queries whose k-th score its radius may still beat. A leaf or a group that holds a third
of all rows is many blocks.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ontospark.llm._frames import batch, cut, parallelism, rows_of
from ontospark.plans.ship import ship

#: Rows of a data block, of one of its nodes, of a query group, and of a piece of a group's result.
BLOCK, NODE_ROWS, GROUP, PIECE = 1024, 64, 4096, 256
#: Leaves of the upper tree (one for LEAF_ROWS rows) and sampled vectors for each leaf; the whole sample is NODES times that.
NODES, LEAF_ROWS, SAMPLE_PER_LEAF = 1024, 4096, 16


class CoverTree:
    """Levels of pivots; node 0 of level 0 covers all. Built on the driver from a bounded sample."""

    def __init__(self, points: np.ndarray, nodes: int):
        self.levels, self.parents = [points[:1]], [np.zeros(1, int)]
        near = _distance(points, points[:1])[:, 0] if len(points) else np.zeros(0)
        r = float(near.max()) if len(points) else 0.0
        while r > 1e-9 and len(self.levels[-1]) < nodes:
            r /= 2
            net = list(self.levels[-1])
            while near.max() > r and len(net) < nodes:
                k = int(near.argmax())
                net.append(points[k])
                near = np.minimum(near, _distance(points, points[k : k + 1])[:, 0])
            new = np.array(net)
            self.parents.append(_distance(new, self.levels[-1]).argmin(1))
            self.levels.append(new)
        self.leaves = self.levels[-1]

    def order(self) -> list[int]:
        """Leaves in the order of a walk through the tree, so neighbours in it are near each other."""
        path = [np.arange(len(self.leaves))]
        for par in self.parents[:0:-1]:
            path.insert(0, par[path[0]])
        return sorted(range(len(self.leaves)), key=lambda i: tuple(int(p[i]) for p in path))

    def pairs(self, q_radius: np.ndarray, x_radius: np.ndarray, worst: np.ndarray, has_q: np.ndarray, has_x: np.ndarray) -> np.ndarray:
        """Which leaf pairs (queries, data) may still hold one of the k best; radii and worst k-th scores are given for leaves."""
        qr, xr, low, hq, hx = [q_radius], [x_radius], [worst], [has_q], [has_x]
        for d in range(len(self.levels) - 1, 0, -1):
            up, own, par = self.levels[d - 1], self.levels[d], self.parents[d]
            step = np.sqrt(((own - up[par]) ** 2).sum(1))
            n = len(up)
            a, b, c, e, f = np.zeros(n), np.zeros(n), np.full(n, np.inf), np.zeros(n, bool), np.zeros(n, bool)
            np.maximum.at(a, par, np.where(hq[0], step + qr[0], 0))
            np.maximum.at(b, par, np.where(hx[0], step + xr[0], 0))
            np.minimum.at(c, par, np.where(hq[0], low[0], np.inf))
            np.logical_or.at(e, par, hq[0])
            np.logical_or.at(f, par, hx[0])
            for x, v in zip((qr, xr, low, hq, hx), (a, b, c, e, f), strict=True):
                x.insert(0, v)
        live = np.ones((1, 1), bool)
        for d, c in enumerate(self.levels):
            if d:
                live = live[np.ix_(self.parents[d], self.parents[d])]
            size = np.sqrt((c**2).sum(1))
            best = c @ c.T + size[:, None] * xr[d][None] + qr[d][:, None] * (size + xr[d])[None]
            live = live & hq[d][:, None] & hx[d][None] & (best + 1e-6 * np.abs(best) + 1e-6 >= low[d][:, None])
        return live


def _distance(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum(0, (a**2).sum(1)[:, None] + (b**2).sum(1)[None] - 2 * a @ b.T))


_ASSIGNED = pa.schema([("vec_id", pa.int64()), ("node", pa.int32()), ("dist", pa.float64()), ("v", pa.binary())])


def _matrix(rows: list, dim: int) -> np.ndarray:
    out = np.zeros((len(rows), dim))
    for i, r in enumerate(rows):
        out[i, : len(r)] = r
    return out


def _kind(top: float) -> str:
    """The narrowest type that holds all components."""
    return next(k for k, most in (("<i1", 1 << 7), ("<i2", 1 << 15), ("<i4", 1 << 31), ("<i8", 1 << 63)) if top < most)


def _assign(leaves: np.ndarray, dim: int, kind: str):
    def of(batches):
        for b in batches:
            for lo in range(0, b.num_rows, 2048):
                rows = list(rows_of([b.slice(lo, 2048)], "vec_id", "v"))
                m = _matrix([r[1] for r in rows], dim)
                near = ((leaves**2).sum(1)[None] - 2 * m @ leaves.T).argmin(1)
                dist = np.sqrt(((m - leaves[near]) ** 2).sum(1))
                yield batch(_ASSIGNED, [[r[0] for r in rows], near.tolist(), dist.tolist(), [x.tobytes() for x in m.astype(kind)]])

    return of


_BLOCK = pa.schema([("place", pa.int32()), ("sub", pa.int32()), ("ids", pa.binary()), ("m", pa.binary()), ("sizes", pa.binary())])


def nodes_of(m: np.ndarray, rows: int) -> tuple[np.ndarray, np.ndarray]:
    """The lower tree of a block: an order of its rows that brings each node together, and the nodes' sizes."""
    n = -(-len(m) // rows)
    pick, near = [0], _distance(m, m[:1])[:, 0]
    while len(pick) < n and near.max() > 0:
        pick.append(int(near.argmax()))
        near = np.minimum(near, _distance(m, m[pick[-1] : pick[-1] + 1])[:, 0])
    own = _distance(m, m[pick]).argmin(1)
    return np.argsort(own, kind="stable"), np.bincount(own, minlength=len(pick))


def _blocks(dim: int, kind: str):
    def of(key: tuple[pa.Scalar, ...], group: pa.Table) -> pa.Table:
        ids = np.array(group.column("vec_id").to_pylist(), "<i8")
        m = np.frombuffer(b"".join(group.column("v").to_pylist()), kind).reshape(-1, dim)
        by_id = np.argsort(ids, kind="stable")
        order, sizes = nodes_of(m[by_id].astype(float), NODE_ROWS)
        order = by_id[order]
        return pa.Table.from_batches([batch(_BLOCK, [[key[0].as_py()], [key[1].as_py()], [ids[order].tobytes()], [m[order].tobytes()], [sizes.astype("<i4").tobytes()]])])

    return of


def _product(q: np.ndarray, x: np.ndarray, most: float) -> np.ndarray:
    """Integer inner products, exact: float32 or float64 where every sum fits the mantissa, else 64-bit integers."""
    kind = np.float32 if most < 1 << 24 else np.float64 if most < 1 << 53 else np.int64
    return q.astype(kind) @ x.astype(kind).T


_NONE, _LAST = -(1 << 63), (1 << 63) - 1


class Best:
    """The k best rows of each query of a group so far, and how many products that took."""

    def __init__(self, ids: np.ndarray, q: np.ndarray, k: int, most: float):
        self.q_ids, self.q, self.k, self.most = ids, q, k, most
        self.ids, self.score = np.full((len(q), k), _LAST), np.full((len(q), k), _NONE)
        self.norm = np.sqrt((q.astype(float) ** 2).sum(1))
        self.products = 0

    def meet(self, ids: np.ndarray, x: np.ndarray, sizes: np.ndarray) -> None:
        """Nodes that no query can gain from are left out; the others meet the queries that can."""
        at = np.concatenate([[0], np.cumsum(sizes)])
        wide = x.astype(float)
        centre = np.array([wide[i:j].mean(0) for i, j in zip(at[:-1], at[1:], strict=True)])
        radius = np.array([np.sqrt(((wide[i:j] - c) ** 2).sum(1).max()) for i, j, c in zip(at[:-1], at[1:], centre, strict=True)])
        bound = self.q.astype(float) @ centre.T + self.norm[:, None] * radius[None]
        may = bound + 1e-6 * np.abs(bound) + 1e-6 >= self.score[:, -1:].astype(float)
        if may.all():
            self._meet(np.arange(len(self.q)), ids, x)
            return
        for j in np.flatnonzero(may.any(0)):
            self._meet(np.flatnonzero(may[:, j]), ids[at[j] : at[j + 1]], x[at[j] : at[j + 1]])

    def _meet(self, rows: np.ndarray, ids: np.ndarray, x: np.ndarray) -> None:
        s = _product(self.q[rows], x, self.most)
        self.products += s.size
        if len(own := np.flatnonzero(np.isin(ids, self.q_ids))):
            s[:, own] = np.where(self.q_ids[rows, None] == ids[None, own], s.dtype.type(_NONE), s[:, own])
        kth = self.score[rows, -1:].astype(s.dtype)
        may = s > kth
        if (tie := (s == kth) & (s > _NONE)).any():
            may |= tie & (ids[None] < self.ids[rows, -1:])
        many = np.flatnonzero(may.sum(1) > self.k)
        if len(many):  # of one row's gains only its k best, smaller ids first
            rank = np.empty(len(ids), np.int64)
            rank[np.argsort(ids, kind="stable")] = np.arange(len(ids))
            if self.most * len(ids) < 1 << 52:
                whole = s[many].astype(float) * len(ids) - rank
                may[many] &= whole >= np.partition(whole, -self.k, axis=1)[:, -self.k, None]
            else:
                for i in many:
                    c = np.flatnonzero(may[i])
                    may[i, c[np.lexsort((rank[c], -s[i, c]))][self.k :]] = False
        hit = np.flatnonzero(may.any(1))
        if not len(hit):
            return
        r, c = np.nonzero(may[hit])
        width = int(np.bincount(r).max())
        place = np.arange(len(r)) - np.searchsorted(r, r)
        new, who = np.full((len(hit), width), _NONE), np.full((len(hit), width), _LAST)
        new[r, place], who[r, place] = s[hit[r], c].astype(np.int64), ids[c]
        rows = rows[hit]
        new, who = np.concatenate([self.score[rows], new], 1), np.concatenate([self.ids[rows], who], 1)
        order = np.lexsort((who, -np.maximum(new, _NONE + 1)), axis=1)[:, : self.k]
        self.score[rows], self.ids[rows] = np.take_along_axis(new, order, 1), np.take_along_axis(who, order, 1)


_WORST = pa.schema([("place", pa.int32()), ("sub", pa.int32()), ("kth", pa.int64())])
_FOUND = pa.schema([("query_id", pa.int64()), ("q_key", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64())])


def _read(ids: bytes, m: bytes, sizes: bytes, dim: int, kind: str):
    return np.frombuffer(ids, "<i8"), np.frombuffer(m, kind).reshape(-1, dim), np.frombuffer(sizes, "<i4")


def _seed(dim: int, kind: str, k: int, most: float):
    """The worst k-th score of a group's queries over one of its own blocks."""

    def of(batches):
        for place, sub, qi, qm, xi, xm, sizes in rows_of(batches, "place", "sub", "q_ids", "q_m", "ids", "m", "sizes"):
            best = Best(np.frombuffer(qi, "<i8"), np.frombuffer(qm, kind).reshape(-1, dim), k, most)
            best.meet(*_read(xi, xm, sizes, dim, kind))
            yield batch(_WORST, [[place], [sub], [int(best.score[:, -1].min())]])

    return of


def _search(dim: int, kind: str, k: int, most: float):
    """Rows: a group's queries (side 0), then its blocks, nearest first; a group's k best leave when the next one starts."""

    def of(batches):
        best, key = None, None

        def drain():
            if best is None:
                return
            for lo in range(0, len(best.q), PIECE):
                s, who = best.score[lo : lo + PIECE], best.ids[lo : lo + PIECE]
                r, c = np.nonzero(s > _NONE)
                tag = (key[0] << 40) + (key[1] << 20)
                yield batch(_FOUND, [best.q_ids[lo + r].tolist(), (tag + lo + r).tolist(), who[r, c].tolist(), s[r, c].tolist()])

        for place, sub, part, side, ids, m, sizes in rows_of(batches, "q_place", "q_sub", "part", "side", "ids", "m", "sizes"):
            if side == 0:
                yield from drain()
                key = (place, sub, part)
                best = Best(np.frombuffer(ids, "<i8"), np.frombuffer(m, kind).reshape(-1, dim), k, most)
            elif key == (place, sub, part):
                best.meet(*_read(ids, m, sizes, dim, kind))
        yield from drain()

    return of


def top_k(vectors: DataFrame, is_query, k: int = 20, scale: float = 64.0) -> DataFrame:
    """The k rows of highest integer inner product for each query row (is_query: a condition on vec_id).

    vectors: vec_id, embedding (array of float or double). Components become floor(scale * x), x as double.
    Candidates are all rows with another vec_id. Returns query_id, rank (from 1), vec_id, score; ties go to the
    smaller vec_id; all candidates if there are fewer than k. Vectors that are null or hold a null or non-finite
    component, and rows without id, take no part. Shorter vectors count as padded with zeros. Query rows that
    repeat id and vector are one query; other repeated ids are rows of their own. No rows: no rows. Vectors whose
    products could leave 64 bits raise ValueError.
    """
    spark = vectors.sparkSession
    ship(spark)
    n = parallelism(spark)
    good = vectors.where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull()).where(
        F.forall("embedding", lambda x: F.coalesce(~F.isnan(x.cast("double")) & (F.abs(x.cast("double")) < float("inf")), F.lit(False)))
    )
    ints = good.select(F.col("vec_id").cast("long").alias("vec_id"), F.transform("embedding", lambda x: F.floor(x.cast("double") * scale).cast("double")).alias("v"))
    rows, dim, top = ints.agg(F.count(F.lit(1)), F.max(F.size("v")), F.max(F.array_max(F.transform("v", F.abs)))).first()
    if not rows:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    dim, top = max(dim or 0, 1), float(top or 0)
    most = top**2 * dim
    if most >= 1 << 62:
        raise ValueError("inner products may leave 64 bits: use a smaller scale")
    kind = _kind(top + 1)
    nodes = max(1, min(NODES, rows // LEAF_ROWS))
    sample = ints.orderBy(F.xxhash64("vec_id"), "vec_id").limit(SAMPLE_PER_LEAF * nodes).collect()
    tree = CoverTree(_matrix([r[1] for r in sample], dim), nodes)
    m = len(tree.leaves)
    placed = cut(ints.mapInArrow(_assign(tree.leaves, dim, kind), "vec_id long, node int, dist double, v binary").withColumn("q", is_query(F.col("vec_id"))))
    stat = placed.groupBy("node").agg(F.count(F.lit(1)).alias("n"), F.max("dist").alias("xr"), F.sum(F.col("q").cast("long")).alias("nq"), F.max(F.when(F.col("q"), F.col("dist"))).alias("qr")).collect()
    xr, qr, nx, nq = np.zeros(m), np.zeros(m), np.zeros(m, int), np.zeros(m, int)
    for r in stat:
        xr[r["node"]], qr[r["node"]], nx[r["node"]], nq[r["node"]] = r["xr"], r["qr"] or 0.0, r["n"], r["nq"] or 0
    group, load = np.zeros(m, int), []  # query groups: neighbouring leaves of together at most GROUP queries, or one leaf
    for leaf in tree.order():
        if not load or load[-1] + nq[leaf] > GROUP:
            load.append(0)
        load[-1] += int(nq[leaf])
        group[leaf] = len(load) - 1

    def blocks(df: DataFrame, place: np.ndarray, parts: np.ndarray) -> DataFrame:
        where = spark.createDataFrame([(i, int(place[i]), int(parts[i])) for i in range(m)], "node int, place int, parts int")
        dealt = df.join(F.broadcast(where), "node").withColumn("sub", F.pmod(F.xxhash64("vec_id"), F.col("parts")).cast("int"))
        return cut(dealt.select("place", "sub", "vec_id", "v").groupBy("place", "sub").applyInArrow(_blocks(dim, kind), "place int, sub int, ids binary, m binary, sizes binary"))

    split = np.array([max(1, -(-load[group[i]] // GROUP)) for i in range(m)])
    data = blocks(placed, np.arange(m), np.maximum(1, -(-nx // BLOCK)))
    ask = blocks(placed.where("q").dropDuplicates(["vec_id", "v"]), group, split).drop("sizes")
    worst = np.full(m, -np.inf)
    if len(load) > 1:  # one group needs everything anyway
        own = spark.createDataFrame([(int(group[i]), i) for i in range(m) if nq[i]], "place int, leaf int")
        first = data.where("sub < 2").select(F.col("place").alias("leaf"), "ids", "m", "sizes")
        seeds = ask.select("place", "sub", F.col("ids").alias("q_ids"), F.col("m").alias("q_m")).join(F.broadcast(own), "place").join(first, "leaf").repartition(n)
        bounds = seeds.mapInArrow(_seed(dim, kind, k, most), "place int, sub int, kth long").groupBy("place", "sub").agg(F.max("kth").alias("kth"))
        got = {r["place"]: r for r in bounds.groupBy("place").agg(F.min("kth").alias("kth"), F.count(F.lit(1)).alias("n")).collect()}
        for i in range(m):
            r = got.get(group[i])
            if r is not None and r["n"] == split[i] and r["kth"] > _NONE:
                worst[i] = r["kth"]
    live = tree.pairs(qr, xr, worst, nq > 0, nx > 0)
    need = np.zeros((len(load), m), bool)
    np.logical_or.at(need, group, live)
    near = np.full((len(load), m), -np.inf)
    np.maximum.at(near, group, np.where(live, tree.leaves @ tree.leaves.T, -np.inf))
    wanted = spark.createDataFrame([(int(g), int(x), float(near[g, x]), max(1, -(-load[g] // GROUP))) for g, x in zip(*np.nonzero(need), strict=True)], "q_place int, place int, near double, subs int")
    n_groups = sum(max(1, -(-x // GROUP)) for x in load)
    ranges = max(1, min(-(-n // n_groups), int((-(-nx // BLOCK)).sum())))
    q_side = ask.select(F.col("place").alias("q_place"), F.col("sub").alias("q_sub"), "ids", "m", F.explode(F.sequence(F.lit(0), F.lit(ranges - 1))).alias("part")).selectExpr("q_place", "q_sub", "part", "0 AS side", "0D AS near", "ids", "m", "X'' AS sizes")
    x_side = data.withColumn("part", F.pmod(F.xxhash64("place", "sub"), F.lit(ranges)).cast("int")).join(F.broadcast(wanted), "place").withColumn("q_sub", F.explode(F.sequence(F.lit(0), F.col("subs") - 1)))
    x_side = x_side.selectExpr("q_place", "q_sub", "part", "1 AS side", "near", "ids", "m", "sizes")
    work = q_side.unionByName(x_side).repartition(n, "q_place", "q_sub", "part").sortWithinPartitions("q_place", "q_sub", "part", "side", F.desc("near"))
    found = work.mapInArrow(_search(dim, kind, k, most), "query_id long, q_key long, vec_id long, score long")
    order = Window.partitionBy("query_id", "q_key").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")

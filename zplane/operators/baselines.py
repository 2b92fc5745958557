"""The methods that the plane walk is compared with; inputs and outputs equal those of knn and link_clusters."""

from __future__ import annotations

import math
from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from zplane.components import components
from zplane.functions.bounds import dist2
from zplane.operators.knn import QUERY, SOURCE, domain_rows, joint_tree, knn, knn_probe, probe_kernel, rows_kernel, squared
from zplane.operators.linking import MARK, link_edges
from zplane.plans import walk
from zplane.plans.planes import Options
from zplane.session import release, ship, stored


def _ends(src: DataFrame, q: DataFrame | None, cols: list[str], id_col: str):
    q = src if q is None else q
    a = q.select(F.col(id_col).cast("long").alias("qid"), *(F.col(c).cast("double").alias(f"q{i}") for i, c in enumerate(cols)))
    b = src.select(F.col(id_col).cast("long").alias("sid"), *(F.col(c).cast("double").alias(f"x{i}") for i, c in enumerate(cols)))
    return a, b


def _blocks(groups: DataFrame, k: int, d: int, box=None) -> DataFrame:
    """The k nearest of every query over the groups (g, h) that it is in, each searched by tiles in a task."""
    near = groups.groupBy("g", "h").applyInArrow(probe_kernel(d, k, box), "qid long, sid long, d2 double")
    rank = F.row_number().over(W.partitionBy("qid").orderBy("d2", "sid"))
    return near.withColumn("rank", rank).where(F.col("rank") <= k).select("qid", F.col("rank").cast("int").alias("rank"), "sid", F.sqrt("d2").alias("dist"))


def _kinds(a: DataFrame, b: DataFrame, d: int) -> DataFrame:
    """Queries a and sources b (each with g and h) as rows of one table."""
    asks = a.select("g", "h", F.lit(QUERY).alias("kind"), F.col("qid").alias("id"), *(F.col(f"q{i}").alias(f"x{i}") for i in range(d)))
    return asks.unionAll(b.select("g", "h", F.lit(SOURCE).alias("kind"), F.col("sid").alias("id"), *(f"x{i}" for i in range(d))))


def knn_brute(src: DataFrame, k: int, cols: list[str], queries: DataFrame | None = None, id_col: str = "id", box=None) -> DataFrame:
    """Every query against every source (quadratic by definition), blocks of queries against blocks of sources."""
    ship(src.sparkSession)
    a, b = _ends(src, queries, cols, id_col)
    g, h = -(-a.count() // 5_000) or 1, -(-b.count() // 200_000) or 1
    deal = lambda c, n: F.pmod(F.xxhash64(c), F.lit(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    return _blocks(_kinds(a.select("*", deal("qid", g).alias("g"), every(h).alias("h")), b.select("*", every(g).alias("g"), deal("sid", h).alias("h")), len(cols)), k, len(cols), box)


class KdTree:
    """A median kd-tree in arrays: leaves of at most `leaf` points, bounding boxes for pruning."""

    def __init__(self, x: np.ndarray, ids: np.ndarray, leaf: int = 32):
        self.x, self.ids, self.leaf = x, ids, leaf
        self.order = np.arange(len(x))
        self.nodes: list[tuple] = []
        self._build(0, len(x))

    def _build(self, lo: int, hi: int) -> int:
        at = len(self.nodes)
        pts = self.x[self.order[lo:hi]]
        low, high = (pts.min(0), pts.max(0)) if hi > lo else (np.zeros(self.x.shape[1]),) * 2
        self.nodes.append((lo, hi, -1, -1, low, high))
        if hi - lo > self.leaf and (high > low).any():
            axis = int((high - low).argmax())
            mid = (lo + hi) // 2
            part = np.argpartition(pts[:, axis], mid - lo)
            self.order[lo:hi] = self.order[lo:hi][part]
            left = self._build(lo, mid)
            right = self._build(mid, hi)
            self.nodes[at] = (lo, hi, left, right, low, high)
        return at

    def query(self, q: np.ndarray, k: int) -> list[tuple[float, int]]:
        import heapq

        found: list[tuple[float, int]] = []  # (-d2, -id), the worst first
        todo = [(0.0, 0)]
        while todo:
            low, at = heapq.heappop(todo)
            if len(found) == k and low > -found[0][0]:
                break
            lo, hi, left, right, _, _ = self.nodes[at]
            if left < 0:
                rows = self.order[lo:hi]
                d2 = squared(q[None], self.x[rows], None)[0]
                for v, i in zip(d2.tolist(), self.ids[rows].tolist()):
                    if len(found) < k:
                        heapq.heappush(found, (-v, -i))
                    elif (-v, -i) > found[0]:
                        heapq.heapreplace(found, (-v, -i))
            else:
                for child in (left, right):
                    _, _, _, _, c_lo, c_hi = self.nodes[child]
                    gap = np.maximum(np.maximum(c_lo - q, q - c_hi), 0)
                    heapq.heappush(todo, (float((gap * gap).sum()) * (1 - 1e-12), child))
        return sorted((-v, -i) for v, i in found)


def knn_kdtree_broadcast(src: DataFrame, k: int, cols: list[str], queries: DataFrame | None = None, id_col: str = "id", tasks: int | None = None, most: int = 2_000_000) -> DataFrame:
    """A kd-tree of all sources in every task (tasks=1: one core), queries one by one. Raises beyond `most` sources."""
    a, b = _ends(src, queries, cols, id_col)
    spark = src.sparkSession
    ship(spark)
    if (n := b.count()) > most:
        raise ValueError(f"{n} sources are too many to broadcast")
    rows = b.toArrow()
    x = np.column_stack([rows.column(f"x{i}").to_numpy() for i in range(len(cols))])
    sent = spark.sparkContext.broadcast((x, rows.column("sid").to_numpy()))
    d = len(cols)

    def run(batches):
        import pyarrow as pa

        from zplane.operators.baselines import KdTree

        tree = KdTree(*sent.value)
        for p in batches:
            qid, q = p.column(0).to_pylist(), np.column_stack([p.column(1 + i).to_numpy() for i in range(d)])
            out = [(i, r, s, v) for i, y in zip(qid, q) for r, (v, s) in enumerate(tree.query(y, k), 1)]
            cols_ = list(zip(*out)) if out else [()] * 4
            yield pa.RecordBatch.from_arrays([pa.array(cols_[0], pa.int64()), pa.array(cols_[1], pa.int32()), pa.array(cols_[2], pa.int64()), pa.array(np.sqrt(np.array(cols_[3], float)))], ["qid", "rank", "sid", "dist"])

    return (a.repartition(tasks) if tasks else a).mapInArrow(run, "qid long, rank int, sid long, dist double")


def knn_one_sided(src: DataFrame, k: int, cols: list[str], queries: DataFrame | None = None, id_col: str = "id", options: Options | None = None) -> DataFrame:
    """Each query walks the source tree alone."""
    tree = joint_tree(src, None, cols, id_col, options)
    return knn_probe(tree, src if queries is None else queries, k, cols, id_col)


def knn_separate_trees(src: DataFrame, k: int, cols: list[str], queries: DataFrame, id_col: str = "id", options: Options | None = None) -> DataFrame:
    """A tree of the sources and another one of the queries, walked against each other (raises where they are too large to broadcast).

    Neither tree is refined by the points of the other, so a query leaf in a region without queries nearby may reach
    over many source leaves, which the joint tree avoids.
    """
    s_tree, q_tree = joint_tree(src, None, cols, id_col, options), joint_tree(queries, None, cols, id_col, options)
    if not (walk.fits(s_tree) and walk.fits(q_tree)):
        raise ValueError("the trees are too large for this baseline")
    spark, ngr = src.sparkSession, s_tree.ngr
    sources = spark.sparkContext.broadcast(walk.collect_planes(s_tree))

    def make(planes, domains):
        import pyarrow as pa

        recv, leaf, low = walk.knn_pairs(planes, domains, k, None, True, None, ngr, None, sources.value)
        pl = planes[0]
        return pa.RecordBatch.from_arrays([pa.array(pl.domain[recv].astype(np.int32)), pa.array(pl.node[recv]), pa.array(sources.value[0].node[leaf]), pa.array(low)], ["domain", "recv", "src", "r_low"])

    ilist = walk.walk_in_tasks(q_tree, make, "domain int, recv long, src long, r_low double")
    asked = q_tree.points.withColumn("ptype", F.lit(1))
    both = replace(q_tree, points=asked.unionByName(s_tree.points.withColumn("domain", F.lit(-1))))  # a source's leaf is that of its own tree
    rows = domain_rows(both, ilist, False).groupBy("domain").applyInArrow(rows_kernel(len(cols), k, None, True, True, None), "qid long, rank int, sid long, dist2 double")
    return rows.select("qid", "rank", "sid", F.sqrt("dist2").alias("dist"))


def knn_voronoi(src: DataFrame, k: int, cols: list[str], queries: DataFrame | None = None, id_col: str = "id", seeds: int | None = None) -> DataFrame:
    """Cells around random seeds (64, or the square root of the rows if that is more): a query visits the cells that its k-th distance bound can reach."""
    spark = src.sparkSession
    ship(spark)
    a, b = _ends(src, queries, cols, id_col)
    d = len(cols)
    seeds = seeds or max(64, int(b.count() ** 0.5))
    at = np.array([[r[f"x{i}"] for i in range(d)] for r in b.orderBy(F.xxhash64("sid")).limit(seeds).collect()]).reshape(-1, d)

    def assign(batches):
        import pyarrow as pa

        for p in batches:
            x = np.column_stack([p.column(1 + i).to_numpy() for i in range(d)])
            d2 = squared(x, at, None)
            cell = d2.argmin(1)
            yield pa.RecordBatch.from_arrays([*p.columns, pa.array(cell.astype(np.int32)), pa.array(np.sqrt(d2[np.arange(len(x)), cell]))], [*p.schema.names, "cell", "far"])

    cells = stored(b.mapInArrow(assign, "sid long, " + ", ".join(f"x{i} double" for i in range(d)) + ", cell int, far double"), "cells")
    info = {r.cell: (r.n, r.far) for r in cells.groupBy("cell").agg(F.count("*").alias("n"), F.max("far").alias("far")).collect()}
    js = sorted(info)
    c, n, radius = at[js], np.array([info[j][0] for j in js]), np.array([info[j][1] for j in js])

    def route(batches):
        import pyarrow as pa

        for p in batches:
            for lo in range(0, p.num_rows, 4096):
                part = p.slice(lo, 4096)
                q = np.column_stack([part.column(1 + i).to_numpy() for i in range(d)])
                away = np.sqrt(squared(q, c, None))
                up = np.argsort(away + radius, axis=1)
                total = np.cumsum(n[up], axis=1)
                enough = (total >= k).argmax(1)
                bound = np.where(total[:, -1] >= k, np.take_along_axis(away + radius, up, 1)[np.arange(len(q)), enough], np.inf)
                i, j = np.nonzero(away - radius <= bound[:, None] * (1 + 1e-12))
                kept = part.take(pa.array(i))
                yield pa.RecordBatch.from_arrays([*kept.columns, pa.array(np.array(js, np.int32)[j])], [*kept.schema.names, "cell"])

    asks = a.mapInArrow(route, "qid long, " + ", ".join(f"q{i} double" for i in range(d)) + ", cell int")
    cell = lambda x: x.withColumnRenamed("cell", "g").withColumn("h", F.lit(0))
    return _blocks(_kinds(cell(asks), cell(cells), d), k, d)


def knn_grid(src: DataFrame, k: int, cols: list[str], queries: DataFrame | None = None, id_col: str = "id", cell: float | None = None) -> DataFrame:
    """Equal grid cells, searched in growing rings until k sources are surely found; what remains after the rings is brute force.

    Queries of a block of cells are searched in one task, which returns their k nearest, so pairs are never rows."""
    ship(src.sparkSession)
    a, b = _ends(src, queries, cols, id_col)
    d = len(cols)
    if cell is None:
        r = b.agg(F.count("*").alias("n"), *(F.max(f"x{i}").alias(f"h{i}") for i in range(d)), *(F.min(f"x{i}").alias(f"l{i}") for i in range(d))).first()
        volume = float(np.prod([max(r[f"h{i}"] - r[f"l{i}"], 1e-12) for i in range(d)]))
        cell = (volume * 2 * k / max(1, r["n"])) ** (1 / d)
    side = 4  # cells that a block has in each dimension: its queries are searched at once, over its cells and the ring around them
    at = lambda c: F.floor(F.floor(F.col(c) / cell) / side)
    named = lambda x: x.withColumn("g", F.concat_ws("/", *(F.col(f"g{i}").cast("string") for i in range(d)))).withColumn("h", F.lit(0))
    left, out = a, None
    for ring in (1, 2, 4):
        asks, near = named(left.withColumns({f"g{i}": at(f"q{i}") for i in range(d)})), b
        for i in range(d):
            low, up = (F.floor((F.floor(F.col(f"x{i}") / cell) + r) / side) for r in (-ring, ring))
            near = near.withColumn(f"g{i}", F.explode(F.sequence(low, up)))
        near = named(near).join(asks.select("g").distinct(), "g", "left_semi")
        got = stored(_blocks(_kinds(asks, near, d), k, d), "ring")
        ok = got.groupBy("qid").agg(F.count("*").alias("n"), F.max("dist").alias("far")).where((F.col("n") == k) & (F.col("far") <= ring * cell * (1 - 1e-12))).select("qid")
        part = got.join(ok, "qid", "left_semi")
        out = part if out is None else out.unionAll(part)
        left = stored(left.join(ok, "qid", "left_anti"), "left")
        release(src.sparkSession)
        if left.isEmpty():
            return out
    rest = left.select(F.col("qid").alias("id"), *(F.col(f"q{i}").alias(f"x{i}") for i in range(d)))
    return out.unionAll(knn_brute(b.withColumnRenamed("sid", "id"), k, [f"x{i}" for i in range(d)], rest))


def _touch(a: np.ndarray, b: np.ndarray, r: float) -> bool:
    """Whether any point of a lies within r of one of b."""
    return any((squared(a[i : i + 1024], b[j : j + 1024], None) <= r * r).any() for i in range(0, len(a), 1024) for j in range(0, len(b), 1024))


def link_union_find(df: DataFrame, cols: list[str], r_link: float, id_col: str = "id") -> DataFrame:
    """One task: cells whose points are surely linked, and a union-find over the cells."""
    d = len(cols)
    ship(df.sparkSession)
    rows = df.select(F.col(id_col).cast("long").alias("id"), *(F.col(c).cast("double").alias(f"x{i}") for i, c in enumerate(cols))).coalesce(1)

    def run(batches):
        import itertools

        import pyarrow as pa

        parts = list(batches)
        if not parts:
            return
        t = pa.Table.from_batches(parts)
        if not t.num_rows:
            return
        ids, x = t.column("id").to_numpy(), np.column_stack([t.column(f"x{i}").to_numpy() for i in range(d)])
        reach = math.isqrt(d - 1) + 1  # points of a cell are closer than r_link, so cells are linked and not points
        g = np.floor(x / (r_link / d**0.5 * (1 - 1e-9))).astype(np.int64)
        order = np.lexsort((*x.T, *g.T))
        ids, x, g = ids[order], x[order], g[order]
        first = np.flatnonzero(np.append(True, (g[1:] != g[:-1]).any(1)))
        ends = np.append(first, len(ids))
        fresh = np.append(True, (x[1:] != x[:-1]).any(1))  # equal points count once in tests
        place, upto = x[fresh], np.append(np.cumsum(fresh) - 1, fresh.sum())[ends]
        at = {c: i for i, c in enumerate(map(tuple, g[first].tolist()))}
        root = list(range(len(first)))

        def find(i):
            while root[i] != i:
                root[i] = root[root[i]]
                i = root[i]
            return i

        steps = [o for o in itertools.product(range(-reach - 1, reach + 2), repeat=d) if o > (0,) * d and sum(max(abs(v) - 1, 0) ** 2 for v in o) <= d * (1 + 1e-6)]  # cells that r_link reaches
        for c, i in at.items():
            for o in steps:
                j = at.get(tuple(u + v for u, v in zip(c, o)))
                if j is not None and find(i) != find(j) and _touch(place[upto[i] : upto[i + 1]], place[upto[j] : upto[j + 1]], r_link):
                    root[max(find(i), find(j))] = min(find(i), find(j))
        group = np.array([find(i) for i in range(len(first))])
        least = np.full(len(first), np.iinfo(np.int64).max)
        np.minimum.at(least, group, np.minimum.reduceat(ids, first))
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(np.repeat(least[group], np.diff(ends)), pa.int64())], ["id", "group_id"])

    return rows.mapInArrow(run, "id long, group_id long")


def link_grid(df: DataFrame, cols: list[str], r_link: float, id_col: str = "id", tasks: int | None = None) -> DataFrame:
    """Cells of the linking length joined with their neighbours as an equi-join, and distributed components."""
    d = len(cols)
    rows = df.select(F.col(id_col).cast("long").alias("id"), *(F.col(c).cast("double").alias(f"x{i}") for i, c in enumerate(cols)))
    rows = rows.repartition(tasks) if tasks else rows
    grid = rows.withColumns({f"g{i}": F.floor(F.col(f"x{i}") / r_link) for i in range(d)})
    a = grid.select(F.col("id").alias("a"), *(F.col(f"x{i}").alias(f"q{i}") for i in range(d)), *(F.col(f"g{i}").alias(f"h{i}") for i in range(d)))
    for i in range(d):
        a = a.withColumn(f"o{i}", F.explode(F.sequence(F.lit(-1), F.lit(1)))).withColumn(f"g{i}", F.col(f"h{i}") + F.col(f"o{i}")).drop(f"o{i}", f"h{i}")
    d2 = dist2([F.col(f"q{i}") for i in range(d)], [F.col(f"x{i}") for i in range(d)])
    edges = a.join(grid, [f"g{i}" for i in range(d)]).where((F.col("a") < F.col("id")) & (d2 <= r_link * r_link)).select("a", F.col("id").alias("b"))
    roots = components(edges)
    return rows.select("id").join(roots.withColumnRenamed("node", "id"), "id", "left").select("id", F.coalesce("root", "id").alias("group_id"))


def link_by_knn(df: DataFrame, cols: list[str], r_link: float, id_col: str = "id", k: int = 8, most: int = 4096) -> DataFrame:
    """Linking by repeated neighbour graphs of sites (places with points): k doubles for the sites whose lists are full of sites within the linking length.

    Doubling ends at `most` neighbours, or where it leaves more than half of its lists full: a link that no list holds
    lies between two sites with full lists, and these alone are linked by the walk's spanning edges, so their number is
    not bounded by a list.
    """
    rows = df.select(F.col(id_col).cast("long").alias("id"), *(F.col(c).cast("double").alias(f"x{i}") for i, c in enumerate(cols)))
    xs = [f"x{i}" for i in range(len(cols))]
    sites = stored(rows.groupBy(*xs).agg(F.min("id").alias("site")), "sites")
    points = sites.withColumnRenamed("site", "id")
    n = asked = points.count()
    edges, left = None, None
    while True:
        near = stored(knn(points, min(k, n), xs, queries=left).where(F.col("dist") <= r_link), "near")
        found = near.select(F.col("qid").alias("a"), F.col("sid").alias("b"))
        edges = found if edges is None else edges.union(found)
        full = near.groupBy("qid").agg(F.count("*").alias("n")).where(F.col("n") >= k)
        left = stored(points.join(full.select(F.col("qid").alias("id")), "id", "left_semi"), "full")
        if k >= n or not (rest := left.count()):
            break
        if k >= most or 2 * rest > asked:
            edges = stored(edges.union(link_edges(left, xs, r_link)[0].select("a", "b")), "edges")
            break
        k, asked = 2 * k, rest
    roots = components(edges).where(F.col("node") < MARK)
    labelled = sites.join(roots.withColumnRenamed("node", "site"), "site", "left").select(*xs, F.coalesce("root", "site").alias("group_id"))
    return rows.join(labelled, xs).select("id", "group_id")

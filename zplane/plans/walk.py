"""The dual tree walk: interaction lists from the coarsest plane down to the leaves.

Planes whose nodes fit a checked bound are sent to all tasks, and each task walks down for the receivers
of its own domains in numpy. Beyond that bound the same walk runs as DataFrame stages, one for each plane,
with equi-joins on parents.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from zplane.components import union_find
from zplane.functions import bounds
from zplane.functions.bounds import BOUND_SLACK, np_bounds
from zplane.plans.planes import NODE_SPAN, PlaneTree
from zplane.session import discard, ship, stored

#: Nodes (about 100 bytes each) that may be broadcast; larger trees are walked by DataFrame stages.
BROADCAST_NODES = 400_000


@dataclass
class Plane:
    node: np.ndarray
    c: np.ndarray
    ext: np.ndarray
    n_src: np.ndarray
    n_qry: np.ndarray
    child: np.ndarray  # first child of each node in the finer plane, and the end
    domain: np.ndarray


def collect_planes(tree: PlaneTree) -> list[Plane]:
    """All planes as arrays (callers check the count first)."""
    rows = tree.nodes.select("plane", "node", "parent", "n_src", "n_qry", "c", "ext", "domain").toArrow()
    plane, node = rows.column("plane").to_numpy(), rows.column("node").to_numpy()
    parent = rows.column("parent").to_numpy()
    wide = lambda c: rows.column(c).combine_chunks().flatten().to_numpy().reshape(-1, tree.d)
    c, ext = wide("c"), wide("ext")
    n_src, n_qry, domain = (rows.column(x).to_numpy() for x in ("n_src", "n_qry", "domain"))
    out: list[Plane] = []
    for p in range(tree.planes):
        at = np.flatnonzero(plane == p)
        at = at[np.argsort(node[at], kind="stable")]
        out.append(Plane(node[at], c[at], ext[at], n_src[at], n_qry[at], np.zeros(0, np.int64), domain[at]))
        if p:
            below = np.flatnonzero(plane == p - 1)
            below = below[np.argsort(node[below], kind="stable")]
            out[p].child = np.append(np.searchsorted(parent[below], node[at], side="left"), len(below))
    return out


def expand(recv: np.ndarray, src: np.ndarray, child: np.ndarray, src_child: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of nodes of a plane -> all pairs of their children (child: first child of each node, and the end)."""
    other = child if src_child is None else src_child
    a, b = child[recv + 1] - child[recv], other[src + 1] - other[src]
    n = a * b
    pair = np.repeat(np.arange(len(recv)), n)
    at = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
    return child[recv][pair] + at // b[pair], other[src][pair] + at % b[pair]


def super_nodes(n_top: int, ngr: int) -> np.ndarray:
    """Where each group of ngr top nodes begins, and the end: the children of the super nodes."""
    return np.append(np.arange(0, n_top, max(1, ngr)), n_top)


def dense_ilist(n_recv: int, n_src: int) -> tuple[np.ndarray, np.ndarray]:
    """Every receiver with every source, sorted by receiver."""
    return np.repeat(np.arange(n_recv), n_src), np.tile(np.arange(n_src), n_recv)


def start_pairs(planes: list[Plane], sources: list[Plane], ngr: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of top nodes: the children of a dense list over super nodes."""
    a, b = super_nodes(len(planes[-1].node), ngr), super_nodes(len(sources[-1].node), ngr)
    return expand(*dense_ilist(len(a) - 1, len(b) - 1), a, b)


def owned(planes: list[Plane], domains: set[int]) -> list[np.ndarray]:
    """For each plane, which nodes are or hold leaves of some domains."""
    out = [np.isin(planes[0].domain, list(domains))]
    for pl in planes[1:]:
        out.append(np.logical_or.reduceat(out[-1], pl.child[:-1]))
    return out


def as_high(planes: list[Plane], height: int) -> list[Plane]:
    """planes with the top one repeated (each node its own child) until there are `height`."""
    out = list(planes)
    while len(out) < height:
        out.append(replace(out[-1], child=np.arange(len(out[-1].node) + 1)))
    return out


def find_rmax(recv: np.ndarray, d_up: np.ndarray, count: np.ndarray, k: int) -> dict[int, float] | tuple[np.ndarray, np.ndarray]:
    """(receivers, R_max): the smallest d_up within which sources count to k; inf if all together are fewer."""
    order = np.lexsort((d_up, recv))
    r, n = recv[order], count[order]
    first = np.flatnonzero(np.append(True, r[1:] != r[:-1])) if len(r) else np.zeros(0, np.int64)
    total = np.cumsum(n)
    before = np.repeat(total[first] - n[first], np.diff(np.append(first, len(r))))
    enough = (total - before) >= k
    rank = np.where(enough, np.arange(len(r)), len(r))
    at = np.minimum.reduceat(rank, first) if len(first) else rank[:0]
    up = np.append(d_up[order], np.inf)
    return r[first], up[at]


def find_rmax_bounded(recv: np.ndarray, d_up: np.ndarray, count: np.ndarray, k: int, slots: int) -> tuple[np.ndarray, np.ndarray]:
    """find_rmax with `slots` (radius, count) places for each receiver: never below the exact radius, and in bounded memory."""
    heaps: dict[int, BoundedHeap] = {}
    for i, r, n in zip(recv.tolist(), d_up.tolist(), count.tolist()):
        if i not in heaps:
            heaps[i] = BoundedHeap(k, slots)
        heaps[i].insert(r, n)
    return np.array(list(heaps), np.int64), np.array([h.radius() for h in heaps.values()], float)


class BoundedHeap:
    """R_max with a fixed number of (radius, count) slots: what overflows is dropped, unless the count would fall below k."""

    def __init__(self, k: int, slots: int):
        self.k, self.slots, self.held = k, slots, []

    def radius(self) -> float:
        total = 0
        for r, n in self.held:
            total += n
            if total >= self.k:
                return r
        return np.inf

    def insert(self, r: float, n: int) -> None:
        if r >= self.radius():
            return
        at = next((i for i, h in enumerate(self.held) if h[0] > r), len(self.held))
        if len(self.held) < self.slots:
            self.held.insert(at, (r, n))
        elif sum(c for _, c in self.held[:-1]) + n >= self.k and at < len(self.held):
            self.held.insert(at, (r, n))
            self.held.pop()
        elif at < len(self.held):
            self.held[at] = (self.held[at][0], self.held[at][1] + n)


def knn_pairs(planes: list[Plane], domains: set[int], k: int, box=None, self_query: bool = True, stats: dict | None = None, ngr: int = 32, slots: int | None = None, sources: list[Plane] | None = None):
    """(recv, src, r_low) leaf pairs (indices in plane 0) for the receivers of some domains, sorted by r_low.

    sources: the planes of another tree (whose leaves src then names); slots: R_max from bounded heaps.
    """
    if sources is None:
        sources = planes
    height = max(len(planes), len(sources))
    planes, sources = as_high(planes, height), as_high(sources, height)
    mine = owned(planes, domains)
    recv, src = start_pairs(planes, sources, ngr)
    low = np.zeros(len(recv))
    for p in range(height - 1, -1, -1):
        pl, other = planes[p], sources[p]
        if p < height - 1:
            recv, src = expand(recv, src, planes[p + 1].child, sources[p + 1].child)
        asks = pl.n_src if self_query else pl.n_qry
        ok = mine[p][recv] & (asks[recv] > 0) & (other.n_src[src] > 0)
        recv, src = recv[ok], src[ok]
        low, up = _pair_bounds(pl, recv, src, box, other)
        r, rmax = find_rmax(recv, up, other.n_src[src], k) if slots is None else find_rmax_bounded(recv, up, other.n_src[src], k, slots)
        limit = np.full(len(pl.node), np.inf)
        limit[r] = rmax
        keep = low <= limit[recv] * (1 + BOUND_SLACK)
        if stats is not None:
            stats.setdefault("pairs", []).append((p, len(recv), int(keep.sum())))
        recv, src, low = recv[keep], src[keep], low[keep]
    order = np.lexsort((low, recv))
    return recv[order], src[order], low[order]


def _pair_bounds(pl: Plane, recv, src, box, other: Plane | None = None):
    to = other or pl
    low, up = np.empty(len(recv)), np.empty(len(recv))
    for lo in range(0, len(recv), 1 << 19):
        s = slice(lo, lo + (1 << 19))
        low[s], up[s] = np_bounds(pl.c[recv[s]], pl.ext[recv[s]], to.c[src[s]], to.ext[src[s]], box)
    return low, up


def radius_pairs(planes: list[Plane], domains: set[int], r: float, box=None, self_query: bool = True, ngr: int = 32):
    """(recv, src) leaf pairs that may hold points within r; for self queries only recv <= src."""
    mine = owned(planes, domains)
    recv, src = start_pairs(planes, planes, ngr)
    for p in range(len(planes) - 1, -1, -1):
        pl = planes[p]
        if p < len(planes) - 1:
            recv, src = expand(recv, src, planes[p + 1].child)
        ok = mine[p][recv] & (((recv <= src) & (pl.n_src[recv] > 0)) if self_query else (pl.n_qry[recv] > 0)) & (pl.n_src[src] > 0)
        recv, src = recv[ok], src[ok]
        near = _pair_bounds(pl, recv, src, box)[0] <= r * (1 + BOUND_SLACK)
        recv, src = recv[near], src[near]
    return recv, src


def count_pairs(planes: list[Plane], domains: set[int], r: float, box=None, self_query: bool = True, ngr: int = 32):
    """((recv, src), n): leaf pairs that points must be tested for, and for each leaf the sources that are surely
    within r of all its points, added whole on the plane where that is first sure."""
    mine = owned(planes, domains)
    recv, src = start_pairs(planes, planes, ngr)
    whole = np.zeros(len(planes[-1].node), np.int64)
    for p in range(len(planes) - 1, -1, -1):
        pl = planes[p]
        if p < len(planes) - 1:
            recv, src = expand(recv, src, planes[p + 1].child)
            whole = np.repeat(whole, np.diff(planes[p + 1].child))
        ok = mine[p][recv] & ((pl.n_src if self_query else pl.n_qry)[recv] > 0) & (pl.n_src[src] > 0)
        recv, src = recv[ok], src[ok]
        low, high = _pair_bounds(pl, recv, src, box)
        sure = high <= r * (1 - BOUND_SLACK)
        np.add.at(whole, recv[sure], pl.n_src[src[sure]])
        open_ = ~sure & (low <= r * (1 + BOUND_SLACK))
        recv, src = recv[open_], src[open_]
    return (recv, src), np.where(mine[0], whole, 0)


def link_pairs(planes: list[Plane], domains: set[int], r: float, box=None, ngr: int = 32):
    """Open leaf pairs (recv <= src), and edges between leaves that are linked whole: ((recv, src), (leaf, leaf)).

    A pair of nodes that is surely within r becomes an edge between their first leaves (given by the domain of the
    receiver's), and every leaf below a linked node an edge to that node's first leaf. Pairs with either end in
    the domains are looked at, so that each domain knows which of its nodes are linked.
    """
    mine = owned(planes, domains)
    heads = [np.arange(len(planes[0].node))]  # the first leaf below each node
    for pl in planes[1:]:
        heads.append(heads[-1][pl.child[:-1]])
    top = planes[-1]
    recv, src = start_pairs(planes, planes, ngr)
    label, anchor = np.arange(len(top.node)), np.full(len(top.node), -1)
    edges = [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
    for p in range(len(planes) - 1, -1, -1):
        pl = planes[p]
        if p < len(planes) - 1:
            up = planes[p + 1]
            recv, src = expand(recv, src, up.child)
            parent = np.repeat(np.arange(len(up.node)), np.diff(up.child))
            anchor = anchor[parent]
            label = np.where(anchor >= 0, up.child[label[parent]], np.arange(len(pl.node)))
        ok = (recv <= src) & (mine[p][recv] | mine[p][src]) & (pl.n_src[recv] > 0) & (pl.n_src[src] > 0)
        recv, src = recv[ok], src[ok]
        low, high = _pair_bounds(pl, recv, src, box)
        near = low <= r * (1 + BOUND_SLACK)
        recv, src, high = recv[near], src[near], high[near]
        sure = high <= r * (1 - BOUND_SLACK)
        a, b = recv[sure], src[sure]
        if len(a):
            for x in (a, b):
                fresh = x[anchor[x] < 0]
                anchor[fresh] = heads[p][fresh]
            give = (a != b) & mine[0][heads[p][a]]
            edges.append((heads[p][a[give]], heads[p][b[give]]))
            nodes, roots = union_find(label[a], label[b])
            to = np.arange(len(pl.node))
            to[nodes] = roots
            label = to[label]
        # a pair of linked nodes with one root is settled; a node with itself only once it is linked
        done = sure | ((anchor[recv] >= 0) & (anchor[src] >= 0) & (label[recv] == label[src]))
        recv, src = recv[~done], src[~done]
    leaves = np.flatnonzero((anchor >= 0) & mine[0])
    edges.append((leaves, anchor[leaves]))
    here = mine[0][recv]
    return (recv[here], src[here]), tuple(np.concatenate(e) for e in zip(*edges))


def fits(tree: PlaneTree) -> bool:
    """Whether the planes may be collected and broadcast."""
    return tree.nodes.count() <= BROADCAST_NODES


def walk_in_tasks(tree: PlaneTree, make, schema: str, plane_arrays: list[Plane] | None = None) -> DataFrame:
    """Rows that make(planes, domains) yields as an Arrow batch, one task for each group of domains."""
    spark = tree.points.sparkSession
    ship(spark)
    sent = spark.sparkContext.broadcast(plane_arrays or collect_planes(tree))  # callers check that it fits
    n = len(tree.starts)

    def run(batches):
        for b in batches:
            for domain in b.column(0).to_pylist():
                yield make(sent.value, {domain})

    return spark.range(0, n, 1, numPartitions=min(n, 10_000)).select(F.col("id").cast("int").alias("domain")).mapInArrow(run, schema)


def knn_ilist(tree: PlaneTree, k: int, box=None, self_query: bool = True, method: str = "auto", slots: int | None = None) -> DataFrame:
    """(domain, recv, src, r_low): source leaves that each receiving leaf must look at."""
    if method == "auto":
        method = "tasks" if fits(tree) else "stages"
    if method == "stages":
        return knn_stages(tree, k, box, self_query)
    ngr = tree.ngr

    def make(planes, domains):
        import pyarrow as pa

        recv, src, low = knn_pairs(planes, domains, k, box, self_query, None, ngr, slots)
        pl = planes[0]
        return pa.RecordBatch.from_arrays([pa.array(pl.domain[recv].astype(np.int32)), pa.array(pl.node[recv]), pa.array(pl.node[src]), pa.array(low)], ["domain", "recv", "src", "r_low"])

    return walk_in_tasks(tree, make, "domain int, recv long, src long, r_low double")


def knn_stages(tree: PlaneTree, k: int, box, self_query: bool, counts: list | None = None) -> DataFrame:
    """The walk as one DataFrame stage for each plane: expand by two joins on the parent, bounds in codegen,
    R_max from a running count, and a filter. counts takes (plane, pairs looked at, pairs kept) of each stage."""
    spark = tree.points.sparkSession
    d = tree.d
    asks = "n_src" if self_query else "n_qry"
    side = lambda p, s: tree.nodes.where(F.col("plane") == p).select(F.col("node").alias(f"{s}"), F.col("parent").alias(f"{s}_up"), F.col("n_src").alias(f"{s}_n"), F.col(asks).alias(f"{s}_asks"), F.col("c").alias(f"{s}_c"), F.col("ext").alias(f"{s}_e"))
    col = lambda name: [F.col(name)[i] for i in range(d)]
    pairs = None
    for p in range(tree.planes - 1, -1, -1):
        a, b = side(p, "recv").where("recv_asks > 0"), side(p, "src").where("src_n > 0")
        if pairs is None:
            joined = _dense(a, b, tree.ngr)
        else:
            up = pairs.select(F.col("recv").alias("recv_up"), F.col("src").alias("src_up"))
            joined = up.join(a, "recv_up").join(b, "src_up")
        low = bounds.d_low(col("recv_c"), col("recv_e"), col("src_c"), col("src_e"), box)
        high = bounds.d_up(col("recv_c"), col("recv_e"), col("src_c"), col("src_e"), box)
        w = W.partitionBy("recv").orderBy("d_up", "src").rowsBetween(W.unboundedPreceding, 0)
        rows = joined.withColumns({"r_low": F.when(F.isnan(low), F.lit(0.0)).otherwise(low), "d_up": F.when(F.isnan(high), F.lit(float("inf"))).otherwise(high)})
        rows = rows.withColumn("got", F.sum("src_n").over(w))
        if counts is not None:
            rows = rows.withColumn("seen", F.count("*").over(W.partitionBy("recv")))
        limit = F.min(F.when(F.col("got") >= k, F.col("d_up"))).over(W.partitionBy("recv"))
        rows = rows.withColumn("r_max", limit).where(F.col("r_max").isNull() | (F.col("r_low") <= F.col("r_max") * (1 + BOUND_SLACK)))
        seen = [] if counts is None else ["seen"]
        nxt = stored(rows.select("recv", "src", "r_low", *seen), f"plane{p}")
        if counts is not None:  # every receiver keeps a pair, and that knows how many it had
            per = nxt.groupBy("recv").agg(F.first("seen").alias("seen"), F.count("*").alias("kept"))
            counts.append((p, *per.agg(F.sum("seen"), F.sum("kept")).first()))
        if pairs is not None:
            discard(spark, pairs)
        pairs = nxt
    return pairs.select(F.floor(F.col("recv") / NODE_SPAN).cast("int").alias("domain"), "recv", "src", "r_low")


def _dense(a: DataFrame, b: DataFrame, ngr: int) -> DataFrame:
    """All pairs of the top plane's nodes, through super nodes: that plane has about n_target nodes, however many points there are."""
    group = lambda c: F.floor(F.col(c) / ngr)  # noqa: E731  ids of one plane are consecutive within a group of domains
    a, b = a.withColumn("recv_sup", group("recv")), b.withColumn("src_sup", group("src"))
    supers = a.select("recv_sup").distinct().crossJoin(F.broadcast(b.select("src_sup").distinct()))
    return supers.join(a, "recv_sup").join(b, "src_sup").drop("recv_sup", "src_sup")


def _sides(tree: PlaneTree, p: int, asks: str):
    """The nodes of a plane as receivers and as sources of a stage."""
    side = lambda s: tree.nodes.where(F.col("plane") == p).select(F.col("node").alias(s), F.col("parent").alias(f"{s}_up"), F.col("n_src").alias(f"{s}_n"), F.col(asks).alias(f"{s}_asks"), F.col("c").alias(f"{s}_c"), F.col("ext").alias(f"{s}_e"))
    return side("recv").where("recv_asks > 0"), side("src").where("src_n > 0")


def marker(node, plane: int):
    """The number that stands for a node of a plane among point ids (which must be below 2^62)."""
    return F.lit(1 << 62) + node * 16 + plane


def radius_stages(tree: PlaneTree, r: float, box=None, self_query: bool = True, link: bool = False):
    """The walk with a fixed radius as one DataFrame stage for each plane: (open leaf pairs, marker edges, linked leaves).

    With link, pairs of nodes that are surely within r are taken off the lists as edges between markers;
    linked nodes pass their mark down to their children, plane by plane.
    """
    spark = tree.points.sparkSession
    d = tree.d
    col = lambda name: [F.col(name)[i] for i in range(d)]
    pairs = marked = edges = None
    for p in range(tree.planes - 1, -1, -1):
        a, b = _sides(tree, p, "n_src" if self_query else "n_qry")
        if pairs is None:
            joined = _dense(a, b, tree.ngr)
        else:
            joined = pairs.select(F.col("recv").alias("recv_up"), F.col("src").alias("src_up")).join(a, "recv_up").join(b, "src_up")
        if self_query:
            joined = joined.where("recv <= src")
        low = bounds.d_low(col("recv_c"), col("recv_e"), col("src_c"), col("src_e"), box)
        high = bounds.d_up(col("recv_c"), col("recv_e"), col("src_c"), col("src_e"), box)
        near = joined.where(F.isnan(low) | (low <= r * (1 + BOUND_SLACK))).withColumn("sure", F.lit(link) & ~F.isnan(high) & (high <= r * (1 - BOUND_SLACK)))
        now = stored(near.select("recv", "src", "sure"), f"radius{p}")
        if link:
            sure = now.where("sure")
            here = sure.select(F.col("recv").alias("node")).union(sure.select(F.col("src").alias("node")))
            out = sure.where("recv <> src").select(marker(F.col("recv"), p).alias("a"), marker(F.col("src"), p).alias("b"))
            if marked is not None:
                kids = tree.nodes.where(F.col("plane") == p).select("node", "parent").join(marked.withColumnRenamed("node", "parent"), "parent")
                out = out.union(kids.select(marker(F.col("node"), p).alias("a"), marker(F.col("parent"), p + 1).alias("b")))
                here = here.union(kids.select("node"))
            marked = stored(here.distinct(), "marked")
            out = stored(out, "markers")
            edges = out if edges is None else edges.union(out)
        if pairs is not None:
            discard(spark, pairs)
        pairs = stored(now.where("NOT sure").select("recv", "src"), "open") if link else now.select("recv", "src")
    return pairs.select(F.floor(F.col("recv") / NODE_SPAN).cast("int").alias("domain"), "recv", "src"), edges, marked


def to_csr(ilist: DataFrame) -> DataFrame:
    """(recv, srcs, r_lows): each receiver's list, sorted by r_low."""
    return ilist.groupBy("recv").agg(F.array_sort(F.collect_list(F.struct("r_low", "src"))).alias("l")).select("recv", F.col("l.src").alias("srcs"), F.col("l.r_low").alias("r_lows"))

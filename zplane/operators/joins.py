"""Joins and searches by distance, and operators built on them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from zplane.functions.bounds import dist2, np_bounds
from zplane.operators.knn import domain_rows, joint_tree, squared, streamed, unpack
from zplane.plans import walk
from zplane.plans.planes import NODE_SPAN, Options, PlaneTree


def distance_join(a: DataFrame, b: DataFrame | None, r: float, cols: list[str], id_col: str = "id", box=None, options: Options | None = None, method: str = "auto") -> DataFrame:
    """(qid, sid, dist2): all pairs within r of a (queries) and b (sources); without b the pairs qid < sid of a itself."""
    self_query = b is None
    tree = joint_tree(a, None, cols, id_col, options) if self_query else joint_tree(b, a, cols, id_col, options)
    d = tree.d

    def parts(table):
        (q_leaf, q_id, q, _), (s_leaf, s_id, s, _), (p_leaf, p_src, _) = unpack(table, d)
        ends = [np.searchsorted(q_leaf, p_leaf, x) for x in ("left", "right")] + [np.searchsorted(s_leaf, p_src, x) for x in ("left", "right")]
        for (lo, hi, c, e), same in zip(zip(*(x.tolist() for x in ends)), (p_leaf == p_src).tolist()):
            for x in range(lo, hi, 2048):
                d2 = squared(q[x : min(x + 2048, hi)], s[c:e], box)
                i, j = np.nonzero(d2 <= r * r)
                u, v, w = q_id[x + i], s_id[c + j], d2[i, j]
                if self_query:
                    keep = u < v if same else u != v
                    u, v, w = np.minimum(u, v)[keep], np.maximum(u, v)[keep], w[keep]
                yield {"qid": u, "sid": v, "dist2": w}

    ilist = _radius_list(tree, r, box, self_query, method)
    return domain_rows(tree, ilist, self_query).groupBy("domain").applyInArrow(streamed(parts), "qid long, sid long, dist2 double")


def _radius_list(tree: PlaneTree, r: float, box, self_query: bool, method: str = "auto") -> DataFrame:
    """(domain, recv, src, r_low): pairs of leaves that may hold points within r."""
    ngr = tree.ngr

    def make(planes, domains):
        import pyarrow as pa

        recv, src = walk.radius_pairs(planes, domains, r, box, self_query, ngr)
        pl = planes[0]
        return pa.RecordBatch.from_arrays([pa.array(pl.domain[recv].astype(np.int32)), pa.array(pl.node[recv]), pa.array(pl.node[src])], ["domain", "recv", "src"])

    if method == "stages" or (method == "auto" and not walk.fits(tree)):
        return walk.radius_stages(tree, r, box, self_query)[0].withColumn("r_low", F.lit(0.0))
    return walk.walk_in_tasks(tree, make, "domain int, recv long, src long").withColumn("r_low", F.lit(0.0))


def count_within(a: DataFrame, b: DataFrame | None, r: float, cols: list[str], id_col: str = "id", box=None, options: Options | None = None, method: str = "auto") -> DataFrame:
    """(id, n): sources within r of each point (of a itself without b, the point included), one row for each row of a.

    Nodes that lie surely within r are added whole; only leaves at the rim have their points tested.
    """
    self_query = b is None
    tree = joint_tree(a, None, cols, id_col, options) if self_query else joint_tree(b, a, cols, id_col, options)
    d, ngr = tree.d, tree.ngr

    def make(planes, domains):
        import pyarrow as pa

        (recv, src), n = walk.count_pairs(planes, domains, r, box, self_query, ngr)
        leaf = np.flatnonzero(n)
        pl, m = planes[0], len(leaf)
        of = np.concatenate([recv, leaf])
        return pa.RecordBatch.from_arrays(
            [pa.array(pl.domain[of].astype(np.int32)), pa.array(pl.node[of]), pa.array(np.concatenate([pl.node[src], np.full(m, -1)])), pa.array(np.concatenate([np.zeros(len(recv)), n[leaf].astype(float)]))],
            ["domain", "recv", "src", "r_low"],
        )

    if method == "stages" or (method == "auto" and not walk.fits(tree)):  # both ends of a self pair see each other
        pairs = walk.radius_stages(tree, r, box, self_query)[0]
        if self_query:
            pairs = pairs.union(pairs.where("recv <> src").select(F.floor(F.col("src") / NODE_SPAN).cast("int"), "src", "recv"))
        ilist = pairs.withColumn("r_low", F.lit(0.0))
    else:
        ilist = walk.walk_in_tasks(tree, make, "domain int, recv long, src long, r_low double")

    def run(table):
        import pyarrow as pa

        (q_leaf, q_id, q, _), (s_leaf, _, s, _), (p_leaf, p_src, p_n) = unpack(table, d)
        n = np.zeros(len(q_id), np.int64)
        ends = [np.searchsorted(q_leaf, p_leaf, x) for x in ("left", "right")] + [np.searchsorted(s_leaf, p_src, x) for x in ("left", "right")]
        for (lo, hi, c, e), src, m in zip(zip(*(x.tolist() for x in ends)), p_src.tolist(), p_n.tolist()):
            if src < 0:
                n[lo:hi] += int(m)
                continue
            for x in range(lo, hi, 2048):
                n[x : min(x + 2048, hi)] += (squared(q[x : min(x + 2048, hi)], s[c:e], box) <= r * r).sum(1)
        return pa.table({"id": q_id, "n": n})

    return domain_rows(tree, ilist, self_query).groupBy("domain").applyInArrow(run, "id long, n long")


def has_neighbour(a: DataFrame, b: DataFrame, r: float, cols: list[str], id_col: str = "id", box=None) -> DataFrame:
    """Rows of a with a point of b within r. A point is tested until one is found, so no pairs are made."""
    tree = joint_tree(b, a, cols, id_col)
    d = tree.d

    def run(table):
        import pyarrow as pa

        return pa.table({id_col: pa.array(near_ids(table, d, r, box), pa.int64())})

    near = domain_rows(tree, _radius_list(tree, r, box, False), False).groupBy("domain").applyInArrow(run, f"`{id_col}` long")
    return a.join(near.distinct(), id_col, "left_semi")


def near_ids(table, d: int, r: float, box=None) -> np.ndarray:
    """Ids of a domain's queries with a source of their listed leaves within r, the own leaf first."""
    (q_leaf, q_id, q, _), (s_leaf, _, s, _), (p_leaf, p_src, _) = unpack(table, d)
    found = np.zeros(len(q_id), bool)
    order = np.argsort(p_leaf != p_src, kind="stable")
    ends = [np.searchsorted(q_leaf, p_leaf, x)[order] for x in ("left", "right")] + [np.searchsorted(s_leaf, p_src, x)[order] for x in ("left", "right")]
    for lo, hi, c, e in zip(*(x.tolist() for x in ends)):
        for x in range(lo, hi, 2048):
            left = x + np.flatnonzero(~found[x : min(x + 2048, hi)])
            for y in range(c, e if len(left) else c, 8192):
                found[left] |= (squared(q[left], s[y : min(y + 8192, e)], box) <= r * r).any(1)
    return q_id[found]


def isolated_points(a: DataFrame, r: float, cols: list[str], id_col: str = "id", box=None) -> DataFrame:
    """Rows of a with no other point of a within r."""
    alone = count_within(a, None, r, cols, id_col, box).where("n = 1").select(F.col("id").alias(id_col))
    return a.join(alone, id_col, "left_semi")


def pair_counts(df: DataFrame, edges: list[float], cols: list[str], id_col: str = "id", box=None, options: Options | None = None, method: str = "auto") -> DataFrame:
    """(bin, pairs): unordered pairs at distance in (edges[i], edges[i + 1]] (the first bin includes its lower end).

    Pairs of leaves whose bounds lie inside one bin are counted whole (where the planes are too large to
    broadcast, all open leaf pairs are tested).
    """
    tree = joint_tree(df, None, cols, id_col, options)
    d, e, ngr = tree.d, np.asarray(edges, float), tree.ngr
    e2 = e * e

    def make(planes, domains):
        import pyarrow as pa

        recv, src = walk.radius_pairs(planes, domains, float(e[-1]), box, True, ngr)
        pl = planes[0]
        low, up = np_bounds(pl.c[recv], pl.ext[recv], pl.c[src], pl.ext[src], box)
        i, j = np.searchsorted(e, low * (1 - 1e-12), "left") - 1, np.searchsorted(e, up * (1 + 1e-12), "left") - 1
        whole = (i == j) & (i >= 0) & (recv != src) & (low > e[0])
        n = np.where(whole, pl.n_src[recv] * pl.n_src[src], 0)
        return pa.RecordBatch.from_arrays([pa.array(pl.domain[recv].astype(np.int32)), pa.array(pl.node[recv]), pa.array(pl.node[src]), pa.array(i.astype(np.int32)), pa.array(n), pa.array(whole)], ["domain", "recv", "src", "bin", "n", "whole"])

    if method == "stages" or (method == "auto" and not walk.fits(tree)):
        sure, ilist = None, walk.radius_stages(tree, float(e[-1]), box, True)[0].withColumn("r_low", F.lit(0.0))
    else:
        rows = walk.walk_in_tasks(tree, make, "domain int, recv long, src long, bin int, n long, whole boolean")
        sure = rows.where("whole").groupBy("bin").agg(F.sum("n").alias("n"))
        ilist = rows.where("NOT whole").select("domain", "recv", "src", F.lit(0.0).alias("r_low"))

    def run(table):
        import pyarrow as pa

        count = bin_counts(table, d, e2, box)
        return pa.table({"bin": pa.array(np.arange(len(count)), pa.int32()), "n": pa.array(count)})

    tested = domain_rows(tree, ilist, True).groupBy("domain").applyInArrow(run, "bin int, n long")
    return (tested if sure is None else sure.unionAll(tested)).groupBy("bin").agg(F.sum("n").alias("pairs"))


def bin_counts(table, d: int, e2: np.ndarray, box=None) -> np.ndarray:
    """Pairs of a domain's listed leaves by bin of squared distance. Rows come in any order, so a leaf meets itself
    as its queries alone: sources in another order would put pairs of a point with itself above the diagonal."""
    (q_leaf, _, q, _), (s_leaf, _, s, _), (p_leaf, p_src, _) = unpack(table, d)
    count = np.zeros(len(e2) - 1, np.int64)
    ends = [np.searchsorted(q_leaf, p_leaf, x) for x in ("left", "right")] + [np.searchsorted(s_leaf, p_src, x) for x in ("left", "right")]
    for (lo, hi, c, f), same in zip(zip(*(x.tolist() for x in ends)), (p_leaf == p_src).tolist()):
        for x in range(lo, hi, 2048):
            rows = min(x + 2048, hi) - x
            d2 = squared(q[x : x + rows], q[x:hi] if same else s[c:f], box)
            v = d2[np.triu_indices(rows, 1, d2.shape[1])] if same else d2.ravel()
            b = np.searchsorted(e2, v, "left") - 1
            b[v == e2[0]] = 0
            ok = (b >= 0) & (b < len(count))
            count += np.bincount(b[ok], minlength=len(count))
    return count


def density_clusters(df: DataFrame, r: float, min_pts: int, cols: list[str], id_col: str = "id", box=None) -> DataFrame:
    """(id, cluster): density-based clusters. Core points have min_pts points within r (themselves included); the
    cluster of a core is its smallest core id; other points take the smallest cluster in reach, or null (noise)."""
    from zplane.operators.linking import link_clusters
    from zplane.session import stored

    points = df.select(F.col(id_col).cast("long").alias("id"), *(F.col(c).alias(c) for c in cols))
    counted = stored(points.join(count_within(points, None, r, cols, box=box), "id"), "counted")
    label = link_clusters(counted.where(F.col("n") >= min_pts).drop("n"), cols, r, box=box).select("id", F.col("group_id").alias("cluster"))
    label = stored(label, "cores")
    # points that are no cores have fewer than min_pts others in reach, so these pairs are few
    near = distance_join(counted.where(F.col("n") < min_pts), counted.where(F.col("n") >= min_pts), r, cols, box=box)
    border = near.join(label.withColumnRenamed("id", "sid"), "sid").groupBy("qid").agg(F.min("cluster").alias("near")).withColumnRenamed("qid", "id")
    return points.select("id").join(label, "id", "left").join(border, "id", "left").select("id", F.coalesce("cluster", "near").alias("cluster"))


def range_query(tree: PlaneTree, center: list[float], r: float, box=None) -> DataFrame:
    """Source points of a tree within r of a place: leaves are pruned by their bounds, then points are tested."""
    import builtins

    d = tree.d
    c = [F.lit(float(v)) for v in center]
    leaf = tree.nodes.where("plane = 0")
    terms = [F.greatest(F.abs(_wrapped(F.col("c")[i] - c[i], box, i)) - F.col("ext")[i] / 2.0, F.lit(0.0)) for i in range(d)]
    low = builtins.sum((t * t for t in terms[1:]), terms[0] * terms[0])
    near = leaf.where(F.isnan(low) | (low <= r * r * (1 + 1e-9))).select(F.col("node").alias("leaf"))
    pts = tree.points.where("ptype = 0").join(near, "leaf", "left_semi")
    return pts.where(dist2([F.col(f"x{i}") for i in range(d)], c, box) <= r * r)


def _wrapped(delta, box, i):
    from zplane.functions.bounds import wrap

    return wrap(delta, box[i] if box else None)


def in_box(df: DataFrame, lo: list, hi: list, cols: list[str]) -> DataFrame:
    """Points in an axis-parallel box; plain range predicates, so parquet statistics prune."""
    cond = None
    for c, a, b in zip(cols, lo, hi):
        t = F.col(c).between(a, b)
        cond = t if cond is None else cond & t
    return df.where(cond)


def box_to_key_ranges(lo: list[float], hi: list[float], box: tuple, max_ranges: int = 16, bits: int | None = None) -> list[tuple[int, int]]:
    """Ranges of 63-bit Morton keys that cover a query box (box: the domain that the keys were made with)."""
    d = len(lo)
    bits = bits or 63 // d
    scale = lambda v, i: int(min((1 << bits) - 1, max(0, np.floor((v - box[i][0]) / (box[i][1] - box[i][0]) * (1 << bits)))))
    a, b = [scale(v, i) for i, v in enumerate(lo)], [scale(v, i) for i, v in enumerate(hi)]
    todo, out = [(0, 0, [0] * d, [(1 << bits) - 1] * d)], []
    total = d * bits
    while todo:
        todo.sort(key=lambda t: t[0])
        depth, prefix, x, y = todo.pop(0)
        if any(y[i] < a[i] or x[i] > b[i] for i in range(d)):
            continue
        inside = all(x[i] >= a[i] and y[i] <= b[i] for i in range(d))
        if inside or depth == total or len(todo) + len(out) + 2 > max_ranges:
            out.append((prefix << (total - depth), ((prefix + 1) << (total - depth)) - 1))
            continue
        i = depth % d
        mid = (x[i] + y[i] + 1) // 2
        todo.append((depth + 1, prefix << 1, x, [*y[:i], mid - 1, *y[i + 1 :]]))
        todo.append((depth + 1, prefix << 1 | 1, [*x[:i], mid, *x[i + 1 :]], y))
    out.sort()
    merged: list[tuple[int, int]] = []
    for s, e in out:
        if merged and s <= merged[-1][1] + 1:
            merged[-1] = (merged[-1][0], max(e, merged[-1][1]))
        else:
            merged.append((s, e))
    return merged


def interval_join(a: DataFrame, b: DataFrame, width: float, point: str = "t", start: str = "lo", end: str = "hi") -> DataFrame:
    """Rows of a whose point lies in [start, end) of rows of b: an equi-join on buckets of `width`, then the predicate."""
    x = a.withColumn("__b", F.floor(F.col(point) / width))
    y = b.withColumn("__b", F.explode(F.sequence(F.floor(F.col(start) / width), F.floor(F.col(end) / width))))
    return x.join(y, "__b").where((F.col(point) >= F.col(start)) & (F.col(point) < F.col(end))).drop("__b")


def asof_nearest(a: DataFrame, b: DataFrame, on: str, by: str, value: str, direction: str = "backward") -> DataFrame:
    """a with the value of the last row of b at or before (backward) or the first at or after (forward) each row, within `by`."""
    rows = a.select(by, on, F.lit(1).alias("__a"), F.struct(*a.columns).alias("__row"), F.lit(None).cast(b.schema[value].dataType).alias("__v"))
    rows = rows.unionByName(b.select(by, on, F.lit(0).alias("__a"), F.lit(None).cast(rows.schema["__row"].dataType).alias("__row"), F.col(value).alias("__v")))
    back = direction == "backward"
    w = W.partitionBy(by).orderBy(F.col(on) if back else F.col(on).desc(), "__a").rowsBetween(W.unboundedPreceding, 0)
    return rows.withColumn("__got", F.last("__v", ignorenulls=True).over(w)).where("__a = 1").select("__row.*", F.col("__got").alias(f"{value}_asof"))


def knn_graph(neighbours: DataFrame, kind: str = "mutual") -> DataFrame:
    """(a, b): pairs that are each other's neighbours (mutual) or at least one way (any), a < b; self pairs left out."""
    e = neighbours.where("qid <> sid").select(F.least("qid", "sid").alias("a"), F.greatest("qid", "sid").alias("b"))
    return e.groupBy("a", "b").agg(F.count("*").alias("n")).where(F.col("n") >= (2 if kind == "mutual" else 1)).select("a", "b")


def reverse_neighbours(neighbours: DataFrame) -> DataFrame:
    """(sid, n): how many other points have each point among their neighbours."""
    return neighbours.where("qid <> sid").groupBy("sid").agg(F.count("*").alias("n"))


def node_moments(tree: PlaneTree, cols: list[str]) -> DataFrame:
    """(plane, node, n, sums..): per-node sums of point columns, leaf sums rolled up along parents."""
    leaf = tree.points.groupBy(F.col("leaf").alias("node")).agg(F.count("*").alias("n"), *(F.sum(c).alias(f"sum_{c}") for c in cols))
    out = leaf.select(F.lit(0).alias("plane"), "*")
    now = leaf
    for p in range(1, tree.planes):
        up = tree.nodes.where(F.col("plane") == p - 1).select("node", "parent")
        now = now.join(up, "node").groupBy(F.col("parent").alias("node")).agg(F.sum("n").alias("n"), *(F.sum(f"sum_{c}").alias(f"sum_{c}") for c in cols))
        out = out.unionByName(now.select(F.lit(p).alias("plane"), "*"))
    return out

"""Linking-length clusters: connected components of the points closer than a length, and their catalogue.

The walk links whole nodes where all their points are surely close, drops pairs that surely are not, and
leaves the rest to point tests. What a domain finds are edges between points, or between points and leaf
markers; contraction over all domains gives the groups, whatever domain their roots lie in.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zplane.components import components_with_rounds, union_find
from zplane.operators.knn import domain_rows, joint_tree, squared, unpack
from zplane.plans import walk
from zplane.plans.planes import NODE_SPAN, Options, PlaneTree
from zplane.session import stored

#: Leaf markers are numbered from here on, so ids must be smaller.
MARK = 1 << 62


def linking_length(n: int, volume: float, d: int = 3, alpha: float = 0.2) -> float:
    """alpha times the mean separation of n points in a volume."""
    return alpha * (volume / n) ** (1.0 / d)


def link_edges(df: DataFrame, cols: list[str], r_link: float, id_col: str = "id", box=None, options: Options | None = None, tree: PlaneTree | None = None, method: str = "auto") -> tuple[DataFrame, PlaneTree]:
    """Edges (a, b) whose components are the groups (points, and node markers from MARK on), and the tree."""
    tree = tree or joint_tree(df, None, cols, id_col, options)
    if method == "stages" or (method == "auto" and not walk.fits(tree)):
        pairs, marks, leaves = walk.radius_stages(tree, r_link, box, True, link=True)
        inside = tree.points.join(leaves.withColumnRenamed("node", "leaf"), "leaf").select(F.col("id").alias("a"), walk.marker(F.col("leaf"), 0).alias("b"))
        return _tested(tree, pairs, r_link, box).unionAll(marks).unionAll(inside), tree

    found = _walked(tree, r_link, box)
    whole = found.where("whole").select(F.col("recv").alias("leaf"), F.col("src").alias("root"))
    marks = whole.select((F.col("leaf") + MARK).alias("a"), (F.col("root") + MARK).alias("b")).where("a <> b")
    ends = whole.select("leaf").union(whole.select(F.col("root").alias("leaf"))).distinct()
    inside = tree.points.join(ends, "leaf").select(F.col("id").alias("a"), (F.col("leaf") + MARK).alias("b"))
    return _tested(tree, found.where("NOT whole").select("domain", "recv", "src"), r_link, box).unionAll(marks).unionAll(inside), tree


def _walked(tree: PlaneTree, r_link: float, box) -> DataFrame:
    """(domain, recv, src, whole): open leaf pairs, and pairs of leaves that are linked whole, by the domain of recv."""
    ngr = tree.ngr

    def make(planes, domains):
        import pyarrow as pa

        (recv, src), (leaf, root) = walk.link_pairs(planes, domains, r_link, box, ngr)
        pl = planes[0]
        a = np.concatenate([pl.node[recv], pl.node[leaf]])
        return pa.RecordBatch.from_arrays(
            [pa.array(np.concatenate([pl.domain[recv], pl.domain[leaf]]).astype(np.int32)), pa.array(a), pa.array(np.concatenate([pl.node[src], pl.node[root]])), pa.array(np.arange(len(a)) >= len(recv))],
            ["domain", "recv", "src", "whole"],
        )

    return stored(walk.walk_in_tasks(tree, make, "domain int, recv long, src long, whole boolean"), "links")


def _tested(tree: PlaneTree, pairs: DataFrame, r_link: float, box) -> DataFrame:
    """Spanning edges of the point pairs within r_link of open leaf pairs, domain by domain."""
    d = tree.d

    def run(table):
        import pyarrow as pa

        x, y = spanning_edges(table, d, r_link, box)
        return pa.table({"a": pa.array(x, pa.int64()), "b": pa.array(y, pa.int64())})

    return domain_rows(tree, pairs.withColumn("r_low", F.lit(0.0)), True).groupBy("domain").applyInArrow(run, "a long, b long")


def spanning_edges(table, d: int, r_link: float, box=None) -> tuple[np.ndarray, np.ndarray]:
    """Edges from each point of a domain's listed leaves to the smallest id that its links within these lists reach.

    Groups grow as pairs of leaves are tested, each leaf with itself first; a pair whose points are one group already
    is not measured, so dense regions cost a test for each pair of leaves and not an edge for each pair of points.
    """
    (q_leaf, q_id, q, _), (s_leaf, s_id, s, _), (p_leaf, p_src, _) = unpack(table, d)
    ids, at = np.unique(np.concatenate([q_id, s_id]), return_inverse=True)
    root = np.arange(len(ids))
    to = test_pairs(root, (q_leaf, at[: len(q_id)], q), (s_leaf, at[len(q_id) :], s), (p_leaf, p_src), r_link, box)
    far = np.flatnonzero(to != np.arange(len(ids)))
    return ids[far], ids[to[far]]


#: Leaf pairs between two looks at which leaves are one group by now.
LOOK = 1024


def test_pairs(root: np.ndarray, q_side, s_side, pairs, r_link: float, box=None) -> np.ndarray:
    """The smallest node that the links of leaf pairs reach, for every node; root holds links known before.

    Both sides are (leaf, node, x) sorted by leaf, pairs (leaf, source leaf). Pairs whose points are one group by now are
    dropped many at a time.
    """
    (q_leaf, q_at, q), (s_leaf, s_at, s), (p_leaf, p_src) = q_side, s_side, pairs

    def find(x):
        r = root[x]
        while (r != (up := root[r])).any():
            r = up
        root[x] = r
        return r

    def spread(leaf, at):
        """(leaves, least and largest root of each)"""
        first = np.flatnonzero(np.append(True, leaf[1:] != leaf[:-1])) if len(leaf) else np.zeros(0, np.int64)
        to = root[at]
        return leaf[first], *((op.reduceat(to, first) if len(first) else first) for op in (np.minimum, np.maximum))

    order = np.argsort(p_leaf != p_src, kind="stable")
    p_leaf, p_src = p_leaf[order], p_src[order]
    ends = np.array([np.searchsorted(l, p, x) for l, p in ((q_leaf, p_leaf), (s_leaf, p_src)) for x in ("left", "right")])
    full = (ends[0] < ends[1]) & (ends[2] < ends[3])
    p_leaf, p_src, ends = p_leaf[full], p_src[full], ends[:, full]
    while len(p_leaf):
        find(np.arange(len(root)))
        (a, a_lo, a_hi), (b, b_lo, b_hi) = spread(q_leaf, q_at), spread(s_leaf, s_at)
        i, j = np.searchsorted(a, p_leaf), np.searchsorted(b, p_src)
        open_ = (a_lo[i] != a_hi[i]) | (b_lo[j] != b_hi[j]) | (a_lo[i] != b_lo[j])
        p_leaf, p_src, ends = p_leaf[open_], p_src[open_], ends[:, open_]
        for lo, hi, c, e in zip(*(x.tolist() for x in ends[:, :LOOK])):
            for x in range(lo, hi, 2048):
                rows = slice(x, min(x + 2048, hi))
                a, b = find(q_at[rows]), find(s_at[c:e])
                if (a == b[0]).all() and (b == b[0]).all():
                    continue
                near = (squared(q[rows], s[c:e], box) <= r_link * r_link) & (a[:, None] != b[None])
                while near.any():  # a link of every row and column at once, until no two groups are left
                    i, j = np.flatnonzero(near.any(1)), np.flatnonzero(near.any(0))
                    nodes, roots = union_find(np.concatenate([a[i], a[near[:, j].argmax(0)]]), np.concatenate([b[near[i].argmax(1)], b[j]]))
                    root[nodes] = roots
                    a, b = find(a), find(b)
                    near &= a[:, None] != b[None]
        p_leaf, p_src, ends = p_leaf[LOOK:], p_src[LOOK:], ends[:, LOOK:]
    return find(np.arange(len(root)))


#: What domain_groups says of: a point of the domain, a point of another one, a leaf of the domain that is one group.
OWN, OTHER, LEAF = 0, 1, 2


def domain_groups(table, d: int, r_link: float, box=None):
    """(kind, id, leaf, root) of a domain: the smallest id that each of its points reaches by the links it has seen,
    the same of other domains' points that are linked with its own, and its leaves whose points are one group.

    Pairs with r = 1 are leaves linked whole; a leaf of another domain that is linked whole comes without a point.
    """
    (o_leaf, o_id, o, _), (f_leaf, f_id, f, _), (p_leaf, p_src, p_r) = unpack(table, d)
    whole = p_r > 0
    leaves = np.unique(np.concatenate([p_leaf[whole], p_src[whole]]))
    ids, at = np.unique(np.concatenate([o_id, f_id]), return_inverse=True)
    n = len(ids)
    root = np.arange(n + len(leaves))  # points by id, then the leaves that are linked whole
    mark = lambda leaf: n + np.searchsorted(leaves, leaf)
    own = at[: len(o_id)]
    inside = np.isin(o_leaf, leaves)
    nodes, to = union_find(np.concatenate([mark(p_leaf[whole]), own[inside]]), np.concatenate([mark(p_src[whole]), mark(o_leaf[inside])]))
    root[nodes] = to
    leaf, x = np.concatenate([o_leaf, f_leaf]), np.concatenate([o, f])
    order = np.argsort(leaf, kind="stable")
    root = test_pairs(root, (o_leaf, own, o), (leaf[order], at[order], x[order]), (p_leaf[~whole], p_src[~whole]), r_link, box)
    held = np.zeros(len(root), bool)
    held[root[own]] = True
    first = np.flatnonzero(np.append(True, o_leaf[1:] != o_leaf[:-1])) if len(o_leaf) else np.zeros(0, np.int64)
    to = root[own]
    low, high = (op.reduceat(to, first) if len(first) else first for op in (np.minimum, np.maximum))
    even = low == high
    other = at[len(o_id) :]
    linked = held[root[other]]
    far = leaves[~np.isin(leaves, o_leaf)]
    far = far[held[root[mark(far)]]]
    kind = np.repeat(np.array([OWN, OTHER, OTHER, LEAF], np.int32), [len(o_id), linked.sum(), len(far), even.sum()])
    node = np.concatenate([o_id, f_id[linked], np.full(len(far) + int(even.sum()), -1)])
    leaf = np.concatenate([o_leaf, f_leaf[linked], far, o_leaf[first][even]])
    return kind, node, leaf, ids[np.concatenate([to, root[other[linked]], root[mark(far)], low[even]])]


def grouped(tree: PlaneTree, r_link: float, box=None) -> tuple[DataFrame, int]:
    """((id, group_id) of every point, contraction rounds): each domain labels its own points, and only labels are contracted.

    Domains meet in points that several of them see. A leaf that is one group at home stands for its points, so few points
    are looked up, and the contracted graph has a node for each group of a domain that others touch, not for each point.
    """
    d = tree.d
    found = _walked(tree, r_link, box)
    open_ = found.where(f"NOT whole AND src div {NODE_SPAN} <> domain").select("domain", "src")
    pairs = found.select("domain", "recv", "src", F.col("whole").cast("double").alias("r_low"))

    def run(table):
        import pyarrow as pa

        return pa.table(dict(zip(("kind", "id", "leaf", "root"), domain_groups(table, d, r_link, box))))

    seen = stored(domain_rows(tree, pairs, True, open_).groupBy("domain").applyInArrow(run, "kind int, id long, leaf long, root long"), "seen")
    own = seen.where(F.col("kind") == OWN).select("id", F.col("root").alias("here"))
    other = seen.where(F.col("kind") == OTHER)
    even = seen.where(F.col("kind") == LEAF).select("leaf", F.col("root").alias("here"))
    by_leaf = other.select("leaf", "root").distinct().join(even, "leaf").select("here", "root")
    by_point = other.join(even, "leaf", "left_anti").select("id", "root").join(own, "id").select("here", "root")
    edges = stored(by_leaf.unionAll(by_point).where("here <> root").distinct(), "edges")
    roots, rounds = components_with_rounds(edges, "here", "root")
    roots = stored(roots.where("node <> root").select(F.col("node").alias("here"), F.col("root").alias("group_id")), "roots")
    return own.join(roots, "here", "left").select("id", F.coalesce("group_id", "here").alias("group_id")), rounds


def link_clusters(df: DataFrame, cols: list[str], r_link: float, id_col: str = "id", box=None, options: Options | None = None, label: str = "min_id", method: str = "auto") -> DataFrame:
    """(id, group_id) of every point; group_id is the smallest id of the group (label='z_root': the id of its first point in Morton order)."""
    return link_clusters_with_rounds(df, cols, r_link, id_col, box, options, label, method)[0]


def link_clusters_with_rounds(df, cols, r_link, id_col="id", box=None, options=None, label="min_id", method="auto"):
    """link_clusters, and the rounds that contraction took."""
    tree = joint_tree(df, None, cols, id_col, options)
    if method == "stages" or (method == "auto" and not walk.fits(tree)):
        edges, _ = link_edges(df, cols, r_link, id_col, box, options, tree, "stages")
        roots, rounds = components_with_rounds(stored(edges, "edges"))
        roots = roots.where(F.col("node") < MARK)
        out = tree.points.select("id").join(roots.withColumnRenamed("node", "id"), "id", "left").select("id", F.coalesce("root", "id").alias("group_id"))
    else:
        out, rounds = grouped(tree, r_link, box)
    if label == "z_root":
        out = out.join(tree.points.select("id", "domain", "pos"), "id")
        first = out.groupBy("group_id").agg(F.min_by("id", F.struct("domain", "pos")).alias("z"))
        out = out.join(first, "group_id").select("id", F.col("z").alias("group_id"))
    return out.select("id", "group_id"), rounds


def group_order(df: DataFrame, labelled: DataFrame, tree: PlaneTree) -> DataFrame:
    """Points sorted by group and in Morton order inside; groups are contiguous and may span partitions."""
    return df.join(labelled, "id").join(tree.points.select("id", "domain", "pos"), "id").repartitionByRange("group_id", "domain", "pos").sortWithinPartitions("group_id", "domain", "pos")


def catalogue(points: DataFrame, labelled: DataFrame, cols: list[str], mass: str | None = None, vel: list[str] = (), min_count: int = 20, box=None) -> DataFrame:
    """(group_id, n, mass, com_x.., com_v.., r_inertia) of groups of at least min_count points.

    Each batch of rows sends one row of moments for each of its groups, so a giant group is no task of its own.
    With a box, positions are unwrapped around the group's first point before they are averaged.
    """
    rows = points.join(labelled, "id")
    m = F.col(mass).cast("double") if mass else F.lit(1.0)
    place = [F.col(c).cast("double") for c in cols]
    if box:
        anchor = points.select(F.col("id").alias("group_id"), *(F.col(c).alias(f"__a{i}") for i, c in enumerate(cols)))
        rows = rows.join(anchor, "group_id")  # one anchor a group, so a giant group is split by skew handling
        from zplane.functions.bounds import wrap

        place = [F.col(f"__a{i}") + wrap(F.col(c) - F.col(f"__a{i}"), box[i]) for i, c in enumerate(cols)]
    d, e = len(cols), len(cols) + len(vel)
    names = ["group_id", "n", "mass", *(f"s{i}" for i in range(e)), "spread"]
    kind = "group_id long, n long, mass double, " + ", ".join(f"s{i} double" for i in range(e)) + ", spread double"

    def partial(batches):
        """Moments of the rows of each batch by group: mass, weighted sums, and the weighted spread around the batch's own centre."""
        import pyarrow as pa

        for b in batches:
            if not b.num_rows:
                continue
            ids, at = np.unique(b.column(0).to_numpy(), return_inverse=True)
            w = b.column(1).to_numpy()
            x = np.column_stack([b.column(2 + i).to_numpy(zero_copy_only=False) for i in range(e)])
            total = np.bincount(at, weights=w, minlength=len(ids))
            sums = np.column_stack([np.bincount(at, weights=w * x[:, i], minlength=len(ids)) for i in range(e)])
            with np.errstate(invalid="ignore", divide="ignore"):
                off = x[:, :d] - (sums[:, :d] / total[:, None])[at]
            spread = np.bincount(at, weights=w * (off * off).sum(1), minlength=len(ids))
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(np.bincount(at, minlength=len(ids))), pa.array(total), *(pa.array(sums[:, i]) for i in range(e)), pa.array(spread)], names)

    parts = rows.select("group_id", m.alias("m"), *(x.alias(f"p{i}") for i, x in enumerate(place)), *(F.col(v).cast("double").alias(f"v{i}") for i, v in enumerate(vel))).mapInArrow(partial, kind)
    parts = stored(parts, "moments")
    sums = parts.groupBy("group_id").agg(F.sum("n").alias("n"), F.sum("mass").alias("mass"), *(F.sum(f"s{i}").alias(f"s{i}") for i in range(e))).where(F.col("n") >= min_count)
    first = sums.select("group_id", "n", "mass", *(F.try_divide(f"s{i}", "mass").alias(f"com_x{i}") for i in range(d)), *(F.try_divide(f"s{d + i}", "mass").alias(f"com_v{i}") for i in range(len(vel))))
    off = None
    for i in range(d):
        t = F.try_divide(f"s{i}", "part") - F.col(f"com_x{i}")
        off = t * t if off is None else off + t * t
    met = parts.select("group_id", F.col("mass").alias("part"), *(f"s{i}" for i in range(d)), "spread").join(first, "group_id")
    spread = met.groupBy("group_id").agg(F.sqrt(F.try_divide(F.sum(F.col("spread") + F.coalesce(F.col("part") * off, F.lit(0.0))), F.first("mass"))).alias("r_inertia"))
    return first.join(spread, "group_id")


def group_sizes(labelled: DataFrame) -> DataFrame:
    """(size, groups): how many groups have each size."""
    return labelled.groupBy("group_id").agg(F.count("*").alias("size")).groupBy("size").agg(F.count("*").alias("groups"))


def group_points(path_or_df, group_id: int, spark=None) -> DataFrame:
    """The points of one group; from a file written in group order, row groups outside it are skipped."""
    df = spark.read.parquet(path_or_df) if isinstance(path_or_df, str) else path_or_df
    return df.where(F.col("group_id") == group_id)

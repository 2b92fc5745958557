"""Exact k-nearest-neighbour joins on the plane hierarchy."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zplane.functions.bounds import BOUND_SLACK
from zplane.plans import walk
from zplane.plans.planes import NODE_SPAN, Options, PlaneTree, build_tree

QUERY, SOURCE, PAIR = 0, 1, 2


def joint_tree(src: DataFrame, queries: DataFrame | None, cols: list[str], id_col: str = "id", options: Options | None = None, payload: list[str] = (), on_invalid: str = "error") -> PlaneTree:
    """One tree over sources and queries (types 0 and 1), or over the sources alone for self queries."""
    keep = [id_col, *cols, *payload]
    rows = src.select(*keep).withColumn("__t", F.lit(0))
    if queries is not None:
        ask = queries.select(id_col, *cols)
        rows = rows.unionByName(ask.withColumns({p: F.lit(None).cast("double") for p in payload}).select(*keep).withColumn("__t", F.lit(1)))
    return build_tree(rows, cols, id_col, "__t", options, on_invalid, list(payload))


def domain_rows(tree: PlaneTree, ilist: DataFrame, self_query: bool, sources: DataFrame | None = None) -> DataFrame:
    """What each domain's leaf step needs: its query points, its list, and every source leaf that is on the
    list once (shipped once for each domain, however many receivers share it). sources: the (domain, src) to ship, if not all."""
    names = [c for c in tree.points.columns if c[0] in "xy" and c[1:].isdigit()]
    none = [F.lit(None).cast("double").alias(c) for c in names]
    pts = tree.points
    q = (pts if self_query else pts.where("ptype = 1")).select("domain", F.lit(QUERY).alias("kind"), "leaf", F.lit(None).cast("long").alias("src"), F.lit(None).cast("double").alias("r"), "id", *names)
    wanted = (ilist if sources is None else sources).select("domain", F.col("src").alias("leaf")).distinct()
    s = wanted.join(pts.where("ptype = 0").drop("domain"), "leaf").select("domain", F.lit(SOURCE).alias("kind"), "leaf", F.lit(None).cast("long").alias("src"), F.lit(None).cast("double").alias("r"), "id", *names)
    p = ilist.select("domain", F.lit(PAIR).alias("kind"), F.col("recv").alias("leaf"), "src", F.col("r_low").alias("r"), F.lit(None).cast("long").alias("id"), *none)
    return q.unionAll(s).unionAll(p)


def unpack(table, d: int):
    """(queries, sources, pairs) of a domain as arrays sorted by leaf: (leaf, id, x), (leaf, id, x, y), (leaf, src, r)."""
    kind = table.column("kind").to_numpy()
    leaf = table.column("leaf").to_numpy()
    names = [c for c in table.column_names if c[0] in "xy" and c[1:].isdigit()]

    def points(which):
        at = np.flatnonzero(kind == which)
        part = table.take(at)
        order = np.argsort(leaf[at], kind="stable")
        x = np.column_stack([part.column(c).to_numpy(zero_copy_only=False) for c in names])[order] if len(at) else np.zeros((0, len(names)))
        return leaf[at][order], part.column("id").to_numpy(zero_copy_only=False).astype(np.int64)[order], x[:, :d], x[:, d:]

    at = np.flatnonzero(kind == PAIR)
    part = table.take(at)
    src, r = part.column("src").to_numpy(zero_copy_only=False).astype(np.int64), part.column("r").to_numpy(zero_copy_only=False)
    order = np.lexsort((src, r, leaf[at]))
    return points(QUERY), points(SOURCE), (leaf[at][order], src[order], r[order])


def squared(q: np.ndarray, s: np.ndarray, box) -> np.ndarray:
    out = None
    for i in range(q.shape[1]):
        t = q[:, None, i] - s[None, :, i]
        if box is not None and box[i] is not None:
            t = t - box[i] * np.floor(t / box[i] + 0.5)
        out = t * t if out is None else out + t * t
    return out


#: Dimensions from which pairs are sifted by a matrix product before they are measured.
SIFT_DIMS = 16


def sifted(q: np.ndarray, s: np.ndarray, k: int, worst: np.ndarray, apart: np.ndarray | None = None):
    """(row, column, squared) of every pair that may be among the k nearest of its row, measured as squared() does; None if a square overflows.

    A matrix product gives each distance up to a bound of its rounding; pairs whose least distance is beyond the
    greatest of k others, or beyond `worst` of the row, are left out. apart: pairs that do not count.
    """
    qq, ss = (q * q).sum(1)[:, None], (s * s).sum(1)[None]
    slack = (qq + ss) * (4 * (q.shape[1] + 8) * np.finfo(float).eps) + np.finfo(float).tiny * 1e6
    about = qq + ss - 2 * (q @ s.T)
    if not np.isfinite(about).all():
        return None
    if apart is not None:
        about[apart] = np.inf
    cut = np.partition(about + slack, k - 1, axis=1)[:, k - 1] if len(s) > k else np.full(len(q), np.inf)
    r, c = np.nonzero((about - slack <= np.minimum(cut, worst)[:, None]) & (about < np.inf))
    out = None
    for i in range(q.shape[1]):
        t = q[r, i] - s[c, i]
        out = t * t if out is None else out + t * t
    return r, c, out


class LeafSearch:
    """The leaf step of one domain: nearest sources of every query over the listed leaves, nearest leaves first."""

    def __init__(self, table, d: int, k: int, box=None, include_self: bool = True, early_exit: bool = True, k_pass: int | None = None):
        (self.q_leaf, self.q_id, self.q, _), (self.s_leaf, self.s_id, self.s, self.y), (self.p_leaf, self.p_src, self.p_r) = unpack(table, d)
        self.k, self.box, self.include_self, self.early_exit, self.k_pass = k, box, include_self, early_exit, k_pass
        self.evaluated = self.listed = self.skipped = 0
        self._thin(k + (not include_self))

    def _thin(self, need: int):
        """Leaves of coincident sources keep their `need` smallest ids: of a site no query takes more."""
        first = np.flatnonzero(np.append(True, self.s_leaf[1:] != self.s_leaf[:-1])) if len(self.s_leaf) else np.zeros(0, np.int64)
        size = np.diff(np.append(first, len(self.s_leaf)))
        if not len(first) or size.max() <= need:
            return
        site = (size > need) & (np.minimum.reduceat(self.s, first) == np.maximum.reduceat(self.s, first)).all(1)
        keep = np.ones(len(self.s_leaf), bool)
        for a, n in zip(first[site].tolist(), size[site].tolist()):
            keep[a : a + n] = False
            keep[a + np.argpartition(self.s_id[a : a + n], need - 1)[:need]] = True
        self.s_leaf, self.s_id, self.s, self.y = self.s_leaf[keep], self.s_id[keep], self.s[keep], self.y[keep]

    def leaves(self):
        """(query rows, neighbours (row, source row, d2) sorted by row, d2, id) of each receiving leaf."""
        recv = np.unique(self.q_leaf)
        q_at = np.searchsorted(self.q_leaf, [recv, recv + 1])
        p_at = np.searchsorted(self.p_leaf, [recv, recv + 1])
        s_lo, s_hi = np.searchsorted(self.s_leaf, self.p_src, "left"), np.searchsorted(self.s_leaf, self.p_src, "right")
        for i in range(len(recv)):
            rows = np.arange(q_at[0][i], q_at[1][i])
            pairs = np.arange(p_at[0][i], p_at[1][i])
            if len(rows) > 1 and (self.q[rows] == self.q[rows[0]]).all():
                yield rows, self._site(rows, pairs, s_lo, s_hi)
            else:
                yield rows, self._passes(rows, pairs, s_lo, s_hi, self.k, self.include_self)

    def _site(self, rows, pairs, s_lo, s_hi):
        """Coincident queries share one search; where a point leaves itself out, one neighbour more is found and its own dropped."""
        k, n = self.k, len(rows)
        _, src, d2 = self._passes(rows[:1], pairs, s_lo, s_hi, k + (not self.include_self), True)
        keep = np.ones((n, len(src)), bool)
        if not self.include_self:
            keep = self.q_id[rows][:, None] != self.s_id[src][None]
            keep[keep.all(1), k:] = False
        row, at = np.nonzero(keep)
        return row, src[at], d2[at]

    def _passes(self, rows, pairs, s_lo, s_hi, k, include_self):
        if not self.k_pass or k <= self.k_pass:
            return self._search(rows, pairs, s_lo, s_hi, k, None, include_self)
        parts, floor, left = [], None, k
        while left > 0:  # passes of k_pass neighbours, each beyond the last one found
            got = self._search(rows, pairs, s_lo, s_hi, min(left, self.k_pass), floor, include_self)
            parts.append(got)
            left -= self.k_pass
            d2, sid = np.full(len(rows), np.inf), np.full(len(rows), np.iinfo(np.int64).max)
            last = np.flatnonzero(np.append(got[0][1:] != got[0][:-1], True)) if len(got[0]) else np.zeros(0, np.int64)
            full = np.bincount(got[0], minlength=len(rows)) == min(left + self.k_pass, self.k_pass)
            d2[got[0][last]], sid[got[0][last]] = got[2][last], self.s_id[got[1][last]]
            d2[~full] = np.inf
            floor = (d2, sid)
        row, src, d2 = (np.concatenate(c) for c in zip(*parts))
        order = np.lexsort((self.s_id[src], d2, row))
        return row[order], src[order], d2[order]

    def _search(self, rows, pairs, s_lo, s_hi, k, floor, include_self):
        q = self.q[rows]
        best = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))
        radius, j = np.inf, 0
        self.listed += len(pairs)
        while j < len(pairs):
            if self.early_exit and self.p_r[pairs[j]] ** 2 > radius * (1 + 4 * BOUND_SLACK):
                self.skipped += len(pairs) - j
                break
            take, size = [], 0
            while j < len(pairs) and size < max(512, 2 * k):
                take.append(np.arange(s_lo[pairs[j]], s_hi[pairs[j]]))
                size += len(take[-1])
                j += 1
            src = np.concatenate(take)
            for lo in range(0, len(src), 8192):
                part = src[lo : lo + 8192]
                self.evaluated += len(q) * len(part)
                worst = np.full(len(rows), np.inf)
                if len(best[0]):
                    count = np.bincount(best[0], minlength=len(rows))
                    last = np.cumsum(count) - 1
                    worst[count >= k] = best[2][last[count >= k]]
                own = None if include_self else self.q_id[rows][:, None] == self.s_id[part][None]
                got = sifted(q, self.s[part], k, worst, own) if q.shape[1] >= SIFT_DIMS and self.box is None and floor is None else None
                if got is None:
                    d2 = squared(q, self.s[part], self.box)
                    if own is not None:
                        d2[own] = np.inf
                    if floor is not None:
                        d2[(d2 < floor[0][:, None]) | ((d2 == floor[0][:, None]) & (self.s_id[part][None] <= floor[1][:, None]))] = np.inf
                    cut = np.partition(d2, k - 1, axis=1)[:, k - 1] if d2.shape[1] > k else np.full(len(rows), np.inf)
                    r, c = np.nonzero((d2 <= np.minimum(cut, worst)[:, None]) & (d2 < np.inf))
                    got = r, c, d2[r, c]
                r, c, new = got
                row, s, v = np.concatenate([best[0], r]), np.concatenate([best[1], part[c]]), np.concatenate([best[2], new])
                order = np.lexsort((self.s_id[s], v, row))
                row, s, v = row[order], s[order], v[order]
                first = np.searchsorted(row, np.arange(len(rows)))
                keep = np.arange(len(row)) - first[row] < k
                best = row[keep], s[keep], v[keep]
            count = np.bincount(best[0], minlength=len(rows))
            radius = best[2].max() if (count >= k).all() else np.inf
        return best


#: Rows of a group's result that a task gathers before it passes them on.
OUT_ROWS = 1 << 18


def streamed(parts):
    """A function for applyInArrow that passes a group's rows on as they are found, so a task holds OUT_ROWS of them or so.

    parts(table) yields dicts of equally long arrays by column.
    """
    import pyarrow as pa

    def run(batches):
        import pyarrow as pa

        held, n = [], 0

        def flush():
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate([h[c] for h in held])) for c in held[0]], list(held[0]))

        for part in parts(pa.Table.from_batches(list(batches))):
            held.append(part)
            n += len(next(iter(part.values())))
            if n >= OUT_ROWS:
                yield flush()
                held, n = [], 0
        if n:
            yield flush()

    run.__annotations__ = {"batches": Iterator[pa.RecordBatch], "return": Iterator[pa.RecordBatch]}  # Spark reads the form from these
    return run


def rows_kernel(d, k, box, include_self, early_exit, k_pass):
    def parts(table):
        search = LeafSearch(table, d, k, box, include_self, early_exit, k_pass)
        for rows, (row, src, d2) in search.leaves():
            first = np.searchsorted(row, np.arange(len(rows)))
            rank = (np.arange(len(row)) - first[row] + 1).astype(np.int32)
            yield {"qid": search.q_id[rows][row].astype(np.int64), "rank": rank, "sid": search.s_id[src].astype(np.int64), "dist2": d2.astype(np.float64)}

    return streamed(parts)


def knn(src: DataFrame, k: int, cols: list[str], queries: DataFrame | None = None, id_col: str = "id", include_self: bool = True, box=None, options: Options | None = None, order: str | None = None, early_exit: bool = True, k_pass: int | None = None, method: str = "auto", on_invalid: str = "error", tree: PlaneTree | None = None, heap_slots: int | None = None) -> DataFrame:
    """(qid, rank, sid, dist): the k nearest sources of every query point; ties go to the smaller id.

    Without queries the sources are their own queries (include_self=False leaves a point itself out, by
    id). box gives a period for each dimension or None. order: 'z', 'input' or None (as computed, which
    costs no shuffle). A query with fewer than k sources gets fewer rows. heap_slots: the walk finds its radii
    in heaps of so many places.
    """
    self_query = queries is None
    tree = tree or joint_tree(src, queries, cols, id_col, options, (), on_invalid)
    ilist = walk.knn_ilist(tree, k + (self_query and not include_self), box, self_query, method, heap_slots)
    rows = domain_rows(tree, ilist, self_query).groupBy("domain").applyInArrow(rows_kernel(tree.d, k, box, include_self, early_exit, k_pass), "qid long, rank int, sid long, dist2 double")
    out = rows.select("qid", "rank", "sid", F.sqrt("dist2").alias("dist"))
    if order == "input":
        return out.orderBy("qid", "rank")
    if order == "z":
        place = tree.points.where(F.col("ptype") == (0 if self_query else 1)).select(F.col("id").alias("qid"), "domain", "pos")
        return out.join(place, "qid").orderBy("domain", "pos", "rank").select("qid", "rank", "sid", "dist")
    return out


def knn_reduce(src: DataFrame, k: int, cols: list[str], value: str, queries: DataFrame | None = None, id_col: str = "id", include_self: bool = True, box=None, options: Options | None = None) -> DataFrame:
    """(qid, n, mean_value, sum_value, kth_dist): each neighbour list reduced where it is found, one row for each query."""
    self_query = queries is None
    tree = joint_tree(src, queries, cols, id_col, options, [value])
    ilist = walk.knn_ilist(tree, k + (self_query and not include_self), box, self_query)
    d = tree.d

    def run(table):
        import pyarrow as pa

        s = LeafSearch(table, d, k, box, include_self)
        cols_ = ([], [], [], [])
        for rows, (row, src_, d2) in s.leaves():
            n = np.bincount(row, minlength=len(rows))
            cols_[0].append(s.q_id[rows])
            cols_[1].append(n)
            cols_[2].append(np.bincount(row, weights=s.y[src_, 0], minlength=len(rows)))
            far = np.full(len(rows), np.nan)
            last = np.cumsum(n) - 1
            far[n > 0] = np.sqrt(d2[last[n > 0]])
            cols_[3].append(far)
        qid, n, total, far = (np.concatenate(c) if c else np.zeros(0) for c in cols_)
        mean = np.divide(total, n, out=np.full(len(n), np.nan), where=n > 0)
        return pa.table({"qid": pa.array(qid.astype(np.int64)), "n": pa.array(n.astype(np.int64)), "mean_value": pa.array(mean, from_pandas=True), "sum_value": pa.array(total), "kth_dist": pa.array(far, from_pandas=True)})

    return domain_rows(tree, ilist, self_query).groupBy("domain").applyInArrow(run, "qid long, n long, mean_value double, sum_value double, kth_dist double")


def knn_density(src: DataFrame, k: int, cols: list[str], id_col: str = "id", options: Options | None = None) -> DataFrame:
    """(qid, density): k over the volume of the ball that reaches the k-th nearest point (itself included)."""
    import math

    d = len(cols)
    unit = math.pi ** (d / 2) / math.gamma(d / 2 + 1)
    far = knn_reduce(src.withColumn("__one", F.lit(1.0)), k, cols, "__one", id_col=id_col, options=options)
    return far.select("qid", F.when(F.col("kth_dist") > 0, F.lit(float(k)) / (F.lit(unit) * F.pow("kth_dist", F.lit(float(d))))).alias("density"))


def knn_metrics(src: DataFrame, k: int, cols: list[str], queries: DataFrame | None = None, id_col: str = "id", box=None, options: Options | None = None) -> DataFrame:
    """One row of counts: queries, sources, leaves, listed leaf pairs, pairs skipped by the early exit, distances
    evaluated, and sources shipped to other domains."""
    self_query = queries is None
    tree = joint_tree(src, queries, cols, id_col, options)
    ilist = walk.knn_ilist(tree, k, box, self_query)
    d = tree.d

    def run(table):
        import pyarrow as pa

        s = LeafSearch(table, d, k, box)
        for _ in s.leaves():
            pass
        far = int((s.s_leaf // NODE_SPAN != table.column("domain")[0].as_py()).sum())  # sources of other domains
        return pa.table({"n_queries": [len(s.q_id)], "shipped": [far], "listed": [int(s.listed)], "skipped": [int(s.skipped)], "evaluated": [int(s.evaluated)]})

    per = domain_rows(tree, ilist, self_query).groupBy("domain").applyInArrow(run, "n_queries long, shipped long, listed long, skipped long, evaluated long")
    sums = per.agg(*(F.sum(c).alias(c) for c in ("n_queries", "shipped", "listed", "skipped", "evaluated")))
    leaves = tree.nodes.where("plane = 0").agg(F.count("*").alias("leaves"), F.sum("n_src").alias("n_sources"))
    out = sums.crossJoin(leaves)  # one row each
    share = F.col("evaluated") / (F.col("n_queries") * F.col("n_sources"))
    return out.withColumns({"checked_share": share, "early_exit_share": F.col("skipped") / F.col("listed"), "node_factor": F.col("leaves") / F.lit(2 * tree.n / tree.limits[0]), "ilist_factor": F.col("listed") / F.lit(2 * tree.n / tree.limits[0]), "remote_share": F.col("shipped") / F.col("n_sources")})


def knn_plane_counts(src: DataFrame, k: int, cols: list[str], id_col: str = "id", box=None, options: Options | None = None, method: str = "auto") -> DataFrame:
    """(plane, looked_at, kept): node pairs of each plane of a self query's walk, before and after pruning.

    Planes too large to broadcast are walked by stages, which count each pair once; in tasks a node above the
    domains counts for each domain that walks it.
    """
    tree = joint_tree(src, None, cols, id_col, options)
    ngr = tree.ngr
    if method == "stages" or (method == "auto" and not walk.fits(tree)):
        counts: list = []
        walk.knn_stages(tree, k, box, True, counts)
        return src.sparkSession.createDataFrame(counts, "plane int, looked_at long, kept long")

    def make(planes, domains):
        import pyarrow as pa

        stats: dict = {}
        walk.knn_pairs(planes, domains, k, box, True, stats, ngr)
        plane, looked, kept = zip(*stats["pairs"])
        return pa.RecordBatch.from_arrays([pa.array(plane, pa.int32()), pa.array(looked, pa.int64()), pa.array(kept, pa.int64())], ["plane", "looked_at", "kept"])

    rows = walk.walk_in_tasks(tree, make, "plane int, looked_at long, kept long")
    return rows.groupBy("plane").agg(F.sum("looked_at").alias("looked_at"), F.sum("kept").alias("kept"))


def knn_probe(tree: PlaneTree, queries: DataFrame, k: int, cols: list[str], id_col: str = "id", box=None, method: str = "auto") -> DataFrame:
    """Few queries against a kept tree: each query walks the planes alone (one-sided), and meets the points of its leaves.

    The planes are broadcast up to walk.BROADCAST_NODES nodes, and queries walk in tasks; larger trees are walked by
    one DataFrame stage for each plane.
    """
    ask = queries.select(F.col(id_col).cast("long").alias("qid"), *(F.col(c).cast("double").alias(f"q{i}") for i, c in enumerate(cols)))
    pairs = one_sided_leaves(tree, ask, k, box, method)
    from pyspark.sql import Window as W

    from zplane.session import stored

    d = tree.d
    pairs = stored(pairs, "asks")
    parts = max(1, -(-pairs.count() // (len(tree.starts) * 1_000_000)))  # of a domain's queries, so that a task's share is bounded
    domain = F.floor(F.col("leaf") / NODE_SPAN).cast("int").alias("domain")
    q = pairs.select(domain, F.pmod(F.xxhash64("qid"), F.lit(parts)).cast("int").alias("part"), "leaf", F.lit(QUERY).alias("kind"), F.col("qid").alias("id"), *(F.col(f"q{i}").alias(f"x{i}") for i in range(d)))
    s = tree.points.where("ptype = 0").select(domain, F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"), "leaf", F.lit(SOURCE).alias("kind"), "id", *(f"x{i}" for i in range(d)))
    near = q.unionAll(s).groupBy("domain", "part").applyInArrow(probe_kernel(d, k, box, "leaf"), "qid long, sid long, d2 double")
    rank = F.row_number().over(W.partitionBy("qid").orderBy("d2", "sid"))
    return near.withColumn("rank", rank).where(F.col("rank") <= k).select("qid", F.col("rank").cast("int").alias("rank"), "sid", F.sqrt("d2").alias("dist"))


def nearest(q: np.ndarray, s: np.ndarray, s_id: np.ndarray, k: int, box=None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of q, source id, d2) of the k nearest sources of every query by (d2, id), every query against every source in tiles."""
    order = np.argsort(s_id, kind="stable")
    s, s_id = s[order], s_id[order]  # so that a smaller place is a smaller id
    out = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
    for lo in range(0, len(q), 512):
        part = q[lo : lo + 512]
        row, src, val, worst = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0), np.full(len(part), np.inf)
        for c in range(0, len(s), 8192):
            d2 = squared(part, s[c : c + 8192], box)
            cut = np.partition(d2, k - 1, axis=1)[:, k - 1] if d2.shape[1] > k and np.isinf(worst).any() else worst
            i, j = np.nonzero(d2 <= np.minimum(cut, worst)[:, None])
            row, src, val = np.concatenate([row, i]), np.concatenate([src, c + j]), np.concatenate([val, d2[i, j]])
            order = np.lexsort((src, val, row))
            row, src, val = row[order], src[order], val[order]
            keep = np.arange(len(row)) - np.searchsorted(row, row) < k
            row, src, val = row[keep], src[keep], val[keep]
            count = np.bincount(row, minlength=len(part))
            full = count >= k
            worst[full] = val[(np.cumsum(count) - 1)[full]]
        out.append((row + lo, s_id[src], val))
    return tuple(np.concatenate(c) for c in zip(*out))


def probe_kernel(d: int, k: int, box=None, by: str | None = None):
    """(qid, sid, d2): up to k nearest sources of every query of a group; with `by`, among the sources of equal `by` only,
    for each query and `by` that there is a row for."""

    def run(table):
        import pyarrow as pa

        kind, ids = table.column("kind").to_numpy(), table.column("id").to_numpy()
        x = np.column_stack([table.column(f"x{i}").to_numpy() for i in range(d)])
        of = table.column(by).to_numpy() if by else np.zeros(len(ids), np.int64)
        q, s = (np.flatnonzero(kind == w) for w in (QUERY, SOURCE))
        q, s = q[np.argsort(of[q], kind="stable")], s[np.argsort(of[s], kind="stable")]
        groups = np.unique(of[q])
        ends = [np.searchsorted(of[q], groups, w).tolist() for w in ("left", "right")] + [np.searchsorted(of[s], groups, w).tolist() for w in ("left", "right")]
        held, n = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))], 0

        def best():
            qid, sid, d2 = (np.concatenate(c) for c in zip(*held))
            order = np.lexsort((sid, d2, qid))
            qid, sid, d2 = qid[order], sid[order], d2[order]
            keep = np.arange(len(qid)) - np.searchsorted(qid, qid) < k
            return qid[keep], sid[keep], d2[keep]

        for a, z, c, e in zip(*ends):
            row, sid, d2 = nearest(x[q[a:z]], x[s[c:e]], ids[s[c:e]], k, box)
            held.append((ids[q[a:z]][row], sid, d2))
            n += len(row)
            if n > 1 << 21:
                held = [best()]
                n = 0
        qid, sid, d2 = best()
        return pa.table({"qid": qid, "sid": sid, "d2": d2})

    return run


def _one_sided_stages(tree: PlaneTree, ask: DataFrame, k: int, box=None) -> DataFrame:
    from pyspark.sql import Window as W

    from zplane.functions import bounds
    from zplane.session import stored

    d = tree.d
    col = lambda name: [F.col(name)[i] for i in range(d)]
    now, none = None, [F.lit(0.0)] * d
    for p in range(tree.planes - 1, -1, -1):
        nodes = tree.nodes.where((F.col("plane") == p) & (F.col("n_src") > 0)).select("node", "parent", "n_src", "c", "ext")
        joined = ask.crossJoin(F.broadcast(nodes.drop("parent"))) if now is None else now.join(nodes, "parent").drop("parent")  # the top plane is small
        at = [F.col(f"q{i}") for i in range(d)]
        low, high = bounds.d_low(at, none, col("c"), col("ext"), box), bounds.d_up(at, none, col("c"), col("ext"), box)
        rows = joined.withColumns({"low": F.when(F.isnan(low), F.lit(0.0)).otherwise(low), "high": F.when(F.isnan(high), F.lit(float("inf"))).otherwise(high)})
        got = F.sum("n_src").over(W.partitionBy("qid").orderBy("high", "node").rowsBetween(W.unboundedPreceding, 0))
        limit = F.min(F.when(F.col("got") >= k, F.col("high"))).over(W.partitionBy("qid"))
        rows = rows.withColumn("got", got).withColumn("r_max", limit).where(F.col("r_max").isNull() | (F.col("low") <= F.col("r_max") * (1 + BOUND_SLACK)))
        now = stored(rows.select("qid", *(f"q{i}" for i in range(d)), F.col("node").alias("parent")), "probe")
    return now.withColumnRenamed("parent", "leaf")


def one_sided_leaves(tree: PlaneTree, ask: DataFrame, k: int, box=None, method: str = "auto") -> DataFrame:
    """(qid, q0.., leaf): the leaves that each query alone must look at."""
    if method == "stages" or (method == "auto" and not walk.fits(tree)):
        return _one_sided_stages(tree, ask, k, box)
    spark = tree.points.sparkSession
    sent = spark.sparkContext.broadcast(walk.collect_planes(tree))
    d = tree.d

    def run(batches):
        import pyarrow as pa

        from zplane.functions.bounds import np_bounds
        from zplane.plans.walk import find_rmax

        planes = sent.value
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                part = b.slice(lo, 256)
                q = np.column_stack([part.column(1 + i).to_numpy() for i in range(d)])
                recv, src = np.repeat(np.arange(len(q)), len(planes[-1].node)), np.tile(np.arange(len(planes[-1].node)), len(q))
                for p in range(len(planes) - 1, -1, -1):
                    pl = planes[p]
                    if p < len(planes) - 1:
                        up = planes[p + 1]
                        n = up.child[src + 1] - up.child[src]
                        base = np.repeat(up.child[src], n)
                        recv = np.repeat(recv, n)
                        src = base + np.arange(len(base)) - np.repeat(np.cumsum(n) - n, n)
                    ok = pl.n_src[src] > 0
                    recv, src = recv[ok], src[ok]
                    low, high = np_bounds(q[recv], 0.0, pl.c[src], pl.ext[src], box)
                    r, far = find_rmax(recv, high, pl.n_src[src], k)
                    limit = np.full(len(q), np.inf)
                    limit[r] = far
                    keep = low <= limit[recv] * (1 + BOUND_SLACK)
                    recv, src = recv[keep], src[keep]
                kept = part.take(pa.array(recv))
                yield pa.RecordBatch.from_arrays([*kept.columns, pa.array(planes[0].node[src])], [*kept.schema.names, "leaf"])

    return ask.mapInArrow(run, "qid long, " + ", ".join(f"q{i} double" for i in range(d)) + ", leaf long")

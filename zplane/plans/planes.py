"""The plane hierarchy: partitions of the points into the largest Morton cells of bounded count.

Domains are whole Morton cells of at most `domain_rows` points (or one coincident site), found by counting
key prefixes from coarse to fine and refining the heavy ones only. No node crosses a domain, so each domain
sorts its keys and cuts its planes by itself, in one grouped Arrow pass. Where there are several domains,
their top nodes are cut into coarser planes in the same way, round by round (nodes stand in for points, with
their counts), until the top plane is small: its size does not grow with the number of points. Only domain
boundaries (one key for each domain) and per-plane level histograms reach the driver.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zplane.functions import zkey
from zplane.session import ship, stored

POINT, NODE = "domain int, leaf long, pos long, zkey binary, id long, ptype int", "plane int, node long, parent long, first_pos long, last_pos long, n_src long, n_qry long, lvl int, domain int"
_NODE = "plane:int,node:long,parent:long,first_pos:long,last_pos:long,n_src:long,n_qry:long,lvl:int,c:array<double>,ext:array<double>,k0:binary,k1:binary"
#: Node ids are domain * NODE_SPAN + index within the domain and plane.
NODE_SPAN = 1 << 32


@dataclass
class Options:
    """n_max0, c and n_target set the planes; domain_rows bounds what one task holds; f_max caps node volumes (None: off);
    ngr top nodes make a super node, from which walks start."""

    n_max0: int = 128
    c: int = 8
    n_target: int = 64
    domain_rows: int = 150_000
    f_max: float | None = None
    schedule: list[int] = field(default_factory=list)
    ngr: int = 32


def paper_options() -> Options:
    return Options(n_max0=48, c=8, n_target=1000, f_max=50.0, ngr=32)


def estimate_nodes(n: int, n_max: int) -> float:
    """Nodes of a plane if they hold at least half their limit: an estimate, no bound."""
    return 2 * n / n_max


def plane_schedule(n: int, n_max0: int = 48, c: int = 8, n_target: int = 1000, to_root: bool = False, most: int | None = None) -> list[int]:
    """Limits of the planes from the leaves up: coarsening stops when fewer nodes than n_target are expected."""
    out = [n_max0]
    while (out[-1] < n if to_root else estimate_nodes(n, out[-1]) >= n_target) and (most is None or out[-1] * c <= most):
        out.append(out[-1] * c)
    return out


# -- gaps in one sorted run of keys --------------------------------------------------------------------
def gap_bits(keys: np.ndarray, plan: zkey.KeyPlan) -> np.ndarray:
    """Shared leading bits at each of the n + 1 gaps; -1 at both ends."""
    out = np.full(len(keys) + 1, -1, np.int64)
    out[1:-1] = zkey.common_bits(keys[:-1], keys[1:], plan)
    return out


def _sliding(x: np.ndarray, w: int, op, pad) -> np.ndarray:
    """op over x[i:i+w] for every i with a full window."""
    if len(x) < w:
        return x[:0]
    full = np.full(-(-len(x) // w) * w, pad, x.dtype)
    full[: len(x)] = x
    rows = full.reshape(-1, w)
    left = op.accumulate(rows, 1).ravel()
    right = op.accumulate(rows[:, ::-1], 1)[:, ::-1].ravel()
    n = len(x) - w + 1
    return op(right[:n], left[w - 1 : w - 1 + n])


def gap_exceeds(bits: np.ndarray, n_max: int) -> np.ndarray:
    """Whether the smallest cell around each gap holds more than n_max points, looking n_max points each way only.

    It does if some n_max + 1 neighbouring points around the gap share as many bits as the gap.
    """
    n = len(bits) - 1
    out = np.zeros(n + 1, bool)
    out[0] = out[-1] = True
    if n > n_max:
        shared = _sliding(bits[1:n], n_max, np.minimum, np.iinfo(np.int64).max)  # of points j .. j + n_max
        padded = np.concatenate([np.full(n_max - 1, -2), shared, np.full(n_max - 1, -2)])
        out[1:n] = _sliding(padded, n_max, np.maximum, -3) >= bits[1:n]
    return out


def gap_ranges(bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(left, right): the gaps that bound the smallest cell around each gap (the next ones with fewer shared bits)."""
    n = len(bits)
    left, right = np.zeros(n, np.int64), np.full(n, n - 1, np.int64)
    stack: list[int] = []
    for i, b in enumerate(bits.tolist()):
        while stack and bits[stack[-1]] > b:
            right[stack.pop()] = i
        j = len(stack) - 1
        while j >= 0 and bits[stack[j]] == b:
            j -= 1
        left[i] = stack[j] if j >= 0 else 0
        stack.append(i)
    return left, right


def gap_counts(bits: np.ndarray) -> np.ndarray:
    """Points in the smallest cell around each gap; both ends count all."""
    left, right = gap_ranges(bits)
    n = right - left
    n[0] = n[-1] = len(bits) - 1
    return n


def binary_parents(bits: np.ndarray) -> np.ndarray:
    """The parent gap of each inner gap's cell in the binary tree: the bounding gap with the smaller cell (-1: none)."""
    left, right = gap_ranges(bits)
    out = np.where(bits[left] >= bits[right], left, right)
    inner = (out > 0) & (out < len(bits) - 1)
    out = np.where(inner, out, -1)
    out[0] = out[-1] = -1
    return out


def split_positions(bits: np.ndarray, limits: list[int], types: np.ndarray | None = None, caps: list[int] | None = None, plan: zkey.KeyPlan | None = None) -> list[np.ndarray]:
    """For each limit, the positions of the gaps that stay (both ends included); every list is part of the one before.

    With types (0 or 1 for each point) the larger of both counts decides. caps are the largest shared levels
    of a plane: gaps of higher level stay whatever their count. With a plan, gaps between coincident points never
    stay, so a site is one leaf however many points it has.
    """
    n = len(bits) - 1
    level = zkey.level_of_bits(np.maximum(bits, 0), plan) if caps else None
    out: list[np.ndarray] = []
    at = None
    for p, limit in enumerate(limits):
        if p == 0:
            if types is None or not len(types) or types.min() == types.max():
                keep = gap_exceeds(bits, limit)
            else:
                left, right = gap_ranges(bits)
                ones = np.concatenate([[0], np.cumsum(types)])
                one = ones[right] - ones[left]
                keep = np.maximum(one, right - left - one) > limit
                keep[0] = keep[-1] = True
            if caps and caps[p] is not None:
                keep[1:-1] |= level[1:-1] > caps[p]
            if plan is not None:
                keep[1:-1] &= bits[1:-1] < plan.bits
            at = np.flatnonzero(keep)
        else:
            sub = bits[at]
            left, right = gap_ranges(sub)
            lo, hi = at[left], at[right]
            if types is None or not len(types):
                count = hi - lo
            else:
                ones = np.concatenate([[0], np.cumsum(types)])
                one = ones[hi] - ones[lo]
                count = np.maximum(one, hi - lo - one)
            keep = count > limit
            keep[0] = keep[-1] = True
            if caps and caps[p] is not None:
                keep[1:-1] |= level[at][1:-1] > caps[p]
            at = at[keep]
        out.append(at)
    assert n == out[-1][-1]
    return out


# -- domains ------------------------------------------------------------------------------------------------
def leaf_cells_by_prefix(df: DataFrame, n_max: int, plan: zkey.KeyPlan, step: int = 12) -> DataFrame:
    """(bits, prefix, n): the largest Morton cells of at most n_max points, by counting prefixes of heavy cells only.

    df has zkey. A prefix is the key cut to `bits` bits (0/1 text). Cells of coincident points may exceed n_max.
    """
    texts = df.select(_bit_text(plan).alias("key"))
    counts, at = None, 0
    heavy = texts
    while True:
        at = min(plan.bits, at + step)
        pieces = heavy.select("key", F.explode(F.sequence(F.lit(max(0, at - step)), F.lit(at))).alias("bits"))
        grouped = pieces.groupBy("bits", F.expr("substring(key, 1, bits)").alias("prefix")).agg(F.count("*").alias("n"))
        counts = grouped if counts is None else counts.union(grouped)
        big = grouped.where((F.col("bits") == at) & (F.col("n") > n_max)).select(F.col("prefix").alias("p"))
        if at >= plan.bits:
            break
        heavy = stored(heavy.join(big, F.substring("key", 1, at) == F.col("p"), "left_semi"))
        if heavy.isEmpty():
            break
    counts = counts.dropDuplicates(["bits", "prefix"])
    fits = (F.col("n") <= n_max) | (F.col("bits") == plan.bits)
    ok = counts.where(fits)
    parents = counts.where(F.col("n") > n_max).select((F.col("bits") + 1).alias("bits"), F.col("prefix").alias("up"))
    inner = ok.where("bits > 0").withColumn("up", F.expr("substring(prefix, 1, bits - 1)")).join(parents, ["bits", "up"], "left_semi").drop("up")
    return inner.select("bits", "prefix", "n").union(ok.where("bits = 0").select("bits", "prefix", "n"))


def _bit_text(plan: zkey.KeyPlan):
    nibbles = "transform(sequence(1, length(hex(zkey))), i -> lpad(conv(substring(hex(zkey), i, 1), 16, 2), 4, '0'))"
    return F.expr(f"substring(array_join({nibbles}, ''), 1, {plan.bits})")


def assign_domains(df: DataFrame, plan: zkey.KeyPlan, rows: int) -> tuple[list[bytes], dict]:
    """First keys of the domains (in order), each a whole Morton cell of at most `rows` points or a site.

    Small inputs are one domain. Otherwise prefixes of 16 more bits are counted round by round inside the heavy
    cells, and each heavy cell (at most 2^16 counted prefixes) is halved in a task of its own. The driver gets
    the first keys of the domains, one for each `rows` points or so, and nothing is packed across cells.
    """
    n = df.count()
    if n <= rows:
        return [b""], {"points": n}
    found, heavy, depth = None, None, 0
    while depth < plan.bytes:
        step = min(2, plan.bytes - depth)
        cut = df.select("zkey")
        if heavy is not None:
            cut = cut.join(heavy.select(F.col("k").alias("p")), F.expr(f"substring(zkey, 1, {depth})") == F.col("p"), "left_semi")
        counts = cut.groupBy(F.expr(f"substring(zkey, 1, {depth + step})").alias("k")).agg(F.count("*").alias("n"))
        parts = counts.withColumn("parent", F.expr(f"substring(k, 1, {depth})")).groupBy("parent").applyInArrow(_halve_cell(8 * depth, 8 * (depth + step), rows), "k binary, heavy boolean")
        parts = stored(parts, "cells")
        light = parts.where("NOT heavy").select("k")
        found = light if found is None else found.union(light)
        heavy = parts.where("heavy").select("k")
        depth += step
        if heavy.isEmpty():
            break
    return sorted(bytes(r["k"]) for r in found.union(heavy).collect()), {"points": n}


def _halve_cell(first: int, last: int, rows: int):
    def halve(table):
        import pyarrow as pa

        kids = sorted(zip((bytes(k) for k in table.column("k").to_pylist()), table.column("n").to_pylist()))
        found: list = []
        heavy: list = []
        _halve(kids, first, last, rows, found, heavy)
        return pa.table({"k": pa.array([*found, *heavy], pa.binary()), "heavy": pa.array([False] * len(found) + [True] * len(heavy))})

    return halve


def _halve(kids: list, bit: int, last: int, rows: int, found: list, heavy: list) -> None:
    """The first prefixes of the cells that a cell with counted prefixes `kids` is halved into, bit by bit."""
    if sum(m for _, m in kids) <= rows:
        found.append(kids[0][0])
    elif bit == last:
        heavy.append(kids[0][0])
    else:
        for side in (0, 1):
            part = [(k, m) for k, m in kids if (k[bit >> 3] >> (7 - (bit & 7)) & 1) == side]
            if part:
                _halve(part, bit + 1, last, rows, found, heavy)


# -- building -------------------------------------------------------------------------------------------------
@dataclass
class PlaneTree:
    """points: (domain, leaf, pos, zkey, id, ptype, x0..); nodes: NODE columns with arrays c and ext."""

    points: DataFrame
    nodes: DataFrame
    plan: zkey.KeyPlan
    limits: list[int]
    d: int
    starts: list[bytes]
    n: int
    ngr: int = 32

    @property
    def planes(self) -> int:
        return len(self.limits)

    def save(self, path: str) -> None:
        self.points.write.mode("overwrite").partitionBy("domain").parquet(f"{path}/points")
        self.nodes.write.mode("overwrite").partitionBy("plane").parquet(f"{path}/nodes")
        meta = [(self.plan.d, self.plan.top, self.plan.low, self.limits, self.d, [bytearray(s) for s in self.starts], self.n, self.ngr)]
        self.points.sparkSession.createDataFrame(meta, "kd int, top int, low int, limits array<long>, d int, starts array<binary>, n long, ngr int").write.mode("overwrite").parquet(f"{path}/meta")

    @staticmethod
    def load(spark, path: str) -> "PlaneTree":
        m = spark.read.parquet(f"{path}/meta").first()
        return PlaneTree(spark.read.parquet(f"{path}/points"), spark.read.parquet(f"{path}/nodes"), zkey.KeyPlan(m.kd, m.top, m.low), list(m.limits), m.d, [bytes(s) for s in m.starts], m.n, m.ngr)


def normalise(df: DataFrame, cols: list[str], on_invalid: str = "error") -> DataFrame:
    """Coordinates as doubles, -0.0 as 0.0; rows with null, NaN or infinite coordinates raise or are dropped."""
    bad = None
    for c in cols:
        x = F.col(c).cast("double")
        b = x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))
        bad = b if bad is None else bad | b
    if on_invalid == "drop":
        df = df.where(~bad)
    elif on_invalid == "error":
        df = df.where(F.when(bad, F.raise_error(F.lit("a coordinate is null, NaN or infinite")).cast("boolean")).otherwise(F.lit(True)))
    return df.withColumns({c: F.col(c).cast("double") + F.lit(0.0) for c in cols})


def build_tree(df: DataFrame, cols: list[str], id_col: str = "id", type_col: str | None = None, options: Options | None = None, on_invalid: str = "error", payload: list[str] = ()) -> PlaneTree:
    """One tree over all points of df; type_col (0 source, 1 query) makes the larger of both counts decide the splits.

    payload columns (numbers) are carried along as y0, y1, ...
    """
    spark = df.sparkSession
    ship(spark)
    opt = options or Options()
    d = len(cols)
    kind = F.col(type_col).cast("int") if type_col else F.lit(0)
    points = df.select(F.col(id_col).cast("long").alias("id"), kind.alias("ptype"), *(F.col(c).alias(f"x{i}") for i, c in enumerate(cols)), *(F.col(c).cast("double").alias(f"y{i}") for i, c in enumerate(payload)))
    points = normalise(points, [f"x{i}" for i in range(d)], on_invalid)
    plan = zkey.plan_key(points, [f"x{i}" for i in range(d)])
    keyed = stored(zkey.with_zkey(points, [f"x{i}" for i in range(d)], plan), "keyed")
    starts, info = assign_domains(keyed, plan, opt.domain_rows)
    n = info["points"]
    limits = opt.schedule or plane_schedule(n, opt.n_max0, opt.c, opt.n_target, most=max(opt.domain_rows, opt.n_max0) if len(starts) > 1 else None)
    extra = [*(f"x{i}" for i in range(d)), *(f"y{i}" for i in range(len(payload)))]
    routed = _with_domain(keyed, starts, extra)
    caps = None
    schema = f"{POINT}, {', '.join(f'{c} double' for c in extra)}, nodes array<struct<{_NODE}>>"
    if opt.f_max is not None:
        caps = _caps(routed, plan, limits, opt.f_max, d)
    built = stored(routed.groupBy("domain").applyInArrow(_build_domain(plan, limits, d, caps, extra), schema), "tree")
    nodes = built.where("nodes IS NOT NULL").select("domain", F.explode("nodes").alias("m")).select("m.*", "domain")
    if len(starts) > 1:
        nodes, limits = _upper_planes(nodes, plan, limits, opt, d)
    return PlaneTree(built.where("nodes IS NULL").drop("nodes"), nodes.drop("k0", "k1"), plan, limits, d, starts, n, opt.ngr)


def _upper_planes(nodes: DataFrame, plan: zkey.KeyPlan, limits: list[int], opt: Options, d: int) -> tuple[DataFrame, list[int]]:
    """nodes with the planes above the domains, and all limits. A round cuts whole cells of at most domain_rows top nodes."""
    parts, limits, rows = [], list(limits), max(opt.domain_rows, 2 * opt.n_target)
    while True:
        last = len(limits) - 1
        top = nodes.where(F.col("plane") == last)
        parts.append(nodes.where(F.col("plane") < last))
        starts, info = assign_domains(top.select(F.col("k0").alias("zkey")), plan, rows)
        routed = _routed(top.withColumnRenamed("domain", "of"), starts, "k0").select("domain", "of", "node", "n_src", "n_qry", "lvl", "c", "ext", "first_pos", "last_pos", "k0", "k1")
        alone = len(starts) == 1
        up = stored(routed.groupBy("domain").applyInArrow(_build_upper(plan, last, limits[-1], opt, d, alone, rows), "nodes array<struct<" + _NODE + ",domain:int>>"), "upper")
        nodes = up.select(F.explode("nodes").alias("m")).select("m.*")
        height = nodes.agg(F.max("plane")).first()[0]
        for _ in range(height - last):
            limits.append(limits[-1] * opt.c)
        if alone or height == last:
            return stored(_all(parts).unionByName(nodes), "nodes"), limits


def _all(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for x in parts[1:]:
        out = out.unionByName(x)
    return out


def _build_upper(plan, plane, limit, opt, d, alone, rows):
    """The nodes of one group with their parents, and the planes above them: to n_target nodes where the group is all there is,
    else as many planes as a full group needs."""

    def build(table):
        import pyarrow as pa

        first, last = (np.frombuffer(b"".join(table.column(c).to_pylist()), np.uint8).reshape(table.num_rows, -1) for c in ("k0", "k1"))
        order = np.lexsort([first[:, j] for j in range(first.shape[1] - 1, -1, -1)])
        first, last = first[order], last[order]
        t = table.take(order)
        domain = t.column("domain")[0].as_py()
        base, n = domain * NODE_SPAN, t.num_rows
        src, qry = t.column("n_src").to_numpy(), t.column("n_qry").to_numpy()
        centre = np.array(t.column("c").to_pylist(), float).reshape(n, d)
        bits = np.full(n + 1, -1, np.int64)
        bits[1:-1] = zkey.common_bits(last[:-1], first[1:], plan)
        upto_s, upto_q = np.concatenate([[0], np.cumsum(src)]), np.concatenate([[0], np.cumsum(qry)])
        at, planes, cap, made = np.arange(n + 1), [], limit, 0
        total = max(int(upto_s[-1]), int(upto_q[-1]))
        while (len(at) - 1 > opt.n_target and cap < total) if alone else rows > opt.c**made:
            cap, made = cap * opt.c, made + 1
            left, right = gap_ranges(bits[at])
            count = np.maximum(upto_s[at[right]] - upto_s[at[left]], upto_q[at[right]] - upto_q[at[left]])
            keep = count > cap
            keep[0] = keep[-1] = True
            at = at[keep]
            planes.append(at)
        keys0, keys1 = [k.tobytes() for k in first], [k.tobytes() for k in last]
        out = []
        for i, r in enumerate(t.select(["of", "node", "first_pos", "last_pos", "lvl", "c", "ext"]).to_pylist()):
            up = base + int(np.searchsorted(planes[0], i, side="right")) - 1 if planes else -1
            out.append({"plane": plane, "node": r["node"], "parent": up, "first_pos": r["first_pos"], "last_pos": r["last_pos"], "n_src": int(src[i]), "n_qry": int(qry[i]), "lvl": r["lvl"], "c": r["c"], "ext": r["ext"], "k0": None if planes else keys0[i], "k1": None if planes else keys1[i], "domain": r["of"]})
        for p, at in enumerate(planes):
            a, z = at[:-1], at[1:] - 1
            lvl = zkey.level_of_bits(zkey.common_bits(first[a], last[z], plan), plan)
            c, ext = zkey.cells(centre[a], lvl)
            up = np.searchsorted(planes[p + 1], a, side="right") - 1 if p + 1 < len(planes) else np.full(len(a), -1 - base)
            top = p + 1 == len(planes)
            for j in range(len(a)):
                out.append({"plane": plane + 1 + p, "node": base + j, "parent": base + int(up[j]), "first_pos": 0, "last_pos": 0, "n_src": int(upto_s[z[j] + 1] - upto_s[a[j]]), "n_qry": int(upto_q[z[j] + 1] - upto_q[a[j]]), "lvl": int(lvl[j]), "c": c[j].tolist(), "ext": ext[j].tolist(), "k0": keys0[a[j]] if top else None, "k1": keys1[z[j]] if top else None, "domain": domain})
        return pa.table({"nodes": pa.array([out], pa.list_(pa.struct([*_node_type(), ("domain", pa.int32())])))})

    return build


def _node_type():
    import pyarrow as pa

    wide = pa.list_(pa.float64())
    return [("plane", pa.int32()), ("node", pa.int64()), ("parent", pa.int64()), ("first_pos", pa.int64()), ("last_pos", pa.int64()), ("n_src", pa.int64()), ("n_qry", pa.int64()), ("lvl", pa.int32()), ("c", wide), ("ext", wide), ("k0", pa.binary()), ("k1", pa.binary())]


def _with_domain(keyed: DataFrame, starts: list[bytes], extra: list[str]) -> DataFrame:
    """keyed with domain: the place of each key among the domains' first keys."""
    return _routed(keyed, starts, "zkey").select("domain", "zkey", "id", "ptype", *extra)


def _routed(rows: DataFrame, starts: list[bytes], key: str) -> DataFrame:
    """rows with domain, by one search in the sorted first keys (a key for each domain_rows points) for each Arrow batch."""
    if len(starts) == 1:
        return rows.withColumn("domain", F.lit(0))
    wide = max(map(len, starts))
    sent = rows.sparkSession.sparkContext.broadcast(np.frombuffer(b"".join(s.ljust(wide, b"\0") for s in starts), f"S{wide}"))

    @F.arrow_udf("int")
    def domain(keys):
        import pyarrow as pa

        at = zkey.key_rows(keys)
        at = np.ascontiguousarray(np.pad(at, ((0, 0), (0, max(0, wide - at.shape[1]))))[:, :wide]).view(f"S{wide}").ravel()
        return pa.array(np.maximum(np.searchsorted(sent.value, at, side="right") - 1, 0).astype(np.int32))

    return rows.withColumn("domain", domain(key))


def _sorted_domain(table, d: int, extra: list[str] | None = None):
    keys = zkey.key_rows(table.column("zkey"))
    ids = table.column("id").to_numpy()
    order = np.lexsort((ids, *(keys[:, j] for j in range(keys.shape[1] - 1, -1, -1)))) if len(ids) else np.zeros(0, np.int64)
    x = np.column_stack([table.column(c).to_numpy() for c in extra or [f"x{i}" for i in range(d)]])[order]
    return keys[order], ids[order], table.column("ptype").to_numpy()[order], x


def _caps(routed: DataFrame, plan, limits, f_max, d):
    """The level cap of each plane: log2(f_max * V90), V90 the count-weighted mean volume of the smallest nodes that
    hold 90 % of the points, from a histogram of levels (a few thousand rows at most)."""

    def levels(table):
        import pyarrow as pa

        keys, _, types, x = _sorted_domain(table, d)
        bits = gap_bits(keys, plan)
        rows = []
        for p, at in enumerate(split_positions(bits, limits, types, None, plan)):
            first, last = at[:-1], at[1:] - 1
            lv = zkey.level_of_bits(zkey.common_bits(keys[first], keys[last], plan), plan)
            u, inv = np.unique(lv, return_inverse=True)
            rows += [(p, int(a), int(b)) for a, b in zip(u, np.bincount(inv, weights=last - first + 1))]
        cols = list(zip(*rows))
        return pa.table({"plane": pa.array(cols[0], pa.int32()), "lvl": pa.array(cols[1], pa.int32()), "n": pa.array(cols[2], pa.int64())})

    hist = routed.groupBy("domain").applyInArrow(levels, "plane int, lvl int, n long").groupBy("plane", "lvl").agg(F.sum("n").alias("n")).collect()
    return [level_cap([(r.lvl, r.n) for r in hist if r.plane == p], f_max, d) for p in range(len(limits))]


def level_cap(hist: list[tuple[int, int]], f_max: float, d: int) -> int | None:
    """The largest level whose volume stays within f_max * V90; the boundary level counts in part. None if V90 is 0."""
    hist = sorted((l, n) for l, n in hist if l <= zkey.EMAX["double"] * d - d)
    total = sum(n for _, n in hist)
    room, mass, volume = 0.9 * total, 0.0, 0.0
    if not total:
        return None
    top = max(l for l, _ in hist)
    for l, n in hist:
        part = min(n, room - mass)
        if part <= 0:
            break
        mass += part
        volume += part * (2.0 ** (l - top) if l > -(2**30) else 0.0)
    v90 = volume / mass
    return None if v90 <= 0 else int(math.floor(math.log2(f_max * v90) + top))


def _build_domain(plan, limits, d, caps, extra):
    def build(table):
        import pyarrow as pa

        keys, ids, types, every = _sorted_domain(table, d, extra)
        x = every[:, :d]
        domain = table.column("domain")[0].as_py()
        n = len(ids)
        bits = gap_bits(keys, plan)
        splits = split_positions(bits, limits, types, caps, plan)
        base = domain * NODE_SPAN
        src = np.concatenate([[0], np.cumsum(types == 0)])
        nodes = []
        for p, at in enumerate(splits):
            first, last = at[:-1], at[1:] - 1
            lvl = zkey.level_of_bits(zkey.common_bits(keys[first], keys[last], plan), plan)
            c, ext = zkey.cells(x[first], lvl)
            up = np.searchsorted(splits[p + 1], first, side="right") - 1 if p + 1 < len(splits) else np.full(len(first), -1)
            s = src[at[1:]] - src[first]
            top = p + 1 == len(splits)
            for j in range(len(first)):
                nodes.append({"plane": p, "node": base + j, "parent": base + int(up[j]) if up[j] >= 0 else -1, "first_pos": int(first[j]), "last_pos": int(last[j]), "n_src": int(s[j]), "n_qry": int(last[j] - first[j] + 1 - s[j]), "lvl": int(lvl[j]), "c": c[j].tolist(), "ext": ext[j].tolist(), "k0": keys[first[j]].tobytes() if top else None, "k1": keys[last[j]].tobytes() if top else None})
        leaf = base + np.searchsorted(splits[0], np.arange(n), side="right") - 1
        kind = pa.list_(pa.struct(_node_type()))
        pad = lambda a, t, v=None: pa.concat_arrays([pa.array(a, t), pa.array([v], t)])  # noqa: E731  the last row carries the nodes
        cols = {
            "domain": pad(np.full(n, domain, np.int32), pa.int32(), domain), "leaf": pad(leaf, pa.int64()), "pos": pad(np.arange(n), pa.int64()), "zkey": pa.concat_arrays([zkey.key_array(keys), pa.nulls(1, pa.binary())]),
            "id": pad(ids, pa.int64()), "ptype": pad(types.astype(np.int32), pa.int32()), **{c: pad(every[:, i], pa.float64()) for i, c in enumerate(extra)}, "nodes": pa.concat_arrays([pa.nulls(n, kind), pa.array([nodes], kind)]),
        }
        return pa.table(cols)

    return build

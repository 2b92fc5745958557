"""Functions for SQL users: register(spark) makes them available by name."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from zplane.session import ship


def register(spark: SparkSession) -> list[str]:
    """z_key(array, top, low), z_level(key, key, d, top, low), z_extent(lvl, d), z_center(array, lvl),
    z_dlow / z_dup (c1, l1, c2, l2), z_dist(p, q), z_wrap_dist(p, q, box), z_key63(array, low, high), rmax_agg(d_up, n, k),
    topk_agg(dist, id, k), z_nodes and knn_of (table functions; knn_of takes a small table of points TABLE(id, x) and k)."""
    ship(spark)
    from zplane.functions import bounds, zkey

    @F.pandas_udf("binary")
    def z_key(x: pd.Series, top: pd.Series, low: pd.Series) -> pd.Series:
        if not len(x):
            return pd.Series([], dtype=object)
        m = np.vstack(x.to_numpy()).astype(float)
        return pd.Series([k.tobytes() for k in zkey.exact_keys(m, zkey.KeyPlan(m.shape[1], int(top.iloc[0]), int(low.iloc[0])))])

    @F.pandas_udf("int")
    def z_level(a: pd.Series, b: pd.Series, d: pd.Series, top: pd.Series, low: pd.Series) -> pd.Series:
        if not len(a):
            return pd.Series([], dtype="int32")
        plan = zkey.KeyPlan(int(d.iloc[0]), int(top.iloc[0]), int(low.iloc[0]))
        m = [np.frombuffer(b"".join(map(bytes, s)), np.uint8).reshape(len(s), -1) for s in (a, b)]
        return pd.Series(zkey.level_of_bits(zkey.common_bits(m[0], m[1], plan), plan)).astype("int32")

    @F.pandas_udf("array<double>")
    def z_center(x: pd.Series, lvl: pd.Series) -> pd.Series:
        return pd.Series(list(zkey.cells(np.vstack(x.to_numpy()).astype(float), lvl.to_numpy())[0])) if len(x) else pd.Series([], dtype=object)

    @F.pandas_udf("double")
    def rmax_agg(d_up: pd.Series, n: pd.Series, k: pd.Series) -> float:
        order = np.argsort(d_up.to_numpy(), kind="stable")
        total = np.cumsum(n.to_numpy()[order])
        at = np.searchsorted(total, int(k.iloc[0]))
        return float(d_up.to_numpy()[order][at]) if at < len(total) else float("inf")

    @F.pandas_udf("array<long>")
    def topk_agg(dist: pd.Series, ids: pd.Series, k: pd.Series) -> list:
        order = np.lexsort((ids.to_numpy(), dist.to_numpy()))[: int(k.iloc[0])] if len(k) else []
        return ids.to_numpy()[order].tolist()

    @F.pandas_udf("long")
    def z_key63(x: pd.Series, low: pd.Series, high: pd.Series) -> pd.Series:
        if not len(x):
            return pd.Series([], dtype="int64")
        m = np.vstack(x.to_numpy()).astype(float)
        d = m.shape[1]
        bits = zkey.morton_bits(d)
        scaled = np.floor((m - low.to_numpy()[:, None]) / (high - low).to_numpy()[:, None] * float(1 << bits))
        cell = np.clip(scaled, 0, (1 << bits) - 1).astype(np.int64)
        out = np.zeros(len(m), np.int64)
        for b in range(bits):
            for i in range(d):
                out |= (cell[:, i] >> b & 1) << (b * d + d - 1 - i)
        return pd.Series(out)

    def bound(which):
        @F.pandas_udf("double")
        def f(c1: pd.Series, l1: pd.Series, c2: pd.Series, l2: pd.Series) -> pd.Series:
            if not len(c1):
                return pd.Series([], dtype=float)
            return pd.Series(bounds.np_bounds(*(np.vstack(v.to_numpy()).astype(float) for v in (c1, l1, c2, l2)))[which])

        return f

    class Nodes:
        """The planes of a small point list: one row for each node (plane, first, last, lvl)."""

        def eval(self, xs: list, limits: list):
            from zplane.plans import planes

            x = np.array(xs, float)
            plan = zkey.plan_of(x, x.shape[1])
            keys = zkey.exact_keys(x, plan)
            keys = keys[np.lexsort([keys[:, j] for j in range(keys.shape[1] - 1, -1, -1)])]
            for p, at in enumerate(planes.split_positions(planes.gap_bits(keys, plan), [int(v) for v in limits])):
                first, last = at[:-1], at[1:] - 1
                for a, b, lvl in zip(first, last, zkey.level_of_bits(zkey.common_bits(keys[first], keys[last], plan), plan)):
                    yield p, int(a), int(b), int(lvl)

    class Near:
        """The k nearest rows of a small table for each of its rows, brute force: (qid, rank, sid, dist). Reads one partition."""

        def __init__(self):
            self.rows, self.k = [], 0

        def eval(self, row, k: int):
            self.rows.append((row["id"], row["x"]))
            self.k = k

        def terminate(self):
            if not self.rows:
                return
            ids, x = np.array([r[0] for r in self.rows]), np.array([r[1] for r in self.rows], float)
            for i, p in zip(ids.tolist(), x):
                d2 = ((x - p) ** 2).sum(1)
                for rank, j in enumerate(np.lexsort((ids, d2))[: self.k].tolist(), 1):
                    yield i, rank, int(ids[j]), float(np.sqrt(d2[j]))

    for name, f in {"z_key63": z_key63, "topk_agg": topk_agg, "z_key": z_key, "z_level": z_level, "z_center": z_center, "rmax_agg": rmax_agg, "z_dlow": bound(0), "z_dup": bound(1)}.items():
        spark.udf.register(name, f)
    spark.udtf.register("z_nodes", F.udtf(Nodes, returnType="plane int, first long, last long, lvl int"))
    spark.udtf.register("knn_of", F.udtf(Near, returnType="qid long, rank int, sid long, dist double"))
    for text in (
        "z_extent(lvl INT, d INT) RETURNS ARRAY<BIGINT> RETURN transform(sequence(0, d - 1), i -> floor(lvl / d) + IF(i >= d - pmod(lvl, d), 1, 0))",
        "z_dist(p ARRAY<DOUBLE>, q ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(aggregate(zip_with(p, q, (a, b) -> (a - b) * (a - b)), 0D, (s, x) -> s + x))",
        "z_wrap_dist(p ARRAY<DOUBLE>, q ARRAY<DOUBLE>, box DOUBLE) RETURNS DOUBLE RETURN sqrt(aggregate(zip_with(p, q, (a, b) -> pow((a - b) - box * floor((a - b) / box + 0.5D), 2)), 0D, (s, x) -> s + x))",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")
    return ["z_key63", "topk_agg", "knn_of", "z_key", "z_level", "z_center", "rmax_agg", "z_dlow", "z_dup", "z_nodes", "z_extent", "z_dist", "z_wrap_dist"]

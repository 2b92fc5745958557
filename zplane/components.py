"""Connected components of an edge table, by star contraction.

Every node ends up pointing at the smallest node of its component. Each round hooks larger neighbours
onto the smallest one of a neighbourhood (first over larger, then over smaller neighbours), which
shortens chains geometrically, so even a path needs O(log n) rounds. Hubs are harmless: the smallest
neighbour comes from a partially aggregated min, and no neighbourhood is ever collected. Before each
round the edges of a partition are replaced by their own spanning stars; once all edges fit one task
(a fixed bound), that task finishes.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zplane.session import discard, ship, stored

#: Edges (two longs each) that one task may finish.
LOCAL_EDGES = 1_000_000


def union_find(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, roots) of the edges a-b, root = smallest node of the component, by vectorised hooking."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    p = np.arange(len(nodes))
    while True:
        px, py = p[x], p[y]
        open_ = px != py
        if not open_.any():
            return nodes, nodes[p]
        x, y, px, py = x[open_], y[open_], px[open_], py[open_]
        np.minimum.at(p, np.maximum(px, py), np.minimum(px, py))
        while True:
            q = p[p]
            if (q == p).all():
                break
            p = q


def contract_partitions(edges: DataFrame) -> DataFrame:
    """Replace the edges (hi, lo) of every partition by the spanning stars of their components."""

    def run(batches):
        import pyarrow as pa

        from zplane.components import union_find

        kept: list = []
        room = 0

        def flush():
            nodes, roots = union_find(np.concatenate([k[0] for k in kept]), np.concatenate([k[1] for k in kept]))
            far = nodes != roots
            return nodes[far], roots[far]

        for b in batches:
            kept.append((b.column(0).to_numpy(), b.column(1).to_numpy()))
            room += b.num_rows
            if room > 4 * LOCAL_EDGES:  # keep what a partition holds bounded by its distinct nodes
                kept = [flush()]
                room = len(kept[0][0])
        if kept:
            hi, lo = flush()
            yield pa.RecordBatch.from_arrays([pa.array(hi, pa.int64()), pa.array(lo, pa.int64())], ["hi", "lo"])

    return edges.mapInArrow(run, "hi long, lo long")


def _stars(edges: DataFrame) -> DataFrame:
    """One large-star and one small-star step on edges (hi, lo), hi > lo."""
    both = edges.select(F.col("hi").alias("u"), F.col("lo").alias("v")).union(edges.select(F.col("lo").alias("u"), F.col("hi").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    large = both.where("v > u").join(least, "u").select(F.col("v").alias("hi"), F.col("m").alias("lo")).where("hi > lo").distinct()
    least = large.groupBy("hi").agg(F.min("lo").alias("m"))
    small = large.join(least, "hi")
    small = small.select(F.col("lo").alias("hi"), F.col("m").alias("lo")).union(least.select("hi", F.col("m").alias("lo")))
    return small.where("hi > lo").distinct()


def components(edges: DataFrame, a: str = "a", b: str = "b", local_edges: int = LOCAL_EDGES) -> DataFrame:
    """(node, root) for every node that has an edge; root is the smallest node of the component.

    Self-loops, repeated edges and edges with a null end are ignored. Rounds are written to the shared
    folder, so a lost executor costs at most one round.
    """
    return components_with_rounds(edges, a, b, local_edges)[0]


def components_with_rounds(edges: DataFrame, a: str = "a", b: str = "b", local_edges: int = LOCAL_EDGES) -> tuple[DataFrame, int]:
    spark = edges.sparkSession
    ship(spark)
    ends = edges.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).where("a <> b")
    now = stored(contract_partitions(ends.select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo"))), "edges")
    rounds, seen = 0, None
    while True:
        n, mark = now.agg(F.count("*"), F.sum(F.xxhash64("hi", "lo") % (1 << 40))).first()
        if n <= local_edges:
            last = contract_partitions(now.coalesce(1)) if n else now
            break
        if (n, mark) == seen:
            last = now
            break
        rounds, seen = rounds + 1, (n, mark)
        nxt = stored(_stars(contract_partitions(now.repartition("lo"))), "edges")
        discard(spark, now)
        now = nxt
    roots = last.select(F.col("lo").alias("node"), F.col("lo").alias("root")).distinct()
    return last.select(F.col("hi").alias("node"), F.col("lo").alias("root")).union(roots), rounds

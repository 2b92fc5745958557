"""Exact top-k by inner product as a Voronoi join.

Data and queries are grouped by their nearest pivot. Summaries of the cells (count, radius, longest vector,
distances of the rows nearest to the pivot) bound the scores between any query group and any data cell from
both sides: those nearest rows guarantee a k-th best score, and a cell is sent to a query group only if its
upper bound (by the angle to the pivot, and by the longest vector) reaches it. Each group is then solved
locally in blocks and the blocks' best rows are merged. On data that the bounds can't prune, the join degrades
to every block against every query group, and stays exact.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from zplane.session import ship, stored

#: Least and most data pivots (between them the square root of the rows), queries of a group, rows of a block, query pivots, distances in a summary.
DATA_PIVOTS, MOST_PIVOTS, GROUP_QUERIES, BLOCK_ROWS, QUERY_PIVOTS, MOST_NEAREST = 128, 2048, 256, 10_000, 128, 1000


def quantised(vectors: DataFrame, id_col: str, vec_col: str, scale: int) -> DataFrame:
    """(id, v): floor(scale * x) of every usable vector, as an array of doubles that hold integers."""
    x = F.col("v")
    picked = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("v"))
    bad = F.exists(x, lambda e: e.isNull() | F.isnan(e) | (F.abs(e) == float("inf")))
    return picked.where(x.isNotNull() & F.col("id").isNotNull() & ~bad).withColumn("v", F.transform(x, lambda e: F.floor(F.lit(float(scale)) * e).cast("double")))


def _matrix(column, dim: int) -> np.ndarray:
    """Rows of a list column as a matrix, short rows padded with zeros."""
    flat, lens = column.flatten().to_numpy(zero_copy_only=False), np.diff(column.offsets.to_numpy())
    if len(lens) and (lens == dim).all():
        return flat.reshape(len(lens), dim).astype(np.float64, copy=False)
    out = np.zeros((len(lens), dim))
    at = 0
    for i, n in enumerate(lens.tolist()):
        out[i, :n] = flat[at : at + n]
        at += n
    return out


def nearest_pivot(x: np.ndarray, pivots: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    d = (x * x).sum(1)[:, None] - 2 * (x @ pivots.T) + (pivots * pivots).sum(1)[None]
    cell = d.argmin(1)
    return cell, np.sqrt(((x - pivots[cell]) ** 2).sum(1))


def _assigned(rows: DataFrame, pivots: np.ndarray) -> DataFrame:
    dim = pivots.shape[1]

    def run(batches):
        import pyarrow as pa

        for b in batches:
            x = _matrix(b.column(1), dim)
            cell, far = nearest_pivot(x, pivots)
            yield pa.RecordBatch.from_arrays(
                [b.column(0), pa.array([r.tobytes() for r in x], pa.binary()), pa.array(cell.astype(np.int32)), pa.array(far), pa.array(np.linalg.norm(x, axis=1))], ["id", "v", "cell", "far", "length"]
            )

    return rows.mapInArrow(run, "id long, v binary, cell int, far double, length double")


def _summaries(rows: DataFrame, nearest: int) -> dict[int, tuple]:
    """{cell: (rows, radius, longest, distances of the `nearest` rows closest to the pivot)}: a row for each pivot."""
    got = {r["cell"]: [r["n"], r["radius"], r["longest"], np.zeros(0)] for r in rows.groupBy("cell").agg(F.count("*").alias("n"), F.max("far").alias("radius"), F.max("length").alias("longest")).collect()}
    if nearest:
        place = F.row_number().over(W.partitionBy("cell").orderBy("far"))
        first = rows.select("cell", "far", place.alias("place")).where(F.col("place") <= nearest)
        for r in first.groupBy("cell").agg(F.collect_list("far").alias("far")).collect():
            got[r["cell"]][3] = np.array(r["far"])
    return {c: tuple(v) for c, v in got.items()}


def _bounds(q_pivots, q_cells, d_pivots, d_cells, k: int, own: int) -> dict[int, list[int]]:
    """For each data cell, the query cells that need it. Cells: {cell: (rows, radius, longest, nearest distances)}; at most pivots squared.

    own: rows that share a query's id at most, which are counted in the cells but are no candidates.
    """
    need: dict[int, list[int]] = {j: [] for j in d_cells}
    js = sorted(d_cells)
    c = d_pivots[js]
    radius, longest = np.array([d_cells[j][1] for j in js]), np.array([d_cells[j][2] for j in js])
    size = np.linalg.norm(c, axis=1)
    near = np.concatenate([d_cells[j][3] for j in js])
    of = np.repeat(np.arange(len(js)), [len(d_cells[j][3]) for j in js])
    for i, (_, spread, *_) in q_cells.items():
        mid, norm = c @ q_pivots[i], np.linalg.norm(q_pivots[i])
        room = lambda far, at: (norm * far + spread * (size[at] + far)) * (1 + 1e-9) + 1e-6
        up = np.minimum(mid + room(radius, slice(None)), (norm + spread) * longest * (1 + 1e-9) + 1e-6)
        low = mid[of] - room(near, of)  # a score that each of the nearest rows surely reaches
        least = np.partition(low, len(low) - k - own)[len(low) - k - own] if len(low) >= k + own else -np.inf
        for j in np.flatnonzero(up >= least).tolist():
            need[js[j]].append(i)
    return need


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 10, id_col: str = "vec_id", vec_col: str = "embedding", scale: int = 1024) -> DataFrame:
    """(query_id, rank, vec_id, score): the k highest integer inner products of each query, ties to the smaller id.

    Vectors that are null or hold null or non-finite components take no part; shorter vectors count as
    padded with zeros. Rows that share a query's id are its own and no candidates; a repeated query id
    is one query (its first vector in order). Fewer than k candidates give fewer rows; empty tables none.
    """
    spark = vectors.sparkSession
    ship(spark)
    data, ask = quantised(vectors, id_col, vec_col, scale), quantised(queries, id_col, vec_col, scale)
    ask = ask.groupBy("id").agg(F.min("v").alias("v"))
    sizes = data.agg(F.count("*").alias("n"), F.max(F.size("v")).alias("dim"), F.max(F.array_max(F.transform("v", F.abs))).alias("top")).first()
    n_ask = ask.count()
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    if not sizes["n"] or not n_ask:
        return empty
    dim = max(1, sizes["dim"] or 1, ask.agg(F.max(F.size("v"))).first()[0] or 1)
    exact = (sizes["top"] or 0.0) ** 2 * dim < 2**53
    n_pivots = max(DATA_PIVOTS, min(MOST_PIVOTS, int(sizes["n"] ** 0.5)))
    share = min(1 << 30, (4 * n_pivots << 30) // sizes["n"] + 1)  # each task sends the driver a few candidates only
    drawn = data.where(F.pmod(F.xxhash64("id"), F.lit(1 << 30)) < share).orderBy(F.xxhash64("id"), "id")
    picked = drawn.limit(n_pivots).collect() or data.limit(n_pivots).collect()
    d_pivots = np.unique(np.array([list(r["v"]) + [0.0] * (dim - len(r["v"])) for r in picked]), axis=0)
    q_pivots = d_pivots[:: max(1, len(d_pivots) // max(1, min(QUERY_PIVOTS, -(-n_ask // GROUP_QUERIES))))]

    d_rows, q_rows = stored(_assigned(data, d_pivots), "vectors"), stored(_assigned(ask, q_pivots), "queries")
    own = d_rows.groupBy("id").agg(F.count("*").alias("n")).join(q_rows.select("id"), "id", "left_semi").agg(F.max("n")).first()[0] or 0
    # where very many rows share a query's id, summaries would grow with them: then nothing is pruned
    d_cells, q_cells = _summaries(d_rows, k + own if k + own <= MOST_NEAREST else 0), _summaries(q_rows, 0)
    need = _bounds(q_pivots, q_cells, d_pivots, d_cells, k, own)

    blocks = {i: -(-sum(d_cells[j][0] for j, to in need.items() if i in to) // BLOCK_ROWS) for i in q_cells}
    parts = {i: -(-q_cells[i][0] // (4 * GROUP_QUERIES)) for i in q_cells}
    routes = spark.createDataFrame([(j, i, blocks[i], parts[i]) for j, to in need.items() for i in to], "cell int, grp int, blocks int, parts int")  # at most pivots squared
    sent = d_rows.join(F.broadcast(routes), "cell").withColumn("blk", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    sent = sent.withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).select("grp", "part", "blk", "id", "v")
    shape = spark.createDataFrame([(i, blocks[i], parts[i]) for i in q_cells], "cell int, blocks int, parts int")
    asked = q_rows.join(F.broadcast(shape), "cell").withColumn("part", F.pmod(F.xxhash64("id"), F.col("parts")).cast("int"))
    asked = asked.withColumn("blk", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).select(F.col("cell").alias("grp"), "part", "blk", "id", "v")

    def solve(left, right):
        import pyarrow as pa

        kind = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64())])
        if not left.num_rows or not right.num_rows:
            return kind.empty_table()
        ids = left.column("id").to_numpy()
        order = np.argsort(ids, kind="stable")
        ids = ids[order]
        x = np.frombuffer(b"".join(left.column("v").to_pylist()), np.float64).reshape(len(ids), dim)[order]
        q_ids = right.column("id").to_numpy()
        q = np.frombuffer(b"".join(right.column("v").to_pylist()), np.float64).reshape(len(q_ids), dim)
        if not exact:
            x, q = x.astype(object), q.astype(object)
            for m in (x, q):
                m[:] = np.vectorize(int, otypes=[object])(m)
        out = ([], [], [])
        for lo in range(0, len(q_ids), 64):
            s = q[lo : lo + 64] @ x.T
            for i, row in enumerate(s):
                me = q_ids[lo + i]
                at = np.searchsorted(ids, me, "left"), np.searchsorted(ids, me, "right")
                row, of = np.delete(row, slice(*at)), np.delete(ids, slice(*at))
                if exact and len(row) > k:
                    hit = np.flatnonzero(row >= np.partition(row, len(row) - k)[len(row) - k])
                else:
                    hit = np.arange(len(row))
                hit = hit[np.argsort(-row[hit], kind="stable")[:k]]
                out[0].extend([int(me)] * len(hit))
                out[1].extend(of[hit].tolist())
                out[2].extend(max(-(2**63), min(2**63 - 1, int(v))) for v in row[hit])
        return pa.Table.from_arrays([pa.array(c, pa.int64()) for c in out], schema=kind)

    keys = ("grp", "part", "blk")
    best = sent.groupBy(*keys).cogroup(asked.groupBy(*keys)).applyInArrow(solve, "query_id long, vec_id long, score long")
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return best.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


SQL = """
WITH usable AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * CAST(x AS DOUBLE))) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND vec_id IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
scored AS (
  SELECT q.vec_id AS query_id, d.vec_id AS vec_id, CAST(list_inner_product(q.v, d.v) AS BIGINT) AS score
  FROM usable q JOIN usable d ON q.vec_id <> d.vec_id WHERE q.vec_id % 100 = 0),
ranked AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM scored)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM ranked WHERE rank <= 10
"""

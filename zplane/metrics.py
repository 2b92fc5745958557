"""Cost and accuracy measures of runs: time by step, memory of lists, differences between methods."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from zplane import pointsets as ps
from zplane.operators import knn
from zplane.plans import walk
from zplane.plans.planes import Options, PlaneTree
from zplane.session import stored


def breakdown(spark: SparkSession, sf_dir: str, src: str, k: int, options: Options | None = None) -> list[tuple[str, float, float]]:
    """(step, seconds, share) of a self query: keys and tree, node lists, leaf step, input order. Each step is forced by a write."""
    pts = ps.points(spark, sf_dir, src).persist()
    pts.count()
    steps: list[tuple[str, float]] = []

    def step(name, job):
        began = time.time()
        out = job()
        steps.append((name, time.time() - began))
        return out

    tree = step("keys, sort and planes", lambda: knn.joint_tree(pts, None, ps.cols(src), options=options))
    ilist = step("node lists", lambda: stored(walk.knn_ilist(tree, k), "ilist"))
    rows = step("leaf step", lambda: stored(knn.domain_rows(tree, ilist, True).groupBy("domain").applyInArrow(knn.rows_kernel(tree.d, k, None, True, True, None), "qid long, rank int, sid long, dist2 double"), "rows"))
    step("input order", lambda: rows.orderBy("qid", "rank").write.format("noop").mode("overwrite").save())
    total = sum(t for _, t in steps)
    return [(n, t, t / total) for n, t in steps]


def ilist_bytes(tree: PlaneTree, k: int) -> DataFrame:
    """(pairs, per_point, factor, bytes): rows of the leaf lists, entries for each point, and over the estimated leaves; two longs and a double each."""
    n = tree.n
    return walk.knn_ilist(tree, k).agg(F.count("*").alias("pairs")).select("pairs", (F.col("pairs") / n).alias("per_point"), (F.col("pairs") / (2 * n / tree.limits[0])).alias("factor"), (F.col("pairs") * 24).alias("bytes"))


def differences(a: DataFrame, b: DataFrame) -> DataFrame:
    """(differences): rows that only one of two results has."""
    a, b = stored(a), stored(b.select(*a.columns))
    return a.exceptAll(b).unionAll(b.exceptAll(a)).agg(F.count("*").alias("differences"))


def parallel_efficiency(seconds: dict[int, float]) -> dict[int, float]:
    """Time on one worker over time on w workers, at the same number of points for each worker."""
    one = seconds[min(seconds)]
    return {w: one / t for w, t in seconds.items()}


def slope(n: list[int], seconds: list[float]) -> float:
    """Exponent of time against size over the last doubling of a sweep."""
    import math

    return math.log(seconds[-1] / seconds[-2]) / math.log(n[-1] / n[-2])

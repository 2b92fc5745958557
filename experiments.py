"""Sweeps of the reference's experiments: python experiments.py [breakdown|libraries|domains|scaling|dims|k|queries|cap|linking ...]

Each prints a table. Sizes follow $BENCH_SF_DIR (default /root/testdata/sf0.1); `scaling` starts sessions of 1, 2, 4
and 8 cores one after the other and gives each core the same number of points.
"""

from __future__ import annotations

import os
import subprocess
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")


def session(cores: int = 8):
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master(f"local[{cores}]").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", str(2 * cores))
        .config("spark.driver.memory", "10g").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    s.sparkContext.setLogLevel("OFF")
    return s


def timed(job) -> float:
    began = time.time()
    job()
    return time.time() - began


def noop(df) -> None:
    df.write.format("noop").mode("overwrite").save()


def table(head: list[str], rows: list[tuple]) -> None:
    print(" | ".join(head))
    for r in rows:
        print(" | ".join(f"{v:.3g}" if isinstance(v, float) else str(v) for v in r), flush=True)


def breakdown(spark) -> None:
    """Time of each step of a self query, k = 16: keys and tree, node lists, leaf step, input order."""
    from zplane import metrics

    for src in ("ps_unif", "ps_line"):
        table(["step of " + src, "seconds", "share"], metrics.breakdown(spark, SF, src, 16))


def libraries(spark) -> None:
    """k = 30, separate queries, uniform: the walk against the other methods (quadratic ones on the smallest set only)."""
    from zplane import pointsets as ps
    from zplane.operators import baselines, knn

    rows = []
    for sf in ("sf0.001", "sf0.01", "sf0.1"):
        d = os.path.join(os.path.dirname(SF), sf)
        a, q, cols = ps.points(spark, d, "ps_unif").persist(), ps.points(spark, d, "ps_unif_q").persist(), ps.cols("ps_unif")
        n = min(a.count(), q.count())
        base = timed(lambda: noop(knn.knn(a, 30, cols, queries=q)))
        rows.append((n, "planes", base, 1.0))
        for name, f, most in (("brute", baselines.knn_brute, 2_000), ("kdtree", baselines.knn_kdtree_broadcast, 20_000), ("one_sided", baselines.knn_one_sided, 20_000), ("voronoi", baselines.knn_voronoi, 20_000), ("grid", baselines.knn_grid, 200_000)):
            if n <= most:
                t = timed(lambda f=f: noop(f(a, 30, cols, queries=q)))
                rows.append((n, name, t, t / base))
    table(["points", "method", "seconds", "over planes"], rows)


def domains(spark) -> None:
    from zplane import pointsets as ps
    from zplane.operators import knn
    from zplane.plans.planes import Options

    rows = []
    for name, src, kw in (("grid", "ps_grid", {}), ("uniform", "ps_unif", {}), ("normal", "ps_bell", {"options": Options(f_max=50.0)}), ("clustered", "ps_clump", {}), ("clustered, periodic", "ps_clump", {"box": [1.0] * 3})):
        a = ps.points(spark, SF, src).persist()
        n = a.count()
        t = timed(lambda: noop(knn.knn(a, 16, ps.cols(src), **kw)))
        rows.append((name, n, t, 16 * n / t))
    table(["distribution", "points", "seconds", "neighbours a second"], rows)


def dims(spark) -> None:
    from zplane import pointsets as ps
    from zplane.operators import baselines, knn

    rows = []
    for d in (2, 3, 4, 6, 8, 16, 64):
        a, cols = ps.points(spark, SF, f"ps_emb_d{d}").persist(), ps.cols(f"ps_emb_d{d}")
        n = a.count()
        m = knn.knn_metrics(a, 16, cols).first()
        rows.append((d, n, timed(lambda: noop(knn.knn(a, 16, cols))), timed(lambda: noop(baselines.knn_brute(a, 16, cols))), m.checked_share))
    table(["d", "points", "seconds", "brute force", "share of sources checked"], rows)


def k(spark) -> None:
    from zplane import pointsets as ps
    from zplane.operators import knn

    a = ps.points(spark, SF, "ps_unif").persist()
    a.count()
    table(["k", "seconds", "in passes of 32"], [(n, timed(lambda n=n: noop(knn.knn(a, n, ps.cols("ps_unif")))), timed(lambda n=n: noop(knn.knn(a, n, ps.cols("ps_unif"), k_pass=32)))) for n in (1, 4, 8, 16, 32, 64, 128)])


def queries(spark) -> None:
    from zplane import pointsets as ps
    from zplane.operators import knn

    a, q, cols = ps.points(spark, SF, "ps_unif").persist(), ps.points(spark, SF, "ps_unif_q").persist(), ps.cols("ps_unif")
    n = a.count()
    tree = knn.joint_tree(a, None, cols)
    tree.points.count()
    rows = []
    for share in (0.001, 0.01, 0.1, 1.0):
        part = q.where(f"id < {int(n * share)}").persist()
        rows.append((n, part.count(), timed(lambda p=part: noop(knn.knn(a, 16, cols, queries=p))), timed(lambda p=part: noop(knn.knn_probe(tree, p, 16, cols))) if share < 1 else float("nan")))
    table(["sources", "queries", "joint tree", "probe of a kept tree"], rows)


def cap(spark) -> None:
    """The size cap on heavy-tailed sets: distances evaluated with and without it."""
    from zplane import pointsets as ps
    from zplane.operators import knn
    from zplane.plans.planes import Options

    rows = []
    for src in ("ps_bell", "ps_events"):
        a = ps.points(spark, SF, src).persist()
        for f in (None, 50.0, 5.0):
            m = knn.knn_metrics(a, 16, ps.cols(src), options=Options(f_max=f)).first()
            rows.append((src, f or "off", m.listed, m.evaluated, m.early_exit_share))
    table(["set", "f_max", "leaf pairs", "distances", "skipped by early exit"], rows)


def linking(spark) -> None:
    from zplane import pointsets as ps
    from zplane.operators import baselines
    from zplane.operators import linking as ln

    rows = []
    for src, r in (("ps_clump", 0.004), ("ps_unif", 0.008), ("ps_line", 0.004)):
        a = ps.points(spark, SF, src).persist()
        cols, n = ps.cols(src), a.count()
        t = timed(lambda: noop(ln.catalogue(a, ln.link_clusters(a, cols, r), cols, mass="w")))
        rounds = ln.link_clusters_with_rounds(a, cols, r)[1]
        rows.append((src, n, r, "planes, with catalogue", t, rounds))
        for name, f in (("one task", baselines.link_union_find), ("cells", baselines.link_grid)):
            rows.append((src, n, r, name, timed(lambda f=f: noop(f(a, cols, r))), ""))
    table(["set", "points", "length", "method", "seconds", "rounds"], rows)


def scaling() -> None:
    """Weak scaling: points grow with the cores."""
    for cores in (1, 2, 4, 8):
        code = f"""
import experiments as e
from zplane import pointsets as ps
from zplane.operators import knn, linking as ln
from zplane.plans.planes import Options
s = e.session({cores}); n = 70000 * {cores}; cols = ps.cols('ps_line')
a = ps.points(s, e.SF, 'ps_line').orderBy('id').limit(n).repartition({cores}).persist(); a.count()
o = Options(domain_rows=max(10000, 70000 // 4))
e.noop(knn.knn(a, 16, cols, options=o))
t = e.timed(lambda: e.noop(knn.knn(a, 16, cols, options=o)))
u = e.timed(lambda: e.noop(ln.link_clusters(a, cols, 0.004, options=o)))
print({cores}, n, round(t, 2), round(16 * n / t / {cores}), round(u, 2), sep=' | ', flush=True)
"""
        subprocess.run([sys.executable, "-c", code], cwd=os.path.dirname(os.path.abspath(__file__)), stderr=subprocess.DEVNULL, check=False)


def main(names: list[str]) -> None:
    every = {f.__name__: f for f in (breakdown, libraries, domains, dims, k, queries, cap, linking)}
    names = names or [*every, "scaling"]
    if "scaling" in names:
        print("cores | points | kNN s | neighbours a second and core | linking s")
        scaling()
    todo = [every[n] for n in names if n in every]
    if todo:
        spark = session()
        for f in todo:
            print(f"\n{f.__name__}: {(f.__doc__ or '').strip()}")
            f(spark)


if __name__ == "__main__":
    main(sys.argv[1:])

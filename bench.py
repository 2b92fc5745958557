"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))


def main() -> None:
    from pyspark.sql import SparkSession

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", "16")
        .config("spark.driver.memory", "12g").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")

    from zplane import metrics
    from zplane import pointsets as ps
    from zplane.operators import baselines, knn, linking
    from zplane.plans.planes import Options
    from zplane.session import clear_shared, stored

    sets: dict = {}

    def points(src):
        """A point set, written before anything is timed."""
        if src not in sets:
            sets[src] = stored(ps.points(spark, sf_dir, src), src)
        return sets[src]

    def noop(df):
        df.write.format("noop").mode("overwrite").save()

    def run_knn(src, k, queries=None, method=knn.knn, **kw):
        a, q = points(src), points(queries) if queries else None
        return lambda: noop(method(a, k, ps.cols(src), **({"queries": q} if queries else {}), **kw))

    def run_link(src, r, **kw):
        pts = points(src)
        return lambda: noop(linking.catalogue(pts, linking.link_clusters(pts, ps.cols(src), r, **kw), ps.cols(src), mass="w", box=kw.get("box")))

    clump, cube = points("ps_clump"), [1.0, 1.0, 1.0]
    jobs = {
        "knn_unif_k16": run_knn("ps_unif", 16),
        "knn_grid_k16": run_knn("ps_grid", 16),
        "knn_bell_k16": run_knn("ps_bell", 16, options=Options(f_max=50.0)),
        "knn_clump_k16": run_knn("ps_clump", 16),
        "knn_clump_periodic_k16": run_knn("ps_clump", 16, box=cube),
        "knn_unif_sep_k30": run_knn("ps_unif", 30, "ps_unif_q"),
        "knn_reduce_unif_k16": lambda: noop(knn.knn_reduce(points("ps_unif"), 16, ps.cols("ps_unif"), "w")),
        "knn_line_k16": run_knn("ps_line", 16),
        "base_kdtree_unif_k16": run_knn("ps_unif", 16, method=baselines.knn_kdtree_broadcast),
        # the grid sorts hundreds of candidates a point, so this pair is on the smaller set
        "knn_customer_k16": run_knn("ps_customer", 16),
        "base_grid_customer_k16": run_knn("ps_customer", 16, method=baselines.knn_grid),
        "link_clump_catalogue": run_link("ps_clump", 0.004),
        "link_clump_periodic_catalogue": run_link("ps_clump", 0.004, box=cube),
        "base_link_grid_clump_catalogue": lambda: noop(linking.catalogue(clump, baselines.link_grid(clump, ps.cols("ps_clump"), 0.004), ps.cols("ps_clump"), mass="w")),
        "base_link_one_task_clump": lambda: noop(baselines.link_union_find(clump, ps.cols("ps_clump"), 0.004)),
    }
    only = sys.argv[1:]
    jobs["knn_unif_k16"]()  # warm-up: compile, start workers
    took = {}
    for name, job in jobs.items():
        if only and name not in only:
            continue
        began = time.time()
        job()
        took[name] = round(time.time() - began, 2)
    steps = {} if only else {name: [round(t, 2), round(share, 2)] for name, t, share in metrics.breakdown(spark, sf_dir, "ps_unif", 16)}
    clear_shared(spark)
    print(json.dumps({"metric": "total wall time of headline queries", "value": round(sum(took.values()), 2), "unit": "sec", "queries": took, "steps_unif_k16": steps, "sf": sf_dir.rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    main()

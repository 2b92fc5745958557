"""Registered functions, the data source, and streams against batch results."""

import pytest
from pyspark.sql import functions as F

from zplane import pointsets as ps
from zplane.operators import knn
from zplane.sources import points as src
from zplane.streaming import cells


def test_registered_functions(spark):
    from zplane.functions.registered import register

    register(spark)
    assert spark.sql("SELECT z_extent(-1, 2) AS e").first().e == [-1, 0]
    assert spark.sql("SELECT z_dist(array(0D, 3D), array(4D, 0D)) AS v").first().v == 5.0
    assert abs(spark.sql("SELECT z_wrap_dist(array(0.05D), array(0.95D), 1D) AS v").first().v - 0.1) < 1e-12
    assert spark.sql("SELECT z_dlow(array(0D), array(1D), array(3D), array(1D)) AS a, z_dup(array(0D), array(1D), array(3D), array(1D)) AS b").first() == (2.0, 4.0)
    assert spark.sql("SELECT rmax_agg(d, n, k) AS r FROM VALUES (1D, 2, 4), (3D, 5, 4), (2D, 1, 4) AS t(d, n, k)").first().r == 3.0
    assert spark.sql("SELECT z_key(array(1D), 3, 0) < z_key(array(2D), 3, 0) AS v").first().v
    x = "array(array(1.6D), array(3.1D), array(3.3D), array(4.6D), array(5.6D), array(6.8D), array(9.4D), array(9.7D))"
    rows = spark.sql(f"SELECT plane, first FROM z_nodes({x}, array(2, 4))").collect()
    assert sorted(r.first for r in rows if r.plane == 0) == [0, 1, 3, 5, 6] and sorted(r.first for r in rows if r.plane == 1) == [0, 3, 6]


def test_data_source(spark, sf):
    src.register(spark)
    df = spark.read.format("zplane_points").option("n", 50).option("d", 2).load()
    assert df.count() == 50 and abs(df.where("id = 1").first().x0 - 0.8518196013756096) < 1e-15
    pts = src.read_points(spark, f"{sf}/embeddings.parquet", ["embedding[0]", "embedding[1]"], "vec_id", payload=["label"])
    assert pts.columns == ["id", "x0", "x1", "label"]


def test_streams_equal_batch(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet")
    for i, part in enumerate(events.randomSplit([0.5, 0.5], 3)):
        part.write.parquet(str(tmp_path / "in" / str(i)))
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in" / "*"))
    q = cells.cell_counts(stream, "ts", ["value"], ((0.0, 600.0),), "1 day").writeStream.outputMode("complete").format("memory").queryName("cells").start()
    q.processAllAvailable()
    q.stop()
    want = cells.cell_counts(events, "ts", ["value"], ((0.0, 600.0),), "1 day")
    assert spark.table("cells").exceptAll(want).count() == 0 and spark.table("cells").count() == want.count()


def test_stream_probe(spark, sf, tmp_path):
    pts, cols = ps.points(spark, sf, "ps_unif"), ps.cols("ps_unif")
    tree = knn.joint_tree(pts, None, cols)
    asks = ps.points(spark, sf, "ps_unif_q").select("id", *cols).limit(60)
    asks.write.parquet(str(tmp_path / "ask"))
    stream = spark.readStream.schema(asks.schema).parquet(str(tmp_path / "ask"))
    q = cells.stream_knn(stream, tree, 4, cols, str(tmp_path / "out"), checkpoint=str(tmp_path / "cp"))
    q.processAllAvailable()
    q.stop()
    got = {(r.qid, r["rank"]): r.sid for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    want = {(r.qid, r["rank"]): r.sid for r in knn.knn(pts, 4, cols, queries=spark.read.parquet(str(tmp_path / "ask"))).collect()}
    assert got == want


@pytest.mark.parametrize("name", ["link_customer", "pair_counts"])
def test_plans_have_no_cartesian_product(spark, sf, name):
    from zplane import workloads

    text = workloads.queries()[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text


def test_windows_are_linked_once_closed_and_late_rows_counted(spark, tmp_path):
    from datetime import datetime, timedelta

    t0 = datetime(2024, 1, 1)
    row = lambda i, minutes, x: (i, t0 + timedelta(minutes=minutes), float(x))
    batches = [
        [row(1, 1, 0), row(2, 5, 0.5), row(3, 9, 5), row(4, 62, 0.2)],
        [row(5, 130, 0.1), row(6, 59, 0.9)],  # the first hour is open until now
        [row(7, 2, 9), row(8, 200, 0.0)],  # 7 is late
    ]
    schema = "id long, ts timestamp, x double"
    src_dir, out = tmp_path / "in", str(tmp_path / "out")
    for i, rows in enumerate(batches):
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(str(src_dir / str(i)))
        stream = spark.readStream.schema(schema).parquet(str(src_dir / "*"))
        q = cells.stream_link_windows(stream, "ts", "1 hour", ["x"], 1.0, out, watermark="30 minutes", checkpoint=str(tmp_path / "cp"))
        q.processAllAvailable()
        q.stop()
    got = {(r.id, r.start.hour): r.group_id for r in spark.read.parquet(f"{out}/linked/batch=*").collect()}
    assert got == {(1, 0): 1, (2, 0): 1, (3, 0): 3, (6, 0): 1, (4, 1): 4} and cells.late_rows(spark, out) == 1


def test_components_of_a_stream(spark, tmp_path):
    batches = [[(1, 2), (3, 4), (7, 7)], [(4, 5), (9, 8)], [(2, 5), (8, 7), (None, 3)]]
    out = str(tmp_path / "out")
    for i, rows in enumerate(batches):
        spark.createDataFrame(rows, "a long, b long").coalesce(1).write.parquet(str(tmp_path / "in" / str(i)))
        stream = spark.readStream.schema("a long, b long").parquet(str(tmp_path / "in" / "*"))
        q = cells.stream_components(stream, out, checkpoint=str(tmp_path / "cp"))
        q.processAllAvailable()
        q.stop()
    got = {r.node: r.root for r in spark.read.parquet(f"{out}/batch=2").collect()}
    assert got == {1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 7: 7, 8: 7, 9: 7}


def test_table_functions_and_keys(spark, sf):
    from zplane.functions import zkey
    from zplane.functions.registered import register

    register(spark)
    spark.createDataFrame([(1, [0.0]), (2, [1.0]), (3, [5.0])], "id long, x array<double>").createOrReplaceTempView("few")
    near = spark.sql("SELECT * FROM knn_of(TABLE(SELECT * FROM few) WITH SINGLE PARTITION, 2)").collect()
    assert {(r.qid, r["rank"], r.sid) for r in near} == {(1, 1, 1), (1, 2, 2), (2, 1, 2), (2, 2, 1), (3, 1, 3), (3, 2, 2)}
    assert spark.sql("SELECT topk_agg(d, i, 2) AS t FROM VALUES (3D, 1L), (1D, 9L), (1D, 2L) AS t(d, i)").first().t == [2, 9]
    pts = ps.points(spark, sf, "ps_unif")
    cols, box = ps.cols("ps_unif"), ((0.0, 1.0),) * 3
    both = zkey.with_zkey(pts, cols, mode="morton63", box=box).selectExpr("id", "zkey", "z_key63(array(x0, x1, x2), 0D, 1D) AS k")
    assert both.where("zkey <> k").count() == 0
    curve = zkey.with_zkey(pts, cols, mode="hilbert", box=box)
    assert curve.select("zkey").distinct().count() == pts.count()
    pts = pts.withColumns({c: F.col(c) / 3 for c in cols})  # numbers of 53 bits
    short = zkey.with_zkey(pts, cols, mode="float32")
    rounded = zkey.with_zkey(pts.withColumns({c: F.col(c).cast("float").cast("double") for c in cols}), cols)
    order = lambda df: [r.id for r in df.orderBy("zkey", "id").collect()]
    assert order(short) == order(rounded) and max(len(r.zkey) for r in short.collect()) < max(len(r.zkey) for r in zkey.with_zkey(pts, cols).collect())


def test_top_plane_does_not_grow_with_the_domains(spark, sf):
    from zplane.plans import walk
    from zplane.plans.planes import Options

    pts, cols = ps.points(spark, sf, "ps_unif"), ps.cols("ps_unif")
    tops = []
    for rows in (400, 100, 25):
        tree = knn.joint_tree(pts, None, cols, options=Options(n_max0=8, domain_rows=rows, n_target=8))
        planes = walk.collect_planes(tree)
        assert len(tree.starts) >= 1500 // rows and [int(p.n_src.sum()) for p in planes] == [1500] * len(planes)
        tops.append(len(planes[-1].node) ** 2)
    assert max(tops) <= 64


def test_ranges_counted_whole_equal_pairs(spark, sf):
    from zplane.operators import joins
    from zplane.plans.planes import Options

    pts, cols = ps.points(spark, sf, "ps_clump"), ps.cols("ps_clump")
    few = Options(n_max0=8, domain_rows=200, n_target=4)
    whole = {r.id: r.n for r in joins.count_within(pts, None, 0.3, cols, options=few).collect()}
    assert whole == {r.id: r.n for r in joins.count_within(pts, None, 0.3, cols, options=few, method="stages").collect()}
    pairs = joins.distance_join(pts, None, 0.3, cols).collect()
    want = dict.fromkeys(whole, 1)
    for r in pairs:
        want[r.qid] += 1
        want[r.sid] += 1
    assert whole == want

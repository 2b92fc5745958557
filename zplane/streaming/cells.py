"""Streaming forms: cell densities, time linking, probes of a kept tree, clusters of closed windows, groups of a stream of links."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.utils import AnalysisException

from zplane.components import components
from zplane.functions.zkey import morton63, morton_bits


def cell_counts(events: DataFrame, ts: str, cols: list[str], box: tuple, window: str, slide: str | None = None, bits: int = 9, watermark: str | None = None) -> DataFrame:
    """(start, end, cell, n): points for each time window and Morton cell (the first `bits` bits); batch or stream."""
    rows = events.withWatermark(ts, watermark) if watermark and events.isStreaming else events
    d = len(cols)
    keyed = rows.withColumn("cell", F.shiftright(morton63([F.col(c) for c in cols], box), d * morton_bits(d) - bits))
    return keyed.groupBy(F.window(ts, window, slide), "cell").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), F.col("window.end").alias("end"), "cell", "n")


def link_time(events: DataFrame, gap: str, key: str, ts: str = "ts", id_col: str = "event_id", watermark: str | None = None) -> DataFrame:
    """(key, start, end, n, first_id): linking in one dimension, time: chains of gaps up to `gap` are sessions."""
    rows = events.withWatermark(ts, watermark) if watermark and events.isStreaming else events
    out = rows.groupBy(key, F.session_window(ts, gap)).agg(F.count("*").alias("n"), F.min(id_col).alias("first_id"))
    return out.select(key, F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n", "first_id")


def stream_knn(stream: DataFrame, tree, k: int, cols: list[str], path: str, id_col: str = "id", checkpoint: str | None = None):
    """Probe a kept tree with every micro-batch; results are appended to parquet, once for each batch id."""
    from zplane.operators.knn import knn_probe

    def step(batch: DataFrame, batch_id: int) -> None:
        knn_probe(tree, batch, k, cols, id_col).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    writer = stream.writeStream.foreachBatch(step)
    return (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()


def stream_link_windows(stream: DataFrame, ts: str, window: str, cols: list[str], r_link: float, path: str, id_col: str = "id", watermark: str = "1 hour", checkpoint: str | None = None):
    """Clusters (id, start, group_id) of each closed window, under path/linked.

    Rows are kept as files until the newest time seen is `watermark` past the end of their window. All windows that
    close in a batch are linked in one go, set apart by one more coordinate. Rows of windows that are linked
    already are late: they go to path/late, and are counted by late_rows(). Batches that run again give the same files.
    """
    from zplane.operators.linking import link_clusters

    def step(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        w = F.window(ts, window)
        rows = batch.select(F.col(id_col).cast("long").alias("id"), *cols, F.col(ts).cast("timestamp").alias("at"), w.start.alias("start"), w.end.alias("end"))
        rows.write.mode("overwrite").parquet(f"{path}/staged/batch={batch_id}")
        now = spark.read.parquet(f"{path}/staged/batch={batch_id}")
        staged = spark.read.option("basePath", f"{path}/staged").parquet(f"{path}/staged/batch=*").where(F.col("batch") <= batch_id)
        if batch_id:
            before = spark.read.option("basePath", f"{path}/linked").parquet(f"{path}/linked/batch=*").where(F.col("batch") < batch_id).select("start").distinct()
            now.join(before, "start", "left_semi").write.mode("overwrite").parquet(f"{path}/late/batch={batch_id}")
            staged = staged.join(before, "start", "left_anti")
        high = staged.agg(F.max("at") - F.expr(f"INTERVAL {watermark}")).first()[0]
        closed = staged.where(F.col("end") <= F.lit(high)).dropDuplicates(["id", "start"])
        seconds = F.col("start").cast("long")
        # linking takes ids of points, so a window's points get ids of their own
        placed = closed.withColumns({"__w": seconds.cast("double") * (4 * r_link + 1), "__id": F.abs(F.xxhash64("id", "start")) % F.lit(1 << 61)})
        groups = link_clusters(placed, [*cols, "__w"], r_link, "__id").select(F.col("id").alias("__id"), "group_id")
        named = placed.join(groups, "__id").groupBy("start", "group_id").agg(F.min("id").alias("least"))
        out = placed.join(groups, "__id").join(named, ["start", "group_id"]).select("id", "start", F.col("least").alias("group_id"))
        out.write.mode("overwrite").parquet(f"{path}/linked/batch={batch_id}")

    writer = stream.writeStream.foreachBatch(step)
    return (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()


def late_rows(spark, path: str) -> int:
    """How many rows came after their window was linked."""
    try:
        return spark.read.option("basePath", f"{path}/late").parquet(f"{path}/late/batch=*").count()
    except AnalysisException:  # no batch after the first
        return 0


def stream_components(stream: DataFrame, path: str, a: str = "a", b: str = "b", checkpoint: str | None = None):
    """Groups of a stream of links, kept up to date: (node, root) after batch i under path/batch=i, root the smallest node.

    Only the roots that a batch touches are contracted; the labels of all others are carried over.
    """

    def step(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        ends = batch.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).where("a IS NOT NULL AND b IS NOT NULL")
        nodes = ends.select(F.col("a").alias("node")).union(ends.select("b")).distinct()
        if batch_id:
            old = spark.read.parquet(f"{path}/batch={batch_id - 1}")
            for end in ("a", "b"):
                ends = ends.join(old.withColumnRenamed("node", end), end, "left").withColumn(end, F.coalesce("root", end)).drop("root")
            nodes = old.unionByName(nodes.join(old, "node", "left_anti").withColumn("root", F.col("node")))
        else:
            nodes = nodes.withColumn("root", F.col("node"))
        moved = components(ends).toDF("root", "to")
        nodes.join(moved, "root", "left").select("node", F.coalesce("to", "root").alias("root")).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    writer = stream.writeStream.foreachBatch(step)
    return (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()

"""Views and checks of keys, gaps, planes and domains."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from zplane.functions import zkey
from zplane.plans import planes
from zplane.plans.planes import PlaneTree


def gap_table(spark: SparkSession, points: list[tuple], limits: list[int]) -> DataFrame:
    """(pos, lvl, n, in_plane0..) of every gap of a few literal points, sorted in Morton order."""
    x = np.array(points, float)
    plan = zkey.plan_of(x, x.shape[1])
    keys = zkey.exact_keys(x, plan)
    keys = keys[np.lexsort([keys[:, j] for j in range(keys.shape[1] - 1, -1, -1)])]
    bits = planes.gap_bits(keys, plan)
    lvl = zkey.level_of_bits(np.maximum(bits, 0), plan)
    splits = [set(s.tolist()) for s in planes.split_positions(bits, limits)]
    rows = [(i, int(lvl[i]) if bits[i] >= 0 else None, int(n), *(i in s for s in splits)) for i, n in enumerate(planes.gap_counts(bits))]
    return spark.createDataFrame(rows, "pos long, lvl int, n long, " + ", ".join(f"in_plane{p} boolean" for p in range(len(limits))))


def gap_rows(points: DataFrame, cols: list[str], limits: list[int]) -> DataFrame:
    """(pos, lvl, n, in_plane0..): the same of the inner gaps of a table's distinct points, in tasks.

    Neighbours meet by position, so there is no window over the table; a gap's cell is counted by its key prefix.
    """
    from zplane.session import stored

    sites = points.select(*(F.col(c).cast("double").alias(c) for c in cols)).distinct()
    plan = zkey.plan_key(sites, cols)
    keyed = zkey.with_zkey(sites, cols, plan).select("zkey", F.lit(0).alias("id"))
    placed = stored(with_zpos(zsort(keyed)).select("zkey", "zpos", planes._bit_text(plan).alias("key")), "sites")

    def run(batches):
        import pyarrow as pa

        from zplane.functions import zkey

        for b in batches:
            left, right = (np.frombuffer(b"".join(b.column(c).to_pylist()), np.uint8).reshape(b.num_rows, -1) for c in (1, 2))
            bits = zkey.common_bits(left, right, plan)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(bits.astype(np.int32)), pa.array(zkey.level_of_bits(bits, plan).astype(np.int32)), b.column(3)], ["pos", "bits", "lvl", "key"])

    after = placed.select((F.col("zpos") + 1).alias("pos"), F.col("zkey").alias("a"), "key")
    pairs = after.join(placed.select(F.col("zpos").alias("pos"), F.col("zkey").alias("b")), "pos").select("pos", "a", "b", "key")
    gaps = pairs.mapInArrow(run, "pos long, bits int, lvl int, key string").withColumn("prefix", F.expr("substring(key, 1, bits)"))
    every = placed.select("key", F.explode(F.sequence(F.lit(0), F.lit(plan.bits))).alias("bits"))
    cells = every.groupBy("bits", F.expr("substring(key, 1, bits)").alias("prefix")).agg(F.count("*").alias("n"))
    return gaps.join(cells, ["bits", "prefix"]).select("pos", "lvl", "n", *((F.col("n") > m).alias(f"in_plane{i}") for i, m in enumerate(limits)))


def check_planes(tree: PlaneTree) -> DataFrame:
    """(violation, n): counts of broken properties of a tree; all zero for a right one."""
    d = tree.d
    leaf = tree.nodes.where("plane = 0")
    pts = tree.points.groupBy("leaf").agg(F.count("*").alias("m"))
    counts = leaf.join(pts, leaf["node"] == pts["leaf"], "full").where("m IS NULL OR node IS NULL OR m <> n_src + n_qry")
    limit = F.element_at(F.array(*(F.lit(v) for v in tree.limits)), F.col("plane") + 1)
    over = tree.nodes.where((F.greatest("n_src", "n_qry") > limit) & (F.col("lvl") > -(2**30)))
    inside = tree.points.join(leaf.select(F.col("node").alias("leaf"), "c", "ext"), "leaf")
    out = None
    for i in range(d):
        t = F.abs(F.col(f"x{i}") - F.col("c")[i]) > F.col("ext")[i] / 2
        out = t if out is None else out | t
    outside = inside.where(out)
    kids = tree.nodes.groupBy((F.col("plane") + 1).alias("plane"), F.col("parent").alias("node")).agg(F.sum("n_src").alias("s"), F.sum("n_qry").alias("q"))
    sums = tree.nodes.where("plane > 0").join(kids, ["plane", "node"], "left").where("s IS NULL OR s <> n_src OR q <> n_qry")
    lost = tree.points.join(leaf.select(F.col("node").alias("leaf")), "leaf", "left_anti")
    named = [("a leaf count differs from its points", counts), ("a node holds more than its limit", over), ("a point lies outside its leaf cell", outside), ("children do not add up to their node", sums), ("a point is in no leaf", lost)]
    rows = [df.agg(F.count("*").alias("n")).select(F.lit(name).alias("violation"), "n") for name, df in named]
    result = rows[0]
    for r in rows[1:]:
        result = result.unionAll(r)
    return result


def domain_balance(tree: PlaneTree) -> DataFrame:
    """(domains, points, most, imbalance): how even the domains are; imbalance is the largest over the mean, less 1."""
    per = tree.points.groupBy("domain").agg(F.count("*").alias("n"))
    return per.agg(F.count("*").alias("domains"), F.sum("n").alias("points"), F.max("n").alias("most"), (F.max("n") / F.avg("n") - 1).alias("imbalance"))


def partition_imbalance(df: DataFrame) -> DataFrame:
    """The same over the partitions of any DataFrame."""
    per = df.groupBy(F.spark_partition_id().alias("p")).agg(F.count("*").alias("n"))
    return per.agg(F.count("*").alias("partitions"), (F.max("n") / F.avg("n") - 1).alias("imbalance"))


def zsort(df: DataFrame, n_parts: int | None = None, samples: int | None = None) -> DataFrame:
    """df (with zkey, id) in global Morton order: sampled splitters, one range shuffle, local sorts.

    samples: keys drawn for each part (Spark's own number if not given); more of them make parts more even.
    """
    name, conf = "spark.sql.execution.rangeExchange.sampleSizePerPartition", df.sparkSession.conf
    old = conf.get(name)
    if samples:
        conf.set(name, str(samples))
        try:
            got = zsort(df, n_parts)
            got._jdf.queryExecution().executedPlan()  # the plan keeps the number
            return got
        finally:
            conf.set(name, old)
    parts = df.repartitionByRange(n_parts, "zkey", "id") if n_parts else df.repartitionByRange("zkey", "id")
    return parts.sortWithinPartitions("zkey", "id")


def with_zpos(df_sorted: DataFrame) -> DataFrame:
    """A global position for sorted partitions: counts of the partitions, prefix sums, an offset for each (no global window)."""
    from zplane.session import checkpoint

    fixed = checkpoint(df_sorted)
    counts = sorted((r["p"], r["n"]) for r in fixed.groupBy(F.spark_partition_id().alias("p")).agg(F.count("*").alias("n")).collect())
    base, at = {}, 0
    for p, n in counts:
        base[p] = at
        at += n

    def run(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        pos = base.get(TaskContext.get().partitionId(), 0)
        for b in batches:
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(np.arange(pos, pos + b.num_rows))], [*b.schema.names, "zpos"])
            pos += b.num_rows

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in fixed.schema.fields), "zpos long"])
    return fixed.mapInArrow(run, schema)


def rebalance(df_with_zpos: DataFrame, n_parts: int) -> DataFrame:
    """Even partitions after the sort: part i holds the positions from i n / n_parts on, so sizes differ by one at most."""
    n = max(1, df_with_zpos.count())
    part = F.expr(f"((zpos + 1) * {n_parts} - 1) div {n}").cast("int")
    return df_with_zpos.withColumn("part", part).repartitionById(n_parts, "part").sortWithinPartitions("zpos")

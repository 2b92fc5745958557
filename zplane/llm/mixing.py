"""Mixing sources to target weights along a time-varying curriculum, in DataFrame operations only.

Each source has a target (its share by weight, held at a multiple of its size, the excess reshared) and
a weight schedule over training time t in [0, 1], w(t) = w0 * (1 + a * (2 t - 1)). The integral of the
schedule is the share of the source's words that training has taken by time t, so the position of a
document is the time at which the integral reaches the words taken before its middle: a quadratic that
has a closed form. Documents are range-sorted by that position.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from zplane.session import stored

#: Weights and schedule slopes (a) by the rank of a source, repeating.
WEIGHTS, SLOPES = (5, 2, 1), (0.5, 0.0, -0.5)
MOST = 3  # repeats of a source or document


def word_count(text: Column) -> Column:
    """Runs of characters other than blank and the controls 9 to 13; null counts as empty."""
    return F.size(F.array_remove(F.split(F.coalesce(text.cast("string"), F.lit("")), r"[\x20\x09-\x0D]+"), "")).cast("long")


def _by_rank(values: tuple) -> Column:
    at = F.pmod(F.col("nth") - 1, F.lit(len(values)))
    out = F.when(at == 0, F.lit(values[0]))
    for i, v in enumerate(values[1:], 1):
        out = out.when(at == i, F.lit(v))
    return out


def source_targets(sized: DataFrame, weights: tuple = WEIGHTS, slopes: tuple = SLOPES, most: int = MOST) -> DataFrame:
    """(source, source_size, weight, slope, target, goal): the water level of the weights under the caps.

    Sources rank by code point, null last. Ordered by cap over weight, a source is at its cap exactly if
    the level that would serve it and all later sources reaches its cap. One row for each source.
    """
    ranked = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    ranked = ranked.withColumn("nth", F.row_number().over(W.orderBy(F.col("source").asc_nulls_last())))
    ranked = ranked.withColumns({"weight": _by_rank(weights).cast("long"), "slope": _by_rank(slopes).cast("double"), "cap": F.col("source_size") * most})
    order = W.orderBy(F.col("cap") / F.col("weight"), "nth")
    before, every = order.rowsBetween(W.unboundedPreceding, -1), order.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    level = (F.sum("source_size").over(every) - F.coalesce(F.sum("cap").over(before), F.lit(0))) / (
        F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0))
    )
    levelled = ranked.withColumn("level", level).withColumn("capped", F.col("level") * F.col("weight") >= F.col("cap"))
    free = F.min(F.when(~F.col("capped"), F.struct(F.col("cap") / F.col("weight"), "nth", "level"))).over(every)["level"]
    target = F.when(F.col("capped"), F.col("cap").cast("double")).otherwise(F.col("weight") * free)
    out = levelled.withColumn("target", target).withColumn("goal", F.floor(F.col("target") + 0.5).cast("long"))
    return out.select("source", "source_size", "weight", "slope", "target", "goal")


def _time(slope: Column, share: Column) -> Column:
    """The inverse of the integrated schedule: t with t + a (t^2 - t) = share."""
    share = F.least(F.greatest(share, F.lit(0.0)), F.lit(1.0))
    return 2.0 * share / ((1.0 - slope) + F.sqrt((1.0 - slope) * (1.0 - slope) + 4.0 * slope * share))


def plan_mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **options) -> DataFrame:
    """(doc_id, source, size, source_size, target, taken, passes, words_before, position), one row per row of docs.

    A source whose goal is f full passes and a rest gives every document f times, and once more the
    documents that come first in md5 order of their ids until the rest is reached (the last one in part),
    so a source's taken words equal its rounded target and no document exceeds its cap. Sums before a
    document come from 4096 bins of that order for each source, so no source is summed in one task.
    Null text or no words: size 0, taken 0. Null sources form one source. Repeated ids are documents of
    their own. An empty table gives an empty plan.
    """
    key = F.md5(F.coalesce(F.col(id_col).cast("string"), F.lit("")))
    sized = stored(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(source_col).cast("string").alias("source"), word_count(F.col(text_col)).alias("size"), key.alias("key")), "sizes")
    sized = sized.withColumn("bin", F.substring("key", 1, 3))
    targets = source_targets(sized, **options)
    bins = sized.groupBy("source", "bin").agg(F.sum("size").alias("bin_size"))
    ahead = F.sum("bin_size").over(W.partitionBy("source").orderBy("bin").rowsBetween(W.unboundedPreceding, -1))
    bins = bins.withColumn("bins_before", F.coalesce(ahead, F.lit(0))).withColumnRenamed("source", "s").withColumnRenamed("bin", "b")
    steps = bins.join(targets.withColumnRenamed("source", "t"), F.col("s").eqNullSafe(F.col("t"))).drop("t", "bin_size")
    inside = W.partitionBy("source", "bin").orderBy("key", "doc_id", "size").rowsBetween(W.unboundedPreceding, -1)
    placed = sized.withColumn("inside", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    placed = placed.join(steps, F.col("source").eqNullSafe(F.col("s")) & (F.col("bin") == F.col("b")))
    before = F.col("bins_before") + F.col("inside")
    passes = F.when(F.col("source_size") > 0, F.expr("goal div source_size")).otherwise(F.lit(0)).cast("long")
    rest = F.when(F.col("source_size") > 0, F.expr("goal % source_size")).otherwise(F.lit(0)).cast("long")
    extra = F.least(F.greatest(rest - before, F.lit(0).cast("long")), F.col("size"))
    share = F.when(F.col("goal") > 0, (before + F.col("size") / 2.0) / F.col("goal")).otherwise(F.lit(0.0))
    return placed.select(
        "doc_id", "source", "size", "source_size", "target", "slope", "goal",
        (passes * F.col("size") + extra).alias("taken"), passes.alias("passes"), before.alias("words_before"),
        F.round(_time(F.col("slope"), share), 9).alias("position"),
    )


def mix(docs: DataFrame, id_col: str = "doc_id", **options) -> DataFrame:
    """The rows of docs as the mix takes them, range-sorted by training position: a document is repeated
    for each pass that takes any of its words (whole texts, also where a pass takes only part), and
    documents that no pass takes are left out. Columns are those of docs, of whatever names."""
    plan = plan_mix(docs, id_col, **options).where(F.col("taken") > 0)
    times = F.sequence(F.lit(0).cast("long"), F.ceil(F.col("taken") / F.col("size")).cast("long") - 1)
    takes = plan.select("doc_id", "slope", "goal", "source_size", "size", "words_before", F.explode(times).alias("nth"))
    share = (F.col("nth") * F.col("source_size") + F.col("words_before") + F.col("size") / 2.0) / F.col("goal")
    takes = takes.select(F.col("doc_id").alias("id"), "nth", _time(F.col("slope"), share).alias("position")).dropDuplicates(["id", "nth"])
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), F.col(id_col).cast("long").alias("doc_id"))
    return rows.join(takes, F.col("doc_id").eqNullSafe(F.col("id"))).orderBy("position", "id", "nth").select("row.*")


SQL = r"""
WITH sized AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
         md5(coalesce(CAST(doc_id AS VARCHAR), '')) AS k FROM documents),
sources AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source),
ranked AS (SELECT *, row_number() OVER (ORDER BY source ASC NULLS LAST) AS nth FROM sources),
weighted AS (SELECT *, CASE (nth - 1) % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS weight,
             CASE (nth - 1) % 3 WHEN 0 THEN 0.5::DOUBLE WHEN 1 THEN 0.0::DOUBLE ELSE -0.5::DOUBLE END AS slope, source_size * 3 AS cap FROM ranked),
levelled AS (
  SELECT *, CAST((SELECT sum(source_size) FROM sources) - coalesce(sum(cap) OVER b, 0) AS DOUBLE)
            / CAST((SELECT sum(weight) FROM weighted) - coalesce(sum(weight) OVER b, 0) AS DOUBLE) AS level,
         row_number() OVER (ORDER BY cap::DOUBLE / weight, nth) AS o
  FROM weighted WINDOW b AS (ORDER BY cap::DOUBLE / weight, nth ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
targets AS (
  SELECT source, source_size, slope,
         CASE WHEN level * weight >= cap THEN cap::DOUBLE
              ELSE weight * (SELECT min_by(level, o) FROM levelled WHERE level * weight < cap) END AS target FROM levelled),
goals AS (SELECT *, CAST(floor(target + 0.5) AS BIGINT) AS goal FROM targets),
placed AS (
  SELECT s.*, g.source_size, g.slope, g.target, g.goal,
         CAST(coalesce(sum(size) OVER (PARTITION BY s.source ORDER BY k, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS before
  FROM sized s JOIN goals g ON s.source IS NOT DISTINCT FROM g.source),
shared AS (SELECT *, CASE WHEN goal > 0 THEN least(greatest((before + size / 2.0::DOUBLE) / goal, 0), 1) ELSE 0 END AS share FROM placed)
SELECT doc_id, size, source_size, target,
       CASE WHEN source_size > 0 THEN (goal // source_size) * size + least(greatest(goal % source_size - before, 0), size) ELSE 0 END AS taken,
       round(2.0::DOUBLE * share / ((1.0::DOUBLE - slope) + sqrt((1.0::DOUBLE - slope) * (1.0::DOUBLE - slope) + 4.0::DOUBLE * slope * share)), 9) AS position
FROM shared
"""

"""Operations on point tables that surround the tree: making points, sites, summaries of cells and groups."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def to_points(df: DataFrame, id_col: str, exprs: list[str | Column], scale: list[float] | None = None, offset: list[float] | None = None, payload: list[str] = ()) -> DataFrame:
    """(id, x0.., payload): coordinates from expressions, as (value - offset) / scale in doubles."""
    d = len(exprs)
    scale, offset = scale or [1.0] * d, offset or [0.0] * d
    xs = [F.expr(e) if isinstance(e, str) else e for e in exprs]
    return df.select(F.col(id_col).cast("long").alias("id"), *(((x.cast("double") - float(o)) / float(s)).alias(f"x{i}") for i, (x, s, o) in enumerate(zip(xs, scale, offset))), *payload)


def standardise(df: DataFrame, cols: list[str]) -> DataFrame:
    """df with each column less its mean, over its population deviation (columns without spread become 0). One aggregate of one row."""
    r = df.agg(*(F.avg(c).alias(f"m{i}") for i, c in enumerate(cols)), *(F.stddev_pop(c).alias(f"s{i}") for i, c in enumerate(cols))).first()
    return df.withColumns({c: (F.col(c) - r[f"m{i}"]) / r[f"s{i}"] if r[f"s{i}"] else F.when(F.col(c).isNotNull(), F.lit(0.0)) for i, c in enumerate(cols)})


def collapse_sites(df: DataFrame, cols: list[str], id_col: str = "id", weight: str | None = None) -> DataFrame:
    """(id, x0.., n, w): one row for each distinct site; id is the smallest of its points, n how many, w their weight.

    Linking, catalogues and counts of sites cost as much as there are sites, however many points coincide.
    """
    w = F.sum(weight) if weight else F.count("*").cast("double")
    return df.groupBy(*(F.col(c) + 0.0 for c in cols)).agg(F.min(id_col).alias("id"), F.count("*").alias("n"), w.alias("w")).toDF(*cols, "id", "n", "w").select("id", *cols, "n", "w")


def link_sites(df: DataFrame, cols: list[str], r_link: float, id_col: str = "id", **kw) -> DataFrame:
    """(id, group_id) of every point, linked through its site: coincident points never meet in one leaf."""
    from zplane.operators.linking import link_clusters

    sites = collapse_sites(df, cols, id_col)
    groups = link_clusters(sites.select("id", *cols), cols, r_link, **kw).withColumnRenamed("id", "site")
    keyed = df.select(F.col(id_col).alias("id"), *((F.col(c) + 0.0).alias(c) for c in cols))
    return keyed.join(sites.select(F.col("id").alias("site"), *cols), cols).join(groups, "site").select("id", "group_id")


def cell_columns(df: DataFrame, cols: list[str], size: float, names: str = "abcdefgh") -> DataFrame:
    """df with the number of the grid cell in each dimension."""
    return df.withColumns({g: F.floor(F.col(c) / size).cast("long") for c, g in zip(cols, names)})


def cell_summary(df: DataFrame, dims: list[str], how: str = "rollup", sets: list[list[str]] | None = None) -> DataFrame:
    """(dims.., n): counts of cells over all prefixes (rollup), all subsets (cube) or given subsets of the dimensions."""
    if how == "sets":
        return df.groupingSets([[F.col(c) for c in s] for s in sets], *(F.col(c) for c in dims)).agg(F.count("*").alias("n"))
    return getattr(df, how)(*dims).agg(F.count("*").alias("n"))


def cell_pivot(df: DataFrame, row: str, col: str, values: list[int]) -> DataFrame:
    """(row, c<value>..): counts of the cells of a plane, one column for each value given (so no pass looks for them)."""
    got = df.groupBy(row).pivot(col, values).agg(F.count(F.lit(1)))
    return got.select(row, *(F.coalesce(F.col(f"`{v}`"), F.lit(0)).cast("long").alias(f"c{v}") for v in values))


def largest_groups(labelled: DataFrame, n: int = 10) -> DataFrame:
    """(group_id, size) of the n largest groups; ties go to the smaller id."""
    return labelled.groupBy("group_id").agg(F.count("*").alias("size")).orderBy(F.desc("size"), "group_id").limit(n)


def distance_quantiles(neighbours: DataFrame, rank: int, levels: list[float]) -> DataFrame:
    """(level, dist): exact quantiles of the distance to the rank-th neighbour."""
    got = neighbours.where(F.col("rank") == rank).agg(F.percentile("dist", F.array(*map(F.lit, levels))).alias("q"))
    return got.select(F.explode(F.arrays_zip(F.array(*map(F.lit, levels)).alias("level"), F.col("q").alias("dist"))).alias("r")).select(F.col("r.level"), F.col("r.dist"))


def neighbour_steps(neighbours: DataFrame) -> DataFrame:
    """(qid, rank, sid, step, place, quarter): how much farther each neighbour is than the one before, its rank with ties, and its quarter of the list."""
    w = W.partitionBy("qid").orderBy("dist", "sid")
    return neighbours.select(
        "qid", "rank", "sid", (F.col("dist") - F.lag("dist").over(w)).alias("step"), F.dense_rank().over(W.partitionBy("qid").orderBy("dist")).cast("int").alias("place"), F.ntile(4).over(w).cast("int").alias("quarter")
    )


def knn_outer(src: DataFrame, k: int, cols: list[str], queries: DataFrame, r_max: float, id_col: str = "id") -> DataFrame:
    """(qid, rank, sid, dist): up to k neighbours within r_max of every query; a query without any keeps one row of nulls."""
    from zplane.operators.knn import knn

    near = knn(src, k, cols, queries=queries, id_col=id_col).where(F.col("dist") <= r_max)
    return queries.select(F.col(id_col).cast("long").alias("qid")).join(near, "qid", "left").select("qid", "rank", "sid", "dist")

"""A corpus pipeline of five operators: toxicity, line dedup, near copies, mixing, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.utils import AnalysisException

from zplane.llm.jaccard_join import jaccard_components
from zplane.llm.line_chunks import CUTS, drop_repeated_chunks, no_cuts
from zplane.llm.line_passages import drop_repeated_passages
from zplane.llm.mixing import mix
from zplane.llm.packing import pack
from zplane.llm.toxicity import drop_toxic
from zplane.session import release, stored

#: Words from which a single repeated line is a passage.
LONG = 50


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the trained network does not predict toxic. A text without letters is kept."""
    return drop_toxic(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document, later copies of repeated content-defined chunks taken out; n_chars follows the text.

    Chunks that share a line with foreign text stay at first; an exact pass takes out every repeated line run, and
    lines of LONG words. It judges whole texts in which the chunks are noted, so a run of which a chunk is part loses no line.
    """
    chunked = stored(drop_repeated_chunks(docs.withColumn(CUTS, no_cuts())), "chunked")
    release(spark)  # the shuffles of the chunks go before those of the runs come
    out = drop_repeated_passages(chunked, long=LONG)
    return out.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(F.length("text").cast("long"))).select(*docs.columns)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document (the smallest id) of each group linked at a Jaccard similarity of 0.8 of 5-word shingles.

    Documents without words or with a null id are in no group and stay. Rows of one id with different texts are
    documents of their own, ordered by id and digest of the text; of rows that agree in both one stays.
    """
    some = docs.where("doc_id is not null")
    digest = F.xxhash64("text")
    ids = some.groupBy("doc_id").agg(F.min(digest).alias("low"), F.max(digest).alias("high"))
    if ids.where("low <> high").isEmpty():
        groups = jaccard_components(docs.select("doc_id", "text"), k=5, percent=80)
        first = groups.where("component_id = doc_id").select("doc_id").distinct()
        single = some.join(first, "doc_id", "left_semi").dropDuplicates(["doc_id"])
    else:
        rows = some.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), "doc_id", "text", digest.alias("mark"))
        places = rows.select("doc_id", "mark").distinct().orderBy("doc_id", "mark")
        nodes = places.rdd.zipWithIndex().map(lambda p: (*p[0], p[1])).toDF("doc_id long, mark long, node long")
        placed = stored(rows.join(stored(nodes, "nodes"), ["doc_id", "mark"]).select("row", "node", "text"), "placed")
        groups = jaccard_components(placed.select(F.col("node").alias("doc_id"), "text"), k=5, percent=80)
        first = groups.where("component_id = doc_id").select(F.col("doc_id").alias("node")).distinct()
        single = placed.join(first, "node", "left_semi").dropDuplicates(["node"]).select("row.*")
    return single.select(*docs.columns).union(docs.where("doc_id is null").select(*docs.columns))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents as often as the mix takes them, in the order of training."""
    return mix(docs)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of packed sequences with their ids. Each source's queue keeps the training order of the files read."""
    import public_tokenizers

    try:
        ordered = docs.select("doc_id", "text", "source", F.col("_metadata.file_name").alias("file"), F.col("_metadata.row_index").alias("row"))
        order = ("file", "row")
    except AnalysisException:  # not read from files: no order to keep
        ordered, order = docs, ()
    return pack(ordered, public_tokenizers.path("word_bpe_49k.json"), order_cols=order)


STAGES = [("toxicity", toxicity), ("line_dedup", line_dedup), ("near_copies", near_copies), ("mixing", mixing), ("packing", packing)]

#: Toxicity and packing can't be expressed in SQL; tests/llm/test_licenses_and_pipeline.py checks the stages by brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages applied to documents, each written as parquet and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)

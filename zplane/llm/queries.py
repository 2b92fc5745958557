"""The registered queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from zplane.llm.token_counts import count_tokens

    return count_tokens(_table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from zplane.llm.toxicity import score_toxicity, train_toxicity

    docs = _table(spark, sf_dir, "documents")
    scored = score_toxicity(docs, train_toxicity(docs, _table(spark, sf_dir, "labels")))
    return scored.select("doc_id", "held_out", "score", "predicted")


def op3_mixture_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from zplane.llm.packing import pack

    pieces = pack(_table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"), with_ids=False)
    return pieces.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")


def op4_flac_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    from zplane.llm.media import text_media

    return text_media(_table(spark, sf_dir, "documents"))


def op5_voronoi_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    from zplane.llm.topk import top_k

    rows = _table(spark, sf_dir, "embeddings")
    return top_k(rows, rows.where("vec_id % 100 = 0"), k=10)


def op6_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    from zplane.llm.licenses import scan_licenses, train_licenses

    docs = _table(spark, sf_dir, "documents")
    return scan_licenses(docs, train_licenses(docs))


def op7_prefix_free_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from zplane.llm.prefix_free import remove_repeats

    found = remove_repeats(_table(spark, sf_dir, "documents"), with_kept=False)
    return found.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")


def op8_line_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    from zplane.llm.line_chunks import line_report

    return line_report(_table(spark, sf_dir, "documents"))


def op8_line_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    from zplane.llm.line_passages import passage_report

    return passage_report(_table(spark, sf_dir, "documents"))


def op9_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from zplane.llm.jaccard_join import jaccard_components

    return jaccard_components(_table(spark, sf_dir, "documents"), k=3, percent=90)


def op10_curriculum_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from zplane.llm.mixing import plan_mix

    plan = plan_mix(_table(spark, sf_dir, "documents"))
    return plan.select("doc_id", "size", "source_size", "target", "taken", "position").orderBy("position", "doc_id")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    return {f.__name__: f for f in (op1_token_counts, op2_toxicity, op3_mixture_packing, op4_flac_media, op5_voronoi_topk, op6_license_scan, op7_prefix_free_dedup, op8_line_chunks, op8_line_passages, op9_jaccard_join, op10_curriculum_mix, pipeline)}


def oracle_sql() -> dict[str, str]:
    from zplane.llm import jaccard_join, line_chunks, mixing, topk

    return {"op5_voronoi_topk": topk.SQL, "op8_line_chunks": line_chunks.SQL, "op9_jaccard_join": jaccard_join.SQL, "op10_curriculum_mix": mixing.SQL}

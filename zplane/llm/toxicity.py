"""Toxicity scores of whole texts by the recurrent network of gru_model."""

from __future__ import annotations

import pickle

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zplane.session import ship

#: Bounds of the training sample: labelled rows of each class, and characters of a text that may be part of it.
TOXIC_ROWS, CLEAN_ROWS, MOST_CHARS = 1500, 2500, 20_000


def held_out(id_col: str = "doc_id"):
    """Rows that are never learnt from: crc32 of the id as text is divisible by 5."""
    return F.coalesce(F.pmod(F.crc32(F.col(id_col).cast("string")), F.lit(5)) == 0, F.lit(False))


def train_toxicity(docs: DataFrame, labels: DataFrame, toxic_rows: int = TOXIC_ROWS, clean_rows: int = CLEAN_ROWS, id_col: str = "doc_id", text_col: str = "text"):
    """Fit on a bounded sample (by hash of the id) of labelled rows that are not held out. None without both classes.

    Texts of more than MOST_CHARS are not learnt from, so the one task that trains holds rows and bytes of a fixed bound;
    the driver gets the weights alone. Rows with a null id or label are ignored; a doc labelled twice counts as toxic if any label says so.
    """
    known = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out("doc_id"))
    known = known.groupBy(F.col("doc_id").cast("long").alias("__id")).agg(F.max("toxic").cast("int").alias("__y"))
    order = [F.xxhash64("__id"), F.col("__id")]
    sample = known.where("__y = 1").orderBy(*order).limit(toxic_rows).union(known.where("__y = 0").orderBy(*order).limit(clean_rows))
    rows = docs.select(F.col(id_col).cast("long").alias("__id"), F.col(text_col).cast("string").alias("__text")).join(F.broadcast(sample), "__id")
    rows = rows.where(F.coalesce(F.length("__text"), F.lit(0)) <= MOST_CHARS)
    rows = rows.groupBy("__id").agg(F.min("__text").alias("__text"), F.max("__y").alias("__y"))
    ship(docs.sparkSession)

    def run(batches):
        import pickle

        import pyarrow as pa

        from zplane.llm import gru_model as g
        from zplane.session import trim, worker_cache

        worker_cache(None)
        got = sorted(r for b in batches for r in zip(*(c.to_pylist() for c in b.columns)))  # toxic_rows + clean_rows at most
        model = g.train([r[1] for r in got], [r[2] for r in got])
        got.clear()
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(model)], pa.binary())], ["model"])
        del model
        trim()

    made = rows.select("__id", "__text", "__y").repartition(1).mapInArrow(run, "model binary").collect()  # one row, under 2 MB
    return pickle.loads(made[0]["model"]) if made else None


def score_toxicity(docs: DataFrame, model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, held_out, score, predicted, windows, worst_window) of every row; one scan, no shuffle.

    score is the calibrated probability of the highest of all windows (32 words each, every 16 words); worst_window is its
    first word. Null and empty texts and texts of blanks, full stops and commas alone score 0. Without a model all score 0.
    """
    spark = docs.sparkSession
    ship(spark)
    sent = spark.sparkContext.broadcast(model)  # of fixed size, under 1 MB

    def run(batches):
        import numpy as np
        import pyarrow as pa

        from zplane.llm import gru_model as g
        from zplane.session import trim, worker_cache

        worker_cache(None)
        scorer = g.Scorer(sent.value) if sent.value else None
        for b in batches:
            for lo in range(0, b.num_rows, 250):
                part = b.slice(lo, 250)
                words = [g.text_words(t) for t in part.column(2).to_pylist()]
                logit, where = scorer.logits(words) if scorer else (np.full(len(words), -np.inf), np.full(len(words), -1))
                score = np.where(where >= 0, scorer.model.score_of(logit), 0.0) if scorer else np.zeros(len(words))
                first = [None if j < 0 else g.spans(len(w))[j][0] for w, j in zip(words, where.tolist())]
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), part.column(1), pa.array(score), pa.array((score >= 0.5).astype(np.int32)), pa.array([len(g.spans(len(w))) for w in words], pa.int32()), pa.array(first, pa.int32())],
                    ["doc_id", "held_out", "score", "predicted", "windows", "worst_window"],
                )
        scorer = None
        trim()

    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), held_out(id_col).alias("held_out"), F.col(text_col).cast("string").alias("text"))
    return picked.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int, windows int, worst_window int")


def drop_toxic(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of docs (all their columns) that the trained scorer does not predict toxic."""
    spark = docs.sparkSession
    ship(spark)
    sent = spark.sparkContext.broadcast(train_toxicity(docs, labels))
    at = docs.columns.index("text")

    def run(batches):
        import pyarrow as pa

        from zplane.llm import gru_model as g
        from zplane.session import trim, worker_cache

        worker_cache(None)
        scorer = g.Scorer(sent.value) if sent.value else None
        for b in batches:
            for lo in range(0, b.num_rows, 250):
                part = b.slice(lo, 250)
                if scorer:
                    logit, where = scorer.logits([g.text_words(t) for t in part.column(at).to_pylist()])
                    part = part.filter(pa.array((where < 0) | (scorer.model.score_of(logit) < 0.5)))
                yield part
        scorer = None
        trim()

    return docs.mapInArrow(run, docs.schema)

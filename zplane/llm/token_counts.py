"""Token counts of whole texts, by the transducer of token_fst."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zplane.session import ship


def count_tokens(docs: DataFrame, model: str, id_col: str = "doc_id", text_col: str = "text", limit: int = 4096) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) of every row: one scan, no shuffle.

    A null text counts as empty (0 bytes, 0 tokens); a null id stays null; repeated rows give repeated
    results; an empty table gives an empty one. Only the two named columns are read, so other columns,
    whatever their names, do no harm. Very long texts are counted chunk by chunk.
    """
    ship(docs.sparkSession)

    def run(batches):
        import pyarrow as pa

        from zplane.llm.token_fst import UnitCounts, load_model
        from zplane.session import worker_cache

        counts = worker_cache(("units", model), lambda: UnitCounts(load_model(model)))
        for b in batches:
            for lo in range(0, b.num_rows, 1000):
                part = b.slice(lo, 1000)
                texts = [t or "" for t in part.column(1).to_pylist()]
                n = counts(texts)
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.array([len(t.encode()) for t in texts], pa.int64()), pa.array(n), pa.array(n > limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"]
                )

    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return picked.mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")

"""Removal of every line run that repeats across the corpus, in DataFrame operations only.

A run qualifies if it begins and ends with a line that has words and has LEAST such lines and WORDS words, or is
one line of LONG words. A line goes exactly if it lies in a qualifying run that stands, byte for byte, at an
earlier place too: in an earlier document, or earlier in its own without overlap. It suffices to look at the
shortest qualifying run forward and backward of each line: a repeated run that qualifies is the union of such
runs within it (from any of its lines either the forward one ends inside, or the rest is too short and the
backward one of its last line covers it), and these repeat wherever it does. A line with words has one at least,
so such a run has WORDS of these lines at most. Runs are compared by the SHA-256 of their bytes.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zplane.llm.line_chunks import CUTS, taken_out
from zplane.llm.mixing import word_count
from zplane.session import release, stored

#: Lines with words and words that a run needs.
LEAST, WORDS = 2, 8


def _shortest(step: int, least: int, words: int) -> str:
    """SQL of the shortest qualifying run of __b from its element p, forward (step 1) or backward (-1).

    A backward run that is also the forward one of its first line is left to that.
    """
    cases, total = [], "x.w"
    for m in range(1, max(least, words)):
        edge = f"get(__b, p + {m * step})"
        total += f" + {edge}.w"
        if m >= least - 1:
            new = "" if step > 0 else f" AND {m} >= {least} AND {total} - x.w >= {words}"
            run = f"named_struct('i', x.i, 'j', {edge}.i)" if step > 0 else f"named_struct('i', {edge}.i, 'j', x.i)"
            cases.append(f"WHEN {total} >= {words} THEN {f'IF(true{new}, {run}, null)' if new else run}")
    return f"filter(transform(__b, (x, p) -> CASE {' '.join(cases)} END), r -> r IS NOT NULL)"


def shortest_runs(docs: DataFrame, id_col: str, text_col: str, least: int = LEAST, words: int = WORDS, long: int | None = None, exact: bool = True) -> DataFrame:
    """(doc_id, digest, i, j, mark, key): the shortest qualifying runs, lines i to j counted from 0, with xxhash64 and SHA-256 of
    their bytes; or (mark) alone of each run unless exact.

    Runs inside a range that a column CUTS of docs notes are left out: such a range stands whole at an earlier place,
    where it isn't noted, so the first place of each run is among the others.
    """
    text = F.col(text_col).cast("string")
    cuts = CUTS in docs.columns
    rows = docs.where(text.isNotNull()).select(*([CUTS] if cuts else []), F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text).alias("digest"), F.split(text, "\n", -1).alias("__lines"))
    sized = rows.withColumn("__w", F.transform("__lines", word_count))
    body = sized.withColumn("__b", F.expr("filter(transform(__w, (w, i) -> named_struct('i', i, 'w', w)), s -> s.w > 0)"))
    alone = [] if long is None else [f"transform(filter(__b, x -> x.w >= {long}), x -> named_struct('i', x.i, 'j', x.i))"]
    runs = body.withColumn("__runs", F.expr(f"concat({', '.join([_shortest(1, least, words), _shortest(-1, least, words), *alone])})"))
    if cuts:
        runs = runs.withColumn("__runs", F.expr(f"filter(__runs, r -> NOT exists({CUTS}, c -> r.i >= c.i AND r.j <= c.j))"))
    own = "array_join(slice(__lines, r.i + 1, r.j - r.i + 1), '\n')"
    if not exact:
        return runs.select(F.explode(F.expr(f"transform(__runs, r -> xxhash64({own}))")).alias("mark"))
    keyed = F.expr(f"transform(__runs, r -> named_struct('i', r.i, 'j', r.j, 'mark', xxhash64({own}), 'key', unhex(sha2({own}, 256))))")
    return runs.select("doc_id", "digest", F.explode(keyed).alias("r")).select("doc_id", "digest", "r.i", "r.j", "r.mark", "r.key")


def repeated_runs(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """(doc_id, digest, i, j): shortest qualifying runs that stand at an earlier place too.

    Places are ordered by id (null first), digest of the text and line. Runs whose 64-bit mark stands nowhere else are
    left out first, so SHA-256 and place are kept for few.
    """
    often = shortest_runs(docs, id_col, text_col, exact=False, **options).groupBy("mark").agg(F.count("*").alias("n")).where("n > 1").select("mark")
    often = stored(often, "marks")
    release(docs.sparkSession)
    runs = stored(shortest_runs(docs, id_col, text_col, **options).join(often, "mark").drop("mark"), "runs")
    release(docs.sparkSession)
    first = runs.groupBy("key").agg(F.count("*").alias("n"), F.min(F.struct("doc_id", "digest", "i")).alias("first")).where("n > 1").select("key", "first")
    inside = F.col("doc_id").eqNullSafe(F.col("first.doc_id")) & (F.col("digest") == F.col("first.digest")) & (F.col("i") <= F.col("first.i") + F.col("j") - F.col("i"))
    return runs.join(first, "key").where(~inside).select("doc_id", "digest", "i", "j")


def drop_repeated_passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """docs with later copies of repeated passages taken out of their texts; rows and other columns stay.

    A null text stays null. Every removed line also stands at an earlier place that keeps it. Blank lines go only
    inside a run. Rows of one id with different texts are documents of their own; rows that agree in both are
    one place and stay alike. Other columns may have any names; but the lines that a column CUTS of docs notes go too.
    """
    return taken_out(docs, repeated_runs(docs, id_col, text_col, **options), id_col, text_col).select("row.*")


def passage_report(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """(doc_id, n_removed, kept_chars, kept_md5) of every row after drop_repeated_passages; n_removed counts lines."""
    docs = docs.select(id_col, text_col)
    rows = taken_out(docs, repeated_runs(docs, id_col, text_col, **options), id_col, text_col).select("row.*", "n")
    text = F.coalesce(F.col(text_col), F.lit(""))
    return rows.select(F.col(id_col).alias("doc_id"), F.col("n").cast("long").alias("n_removed"), F.length(text).cast("long").alias("kept_chars"), F.md5(text).alias("kept_md5"))

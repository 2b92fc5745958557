"""Removal of multi-line passages that repeat across the corpus, in DataFrame operations only.

Every line has a hash; a line ends a chunk if a rolling hash of it and the line before says so (one in
CUT), which depends on content alone, so the same passage is cut the same way wherever it stands. Chunks
of two lines and more that occur elsewhere too are removed except at their first place. Chunks are compared
by the SHA-256 of their bytes, so that only digests are shuffled and each text once. Lines that
share a chunk with foreign lines stay, as do chunks of one line; line_passages removes every repeated run.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zplane.session import stored

#: One line in CUT ends a chunk; chunks of fewer lines than LEAST or fewer words than WORDS are left alone.
CUT, LEAST, WORDS = 2, 2, 8


def chunk_lines(docs: DataFrame, text_col: str, cut: int = CUT) -> DataFrame:
    """docs with __lines, __ends (the last line of each chunk) and __chunks (their texts)."""
    hashed = docs.withColumn("__lines", F.split(F.coalesce(F.col(text_col).cast("string"), F.lit("")), "\n", -1))
    hashed = hashed.withColumn("__h", F.expr("transform(__lines, x -> CAST(conv(substring(md5(x), 1, 7), 16, 10) AS BIGINT))"))
    rolled = F.expr(f"transform(__h, (x, i) -> (x * 31 + IF(i > 0, __h[i - 1], 0)) % 1000003 % {cut})")
    hashed = hashed.withColumn("__r", rolled)
    ends = F.expr("filter(transform(__r, (x, i) -> IF(x = 0 OR i = size(__r) - 1, i, -1)), x -> x >= 0)")
    hashed = hashed.withColumn("__ends", ends)
    cuts = F.expr("transform(__ends, (e, i) -> array_join(slice(__lines, IF(i = 0, 0, __ends[i - 1] + 1) + 1, e - IF(i = 0, -1, __ends[i - 1])), '\n'))")
    return hashed.withColumn("__chunks", cuts).drop("__h", "__r")


def repeated_chunks(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", cut: int = CUT, least: int = LEAST, words: int = WORDS) -> DataFrame:
    """(doc_id, digest, i, j): chunks that occur earlier too, as lines i to j counted from 0.

    Places are ordered by id (null first), digest of the text and line. A chunk qualifies with `least` lines and `words` words.
    """
    text = F.col(text_col).cast("string")
    cutted = chunk_lines(docs.where(text.isNotNull()).select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text).alias("digest"), text.alias("text")), "text", cut)
    every = cutted.select("doc_id", "digest", F.posexplode(F.arrays_zip(F.col("__chunks").alias("c"), F.col("__ends").alias("e"))).alias("pos", "z"), "__ends")
    begin = F.when(F.col("pos") > 0, F.expr("__ends[pos - 1] + 1")).otherwise(F.lit(0))
    able = (F.col("z.e") - begin + 1 >= least) & (F.size(F.split("z.c", "[ \n]+")) >= words)
    found = stored(every.where(able).select("doc_id", "digest", begin.alias("i"), F.col("z.e").alias("j"), F.unhex(F.sha2("z.c", 256)).alias("key")), "chunks")
    first = found.groupBy("key").agg(F.count("*").alias("n"), F.min(F.struct("doc_id", "digest", "i")).alias("first")).where("n > 1").select("key", "first")
    return found.join(first, "key").where(~F.struct("doc_id", "digest", "i").eqNullSafe(F.col("first"))).select("doc_id", "digest", "i", "j")


def drop_repeated_chunks(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """docs with later copies of repeated chunks taken out of their texts; rows and other columns stay.

    A null text stays null; an empty one stays empty. Rows of one id with different texts are documents of their own;
    a full repeat of a row with its id keeps its chunks; rows without an id come first. Texts without line breaks
    are one line and stay. Other columns may have any names; but where docs have a column CUTS (see no_cuts), the
    lines that go are noted in it and the texts stay whole.
    """
    return taken_out(docs, repeated_chunks(docs, id_col, text_col, **options), id_col, text_col, note=CUTS in docs.columns).select("row.*")


#: A column of the lines to take out of a text, as ranges (i, j) counted from 0, and its value for none.
CUTS = "__cuts"


def no_cuts():
    return F.expr("CAST(array() AS array<struct<i: int, j: int>>)")


def taken_out(docs: DataFrame, gone: DataFrame, id_col: str, text_col: str, note: bool = False) -> DataFrame:
    """(row, gone, n): whole rows as one column, so that no helper column can clash with theirs, without the lines i to j
    of gone (doc_id, digest, i, j), which become a list (null for none), and the number of lines that went.

    Where docs have a column CUTS, its lines go too; with note all go into it and stay in the text. The text is in the row only, so a shuffle carries it once.
    """
    lists = gone.groupBy(F.col("doc_id").alias("id"), "digest").agg(F.collect_set(F.struct("i", "j")).alias("gone"))
    text = F.col(text_col).cast("string")
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), F.col(id_col).cast("long").alias("doc_id"), F.when(text.isNotNull(), F.xxhash64(text)).alias("mark"))
    both = rows.join(lists, F.col("doc_id").eqNullSafe(F.col("id")) & (F.col("mark") == F.col("digest")), "left")
    if CUTS in docs.columns:
        every = F.concat(F.coalesce("gone", no_cuts()), F.col("row").getField(CUTS))
        both = both.withColumn("gone", F.when(F.size(every) > 0, every))
    if note:
        return both.select(F.col("row").withField(CUTS, F.coalesce("gone", no_cuts())).alias("row"), "gone", F.lit(0).alias("n"))
    text = F.col("row").getField(text_col).cast("string")
    parts = both.withColumn("lines", F.when(F.col("gone").isNotNull(), F.split(text, "\n", -1))).withColumn("total", F.size("lines"))
    parts = parts.withColumn("kept", F.when(F.col("gone").isNotNull(), F.expr("array_except(sequence(0, total - 1), flatten(transform(gone, g -> sequence(g.i, g.j))))")))
    left = F.when(F.col("gone").isNull(), text).otherwise(F.expr("array_join(transform(kept, x -> get(lines, x)), '\n')"))
    n = F.when(F.col("gone").isNull(), 0).otherwise(F.col("total") - F.size("kept"))
    return parts.select(F.col("row").withField(f"`{text_col}`", left).alias("row"), "gone", n.alias("n"))


def line_report(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """(doc_id, n_removed, kept_chars, kept_md5) of every row after drop_repeated_chunks."""
    docs = docs.select(id_col, text_col)
    rows = taken_out(docs, repeated_chunks(docs, id_col, text_col, **options), id_col, text_col)
    rows = rows.select("row.*", F.when(F.col("gone").isNull(), 0).otherwise(F.size("gone")).alias("n"))
    text = F.coalesce(F.col(text_col), F.lit(""))
    return rows.select(F.col(id_col).alias("doc_id"), F.col("n").cast("long").alias("n_removed"), F.length(text).cast("long").alias("kept_chars"), F.md5(text).alias("kept_md5"))


SQL = r"""
WITH lines AS (
  SELECT doc_id, i, l[i] AS line, len(l) AS n FROM (SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS l FROM documents), unnest(range(1, len(l) + 1)) AS r(i)),
hashed AS (SELECT *, CAST(('0x' || substr(md5(line), 1, 7)) AS BIGINT) AS h FROM lines),
rolled AS (SELECT *, (h * 31 + coalesce(lag(h) OVER d, 0)) % 1000003 % 2 = 0 OR i = n AS e FROM hashed WINDOW d AS (PARTITION BY doc_id ORDER BY i)),
numbered AS (SELECT *, coalesce(sum(CASE WHEN e THEN 1 ELSE 0 END) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS pos FROM rolled),
chunks AS (SELECT doc_id, pos, string_agg(line, chr(10) ORDER BY i) AS chunk, count(*) AS m FROM numbered GROUP BY doc_id, pos),
able AS (SELECT *, m >= 2 AND len(string_split_regex(chunk, '[ \n]+')) >= 8 AS a FROM chunks),
judged AS (SELECT *, a AND row_number() OVER (PARTITION BY a, chunk ORDER BY doc_id, pos) > 1 AS gone FROM able),
kept AS (SELECT doc_id, coalesce(string_agg(chunk, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '') AS t, count(*) FILTER (WHERE gone) AS n_removed FROM judged GROUP BY doc_id)
SELECT doc_id, CAST(n_removed AS BIGINT) AS n_removed, CAST(length(t) AS BIGINT) AS kept_chars, md5(t) AS kept_md5 FROM kept
"""

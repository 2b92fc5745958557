"""Repeated passages against all maximal repeated line runs, found by comparing every pair of places."""

import random

import corpus_pipeline
from zplane.llm.line_passages import drop_repeated_passages, passage_report
from zplane.session import stored


def brute(docs, least=2, words=8, long=None):
    """{(id, at): kept lines} of (id, text) rows in order of place: all qualifying runs of all pairs of places."""
    texts = [t.split("\n") for _, t in docs]
    gone = [set() for _ in docs]
    for b, later in enumerate(texts):
        for a, early in enumerate(texts[: b + 1]):
            for y in range(len(later)):
                for x in range(len(early) if a < b else y):
                    n = 0
                    while y + n < len(later) and x + n < (len(early) if a < b else y) and later[y + n] == early[x + n]:
                        n += 1
                    for m in range(1, n + 1):
                        run = [len(s.split()) for s in later[y : y + m]]
                        able = run[0] and run[-1] and (sum(r > 0 for r in run) >= least and sum(run) >= words or (long is not None and m == 1 and run[0] >= long))
                        if able:
                            gone[b].update(range(y, y + m))
    return [[s for i, s in enumerate(t) if i not in g] for t, g in zip(texts, gone)]


def _lines(rng, n, lo=4, hi=12):
    return [" ".join(rng.choice("alpha beta gamma delta eps zeta eta".split()) + str(rng.randrange(50)) for _ in range(rng.randint(lo, hi))) for _ in range(n)]


def test_every_line_of_a_repeated_run_goes(spark):
    rng = random.Random(3)
    passages = [_lines(rng, n, lo, hi) for n, lo, hi in [(2, 8, 9), (3, 1, 4), (5, 6, 9), (9, 1, 1), (30, 1, 12), (2, 3, 4), (2, 1, 3), (1, 20, 20)]]
    passages += [["one", "", "", "two three four five six seven eight", "", "nine"], ["x"] * 12, ["a b c d e"] * 6, ["", "lone line of more than eight words in all here", ""]]
    docs = []
    for i in range(60):
        out = _lines(rng, rng.randint(0, 3), 1, 9)
        for _ in range(rng.randint(0, 3)):
            p = rng.choice(passages)
            lo = rng.choice([0, 0, rng.randrange(len(p))])
            out += p[lo : rng.choice([len(p), rng.randint(lo + 1, len(p))])] + _lines(rng, rng.randint(0, 2), 1, 9) + [""] * rng.randint(0, 1)
        docs.append((i, "\n".join(out)))
    df = spark.createDataFrame(docs, "doc_id long, text string").selectExpr("*", "1 as i", "2 as key").repartition(3)
    want = brute(docs)
    assert {r.doc_id: r.text for r in drop_repeated_passages(df).collect()} == {i: "\n".join(w) for (i, _), w in zip(docs, want)}
    got = {r.doc_id: r.n_removed for r in passage_report(df).collect()}
    assert got == {i: len(t.split("\n")) - len(w) for (i, t), w in zip(docs, want)} and sum(got.values()) > 100


def test_passages_of_odd_rows(spark):
    p = "a first line of five\na second line of five"
    rows = [(5, p), (None, p), (5, p), (5, "other\n" + p), (6, None), (7, ""), (8, "\n\n"), (9, "own\n" + p + "\n\nend")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted(((r.doc_id, r.text) for r in drop_repeated_passages(df).collect()), key=repr)
    assert got == sorted([(None, p), (5, ""), (5, ""), (5, "other"), (6, None), (7, ""), (8, "\n\n"), (9, "own\n\nend")], key=repr)
    assert drop_repeated_passages(df.limit(0)).count() == 0


def test_line_dedup_takes_planted_passages(spark):
    rng = random.Random(5)
    long, two, three = _lines(rng, 1, 50, 50), _lines(rng, 2, 30, 30), _lines(rng, 3, 20, 20)
    short = _lines(rng, 1, 49, 49)  # a single line that is no passage
    docs = []
    for i in range(60):
        p = (long, two, three, short)[i % 4]
        docs.append((i, "\n".join(_lines(rng, rng.randint(1, 4)) + p + _lines(rng, rng.randint(1, 4)))))
    df = spark.createDataFrame(docs, "doc_id long, text string").selectExpr("*", "CAST(length(text) AS BIGINT) AS n_chars")
    out = {r.doc_id: r for r in dict(corpus_pipeline.STAGES)["line_dedup"](spark, df, "").collect()}
    assert {i: r.text.split("\n") for i, r in out.items()} == dict(enumerate(brute(docs, long=50)))
    for i, r in out.items():
        p, left = (long, two, three, short)[i % 4], r.text.split("\n")
        assert sum(s in left for s in p) == (len(p) if i < 4 or p is short else 0) and r.n_chars == len(r.text)


def test_line_dedup_shuffles_a_text_once_a_pass(spark, shuffled):
    """Random lines, so that nothing is compressed away: each of the two passes may carry the texts once, and digests."""
    rng = random.Random(5)
    word = lambda: f"{rng.getrandbits(200):050x}"
    shared = "\n".join(" ".join(word() for _ in range(8)) for _ in range(6))
    texts = ["\n".join([" ".join(word() for _ in range(40)) for _ in range(8)] + [shared]) for _ in range(300)]
    df = stored(spark.createDataFrame([(i, t, len(t)) for i, t in enumerate(texts)], "doc_id long, text string, n_chars long").repartition(3), "docs")
    out, written = shuffled(lambda: corpus_pipeline.line_dedup(spark, df, "").collect())
    assert sum(shared in r.text for r in out) == 1
    assert written < 2.5 * sum(map(len, texts))

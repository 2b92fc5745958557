import corpus_pipeline
from zplane.llm import licenses
from zplane.llm.licenses import scan_licenses, train_licenses


def test_licence_notices_are_found_and_others_are_not(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = train_licenses(docs)
    assert model["accuracy"] > 0.95 and model["anchors"]
    rows = [(1, "some prose here\nReleased under the MIT License.\nmore"), (2, "This work is licensed under the GNU General Public License, version 3."), (3, "Licensed under CC BY-NC 4.0."), (4, "LICENSED UNDER THE APACHE LICENSE, VERSION 2.0!")]
    rows += [(5, "He lost his license to drive."), (6, None), (7, ""), (None, "Released under the MIT License."), (8, "word " * 30000 + "\nReleased under the BSD License.")]
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as para", "2 as family")
    got = {(r.doc_id, r.para): r for r in scan_licenses(df, model).collect()}
    want = {(1, 1): "mit", (2, 0): "gpl", (3, 0): "cc-by-nc", (4, 0): "apache", (8, 1): "bsd"}
    assert {k: r.family for k, r in got.items() if k[0] is not None} == want and all(r.confirmed for r in got.values())
    assert scan_licenses(df.limit(0), model).count() == 0
    slow = scan_licenses(docs, model | {"anchors": None}).collect()  # without the bound: the same rows
    assert sorted(map(tuple, slow)) == sorted(map(tuple, scan_licenses(docs, model).collect()))
    found = {(r.doc_id, r.para) for r in slow}
    planted = {(r.doc_id, i) for r in docs.collect() for i, line in enumerate((r.text or "").split("\n")) if line in {n for f in licenses.FAMILIES for n in licenses.NOTICES[f]}}
    assert planted <= found


def test_stages_by_their_own_inputs(spark, sf):
    from zplane.llm.toxicity import score_toxicity, train_toxicity
    from zplane.session import stored

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["toxicity", "line_dedup", "near_copies", "mixing", "packing"]
    steps = dict(corpus_pipeline.STAGES)
    clean = stored(steps["toxicity"](spark, docs, sf), "t")
    bad = {r.doc_id for r in score_toxicity(docs, train_toxicity(docs, spark.read.parquet(f"{sf}/labels.parquet"))).where("predicted = 1").collect()}
    assert {r.doc_id for r in clean.collect()} == {r.doc_id for r in docs.collect()} - bad and clean.columns == docs.columns
    lines = stored(steps["line_dedup"](spark, clean, sf), "t")
    assert lines.columns == docs.columns and lines.count() == clean.count() and lines.where("n_chars <> length(text)").count() == clean.where("n_chars <> length(text)").count()
    single = stored(steps["near_copies"](spark, lines, sf), "t")
    import re

    sets = {r.doc_id: (lambda w: {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set()))(re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), r.text or ""))) for r in lines.collect()}
    kept = {r.doc_id for r in single.collect()}
    near = lambda a, b: a and b and 100 * len(a & b) >= 80 * len(a | b)
    assert not any(near(sets[i], sets[j]) for i in kept for j in kept if i < j)
    assert all(any(near(sets[i], sets[j]) for j in sets if j != i) for i in set(sets) - kept)
    mixed = stored(steps["mixing"](spark, single, sf), "t")
    assert mixed.columns == docs.columns and {r.doc_id for r in mixed.collect()} <= kept
    packed = steps["packing"](spark, mixed, sf).collect()
    assert sum(r.length for r in packed if r.start == 0) and {r.doc_id for r in packed} == {r.doc_id for r in mixed.collect()}
    seq: dict = {}
    for r in packed:
        seq[r.sequence_id] = seq.get(r.sequence_id, 0) + r.length
    assert all(n == 4096 or n & (n - 1) == 0 for n in seq.values())


def test_run_survives_missing_texts(spark, sf, tmp_path):
    docs = spark.createDataFrame([(1, None, None, None, None), (2, "", "en", "a", 0), (None, "some text here", "en", None, 14), (3, "x " * 20000, "en", "a", 40000)], "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame([(1, 0, 1)], "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    assert {r.doc_id for r in corpus_pipeline.run(spark, str(tmp_path)).collect()} <= {None, 3}


def test_near_copies_of_repeated_ids(spark):
    a, b, c = (" ".join(f"{x}{i}" for i in range(40)) for x in "abc")
    rows = [(1, a), (2, a), (2, b), (2, b), (3, c), (3, a), (4, c + " more"), (5, None), (5, ""), (None, a)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = [(r.doc_id, r.text) for r in dict(corpus_pipeline.STAGES)["near_copies"](spark, docs, "").collect()]
    assert sorted(got, key=repr) == sorted([(1, a), (2, b), (3, c), (5, None), (5, ""), (None, a)], key=repr)


def test_scan_equals_a_plain_scan_with_the_same_weights(spark, sf):
    import math
    import re

    model = train_licenses(spark.read.parquet(f"{sf}/documents.parquet"))
    weights, temperature = dict(model["grams"]), model["temperature"]
    grant = licenses.NOTICES["mit"][3].split(" ")
    wrapped = "\n".join(" ".join(grant[i : i + 6]) for i in range(0, len(grant), 6))
    rows = [(1, f"Some prose.\n{wrapped}.\nMore prose."), (None, "Released under the MIT License."), (2, "Released under the MIT License."), (2, "Released under the MIT License."), (2, "Licensed under CC BY 4.0."), (3, "all rights reserved for the library")]
    rows += [(10 + i, "\n".join(n for n in licenses.NOTICES[f])) for i, f in enumerate(licenses.FAMILIES)] + [(40 + i, t) for i, t in enumerate(licenses.OTHERS)]
    want = set()
    for doc, text in rows:
        joined = re.sub(r"(?<![.!?:;])[ \t\r]*\n[ \t]*(?=[a-z])", " ", text)
        for para, line in enumerate(joined.split("\n")):
            w = re.findall("[a-z0-9]+", line.lower())
            g = {" ".join(w[i : i + n]) for n in (1, 2, 3) for i in range(len(w) - n + 1)}
            if not any(x in weights for x in g):
                continue
            z = [(round(sum(weights[x][c] for x in sorted(g) if x in weights), 9) + b) / temperature for c, b in enumerate(model["bias"])]
            best = max(range(len(z)), key=lambda c: (z[c], c == licenses.UNKNOWN))
            p = 1 / sum(math.exp(v - max(z)) for v in z)
            if best == licenses.UNKNOWN or p < licenses.LEAST:
                continue
            pairs = lambda w: {a + " " + b for a, b in zip(w, w[1:])} if len(w) > 1 else {w[0] + " " + w[0]}
            near = max(len(pairs(re.findall("[a-z0-9]+", n.lower())) & pairs(w)) / len(pairs(re.findall("[a-z0-9]+", n.lower()))) for n in licenses.NOTICES[licenses.FAMILIES[best]])
            want.add((doc, para, licenses.FAMILIES[best], round(p, 4), round(near, 4), near >= licenses.SIMILAR))
    got = scan_licenses(spark.createDataFrame(rows, "doc_id long, text string"), model).collect()
    assert len(got) == len({(r.doc_id, r.para, r.family) for r in got})
    assert {(r.doc_id, r.para, r.family, round(r.probability, 4), round(r.similarity, 4), r.confirmed) for r in got} == want
    assert {(r.doc_id, r.family, r.confirmed) for r in got} >= {(1, "mit", True), (None, "mit", True), (2, "mit", True), (2, "cc-by", True)}


def test_line_dedup_goes_through_content_defined_chunks(spark, sf, monkeypatch):
    from zplane.llm.line_chunks import drop_repeated_chunks, line_report
    from zplane.llm.line_passages import repeated_runs
    from zplane.session import stored

    seen = []
    monkeypatch.setattr(corpus_pipeline, "drop_repeated_chunks", lambda d: seen.append(d) or drop_repeated_chunks(d))
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out = stored(corpus_pipeline.line_dedup(spark, docs, sf), "t")
    assert len(seen) == 1 and line_report(docs).where("n_removed > 0").count() and not line_report(out).where("n_removed > 0").count()
    assert repeated_runs(out, long=corpus_pipeline.LONG).isEmpty()  # the exact pass leaves none

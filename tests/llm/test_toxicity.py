import zlib

import numpy as np

from zplane.llm import gru_model as g
from zplane.llm.toxicity import drop_toxic, score_toxicity, train_toxicity


def test_gradients_equal_differences(monkeypatch):
    monkeypatch.setattr(g, "F4", np.float64)
    m = g.Model(1)
    for k in m.w:
        m.w[k] = m.w[k].astype(np.float64)
    table, idx = g.index_windows([["abc", "de", "fghij"], ["xx", "abc"], ["qq"] * 5])
    feats, y = g.features(table), np.array([1.0, 0, 1])
    _, grads = m.gradients(feats, idx, y)
    for k, d in grads.items():
        for j in np.argsort(-np.abs(d).ravel())[:2]:
            w, at = m.w[k].reshape(-1), 1e-5
            old = w[j]
            w[j] = old + at
            up = m.gradients(feats, idx, y)[0]
            w[j] = old - at
            down = m.gradients(feats, idx, y)[0]
            w[j] = old
            assert abs((up - down) / (2 * at) - d.ravel()[j]) < 1e-5, k


def test_windows_overlap_and_cover():
    for n in (1, 15, 16, 17, 32, 33, 100):
        s = g.spans(n)
        assert s[0][0] == 0 and s[-1][1] == n and all(b[0] - a[0] == g.STRIDE for a, b in zip(s, s[1:]))
        assert set().union(*(range(*x) for x in s)) == set(range(n))
    assert g.spans(0) == []


def test_batched_scores_equal_one_by_one():
    m = g.Model(2)
    texts = [g.text_words("one two three four " * k) for k in (0, 1, 9, 40)]
    many, _ = g.Scorer(m).logits(texts)
    alone = [g.Scorer(m, most=3).logits([t])[0][0] for t in texts]
    assert np.allclose(many[1:], alone[1:], atol=1e-5) and many[0] == -np.inf


def test_held_out_accuracy_and_pipeline_filter(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = train_toxicity(docs, labels)
    truth = {r.doc_id: r.toxic for r in labels.collect()}
    rows = [r for r in score_toxicity(docs, model).collect() if r.doc_id in truth]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in rows)
    apart = [r for r in rows if r.held_out]
    toxic, clean = [r.score for r in apart if truth[r.doc_id]], [r.score for r in apart if not truth[r.doc_id]]
    auc = np.mean([(t > c) + 0.5 * (t == c) for t in toxic for c in clean])
    assert auc > 0.97 and np.mean([r.predicted == truth[r.doc_id] for r in apart]) > 0.97


def test_edges(spark):
    docs = spark.createDataFrame([(1, None, "s"), (2, "", "s"), (3, "a fine day " * 20, "s"), (4, "vile nasty brute " * 20, "s"), (4, "vile nasty brute " * 20, "s"), (None, "...", "s")], "doc_id long, text string, score string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(100, 160)] + [(1, None), (None, 1)], "doc_id long, toxic int")
    more = spark.createDataFrame([(i, ("vile nasty brute " if i % 2 else "a fine day ") * 10, "s") for i in range(100, 160)], docs.schema)
    model = train_toxicity(docs.union(more), labels)
    got = score_toxicity(docs, model).collect()
    assert len(got) == 6 and {(r.doc_id, r.predicted) for r in got} == {(1, 0), (2, 0), (3, 0), (4, 1), (None, 0)}
    kept = drop_toxic(docs.union(more), labels)
    assert kept.columns == docs.columns and sorted(r.doc_id or 0 for r in kept.where("doc_id < 100 OR doc_id IS NULL").collect()) == [0, 1, 2, 3]
    assert train_toxicity(docs, labels.limit(0)) is None
    assert {r.score for r in score_toxicity(docs, None).collect()} == {0.0}
    assert score_toxicity(docs.limit(0), model).count() == 0


def test_driver_does_not_train(spark, monkeypatch):
    """The sample and the training lie in one task, not beside the driver's JVM."""
    docs = spark.createDataFrame([(i, ("vile nasty " if i % 2 else "a fine day ") * 20) for i in range(60)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(60)], "doc_id long, toxic int")
    rows = [i for i in range(60) if zlib.crc32(str(i).encode()) % 5]
    same = g.train([("vile nasty " if i % 2 else "a fine day ") * 20 for i in rows], [i % 2 for i in rows])

    def here(*_, **__):
        raise AssertionError("trained on the driver")

    monkeypatch.setattr(g, "train", here)
    model = train_toxicity(docs, labels)
    assert all(np.allclose(model.w[k], same.w[k], atol=1e-5) for k in same.w)

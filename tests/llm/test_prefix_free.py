import hashlib
import random

import pytest

from zplane.llm import prefix_free as pf


def brute(rows, length):
    """Per row: removed flags, from all windows in (id, start) order."""
    seen, out = {}, {}
    order = sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0))
    for i, t in order:
        raw = (t or "").encode()
        gone = bytearray(len(raw))
        for s in range(len(raw) - length + 1):
            w = raw[s : s + length]
            if w in seen:
                if seen[w] != (i, s):
                    gone[s : s + length] = b"\1" * length
            else:
                seen[w] = (i, s)
        out[i] = gone
    return out


def check(spark, rows, length=100, k=24, **kw):
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as doc", "2 as kind").repartition(3)
    got = pf.remove_repeats(df, length=length, k=k).collect()
    want = brute(dict(rows).items() if len(dict(rows)) < len(rows) else rows, length)
    assert len(got) == len(rows)
    texts = dict(rows)
    for r in got:
        gone = want[r.doc_id]
        raw = (texts[r.doc_id] or "").encode()
        kept = bytes(c for c, g in zip(raw, gone) if not g)
        spans = sum(1 for a, b in zip(b"\0" + bytes(gone), bytes(gone)) if b and not a)
        assert (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) == (len(raw), sum(gone), spans, hashlib.sha256(kept).hexdigest()), r.doc_id


def _corpus(seed, n=60):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice(["th", "er", "an", "in", "é", "ou"]) for _ in range(rng.randint(1, 3)))
    para = lambda m: " ".join(word() for _ in range(m))
    shared = [para(rng.randint(15, 120)) for _ in range(6)]
    rows = []
    for i in range(n):
        parts = [rng.choice(shared) if rng.random() < 0.5 else para(rng.randint(1, 80)) for _ in range(rng.randint(0, 5))]
        t = "\n".join(parts)
        if rng.random() < 0.3 and rows:
            old = rows[rng.randrange(len(rows))][1] or ""
            w = old.split(" ")
            for _ in range(len(w) // 30):
                w[rng.randrange(len(w))] = word()
            t = " ".join(w)
        rows.append((i * 7, t))
    rows += [(5000, None), (5001, ""), (5002, "a" * 700), (5003, "ab" * 400), (5004, "x" * 99), (5005, "a" * 100), (None, shared[0])]
    rng.shuffle(rows)
    return rows


def test_equals_brute_force(spark):
    check(spark, _corpus(1))


def test_hot_triggers(spark, monkeypatch):
    monkeypatch.setattr(pf, "HOT", 1)
    monkeypatch.setattr(pf, "HOT_LOCAL", 1)
    check(spark, _corpus(2, 40))


@pytest.mark.parametrize("length,k", [(20, 8), (40, 40), (100, 50)])
def test_other_lengths(spark, length, k):
    check(spark, _corpus(3, 30), length, k)


def test_repeated_rows_and_empty_table(spark):
    rows = _corpus(4, 15)
    check(spark, rows + rows[:3])
    assert pf.remove_repeats(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_long_text(spark):
    rng = random.Random(6)
    base = "".join(rng.choice("abcdefgh ") for _ in range(40_000))
    check(spark, [(1, base + base[100:20_000] + "tail"), (2, "head " + base[5_000:9_000])])

"""Top-k search, Jaccard join, mixing and line chunks against brute force."""

import random

import duckdb
import pytest

from zplane.llm import jaccard_join, line_chunks, mixing, topk
from zplane.llm.jaccard_join import LocalJoin, jaccard_components, pair_prefix
from zplane.llm.line_chunks import drop_repeated_chunks, line_report
from zplane.llm.mixing import mix, plan_mix
from zplane.llm.topk import top_k


def _rows(df, *cols):
    return sorted(map(tuple, df.select(*cols).collect()), key=repr)


def _sql(text, **tables):
    con = duckdb.connect()
    for name, df in tables.items():
        con.register("t_" + name, df.toArrow())
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM t_{name}")
    return con.execute(text)


def test_top_k_with_ties_nulls_and_repeats(spark, monkeypatch):
    monkeypatch.setattr(topk, "BLOCK_ROWS", 40)
    monkeypatch.setattr(topk, "GROUP_QUERIES", 2)
    rng = random.Random(4)
    rows = [(i, [rng.choice([-1.0, 0.0, 0.5, 1.0]) for _ in range(4)]) for i in range(300)]
    rows += [(300 + i, [1.0, 0.5, 0.0, 1.0]) for i in range(100)] + [(1000, None), (1100, [1.0, None, 0.0, 0.0]), (1200, [float("nan")] * 4), (1300, [float("inf"), 0.0, 0.0, 0.0]), (1400, []), (100, [0.25] * 4)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").selectExpr("*", "1 as score")
    got = _rows(top_k(df, df.where("vec_id % 100 = 0"), 10), "query_id", "rank", "vec_id", "score")
    import math

    usable = [(i, v) for i, v in rows if v is not None and all(x is not None and math.isfinite(x) for x in v)]
    want = []
    asks = {}
    for i, v in usable:
        if i % 100 == 0:
            asks[i] = min(asks.get(i, v), v)
    q = lambda v: [math.floor(1024 * x) for x in v] + [0] * (4 - len(v))
    for i, v in asks.items():
        best = sorted((-sum(a * b for a, b in zip(q(v), q(w))), j) for j, w in usable if j != i)[:10]
        want += [(i, r, j, -s) for r, (s, j) in enumerate(best, 1)]
    assert got == sorted(want, key=repr)
    assert top_k(df.limit(0), df, 3).count() == 0 and top_k(df, df.limit(0), 3).count() == 0


def test_top_k_beyond_many_own_rows(spark):
    rows = [(0, [-1.0, 0.0])] * 20 + [(i, [-0.5 + i / 64, 0.0]) for i in range(1, 31)]  # 20 rows of the query's id, nearest of all
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = _rows(top_k(df, df.where("vec_id = 0"), 10), "rank", "vec_id")
    assert got == sorted(((i, i) for i in range(1, 11)), key=repr)


def _near_texts(seed, n=160):
    rng = random.Random(seed)
    words = [f"w{i}" for i in range(400)]
    base = [[rng.choice(words) for _ in range(rng.randint(1, 120))] for _ in range(25)]
    out = []
    for i in range(n):
        w = list(rng.choice(base))
        for _ in range(rng.choice([0, 0, 1, 2, 5])):
            w[rng.randrange(len(w))] = rng.choice(words)
        t = " ".join(w)
        out.append((i, t.upper() if rng.random() < 0.2 else t))
    return out + [(900, None), (901, ""), (902, " \t\n"), (903, "One"), (904, "one"), (905, "one two"), (906, "a\x1cb c"), (0, out[0][1])]


def _brute_components(rows, k, percent):
    import re

    sets = {}
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets[i] = {tuple(w[j : j + k]) for j in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(sets)
    for x, a in enumerate(ids):
        for b in ids[:x]:
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                p, q = find(a), find(b)
                root[max(p, q)] = min(p, q)
    return {i: (len(sets[i]), find(i)) for i in ids}


@pytest.mark.parametrize("k,percent,block", [(3, 90, 300_000), (5, 80, 300_000), (3, 80, 200), (1, 60, 300_000)])
def test_jaccard_components(spark, monkeypatch, k, percent, block):
    monkeypatch.setattr(jaccard_join, "BLOCK_SHINGLES", block)
    rows = _near_texts(percent + k)
    df = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as rep", "2 as n").repartition(4)
    got = jaccard_components(df, k, percent).collect()
    want = _brute_components(rows, k, percent)
    assert len(got) == len(rows) and {r.doc_id: (r.n_shingles, r.component_id) for r in got} == want


def test_jaccard_edges(spark):
    df = spark.createDataFrame([(None, "a b c d"), (5, "a b c d"), (6, "a b c d")], "doc_id long, text string")
    assert _rows(jaccard_components(df, 3, 90), "doc_id", "component_id") == sorted([(None, None), (5, 5), (6, 5)], key=repr)
    assert jaccard_components(df.limit(0), 3, 90).count() == 0


def test_local_join_equals_all_pairs():
    import numpy as np

    rng = random.Random(8)
    for _ in range(20):
        universe = list(range(1, 300))
        base = [set(rng.sample(universe, rng.randint(5, 60))) for _ in range(6)]
        sets = []
        for _ in range(70):
            s = set(rng.choice(base))
            for _ in range(rng.randint(0, 4)):
                s.discard(rng.choice(sorted(s))) if rng.random() < 0.5 and len(s) > 1 else s.add(rng.choice(universe))
            sets.append(s)
        edges = LocalJoin(list(range(70)), [np.array(sorted(s), np.uint64) for s in sets], 80).run()
        from zplane.components import union_find

        def roots(pairs):
            a = np.array([p[0] for p in pairs] + list(range(70))), np.array([p[1] for p in pairs] + list(range(70)))
            return union_find(*a)[1].tolist()

        every = [(i, j) for i in range(70) for j in range(i) if 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j])]
        assert roots(edges) == roots(every)


def test_pair_prefix_guarantee():
    for percent in (80, 90):
        for n in range(1, 200):
            length = pair_prefix(n, percent)
            assert 0 <= length <= n


def _mix_docs(spark):
    rng = random.Random(5)
    rows = [(i, "w " * rng.randint(0, 60), rng.choice(["a", "a", "a", "b", "c", "d", None])) for i in range(400)] + [(1000, None, "e"), (1001, "x", ""), (3, "w w", "b")]
    return spark.createDataFrame(rows, "doc_id long, text string, source string").selectExpr("*", "7 as size", "8 as taken").repartition(3)


def test_mix_plan(spark):
    docs = _mix_docs(spark)
    got = plan_mix(docs)
    cols = ["doc_id", "size", "source_size", "target", "taken", "position"]
    want = _sql(mixing.SQL, documents=docs).fetchall()
    assert _rows(got, *cols) == sorted(want, key=repr)
    rows = got.collect()
    by: dict = {}
    for r in rows:
        assert 0 <= r.taken <= 3 * r["size"] and 0 <= r.position <= 1
        by.setdefault(r.source, [0, r.target])[0] += r.taken
    assert all(abs(t - goal) <= 1 for t, goal in by.values())
    assert plan_mix(docs.limit(0)).count() == 0
    assert _rows(plan_mix(docs), *cols) == _rows(got, *cols)


def test_mix_repeats_and_order(spark):
    docs = _mix_docs(spark).where("doc_id < 1000").dropDuplicates(["doc_id"])
    plan = {r.doc_id: r for r in plan_mix(docs).collect()}
    out = mix(docs)
    assert out.columns == docs.columns
    count: dict = {}
    for r in out.collect():
        count[r.doc_id] = count.get(r.doc_id, 0) + 1
    assert count == {i: -(-r.taken // r["size"]) for i, r in plan.items() if r.taken}


def test_schedule_inverse():
    import numpy as np

    for a in (-0.9, -0.5, 0.0, 0.5, 0.9):
        t = np.linspace(0, 1, 11)
        share = t + a * (t * t - t)
        back = 2 * share / ((1 - a) + np.sqrt((1 - a) ** 2 + 4 * a * share))
        assert np.allclose(back, t)


def test_line_chunks_shift_and_edges(spark):
    rng = random.Random(9)
    line = lambda: " ".join(rng.choice("alpha beta gamma delta eps zeta eta".split()) + str(rng.randrange(50)) for _ in range(9))
    passage = [line() for _ in range(30)]
    rows = []
    for i in range(40):
        own = [line() for _ in range(rng.randint(0, 12))]
        at = rng.randint(0, len(own))
        rows.append((i, "\n".join(own[:at] + (passage if i % 3 == 0 else []) + own[at:])))
    rows += [(100, None), (101, ""), (102, "\n\n"), (0, rows[0][1])]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as pos", "2 as chunk").repartition(3)
    unique = docs.dropDuplicates(["doc_id"])
    want = _sql(line_chunks.SQL, documents=unique.select("doc_id", "text")).fetchall()
    assert _rows(line_report(unique), "doc_id", "n_removed", "kept_chars", "kept_md5") == sorted(want, key=repr)
    kept = {r.doc_id: r.text for r in drop_repeated_chunks(unique).collect()}
    inside = sum(sum(p in (kept[i] or "").split("\n") for p in passage) for i in range(3, 40, 3))
    assert inside < 0.35 * 30 * 13 and all(p in kept[0].split("\n") for p in passage)
    assert kept[100] is None and kept[101] == "" and drop_repeated_chunks(docs).count() == len(rows)
    assert drop_repeated_chunks(docs.limit(0)).count() == 0


def test_words_with_one_polynomial_hash_are_kept_apart(spark):
    word = "t"
    while len(word) < 1024:
        word += word.translate(str.maketrans("th", "ht"))
    other = word.translate(str.maketrans("th", "ht"))
    df = spark.createDataFrame([(1, word), (2, other), (3, f"a {word} b"), (4, f"a {other} b"), (5, word)], "doc_id long, text string")
    assert _rows(jaccard_components(df, 3, 90), "doc_id", "component_id") == [(1, 1), (2, 2), (3, 3), (4, 4), (5, 1)]


def test_one_giant_component(spark, monkeypatch):
    monkeypatch.setattr(jaccard_join, "BLOCK_SHINGLES", 2000)
    monkeypatch.setattr(jaccard_join, "CROWD", 30)
    rng = random.Random(9)
    words = [f"w{i}" for i in range(500)]
    base = [rng.choice(words) for _ in range(100)]
    rows = []
    for i in range(300):  # a chain of near copies and, every third, copies of the base with little change
        w = list(base)
        for _ in range(rng.choice([0, 1, 2, 6])):
            w[rng.randrange(len(w))] = rng.choice(words)
        rows.append((1000 - i, " ".join(w)))
        if i % 3 == 0:
            base[rng.randrange(len(base))] = rng.choice(words)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_components(df, 3, 80).collect()}
    assert got == _brute_components(rows, 3, 80)


def test_top_k_bounds_prune_clustered_vectors():
    import numpy as np

    rng = np.random.default_rng(3)
    centres = rng.normal(0, 1000, (40, 8))
    x = np.floor(np.repeat(centres, 100, axis=0) + rng.normal(0, 5, (4000, 8)))
    pivots = x[::100]
    cell, far = topk.nearest_pivot(x, pivots)
    summary = lambda of, near: {j: (int((of == j).sum()), float(far[of == j].max()), float(np.linalg.norm(x[of == j], axis=1).max()), np.sort(far[of == j])[:near]) for j in set(of.tolist())}
    need = topk._bounds(pivots, summary(cell, 0), pivots, summary(cell, 11), 10, 1)
    assert sum(map(len, need.values())) < 0.2 * 40 * 40  # of all pairs of groups and cells
    scores = x @ x.T
    for q in range(0, 4000, 97):
        best = np.argsort(-scores[q], kind="stable")
        best = best[best != q][:10]
        assert all(cell[q] in need[int(cell[j])] for j in best)


def test_near_copies_shuffle_all_texts_once(spark, shuffled):
    """Random words: every text may be shuffled once, and then only those that have a near copy."""
    from zplane.session import stored

    rng = random.Random(4)
    text = lambda n: [f"{rng.getrandbits(200):050x}" for _ in range(n)]
    rows = [(i, " ".join(text(300))) for i in range(300)]
    near = [text(300) for _ in range(3)]
    rows += [(1000 + 10 * i + j, " ".join(w + [f"end{j}"])) for i, w in enumerate(near) for j in range(3)]
    docs = stored(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), "docs")
    got, written = shuffled(lambda: {r.doc_id: r.component_id for r in jaccard_components(docs, k=3, percent=90).collect()})
    assert got == {i: i if i < 1000 else i // 10 * 10 for i, _ in rows}
    assert written < 1.5 * sum(len(t) for _, t in rows)


def test_prefixes_are_shuffled_in_turns(spark, shuffled, monkeypatch):
    """No job of the search for partners may shuffle more than a share of the prefixes of random texts."""
    from zplane.llm import jaccard_join

    rng = random.Random(5)
    rows = [(i, " ".join(f"{rng.getrandbits(20):05x}" for _ in range(400))) for i in range(400)]
    rows += [(1000 + i, t + " more") for i, t in rows[:5]]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    kept, write = {}, jaccard_join.stored

    def measured(df, name="table"):
        out, n = shuffled(lambda: write(df, name))
        kept[name] = max(n, kept.get(name, 0))
        return out

    monkeypatch.setattr(jaccard_join, "stored", measured)
    got = {r.doc_id: r.component_id for r in jaccard_components(docs, k=5, percent=80).collect()}
    assert got == {i: i % 1000 for i, _ in rows}
    del kept["texts"]  # all texts go once, as test_near_copies_shuffle_all_texts_once says
    assert max(kept.values()) < 24 * 100 * len(rows)  # a prefix has about 100 shingles; all at once took about 40 bytes each


def test_levels_need_little_memory_on_the_driver():
    import tracemalloc

    import numpy as np

    counts = np.random.default_rng(1).poisson(3, 1 << jaccard_join.SKETCH_BITS).astype(np.int32)
    counts[::1000] = 50_000
    mean = float(counts.mean())
    plain = np.ceil(np.log2(np.maximum(0, counts - mean - 4 * np.sqrt(mean) - 4) + 1)).astype(np.uint8)
    tracemalloc.start()
    levels = jaccard_join._levels(counts)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert (levels == plain).all() and peak < 30e6

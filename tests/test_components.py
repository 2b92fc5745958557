import random

import pytest

from zplane.components import components, components_with_rounds


def _brute(edges):
    p = {}

    def find(x):
        p.setdefault(x, x)
        while p[x] != x:
            x = p[x]
        return x

    for a, b in edges:
        if a is not None and b is not None and a != b:
            x, y = find(a), find(b)
            p[max(x, y)] = min(x, y)
    return {x: find(x) for x in list(p)}


@pytest.mark.parametrize("local", [1_000_000, 0])
def test_components_equal_union_find(spark, local):
    rng = random.Random(3)
    edges = [(rng.randrange(-50, 400), rng.randrange(-50, 400)) for _ in range(260)] + [(i, i + 1) for i in range(1000, 1200)] + [(5000, i) for i in range(2000, 2100)]
    edges += [(1, 1), (None, 3), (7, None)] + edges[:20]
    rng.shuffle(edges)
    df = spark.createDataFrame(edges, "a long, b long").repartition(5)
    got, rounds = components_with_rounds(df, local_edges=local)
    assert {r.node: r.root for r in got.collect()} == _brute(edges)
    assert rounds <= 14


def test_no_edges(spark):
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_link_by_knn_joins_sites_beyond_its_lists(spark):
    from zplane.operators.baselines import link_by_knn

    sites = [(0.0, 40), (0.5, 40), (9.0, 30), (20.0, 1), (9.4, 1)]  # 40 copies of a place fill every list of 8
    rows = [(i, x) for i, x in enumerate(x for x, n in sites for _ in range(n))]
    df = spark.createDataFrame(rows, "id long, x double").repartition(3)
    got = {r.id: r.group_id for r in link_by_knn(df, ["x"], 1.0, k=4, most=8).collect()}
    assert got == {i: 0 if x < 1 else 80 if x < 10 else 110 for i, x in rows}


def test_link_by_knn_doubles_only_lists_that_are_full(spark, monkeypatch):
    from zplane.operators import baselines

    calls, plain = [], baselines.knn

    def noted(src, k, cols, queries=None, **kw):
        calls.append((k, src.count() if queries is None else queries.count()))
        return plain(src, k, cols, queries=queries, **kw)

    monkeypatch.setattr(baselines, "knn", noted)

    def groups(places):
        calls.clear()
        df = spark.createDataFrame([(i, x) for i, x in enumerate(places)], "id long, x double").repartition(3)
        return [r.group_id for r in sorted(baselines.link_by_knn(df, ["x"], 1.0, k=4).collect())]

    crowd, lone = [i / 100 for i in range(10)], [10.0 + 2 * i for i in range(50)]
    assert groups(3 * crowd + lone) == [0] * 30 + list(range(30, 80))  # copies are one site
    assert calls == [(4, 60), (8, 10)]  # all ten are full again, so no list of 16 is made
    assert groups([i / 100 for i in range(500)] + [7.5, 7.0, 5.0]) == [0] * 500 + [500, 500, 0]
    assert calls == [(4, 503)]

"""Linking of many domains: groups of brute force, and a contraction of labels instead of points."""

import numpy as np
import pytest

from zplane.components import union_find
from zplane.operators import linking
from zplane.plans.planes import Options


def brute(x, ids, r, box=None):
    d2 = 0.0
    for i in range(x.shape[1]):
        t = x[:, None, i] - x[None, :, i]
        if box and box[i]:
            t = t - box[i] * np.floor(t / box[i] + 0.5)
        d2 = d2 + t * t
    a, b = np.nonzero(d2 <= r * r)
    nodes, roots = union_find(ids[a], ids[b])
    return dict(zip(nodes.tolist(), roots.tolist()))


def clumps(seed):
    """Chains and clumps that cross many domains, coincident points, and lonely ones; ids without order."""
    rng = np.random.default_rng(seed)
    line = np.column_stack([np.linspace(0.01, 0.99, 700), np.full(700, 0.5)])
    near = rng.normal(0.3, 0.002, (500, 2))
    x = np.concatenate([line, near, rng.random((500, 2)), np.repeat(rng.random((3, 2)), 60, 0)])
    return x, rng.permutation(len(x)) + 5


@pytest.mark.parametrize("r,box", [(0.02, None), (0.004, None), (0.02, [1.0, 1.0]), (0.0, None), (0.3, None)])
def test_domains_contract_labels(spark, monkeypatch, r, box):
    x, ids = clumps(3)
    df = spark.createDataFrame([(int(i), float(a), float(b)) for i, (a, b) in zip(ids, x)], "id long, x double, y double").repartition(3)
    sizes, keep = [], linking.components_with_rounds
    monkeypatch.setattr(linking, "components_with_rounds", lambda e, *a: sizes.append(e.count()) or keep(e, *a))
    got = linking.link_clusters(df, ["x", "y"], r, box=box, options=Options(n_max0=16, domain_rows=150, n_target=8))
    want = brute(x, ids, r, box)
    assert {q.id: q.group_id for q in got.collect()} == want and got.count() == len(ids)
    assert sizes and max(sizes) < len(ids) / 8  # labels of domains, not an edge for each point


def test_coincident_points_are_contracted_at_home(spark, monkeypatch):
    """A few sites of many points in many domains: an edge for a pair of near sites at most, and groups by the first coordinate."""
    rows = [(7 * i + 1, float(i % 9), (i // 9) % 5 / 100) for i in range(6000)]
    sizes, keep = [], linking.components_with_rounds
    monkeypatch.setattr(linking, "components_with_rounds", lambda e, *a: sizes.append(e.count()) or keep(e, *a))
    got = linking.link_clusters(spark.createDataFrame(rows, "id long, x double, y double"), ["x", "y"], 0.5, options=Options(n_max0=32, domain_rows=200, n_target=8))
    assert sorted(map(tuple, got.collect())) == [(i, 7 * ((i - 1) // 7 % 9) + 1) for i, _, _ in rows]
    assert sizes and max(sizes) <= 9 * 10


def test_keys_need_no_object_a_row(spark, monkeypatch):
    """Keys of many windows and signs equal those made bit by bit, and travel as one buffer."""
    import pyarrow as pa

    from zplane.functions import zkey

    rng = np.random.default_rng(5)
    for t in range(60):
        d = int(rng.integers(1, 9))
        x = rng.normal(size=(50, d)) * 10.0 ** rng.integers(-9, 9, size=(50, d) if t % 3 == 0 else (1, 1))
        x = [x, np.round(np.abs(x), 2), np.trunc(x)][t % 3]
        x[rng.random(x.shape) < 0.1] = -0.0
        plan = zkey.plan_of(x, d)
        if t % 5 == 0 and plan.top > plan.low + 9:
            plan = zkey.KeyPlan(d, plan.top - 2, plan.low + 5)
        k = zkey.exact_keys(x, plan)
        assert (k == zkey._keys_by_rows(x, plan)).all() and k.shape == (50, plan.bytes)
        col = zkey.key_array(k)
        assert col.to_pylist() == [r.tobytes() for r in k] and (zkey.key_rows(pa.chunked_array([col.slice(3, 9), col.slice(20)])) == np.concatenate([k[3:12], k[20:]])).all()

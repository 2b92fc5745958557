"""Keys, levels, planes, walk parts and operators against their definitions."""

import math
import random

import numpy as np
import pytest

from zplane import pointsets as ps
from zplane.functions import bounds, zkey
from zplane.operators import joins, knn, linking
from zplane.plans import planes, walk
from zplane.plans.planes import Options


def _cloud(d, seed=0):
    rng = np.random.default_rng(seed)
    return np.concatenate([rng.normal(size=(200, d)), rng.integers(-3, 3, size=(80, d)) * 1.0, rng.normal(size=(40, d)) * 1e-9])


def test_msb_cases():
    assert zkey.msb_fixed(0b10101001, 0b10100101) == 3
    assert zkey.msb(1.0, -1.0) == 1024 and zkey.msb(1.0, -1.0, "float") == 128
    assert zkey.msb(4.0, 1.0) == 2 and zkey.msb(1.0, 1.5) == -1 and zkey.msb(0.0, -0.0) == -math.inf
    assert zkey.msb(5e-324, 0.0) == -1074 and zkey.msb(1.0, 1.0 + 2**-52) == -52


@pytest.mark.parametrize("d", [1, 2, 3, 5])
def test_exact_keys_order_like_the_comparator(d):
    x = _cloud(d)
    plan = zkey.plan_of(x, d)
    k = zkey.exact_keys(x, plan)
    rng = random.Random(1)
    for _ in range(2000):
        i, j = rng.randrange(len(x)), rng.randrange(len(x))
        assert (k[i].tobytes() < k[j].tobytes()) == zkey.z_less(x[i], x[j])
        lvl = zkey.level_of_bits(zkey.common_bits(k[i : i + 1], k[j : j + 1], plan), plan)[0]
        want = zkey.morton_level(x[i], x[j])
        assert lvl == (-(2**31) if want == -math.inf else want)


def test_extreme_exponents():
    x = np.array([[5e-324], [1e308], [-1e308], [0.0], [1.0]])
    plan = zkey.plan_of(x, 1)
    k = zkey.exact_keys(x, plan)
    order = sorted(range(5), key=lambda i: k[i].tobytes())
    assert [float(x[i, 0]) for i in order] == [-1e308, 0.0, 5e-324, 1.0, 1e308]


def test_extents_sum_to_the_level():
    for d in (1, 2, 3, 4):
        for lvl in range(-20, 20):
            e = zkey.extent_levels(lvl, d)
            assert sum(e) == lvl and max(e) - min(e) <= 1


def test_worked_example():
    x = np.array([1.6, 3.1, 3.3, 4.6, 5.6, 6.8, 9.4, 9.7])[:, None]
    plan = zkey.plan_of(x, 1)
    bits = planes.gap_bits(zkey.exact_keys(x, plan), plan)
    assert zkey.level_of_bits(bits[1:-1], plan).tolist() == [2, -1, 3, 1, 2, 4, 0]
    assert planes.gap_counts(bits).tolist() == [8, 3, 2, 6, 2, 3, 8, 2, 8]
    assert [s.tolist() for s in planes.split_positions(bits, [2, 4])] == [[0, 1, 3, 5, 6, 8], [0, 3, 6, 8]]
    assert planes.binary_parents(bits)[2] == 1 and planes.binary_parents(bits)[6] == -1


@pytest.mark.parametrize("d", [1, 2, 3])
def test_gap_shortcut_and_cells(d):
    x = _cloud(d, 4)
    plan = zkey.plan_of(x, d)
    k = zkey.exact_keys(x, plan)
    o = np.lexsort([k[:, j] for j in range(k.shape[1] - 1, -1, -1)])
    k, x = k[o], x[o]
    bits = planes.gap_bits(k, plan)
    ends = np.isin(np.arange(len(bits)), [0, len(bits) - 1])
    for n in (1, 3, 10, 50):
        assert (planes.gap_exceeds(bits, n) == ((planes.gap_counts(bits) > n) | ends)).all()
    splits = planes.split_positions(bits, [5, 20, 80])
    assert set(splits[2]) <= set(splits[1]) <= set(splits[0])
    for at in splits:
        first, last = at[:-1], at[1:] - 1
        c, e = zkey.cells(x[first], zkey.level_of_bits(zkey.common_bits(k[first], k[last], plan), plan))
        for a, b, cc, ee in zip(first, last, c, e):
            assert (np.abs(x[a : b + 1] - cc) <= ee / 2).all()


def test_schedule_and_estimates():
    assert planes.plane_schedule(10**7) == [48, 384, 3072, 24576]
    assert planes.plane_schedule(1000, 48, 8, to_root=True)[-1] >= 1000
    assert planes.estimate_nodes(960, 48) == 40
    assert planes.level_cap([(0, 90), (10, 10)], 50, 2) == 5 and planes.level_cap([(-(2**31), 5)], 50, 2) is None


def test_bounds_hold():
    rng = np.random.default_rng(3)
    for box in (None, [1.0, None]):
        for _ in range(200):
            c1, c2, l1, l2 = rng.random(2), rng.random(2), rng.random(2) * 0.3, rng.random(2) * 0.3
            low, up = bounds.np_bounds(c1, l1, c2, l2, box)
            p, q = c1 + (rng.random((20, 2)) - 0.5) * l1, c2 + (rng.random((20, 2)) - 0.5) * l2
            d = np.sqrt((bounds.np_wrap(p - q, box) ** 2).sum(-1))
            assert (low <= d + 1e-12).all() and (d <= up + 1e-12).all()


def test_bounded_heap_is_safe():
    rng = random.Random(2)
    for _ in range(300):
        items = [(rng.random(), rng.randint(1, 5)) for _ in range(rng.randint(1, 40))]
        k = rng.randint(1, 12)
        heap = walk.BoundedHeap(k, 4)
        for r, n in items:
            heap.insert(r, n)
        _, exact = walk.find_rmax(np.zeros(len(items), int), np.array([r for r, _ in items]), np.array([n for _, n in items]), k)
        assert heap.radius() >= exact[0]


def _brute(p, q, k, box=None, own=False):
    out = {}
    for i, x in q:
        d = []
        for j, y in p:
            if own and i == j:
                continue
            t = np.array(x) - np.array(y)
            if box:
                t = bounds.np_wrap(t.copy(), box)
            d.append((float((t * t).sum()), j))
        out[i] = [j for _, j in sorted(d)[:k]]
    return out


@pytest.mark.parametrize("n,k", [(0, 3), (1, 3), (2, 3), (3, 3), (4, 3), (90, 7)])
def test_knn_small_inputs(spark, n, k):
    rng = np.random.default_rng(n)
    pts = [(i, [float(v) for v in rng.integers(0, 6, 2)]) for i in range(n)]
    df = spark.createDataFrame([(i, *x) for i, x in pts], "id long, x0 double, x1 double")
    for own in (False, True):
        got: dict = {}
        for r in knn.knn(df, k, ["x0", "x1"], include_self=not own, options=Options(n_max0=4, domain_rows=30, n_target=2, c=2)).collect():
            got.setdefault(r.qid, {})[r["rank"]] = r.sid
        want = {i: v for i, v in _brute(pts, pts, k, own=own).items() if v}
        assert {i: [v[r] for r in sorted(v)] for i, v in got.items()} == want


def test_knn_variants_agree(spark, sf):
    p, cols = ps.points(spark, sf, "ps_unif"), ps.cols("ps_unif")
    base = {(r.qid, r["rank"]): r.sid for r in knn.knn(p, 12, cols).collect()}
    for kw in ({"options": Options(n_max0=16, domain_rows=200, n_target=4)}, {"early_exit": False}, {"k_pass": 5}, {"method": "stages", "options": Options(n_max0=32, n_target=4)}, {"options": Options(f_max=5.0, n_max0=24)}):
        assert {(r.qid, r["rank"]): r.sid for r in knn.knn(p, 12, cols, **kw).collect()} == base, kw
    z = knn.knn(p, 2, cols, order="z").collect()
    assert len(z) == 2 * p.count() and [r.qid for r in knn.knn(p, 1, cols, order="input").collect()] == sorted(r.id for r in p.collect())


def test_large_sets_against_brute_force_on_a_fixture(spark, sf):
    for name in ("ps_line", "ps_dup"):
        p = ps.points(spark, sf, name).where("id <= 700")
        pts = [(r.id, [r[c] for c in ps.cols(name)]) for r in p.collect()]
        got: dict = {}
        for r in knn.knn(p, 8, ps.cols(name), options=Options(n_max0=24, domain_rows=150, n_target=4)).orderBy("qid", "rank").collect():
            got.setdefault(r.qid, []).append(r.sid)
        assert got == _brute(pts, pts, 8)


def test_invalid_rows(spark):
    df = spark.createDataFrame([(1, 0.0, 1.0), (2, None, 1.0), (3, float("nan"), 0.0), (4, -0.0, 1.0)], "id long, x0 double, x1 double")
    assert {r.qid for r in knn.knn(df, 1, ["x0", "x1"], on_invalid="drop").collect()} == {1, 4}
    with pytest.raises(Exception):
        knn.knn(df, 1, ["x0", "x1"]).collect()


def test_metrics_are_sensible(spark):
    sf = "/root/testdata/sf0.01"
    m = knn.knn_metrics(ps.points(spark, sf, "ps_unif"), 16, ps.cols("ps_unif"), options=planes.paper_options()).first()
    assert 0 < m.checked_share < 0.2 and 0 <= m.early_exit_share < 1 and 0.5 < m.node_factor < 2.5


def test_chain_links_at_the_length_and_not_beyond(spark):
    step = 0.25
    near = spark.createDataFrame([(i, i * step) for i in range(300)], "id long, x0 double")
    assert {r.group_id for r in linking.link_clusters(near, ["x0"], step, options=Options(n_max0=8, domain_rows=60, n_target=2)).collect()} == {0}
    far = linking.link_clusters(near, ["x0"], step * (1 - 1e-9), options=Options(n_max0=8, n_target=2)).collect()
    assert all(r.id == r.group_id for r in far)


def test_periodic_links_and_unwrapped_catalogue(spark):
    df = spark.createDataFrame([(1, 0.01, 0.5), (2, 0.99, 0.5), (3, 0.5, 0.5)], "id long, x0 double, x1 double")
    open_ = {r.id: r.group_id for r in linking.link_clusters(df, ["x0", "x1"], 0.05).collect()}
    wrapped = linking.link_clusters(df, ["x0", "x1"], 0.05, box=[1.0, None])
    assert open_ == {1: 1, 2: 2, 3: 3} and {r.id: r.group_id for r in wrapped.collect()} == {1: 1, 2: 1, 3: 3}
    row = linking.catalogue(df, wrapped, ["x0", "x1"], min_count=2, box=[1.0, None]).first()
    assert row.n == 2 and abs(row.com_x0 - 0.0) < 1e-12


def test_range_query_and_tree_file(spark, sf, tmp_path):
    p, cols = ps.points(spark, sf, "ps_unif"), ps.cols("ps_unif")
    tree = knn.joint_tree(p, None, cols, options=Options(n_max0=32, domain_rows=400, n_target=4))
    tree.save(str(tmp_path / "tree"))
    again = planes.PlaneTree.load(spark, str(tmp_path / "tree"))
    want = {r.id for r in p.collect() if (r.x0 - 0.5) ** 2 + (r.x1 - 0.5) ** 2 + (r.x2 - 0.5) ** 2 <= 0.04}
    assert {r.id for r in joins.range_query(again, [0.5, 0.5, 0.5], 0.2).collect()} == want


def test_key_ranges_cover_the_box():
    box = ((0.0, 1.0), (0.0, 1.0))
    ranges = joins.box_to_key_ranges([0.2, 0.3], [0.4, 0.35], box, 16, bits=8)
    rng = random.Random(1)
    for _ in range(500):
        x, y = int(rng.uniform(0.2, 0.4) * 256), int(rng.uniform(0.3, 0.35) * 256)
        key = sum(((x >> b & 1) << (2 * b + 1)) | ((y >> b & 1) << (2 * b)) for b in range(8))
        assert any(a <= key <= b for a, b in ranges)
    assert sum(b - a + 1 for a, b in ranges) < 65536 / 4


def test_zpos_and_rebalance(spark, sf):
    from zplane.operators.inspect import partition_imbalance, rebalance, with_zpos, zsort

    p = zkey.with_zkey(ps.points(spark, sf, "ps_unif"), ps.cols("ps_unif"))
    z = with_zpos(zsort(p, 4))
    rows = z.orderBy("zpos").collect()
    assert [r.zpos for r in rows] == list(range(len(rows))) and [bytes(r.zkey) for r in rows] == sorted(bytes(r.zkey) for r in rows)
    assert partition_imbalance(rebalance(z, 5)).first().imbalance < 0.35


def test_hilbert_neighbours_are_adjacent():
    g = np.array([(i, j) for i in range(8) for j in range(8)])
    order = g[np.argsort(zkey.hilbert_index(g, 3))]
    assert (np.abs(np.diff(order, axis=0)).sum(1) == 1).all()


def test_every_option_is_read():
    import dataclasses
    import pathlib
    import re

    code = "".join(p.read_text() for p in pathlib.Path(planes.__file__).parents[1].rglob("*.py"))
    assert all(re.search(rf"\w\.{f.name}\b", code) for f in dataclasses.fields(Options))


def test_bins_of_a_leaf_whose_sources_come_in_another_order():
    import pyarrow as pa

    from zplane.operators.joins import bin_counts

    x = [0.0, 1.0, 3.0, 3.0]
    rows = [(0, 7, None, v) for v in x] + [(1, 7, None, v) for v in x[::-1]] + [(2, 7, 7, None)]
    kind, leaf, src, at = zip(*rows)
    table = pa.table({"kind": kind, "leaf": leaf, "src": pa.array(src, pa.int64()), "r": pa.array([None] * 8 + [0.0], pa.float64()), "id": pa.array([*range(4), *range(3, -1, -1), None], pa.int64()), "x0": pa.array(at, pa.float64())})
    assert bin_counts(table, 1, np.array([0.0, 0.25, 4.0, 9.0])).tolist() == [1, 3, 2]


@pytest.mark.parametrize("include_self,k_pass", [(True, None), (False, None), (False, 3), (True, 3)])
def test_sites_larger_than_a_leaf_are_one_leaf(spark, include_self, k_pass):
    """A site of more points than a leaf may hold makes one leaf, not one for each point, and its queries one search."""
    places = [(0.0, 300), (1.0, 2), (1.5, 1), (4.0, 40), (-2.0, 5)]
    x = [p for p, n in places for _ in range(n)]
    random.Random(4).shuffle(x)
    df = spark.createDataFrame(list(enumerate(x)), "id long, x0 double")
    tree = knn.joint_tree(df, None, ["x0"], options=Options(n_max0=8, domain_rows=60))
    sizes = sorted(r.n_src for r in tree.nodes.where("plane = 0").collect())
    assert sizes[-2:] == [40, 300] and len(sizes) <= 5
    got = {}
    for r in knn.knn(df, 7, ["x0"], include_self=include_self, k_pass=k_pass, tree=tree).collect():
        got.setdefault(r.qid, []).append((r.rank, r.sid, r.dist))
    for q, v in enumerate(x):
        want = sorted((abs(v - s), i) for i, s in enumerate(x) if include_self or i != q)[:7]
        assert [(s, d) for _, s, d in sorted(got[q])] == [(i, d) for d, i in want]


def _domain(q, s, pairs):
    """A domain's rows as the leaf kernels get them: queries and sources (leaf, id, x), pairs of leaves."""
    import pyarrow as pa

    rows = [(0, l, None, None, i, x) for l, i, x in q] + [(1, l, None, None, i, x) for l, i, x in s] + [(2, a, b, 0.0, None, None) for a, b in pairs]
    kind, leaf, src, r, ids, x = zip(*rows)
    return pa.table({"kind": kind, "leaf": leaf, "src": pa.array(src, pa.int64()), "r": pa.array(r, pa.float64()), "id": pa.array(ids, pa.int64()), "x0": pa.array(x, pa.float64())})


def test_semi_join_makes_no_pairs():
    table = _domain([(0, 1, 0.0), (0, 2, 5.0), (1, 3, 9.0)], [(0, 7, 0.5), (0, 8, 0.4), (1, 9, 5.5)], [(0, 0), (0, 1), (1, 1)])
    assert sorted(joins.near_ids(table, 1, 0.5).tolist()) == [1, 2]


def test_rows_of_a_domain_come_in_parts(monkeypatch):
    monkeypatch.setattr(knn, "OUT_ROWS", 100)
    pts = [(i // 10, i, float(i)) for i in range(200)]
    table = _domain(pts, pts, [(a, b) for a in range(20) for b in range(max(0, a - 1), min(20, a + 2))])
    got = list(knn.rows_kernel(1, 5, None, True, True, None)(iter(table.to_batches())))
    assert len(got) >= 9 and sum(b.num_rows for b in got) == 1000 and max(b.num_rows for b in got) <= 150


def test_leaves_of_one_group_are_not_measured(monkeypatch):
    calls = []
    monkeypatch.setattr(linking, "squared", lambda *a: calls.append(1) or knn.squared(*a))
    pts = [(i // 50, i, float(i % 50)) for i in range(200)]  # four leaves over the same places
    table = _domain(pts, pts, [(a, b) for a in range(4) for b in range(a, 4)])
    a, b = linking.spanning_edges(table, 1, 1.0)
    assert len(a) == 199 and set(b.tolist()) == {0} and len(calls) < 10
    a, b = linking.spanning_edges(table, 1, 0.5)  # only copies of a place are linked
    assert sorted(zip(a.tolist(), b.tolist())) == [(i, i % 50) for i in range(50, 200)]


@pytest.mark.parametrize("d", [1, 2, 3])
def test_one_task_linking_of_dense_points(spark, d):
    from zplane.operators import baselines

    rng = np.random.default_rng(d)
    x = np.round(rng.random((300, d)) * 3 - 1, 2)
    x[200:] = x[:100]
    r = {1: 0.01, 2: 0.1, 3: 0.25}[d]
    cols = [f"x{i}" for i in range(d)]
    df = spark.createDataFrame([(i, *v) for i, v in enumerate(x.tolist())], "id long, " + ", ".join(f"{c} double" for c in cols))
    near = knn.squared(x, x, None) <= r * r
    label = np.arange(300)
    while (new := np.where(near, label[None], 999).min(1)).tolist() != label.tolist():
        label = new
    assert [g for _, g in sorted(map(tuple, baselines.link_union_find(df, cols, r).collect()))] == label.tolist()


def test_tiles_keep_ties_in_order_of_ids():
    s_id = np.random.default_rng(1).permutation(20_000)
    s = (s_id % 3).astype(float)[:, None]
    row, sid, d2 = knn.nearest(np.array([[0.0], [2.0]]), s, s_id, 4)
    assert row.tolist() == [0] * 4 + [1] * 4 and sid.tolist() == [0, 3, 6, 9, 2, 5, 8, 11] and not d2.any()


def test_plane_counts_of_stages_equal_those_of_tasks(spark, sf, monkeypatch):
    pts = ps.points(spark, sf, "ps_customer")
    ask = lambda: sorted(map(tuple, knn.knn_plane_counts(pts, 4, ps.cols("ps_customer"), options=Options(n_max0=8, n_target=4)).collect()))
    tasks = ask()
    monkeypatch.setattr(walk, "BROADCAST_NODES", 0)  # planes that are too large to broadcast
    assert ask() == tasks and len(tasks) > 1


def test_sifted_pairs_hold_the_nearest():
    """A matrix product leaves few pairs of many dimensions to be measured, and none of the nearest is among those left out."""
    from zplane.operators.knn import sifted, squared

    rng = np.random.default_rng(2)
    s = rng.normal(size=(2000, 64)) + 50.0
    s[100:140] = s[:40]  # ties
    q = np.concatenate([s[:60], rng.normal(size=(40, 64)) + 50.0])
    d2 = squared(q, s, None)
    worst = np.where(np.arange(100) % 2, np.inf, np.sort(d2, axis=1)[:, 9])
    r, c, v = sifted(q, s, 16, worst)
    assert (v == d2[r, c]).all() and len(v) < 100 * 16 * 4
    kept = np.zeros(d2.shape, bool)
    kept[r, c] = True
    assert kept[d2 <= np.minimum(np.sort(d2, axis=1)[:, 15], worst)[:, None]].all()
    own = np.zeros(d2.shape, bool)
    own[np.arange(60), np.arange(60)] = True
    r, c, _ = sifted(q, s, 16, np.full(100, np.inf), own)
    assert not own[r, c].any() and (np.bincount(r, minlength=100) >= 16).all()
    assert sifted(q * 1e200, s, 16, worst) is None

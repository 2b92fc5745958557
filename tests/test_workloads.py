"""Workload queries against their SQL on tables that the given small ones don't resemble."""

import duckdb
import pytest

from zplane import workloads


def rows_of(spark, folder, name, tables):
    """The rows of a query and of its SQL, sorted."""
    got = workloads.queries()[name](spark, str(folder))
    con = duckdb.connect()
    for t in tables:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{folder}/{t}.parquet{'/*.parquet' if (folder / f'{t}.parquet').is_dir() else ''}')")
    cur = con.execute(workloads.oracle_sql()[name])
    names = [c[0] for c in cur.description]
    return sorted(tuple(r[c] for c in names) for r in got.collect()), sorted(cur.fetchall())


@pytest.fixture
def far_orders(spark, tmp_path):
    """Orders whose keys put grid points beyond 1,023 in the third dimension."""
    keys = [0, 1, 26, 640, 639_999, 640_000, 640_001, 640_026, 641_250, 2_000_000]
    spark.createDataFrame([(k, float(k)) for k in keys], "o_orderkey long, o_totalprice double").write.parquet(str(tmp_path / "orders.parquet"))
    return tmp_path


def test_grid_keys_of_ten_bits(spark, far_orders):
    got, want = rows_of(spark, far_orders, "zorder_grid", ["orders"])
    assert got == want


def test_grid_positions_of_ten_bits(spark, far_orders):
    got, want = rows_of(spark, far_orders, "zorder_positions", ["orders"])
    assert got == want


def test_moments_of_three_planes(spark, tmp_path):
    """A table that would get one plane by itself, and prices whose sum needs all of its rows."""
    spark.createDataFrame([(i, i % 7 + 1, 900 + i / 4) for i in range(60)], "p_partkey long, p_size int, p_retailprice double").write.parquet(str(tmp_path / "part.parquet"))
    got, want = rows_of(spark, tmp_path, "node_moments", ["part"])
    assert got == want and len(got) == 3


def test_worked_gaps_follow_the_table(spark, tmp_path):
    """Prices that repeat, and neighbours on both sides of a power of two."""
    cents = [1, 2, 3, 3, 7, 8, 9, 64, 65, 1000, 1023, 1024, 1024, 90_000]
    spark.createDataFrame([(i, c / 100) for i, c in enumerate(cents)], "p_partkey long, p_retailprice double").write.parquet(str(tmp_path / "part.parquet"))
    got, want = rows_of(spark, tmp_path, "planes_worked_example", ["part"])
    assert got == want and len(got) == 11


def test_gap_rows_equal_the_gap_table(spark):
    from zplane.operators.inspect import gap_rows, gap_table

    x = [1.6, 3.1, 3.3, 4.6, 5.6, 6.8, 9.4, 9.7]
    want = gap_table(spark, [(v,) for v in x], [2, 4]).where("pos > 0 AND pos < 8").collect()
    got = gap_rows(spark.createDataFrame([(v,) for v in [*x[::-1], 3.1]], "x0 double"), ["x0"], [2, 4]).orderBy("pos").collect()
    assert [tuple(r) for r in got] == [tuple(r) for r in want]


def test_grid_makes_no_rows_of_pairs(spark, monkeypatch):
    """A dense clump and far points, negative ones too: results of brute force, and no join of queries with sources."""
    import random

    from zplane.operators import baselines

    rng = random.Random(2)
    rows = [(i, rng.gauss(0, 0.01), rng.gauss(0, 0.01)) for i in range(1500)] + [(2000 + i, rng.uniform(-9, 9), rng.uniform(-9, 9)) for i in range(60)] + [(3000 + i, 5.0, 5.0) for i in range(12)]
    df = spark.createDataFrame(rows, "id long, x double, y double").repartition(2)
    plans, keep = [], baselines.stored
    monkeypatch.setattr(baselines, "stored", lambda d, name: plans.append(d._jdf.queryExecution().optimizedPlan().toString()) or keep(d, name))
    got = sorted(tuple(r) for r in baselines.knn_grid(df, 8, ["x", "y"]).collect())
    assert got == sorted(tuple(r) for r in baselines.knn_brute(df, 8, ["x", "y"]).collect()) and len(got) == 8 * len(rows)
    assert plans and not any("Join Inner" in p for p in plans)


def test_grid_keys_of_all_bits(spark, far_orders):
    """Grid points beyond 1,023 in the third dimension, and beyond what a key holds, keep their own cells."""
    spark.createDataFrame([(625 * x + 7, 1.0) for x in (1023, 1024, 2047, 2048, 100_000, (1 << 21) - 1, 1 << 21)], "o_orderkey long, o_totalprice double").write.mode("append").parquet(str(far_orders / "orders.parquet"))
    got, want = rows_of(spark, far_orders, "zorder_grid", ["orders"])
    keys = dict(got)
    assert got == want and len(set(keys.values())) == len(keys) - 1  # the last two share the last cell
    assert [k for k, _ in sorted(keys.items(), key=lambda kv: kv[1]) if k % 625 == 7] == sorted(k for k in keys if k % 625 == 7)

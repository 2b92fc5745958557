"""The point sets of the workloads as SQL over the given tables, one text for both engines.

Only + - * /, integer division and remainder are used, so Spark and DuckDB compute equal bits. Tables are
written {orders}; T(spark dialect) fills them and the few functions that differ.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

P = 2147483647


def big(v) -> str:
    return f"CAST({v} AS BIGINT)"


def drawn(rows: str, draws: dict[str, tuple[str, int]], spark: bool) -> str:
    """rows (a SELECT) with a portable number in [0, 1) for each name: (integer key, stream).

    One level of SELECT for each mixing step, so that no step is computed twice. Many draws go through
    arrays in Spark, whose generated code would grow too large otherwise.
    """
    p = big(P)
    if spark and len(draws) > 4:
        keys, streams = ", ".join(big(k) for k, _ in draws.values()), ", ".join(big(s) for _, s in draws.values())
        steps = f"SELECT *, array({keys}) AS k_, array({streams}) AS s_ FROM ({rows}) AS r0"
        for name, a, b, e in (
            ("a_", "k_", "s_", f"(x * {big(48271)} + y * {big(716151379)}) % {p}"),
            ("b_", "s_", "a_", f"(y * y + x * {big(40692)}) % {p}"),
            ("c_", "a_", "b_", f"(y * y + x) % {p}"),
            ("u_", "b_", "c_", f"CAST((y * y + x) % {p} AS DOUBLE) / CAST(2147483648 AS DOUBLE)"),
        ):
            steps = f"SELECT *, zip_with({a}, {b}, (x, y) -> {e}) AS {name} FROM ({steps}) AS r{name}"
        return f"SELECT *, {', '.join(f'u_[{i}] AS {n}' for i, n in enumerate(draws))} FROM ({steps}) AS r"
    one = ", ".join(f"(({k}) * {big(48271)} + {big(s)} * {big(716151379)}) % {p} AS a_{n}" for n, (k, s) in draws.items())
    two = ", ".join(f"(a_{n} * a_{n} + {big(s)} * {big(40692)}) % {p} AS b_{n}" for n, (_, s) in draws.items())
    three = ", ".join(f"(b_{n} * b_{n} + a_{n}) % {p} AS c_{n}" for n in draws)
    four = ", ".join(f"CAST((c_{n} * c_{n} + b_{n}) % {p} AS DOUBLE) / CAST(2147483648 AS DOUBLE) AS {n}" for n in draws)
    return f"SELECT *, {four} FROM (SELECT *, {three} FROM (SELECT *, {two} FROM (SELECT *, {one} FROM ({rows}) AS r0) AS r1) AS r2) AS r3"


class Dialect:
    def __init__(self, spark: bool, sf_dir: str = ""):
        self.spark, self.sf_dir = spark, sf_dir

    def table(self, name: str) -> str:
        return f"parquet.`{self.sf_dir}/{name}.parquet`" if self.spark else name

    def div(self, a: str, b) -> str:
        return f"(({a}) div {b})" if self.spark else f"(({a}) // {b})"

    def days(self, ts: str, since: str) -> str:
        """Days since a date, exact to the microsecond."""
        if self.spark:
            return f"CAST(timestampdiff(MICROSECOND, TIMESTAMP_NTZ'{since}', CAST({ts} AS TIMESTAMP_NTZ)) AS DOUBLE) / 86400000000D"
        return f"CAST(date_diff('microsecond', TIMESTAMP '{since}', CAST({ts} AS TIMESTAMP)) AS DOUBLE) / CAST(86400000000 AS DOUBLE)"

    def hours_of_day(self, ts: str) -> str:
        micros = f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'2024-01-01', CAST({ts} AS TIMESTAMP_NTZ))" if self.spark else f"date_diff('microsecond', TIMESTAMP '2024-01-01', CAST({ts} AS TIMESTAMP))"
        return f"CAST(({micros}) % {big(86400000000)} AS DOUBLE) / CAST(3600000000 AS DOUBLE)"

    def item(self, a: str, i: int) -> str:
        return f"{a}[{i}]" if self.spark else f"{a}[{i + 1}]"

    def words(self, t: str) -> str:
        return f"size(array_remove(split({t}, ' '), ''))" if self.spark else f"len(list_filter(string_split({t}, ' '), lambda w: w <> ''))"


def sql(name: str, t: Dialect) -> str:
    """The SELECT of a point set: id, x0.., and payload."""
    o, k = t.table("orders"), "o_orderkey"
    if name.startswith("ps_emb"):
        d = int(name.removeprefix("ps_emb_d"))
        return f"SELECT vec_id AS id, {', '.join(f'CAST({t.item("embedding", i)} AS DOUBLE) AS x{i}' for i in range(d))}, CAST(label AS DOUBLE) AS w FROM {t.table('embeddings')}"
    keyed = f"SELECT {k}, o_totalprice FROM {o}"
    if name == "ps_bell":
        sums = ["(" + " + ".join(f"u{12 * j + i}" for i in range(12)) + ") - CAST(6 AS DOUBLE)" for j in range(3)]
        rows = drawn(keyed, {f"u{12 * j + i}": (k, 20 + 12 * j + i) for j in range(3) for i in range(12)}, t.spark)
        return f"SELECT {k} AS id, {', '.join(f'{s} AS x{j}' for j, s in enumerate(sums))}, o_totalprice AS w FROM ({rows}) AS r"
    if name == "ps_clump":
        size = " ".join(f"WHEN {m} THEN {2.0 ** -(1 + m)!r}" for m in range(8))
        rows = drawn(keyed, {f"c{j}": (t.div(k, 64), 61 + j) for j in range(3)} | {f"o{j}": (k, 71 + j) for j in range(3)}, t.spark)
        raw = ", ".join(f"(c{j} + (o{j} - CAST(0.5 AS DOUBLE)) * CAST(CASE {k} % 8 {size} END AS DOUBLE)) AS r{j}" for j in range(3))
        return f"SELECT {k} AS id, {', '.join(f'r{j} - floor(r{j}) AS x{j}' for j in range(3))}, o_totalprice AS w FROM (SELECT *, {raw} FROM ({rows}) AS r) AS s"
    if name == "ps_moving":
        rows = drawn(f"SELECT *, id AS k FROM ({sql('ps_clump', t)}) AS c", {f"r{j}": ("k", 81 + j) for j in range(3)}, t.spark)
        return f"SELECT id, x0, x1, x2, w, {', '.join(f'(r{j} - CAST(0.5 AS DOUBLE)) * CAST(600 AS DOUBLE) AS v{j}' for j in range(3))} FROM ({rows}) AS m"
    if name == "ps_hundred":
        rows = drawn("SELECT i FROM (SELECT explode(sequence(1, 100)) AS i) AS s" if t.spark else "SELECT i FROM range(1, 101) AS s(i)", {f"x{j}": ("i", 91 + j) for j in range(2)}, t.spark)
        return f"SELECT {big('i')} AS id, x0, x1 FROM ({rows}) AS r"
    if name in ("ps_unif", "ps_unif_q"):
        rows = drawn(keyed, {f"x{j}": (k, (1 if name == "ps_unif" else 11) + j) for j in range(3)}, t.spark)
        return f"SELECT {k} AS id, x0, x1, x2, o_totalprice AS w FROM ({rows}) AS r"
    # lines repeat their key, so a number within the key makes ids (a window over each key, none over the table)
    line_id = f"(CAST(l_orderkey AS BIGINT) * 8 + l_linenumber) * {big(4096)} + row_number() OVER (PARTITION BY l_orderkey, l_linenumber ORDER BY l_partkey, l_suppkey, l_quantity, l_extendedprice)"
    return {
        "ps_part": f"SELECT p_partkey AS id, p_size / CAST(50 AS DOUBLE) AS x0, (p_retailprice - 900) / CAST(100 AS DOUBLE) AS x1, p_retailprice AS w FROM {t.table('part')}",
        "ps_acct": f"SELECT c_custkey AS id, c_acctbal AS x0, CAST(c_nationkey AS DOUBLE) AS w FROM {t.table('customer')}",
        "ps_customer": f"SELECT c_custkey AS id, c_acctbal / CAST(10000 AS DOUBLE) AS x0, CAST(coalesce(s, 0) AS DOUBLE) / CAST(2000000 AS DOUBLE) AS x1, CAST(coalesce(n, 0) AS DOUBLE) / CAST(20 AS DOUBLE) AS x2, c_acctbal AS w FROM {t.table('customer')} LEFT JOIN (SELECT o_custkey, sum(CAST(o_totalprice AS DECIMAL(18,2))) AS s, count(*) AS n FROM {o} GROUP BY o_custkey) AS q ON c_custkey = o_custkey",
        "ps_orders": f"SELECT {k} AS id, o_totalprice / CAST(500000 AS DOUBLE) AS x0, ({t.days('o_orderdate', '1995-01-01')}) / CAST(2404 AS DOUBLE) AS x1, o_totalprice AS w FROM {o}",
        "ps_line": f"SELECT {line_id} AS id, l_quantity / CAST(50 AS DOUBLE) AS x0, l_extendedprice / CAST(105000 AS DOUBLE) AS x1, l_discount * 10 AS x2, l_tax AS w FROM {t.table('lineitem')}",
        "ps_dup": f"SELECT {line_id} AS id, l_quantity AS x0, l_discount AS x1, l_tax AS w FROM {t.table('lineitem')}",
        "ps_events": f"SELECT event_id AS id, {t.days('ts', '2024-01-01')} AS x0, value / CAST(50 AS DOUBLE) AS x1, value AS w FROM {t.table('events')}",
        "ps_cyclic": f"SELECT event_id AS id, {t.hours_of_day('ts')} AS x0, value / CAST(20 AS DOUBLE) AS x1, value AS w FROM {t.table('events')}",
        "ps_grid": f"SELECT {k} AS id, CAST({k} % 25 AS DOUBLE) AS x0, CAST({t.div(k, 25)} % 25 AS DOUBLE) AS x1, CAST({t.div(k, 625)} AS DOUBLE) AS x2, o_totalprice AS w FROM {o}",
        "ps_text": f"SELECT doc_id AS id, n_chars / CAST(1000 AS DOUBLE) AS x0, {t.words('text')} / CAST(200 AS DOUBLE) AS x1, CAST(n_chars AS DOUBLE) AS w FROM {t.table('documents')}",
    }[name]


def dims(name: str) -> int:
    if name.startswith("ps_emb"):
        return int(name.removeprefix("ps_emb_d"))
    return {"ps_acct": 1, "ps_part": 2, "ps_orders": 2, "ps_dup": 2, "ps_events": 2, "ps_cyclic": 2, "ps_text": 2, "ps_hundred": 2}.get(name, 3)


def cols(name: str) -> list[str]:
    return [f"x{i}" for i in range(dims(name))]


def points(spark: SparkSession, sf_dir: str, name: str, where: str = "") -> DataFrame:
    """A point set as a DataFrame."""
    text = sql(name, Dialect(True, sf_dir))
    return spark.sql(f"SELECT * FROM ({text}) AS p" + (f" WHERE {where}" if where else ""))

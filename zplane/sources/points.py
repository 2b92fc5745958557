"""Reading points from files and tables, and a data source that generates the uniform set, in batch or as a stream."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

P = 2147483647


def read_points(spark: SparkSession, path: str, cols: list[str], id_col: str, fmt: str = "parquet", schema: str | None = None, payload: list[str] = ()) -> DataFrame:
    """(id, x0.., payload) from parquet, orc, json, csv or a catalog table (fmt='table'); only the named columns are read.

    A single array column gives its items as coordinates when cols is like ['embedding[0]', 'embedding[1]'].
    """
    if fmt == "table":
        df = spark.table(path)
    else:
        reader = spark.read.format(fmt)
        reader = reader.schema(schema) if schema else reader
        df = (reader.option("header", True) if fmt == "csv" else reader).load(path)
    return df.select(F.col(id_col).cast("long").alias("id"), *(F.expr(c).cast("double").alias(f"x{i}") for i, c in enumerate(cols)), *payload)


def draw(key: int, stream: int) -> float:
    a = (key * 48271 + stream * 716151379) % P
    b = (a * a + stream * 40692) % P
    c = (b * b + a) % P
    return ((c * c + b) % P) / 2147483648.0


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


def _rows(lo: int, hi: int, d: int):
    for k in range(lo, hi):
        yield (k, *(draw(k, 1 + j) for j in range(d)))


class UniformPoints(DataSource):
    """spark.read.format('zplane_points').option('n', ..).option('d', ..).option('partitions', ..)"""

    @classmethod
    def name(cls) -> str:
        return "zplane_points"

    def schema(self) -> str:
        return "id long, " + ", ".join(f"x{i} double" for i in range(int(self.options.get("d", 3))))

    def reader(self, schema):
        return _Reader(self.options)

    def simpleStreamReader(self, schema):
        return _Stream(self.options)


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.n, self.d, self.parts = int(options.get("n", 1000)), int(options.get("d", 3)), int(options.get("partitions", 4))

    def partitions(self):
        return [_Range(self.n * i // self.parts, self.n * (i + 1) // self.parts) for i in range(self.parts)]

    def read(self, partition):
        return _rows(partition.lo, partition.hi, self.d)


class _Stream(SimpleDataSourceStreamReader):
    def __init__(self, options):
        self.n, self.d, self.step = int(options.get("n", 1000)), int(options.get("d", 3)), int(options.get("rows_per_batch", 100))

    def initialOffset(self):
        return {"at": 0}

    def read(self, start):
        end = min(self.n, start["at"] + self.step)
        return iter(list(_rows(start["at"], end, self.d))), {"at": end}

    def readBetweenOffsets(self, start, end):
        return _rows(start["at"], end["at"], self.d)


def register(spark: SparkSession) -> None:
    from zplane.session import ship

    ship(spark)
    spark.dataSource.register(UniformPoints)

"""Sources and sinks: a generator of key-arithmetic forests, edge-list readers, bucketed and partitioned sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class ForestSource(DataSource):
    """``spark.read.format('canopy_forest').option('n', ..).option('k', ..)``: rows (id, parent) of a k-ary heap."""

    @classmethod
    def name(cls) -> str:
        return "canopy_forest"

    def schema(self) -> str:
        return "id long, parent long"

    def reader(self, schema) -> DataSourceReader:
        return _HeapReader(int(self.options.get("n", 0)), int(self.options.get("k", 2)), int(self.options.get("parts", 8)))


class _Range(InputPartition):
    def __init__(self, lo: int, hi: int):
        self.lo, self.hi = lo, hi


class _HeapReader(DataSourceReader):
    def __init__(self, n: int, k: int, parts: int):
        self.n, self.k, self.parts = n, k, parts

    def partitions(self):
        step = -(-self.n // max(1, self.parts)) or 1
        return [_Range(lo, min(self.n, lo + step)) for lo in range(0, self.n, step)] or [_Range(0, 0)]

    def read(self, partition):
        for i in range(partition.lo, partition.hi):
            yield (i, (i - 1) // self.k if i else None)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(ForestSource)


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", a: str = "a", b: str = "b") -> DataFrame:
    """Pairs from Parquet, ORC, JSON or CSV with a header; only the two key columns are read."""
    if fmt in ("parquet", "orc"):
        r = spark.read.format(fmt).load(path)
    else:
        r = spark.read.format(fmt).schema(f"{a} long, {b} long").option("header", True).load(path)
    return r.selectExpr(f"cast({a} as bigint) a", f"cast({b} as bigint) b")


def layout(edges: DataFrame, parts: int | None = None) -> DataFrame:
    """Edges in (src, dst) order: a node's edges stand together, a big node's over neighbouring partitions."""
    e = edges.repartitionByRange(parts, "src", "dst") if parts else edges.repartitionByRange("src", "dst")
    return e.sortWithinPartitions("src", "dst")


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int = 8) -> DataFrame:
    """A bucketed, sorted table: later joins and aggregates on ``key`` need no exchange."""
    df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(table)
    return df.sparkSession.table(table)


def append_folds(folds: DataFrame, path: str) -> None:
    """Fold log, partitioned so that a replay reads one step."""
    folds.write.mode("append").partitionBy("phase", "step").parquet(path)

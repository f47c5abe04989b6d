"""The forest value and its builders.

All builders are declarative: a scan, a projection to two LONG columns and one
``distinct``; views, states and folds never hold arrays that grow with the data.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from canopy.store import write


@dataclass(frozen=True)
class Forest:
    nodes: DataFrame  # id
    edges: DataFrame  # src, dst; both directions, distinct, no loops

    def kept(self, name: str = "forest") -> Forest:
        """The same forest, written once, so that loops don't rescan its sources."""
        return replace(self, nodes=write(self.nodes, name).df, edges=write(self.edges, name).df)

    def degrees(self) -> DataFrame:
        """``(id, degree)`` with 0 for isolated nodes."""
        d = self.edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("d"))
        return self.nodes.join(d, "id", "left").select("id", F.coalesce("d", F.lit(0)).cast("long").alias("degree"))


def edges_from_pairs(pairs: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Symmetric, distinct, loop-free edges of a table of pairs; pairs with a null are left out."""
    p = pairs.select(F.col(a).cast("long").alias("src"), F.col(b).cast("long").alias("dst")).filter("src <> dst")
    return p.unionByName(p.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def from_pairs(pairs: DataFrame, ids: DataFrame | None = None) -> Forest:
    """``pairs(a, b)`` and, where nodes may be isolated, ``ids(id)``."""
    edges = edges_from_pairs(pairs)
    nodes = edges.select(F.col("src").alias("id"))
    if ids is not None:
        nodes = nodes.unionByName(ids.select(F.col("id").cast("long").alias("id")))
    return Forest(nodes.filter("id is not null").distinct(), edges)


def from_parent(table: DataFrame, child: Column, parent: Column) -> Forest:
    """Child-to-parent keys; a null parent makes a root."""
    t = table.select(child.cast("long").alias("a"), parent.cast("long").alias("b"))
    return from_pairs(t, t.select(F.col("a").alias("id")))


def from_sequence(table: DataFrame, key: list[Column], order: list[Column], ident: Column, cut: Column | None = None) -> Forest:
    """Paths: each row and the next one of its key; ``cut`` (over columns ``prev``-aware expressions) breaks a link."""
    w = W.partitionBy(*key).orderBy(*order)
    t = table.withColumn("a", ident.cast("long")).withColumn("b", F.lead(ident.cast("long")).over(w))
    if cut is not None:
        t = t.withColumn("b", F.when(~cut, F.col("b")))
    return from_pairs(t.select("a", "b"), t.select(F.col("a").alias("id")))


def prefix_chain(path: Column, sep: str = "/") -> Column:
    """All prefixes of a path, shortest first."""
    parts = F.split(path, sep)
    return F.transform(F.sequence(F.lit(1), F.size(parts)), lambda k: F.array_join(F.slice(parts, 1, k), sep))


def from_prefix(paths: DataFrame, path: str = "path") -> tuple[Forest, DataFrame]:
    """Trie of path prefixes; also the names ``(id, prefix)``.  Ids are 64-bit hashes, checked for collisions by ``names``."""
    p = paths.select(prefix_chain(F.col(path)).alias("p"))
    e = p.select(F.explode(F.arrays_zip(F.slice("p", 1, 1 << 20).alias("x"), F.concat(F.array(F.lit(None)), "p").alias("y"))).alias("z")).filter("z.x is not null")
    t = e.select(F.xxhash64("z.x").alias("a"), F.when(F.col("z.y").isNotNull(), F.xxhash64("z.y")).alias("b"))
    names = e.select(F.xxhash64("z.x").alias("id"), F.col("z.x").alias("prefix")).distinct()
    return from_pairs(t, t.select(F.col("a").alias("id"))), names


def literal(spark: SparkSession, pairs: list[tuple[int, int]], ids: list[int] = ()) -> Forest:
    p = spark.createDataFrame([(int(a), int(b)) for a, b in pairs], "a long, b long")
    return from_pairs(p, spark.createDataFrame([(int(i),) for i in ids], "id long") if ids else None)

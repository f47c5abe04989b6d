"""Labelling problems in node-edge form, their checker and a catalogue.

A solution puts a label on each half-edge.  The multiset around a node must be allowed for its
degree and input label, and the two labels of an edge must be an allowed pair.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass
from itertools import combinations_with_replacement, permutations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Labels that fit a boolean matrix in one LONG (7 x 7 bits, so products do not overflow).
MAX_LABELS = 7
MAX_DEGREE = 6


@dataclass(frozen=True)
class LclProblem:
    name: str
    labels: int
    node: Callable[[tuple[int, ...], int], bool]  # sorted labels around a node, its input label
    edges: frozenset[tuple[int, int]]  # allowed pairs, smaller label first

    def __post_init__(self):
        if not 0 < self.labels <= MAX_LABELS:
            raise ValueError(f"between 1 and {MAX_LABELS} labels")

    def multisets(self, degree: int, given: int = 0) -> list[tuple[int, ...]]:
        return [m for m in combinations_with_replacement(range(self.labels), degree) if self.node(m, given)]

    def tuples(self, degree: int, given: int = 0) -> list[list[int]]:
        """All port assignments of the allowed multisets, in order."""
        return [list(t) for t in sorted({t for m in self.multisets(degree, given) for t in permutations(m)})]

    def edge_ok(self, a: int, b: int) -> bool:
        return (min(a, b), max(a, b)) in self.edges

    def matrix(self) -> int:
        """The edge constraint as a bit matrix: bit 7a+b."""
        return sum(1 << (7 * a + b) for a in range(self.labels) for b in range(self.labels) if self.edge_ok(a, b))

    def table(self, spark: SparkSession, degrees: Iterable[tuple[int, int]]) -> DataFrame:
        """``(degree, given, tuples)`` for the (degree, input label) pairs; a constant-size table."""
        rows = [(d, g, self.tuples(d, g)) for d, g in degrees]
        return spark.createDataFrame(rows, "degree long, given int, tuples array<array<int>>")


def violations(problem: LclProblem, edges: DataFrame, labels: DataFrame, given: DataFrame | None = None) -> DataFrame:
    """``(id, kind)`` of nodes and edges whose constraint breaks; ``labels(node, other, label)`` for each half-edge."""
    spark = edges.sparkSession
    missing = edges.join(labels, (edges.src == labels.node) & (edges.dst == labels.other), "left_anti").select(F.col("src").alias("id"), F.lit("missing").alias("kind"))
    around = labels.groupBy("node").agg(F.sort_array(F.collect_list("label")).alias("got"))
    if given is not None:
        around = around.join(given.select(F.col("id").alias("node"), "given"), "node", "left")
        around = around.withColumn("given", F.coalesce("given", F.lit(0)))
    else:
        around = around.withColumn("given", F.lit(0))
    kinds = [(r["d"], r["given"]) for r in around.select(F.size("got").alias("d"), "given").distinct().collect()]
    good = spark.createDataFrame([(g, list(m)) for d, g in kinds for m in problem.multisets(d, g)] or [(0, [0])], "given int, got array<int>")
    bad_nodes = around.join(F.broadcast(good), ["given", "got"], "left_anti").select(F.col("node").alias("id"), F.lit("node").alias("kind"))
    back = labels.select(F.col("other").alias("node"), F.col("node").alias("other"), F.col("label").alias("far"))
    pairs = spark.createDataFrame(sorted(problem.edges) or [(-1, -1)], "x int, y int")
    two = labels.join(back, ["node", "other"]).select("node", F.least("label", "far").alias("x"), F.greatest("label", "far").alias("y"))
    bad_edges = two.join(F.broadcast(pairs), ["x", "y"], "left_anti").select(F.col("node").alias("id"), F.lit("edge").alias("kind"))
    return missing.unionByName(bad_nodes).unionByName(bad_edges)


def _pairs(*p: tuple[int, int]) -> frozenset:
    return frozenset((min(a, b), max(a, b)) for a, b in p)


def independent_set() -> LclProblem:
    """Maximal independent set: 0 inside, 1 other, 2 pointer to an inside neighbour."""
    return LclProblem("mis", 3, lambda m, _: not m or set(m) == {0} or (m.count(2) == 1 and 0 not in m), _pairs((0, 2), (0, 1), (1, 1)))


def matching() -> LclProblem:
    """Maximal matching: 0 matched edge, 1 other edge of a matched node, 2 edge of an unmatched node."""
    return LclProblem("match", 3, lambda m, _: not m or set(m) == {2} or (m.count(0) == 1 and 2 not in m), _pairs((0, 0), (1, 1), (1, 2)))


def colouring(k: int) -> LclProblem:
    return LclProblem(f"col{k}", k, lambda m, _: len(set(m)) <= 1, _pairs(*[(a, b) for a in range(k) for b in range(a)]))


def precoloured() -> LclProblem:
    """2-colouring that agrees with input labels 1 and 2 (0: free)."""
    return LclProblem("precoloured", 2, lambda m, g: len(set(m)) <= 1 and (not g or not m or m[0] == g - 1), _pairs((0, 1)))


def odd_out_degree() -> LclProblem:
    """Orientation (1 out, 0 in) with an odd out-degree everywhere; no tree has one."""
    return LclProblem("odd", 2, lambda m, _: sum(m) % 2 == 1, _pairs((0, 1)))


def endpoint_reach() -> LclProblem:
    """On paths: 0 in, 1 out, 2 none; ends marked 1 are oriented toward the other end, all else is not."""

    def node(m: tuple[int, ...], given: int) -> bool:
        if not m:
            return True
        if len(m) == 1:
            return m[0] in ((0, 1) if given else (0, 2))
        return m in ((0, 1), (2, 2))

    return LclProblem("reach", 3, node, _pairs((0, 1), (2, 2)))

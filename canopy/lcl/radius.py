"""Radius form of labelling problems and its translation to node-edge form.

A radius-1 problem allows a node's label by the multiset of its neighbours' labels.  In node-edge
form a half-edge carries (own label, neighbour's label); all half-edges of a node agree on the
first, the two halves of an edge mirror each other.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.lcl.problem import MAX_LABELS, LclProblem


@dataclass(frozen=True)
class LclRadius:
    name: str
    labels: int
    ball: Callable[[int, tuple[int, ...]], bool]  # own label, sorted labels of neighbours


def independent_set() -> LclRadius:
    """Maximal independent set with labels 1 inside, 0 outside."""
    return LclRadius("mis", 2, lambda x, near: (1 in near) != (x == 1))


#: Kinds of balls that are checked one by one.
MAX_KINDS = 100_000


def check_radius(problem: LclRadius, edges: DataFrame, labels: DataFrame) -> DataFrame:
    """Ids whose ball is not allowed; ``labels(id, label)``."""
    far = labels.select(F.col("id").alias("dst"), F.col("label").alias("n"))
    near = edges.join(far, "dst").groupBy(F.col("src").alias("id")).agg(F.sort_array(F.collect_list("n")).alias("near"))
    balls = labels.join(near, "id", "left").withColumn("near", F.coalesce("near", F.array().cast("array<int>")))
    kinds = balls.select("label", "near").distinct().limit(MAX_KINDS + 1).collect()
    if len(kinds) > MAX_KINDS:
        raise ValueError(f"more than {MAX_KINDS} kinds of balls: degrees and labels of a problem are constant")
    bad = [(r["label"], r["near"]) for r in kinds if not problem.ball(r["label"], tuple(r["near"]))]
    wrong = edges.sparkSession.createDataFrame(bad or [(-1, [-1])], "label int, near array<int>")
    return balls.join(F.broadcast(wrong), ["label", "near"]).select("id")


def to_node_edge(problem: LclRadius) -> LclProblem:
    k = problem.labels
    if k * k > MAX_LABELS:
        raise ValueError("too many labels for the bit-matrix form")

    def node(m: tuple[int, ...], _: int) -> bool:
        own = {x // k for x in m}
        if not m:
            return any(problem.ball(x, ()) for x in range(k))
        return len(own) == 1 and problem.ball(own.pop(), tuple(sorted(x % k for x in m)))

    mirror = {(min(a * k + b, b * k + a), max(a * k + b, b * k + a)) for a in range(k) for b in range(k)}
    return LclProblem(problem.name, k * k, node, frozenset(mirror))


def node_labels(problem: LclRadius, half_edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """``(id, label)`` from a solution in node-edge form; isolated nodes take their smallest allowed label."""
    alone = min((x for x in range(problem.labels) if problem.ball(x, ())), default=None)
    own = half_edges.groupBy(F.col("node").alias("id")).agg(F.min(F.expr(f"label div {problem.labels}")).cast("int").alias("label"))
    return nodes.join(own, "id", "left").select("id", F.coalesce("label", F.lit(alone).cast("int")).alias("label"))

"""Reductions behind the conditional lower bounds, as runnable workloads."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.components.fallback import star_components
from canopy.components.solve import components
from canopy.ledger import Ledger
from canopy.model.forest import Forest, edges_from_pairs
from canopy.store import write


def st_connected(forest: Forest, pairs: DataFrame) -> DataFrame:
    """``(s, t, connected)`` for ``pairs(s, t)`` by component labels."""
    c = write(components(forest), "components").df
    a = c.select(F.col("id").alias("s"), F.col("component").alias("cs"))
    b = c.select(F.col("id").alias("t"), F.col("component").alias("ct"))
    return pairs.join(a, "s").join(b, "t").select("s", "t", (F.col("cs") == F.col("ct")).alias("connected"))


def cycle_count(pairs: DataFrame) -> DataFrame:
    """``(nodes, cycles)`` of a union of cycles by star contraction."""
    c = star_components(pairs)
    return c.agg(F.count(F.lit(1)).alias("nodes"), F.count_distinct("component").alias("cycles"))


def shrink_cycles(pairs: DataFrame, d: int, seed: int = 1, target: int = 64, ledger: Ledger | None = None) -> tuple[DataFrame, list[dict]]:
    """Replace the paths between sampled anchors by single edges, until at most ``target`` nodes are left.

    Anchors are the nodes with hash mod ``d`` = 0; every cycle must hold one (checked: a cycle
    without an anchor keeps its smallest id as one).  The report has, for each round, nodes before and
    after and the longest path.
    """
    from canopy.components.shrink import coefficients, poly_hash

    edges = write(edges_from_pairs(pairs), "cycles").df
    report = []
    for k in range(64):
        ids = write(edges.select(F.col("src").alias("id")).distinct(), "ids").df
        n = ids.count()
        if n <= target:
            break
        anchor = ids.filter(F.pmod(poly_hash(F.col("id"), coefficients(seed + k)), F.lit(d)) == 0)
        anchor = write(anchor, "anchors").df
        a_src, a_dst = anchor.select(F.col("id").alias("src")), anchor.select(F.col("id").alias("dst"))
        rest = write(edges.join(a_src, "src", "left_anti").join(a_dst, "dst", "left_anti").select("src", "dst"), "rest").df
        inner = ids.join(anchor, "id", "left_anti")
        # a component of the rest in which every node keeps two neighbours is a whole cycle
        comp = write(star_components(rest.unionByName(inner.select(F.col("id").alias("src"), F.col("id").alias("dst"))), "src", "dst"), "paths").df
        border = edges.join(a_dst, "dst", "left_semi").join(a_src, "src", "left_anti").select(F.col("src").alias("id"), F.col("dst").alias("anchor"))
        ends = comp.join(border, "id").groupBy("component").agg(F.min("anchor").alias("src"), F.max("anchor").alias("dst"))
        whole = comp.select("component").distinct().join(ends, "component", "left_anti")
        longest = comp.groupBy("component").count().agg(F.max("count")).first()[0] or 0
        direct = edges.join(a_src, "src", "left_semi").join(a_dst, "dst", "left_semi")
        bridged = ends.select("src", "dst").unionByName(ends.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
        kept = whole.select(F.col("component").alias("src"), F.col("component").alias("dst"))
        edges = write(direct.unionByName(bridged).unionByName(kept).distinct(), "cycles").df
        after = edges.select("src").distinct().count()
        report.append({"before": n, "after": after, "longest": longest})
        if ledger is not None:
            ledger.add("cycles", "anchors", iter=k, rows_in=n, rows_out=after, max_per_key=longest)
        if after >= n:
            break
    return edges, report



"""Is it a forest?  Every component must have one edge less than nodes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.components.fallback import star_components


class ForestError(ValueError):
    pass


def defects(pairs: DataFrame) -> DataFrame:
    """``(component, nodes, edges)`` of components of ``pairs(a, b)`` that hold a cycle, a loop or a parallel edge."""
    p = pairs.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).filter("a is not null and b is not null")
    comp = star_components(p)
    nodes = comp.groupBy("component").agg(F.count(F.lit(1)).alias("nodes"))
    edges = p.join(comp, p.a == comp.id).groupBy("component").agg(F.count(F.lit(1)).alias("edges"))
    return nodes.join(edges, "component").filter("edges >= nodes")


def validate_forest(pairs: DataFrame) -> DataFrame:
    """``pairs`` itself, if it is a forest."""
    bad = defects(pairs).limit(5).collect()
    if bad:
        raise ForestError(f"not a forest: components {[r['component'] for r in bad]} have cycles")
    return pairs

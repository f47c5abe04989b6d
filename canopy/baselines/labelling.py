"""Labelling baselines: rake and compress, gather everything, independent sets by colour reduction, unstable sets."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.components.fallback import star_components
from canopy.components.shrink import shrink
from canopy.ledger import Ledger
from canopy.lcl.problem import LclProblem
from canopy.lcl.solve import solve_lcl
from canopy.model.forest import Forest
from canopy.store import write


def lcl_rake_compress(forest: Forest, problem: LclProblem, given: DataFrame | None = None, ledger: Ledger | None = None):
    """Only leaves are folded, paths packed: O(log n) phases."""
    return solve_lcl(forest, problem, given, cap=1, ledger=ledger)


def lcl_gather(forest: Forest, problem: LclProblem, given: DataFrame | None = None, limit: int = 200_000):
    """Every tree in one group; refuses trees above ``limit`` nodes (that is the point of the baseline)."""
    comp = star_components(forest.edges, "src", "dst").groupBy("component").count().agg(F.max("count")).first()[0] or 0
    if comp > limit:
        raise MemoryError(f"a tree of {comp} nodes would have to be gathered")
    return solve_lcl(forest, problem, given, cap=limit)


def mis_colour_reduction(chain: DataFrame, ledger: Ledger | None = None) -> DataFrame:
    """Maximal independent set ``(id)`` on directed paths ``chain(id, next)`` by reducing id colours to six, then greedily by class.

    Each reduction compares a colour with the successor's: the lowest differing bit and its value; O(log* n) rounds.
    """
    at = write(chain.select("id", "next", F.col("id").alias("c")), "colours").df
    for k in range(8):
        top = at.agg(F.max("c")).first()[0] or 0
        if top < 6:
            break
        nxt = at.select(F.col("id").alias("next"), F.col("c").alias("d"))
        j = at.join(nxt, "next", "left")
        d = F.coalesce("d", F.col("c").bitwiseXOR(F.lit(1)))
        diff = F.col("c").bitwiseXOR(d)
        low = F.log2(diff.bitwiseAND(-diff).cast("double")).cast("int")
        bit = F.call_function("shiftright", F.col("c"), low).bitwiseAND(F.lit(1))
        at = write(j.select("id", "next", (low * 2 + bit).cast("long").alias("c")), "colours").df
        if ledger is not None:
            ledger.add("colour reduction", "round", iter=k)
    inside = at.sparkSession.createDataFrame([], "id long")
    for colour in range(6):
        back = at.select(F.col("next").alias("id"), F.col("id").alias("before"))
        mine = at.filter(F.col("c") == colour).select("id", "next").join(back, "id", "left")
        a = inside.select(F.col("id").alias("next"), F.lit(1).alias("x"))
        b = inside.select(F.col("id").alias("before"), F.lit(1).alias("y"))
        free = mine.join(a, "next", "left").join(b, "before", "left").filter("x is null and y is null").select("id")
        inside = write(inside.unionByName(free), "inside").df
        if ledger is not None:
            ledger.add("colour reduction", "class", iter=colour)
    return inside


def contract_until_small(forest: Forest, target: int = 1000, ledger: Ledger | None = None) -> DataFrame:
    """Shrink until few nodes are left, finish those by star contraction: rounds depend on n, not on the diameter only."""
    from canopy.components.shrink import replay

    nodes = write(forest.nodes.withColumn("best", F.col("id")), "nodes").df
    s = shrink(nodes, write(forest.edges, "edges").df, 10_000, stop_at=target, ledger=ledger)
    rest = star_components(s.edges, "src", "dst")
    top = s.nodes.join(rest, "id", "left").withColumn("component", F.coalesce("component", "id"))
    best = top.groupBy("component").agg(F.max("best").alias("top"))
    answers = write(top.join(best, "component").select("id", F.col("top").alias("best")), "answers").df
    return replay(s.folds, answers).select("id", F.col("best").alias("component"))

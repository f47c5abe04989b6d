"""What the forest methods are compared with; all give the same answers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy import views as V
from canopy.components.shrink import replay, shrink
from canopy.ledger import Ledger
from canopy.model.forest import Forest
from canopy.store import write


def flood_max(forest: Forest, ledger: Ledger | None = None, rounds: int = 100_000) -> DataFrame:
    """Everyone takes the largest label of its neighbours: a round for each hop of the diameter."""
    at = write(forest.nodes.select("id", F.col("id").alias("component")), "flood").df
    for k in range(rounds):
        near = forest.edges.join(at.select(F.col("id").alias("dst"), "component"), "dst").groupBy(F.col("src").alias("id")).agg(F.max("component").alias("n"))
        new = write(at.join(near, "id", "left").select("id", F.greatest("component", F.coalesce("n", "component")).alias("component")), "flood").df
        if ledger is not None:
            ledger.add("flood", "round", iter=k, rounds=2)
        changed = new.join(at.withColumnRenamed("component", "old"), "id").filter("component <> old").isEmpty()
        at = new
        if changed:
            break
    return at


def peel(forest: Forest, ledger: Ledger | None = None) -> DataFrame:
    """Leaves only, layer by layer: O(diameter) rounds; answers replayed."""
    nodes, edges = write(forest.nodes.withColumn("best", F.col("id")), "nodes").df, write(forest.edges, "edges").df
    folds, k = [], 0
    while not edges.isEmpty():
        info = edges.groupBy(F.col("src").alias("node")).agg(F.count(F.lit(1)).alias("deg"), F.min("dst").alias("into"))
        leaves = info.filter("deg = 1")
        pair = leaves.groupBy(F.least("node", "into").alias("a"), F.greatest("node", "into").alias("b")).agg(F.max("node").alias("node"), F.min("into").alias("into"), F.count(F.lit(1)).alias("c"))
        acts = write(pair.select("node", F.when(F.col("c") == 2, F.col("a")).otherwise(F.col("into")).alias("into")), "leaves").df
        both = acts.select(F.col("node").alias("src"), F.col("into").alias("dst")).unionByName(acts.select(F.col("into").alias("src"), F.col("node").alias("dst")))
        edges = write(edges.join(both, ["src", "dst"], "left_anti"), "edges").df
        m = acts.select(F.col("node").alias("id"), "into")
        nodes = write(nodes.join(m, "id", "left").groupBy(F.coalesce("into", "id").alias("id")).agg(F.max("best").alias("best")), "nodes").df
        folds.append(acts)
        k += 1
        if ledger is not None:
            ledger.add("peel", "layer", iter=k, rounds=3)
    return replay(folds, nodes).select("id", F.col("best").alias("component"))


def uniform_doubling(forest: Forest, ledger: Ledger | None = None, radius: int | None = None, row_cap: int | None = None) -> DataFrame:
    """Everyone doubles in all directions: O(log D) rounds, memory up to the sum of squared tree sizes.

    ``radius`` stops early (answers are then the maximum within 2^radius hops); ``row_cap`` raises an
    error above so many rows, where one is given.
    """
    views = write(V.start(forest.edges), "views").df
    have = views.count()
    k = 0
    while radius is None or k < radius:
        # all nodes within 2^k hops are known: those further on are seen once each, by way of the last of these
        new = write(V.grow(views.filter(F.col("dist") == 1 << k), views), "views").df
        n = have + new.count()
        k += 1
        if ledger is not None:
            ledger.add("uniform", "double", iter=k, rounds=2, rows_in=have, rows_out=n, width=5)
        views = views.unionByName(new)
        if row_cap is not None and n > row_cap:
            raise MemoryError(f"uniform doubling reached {n} rows")
        if n == have:
            break
        have = n
    top = views.groupBy(F.col("owner").alias("id")).agg(F.max("known").alias("m"))
    return forest.nodes.join(top, "id", "left").select("id", F.greatest("id", F.coalesce("m", "id")).alias("component"))


def rake_compress(forest: Forest, ledger: Ledger | None = None) -> DataFrame:
    """Rake and compress to one node for each tree: O(log n) rounds."""
    nodes = write(forest.nodes.withColumn("best", F.col("id")), "nodes").df
    s = shrink(nodes, write(forest.edges, "edges").df, 10_000, ledger=ledger)
    return replay(s.folds, s.nodes).select("id", F.col("best").alias("component"))


def broadcast_max(forest: Forest) -> DataFrame:
    """One tree only: one aggregate, sent to all."""
    top = forest.nodes.agg(F.max("id").alias("component"))
    return forest.nodes.crossJoin(F.broadcast(top))

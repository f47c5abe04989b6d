"""Root every tree at its largest id, and pointer algorithms on rooted forests."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.budget import Budget
from canopy.components.solve import Rung, climb
from canopy.ledger import Ledger
from canopy.maxid.core import Phase
from canopy.model.forest import Forest
from canopy.store import scope, unsent, write


def root_forest(
    forest: Forest, budget: Budget | None = None, ledger: Ledger | None = None, shrink_rounds: int | None = None, strategy: str = "local_minimum", steps_per_log: int = 3, first_guess: int = 16
) -> DataFrame:
    """``(id, parent, root)``; parent is null at the root, the largest id of the tree.

    One run of the components ladder: its rungs are undone from the last to the first, each giving the nodes that
    come back their place in the orientation so far.  That roots each tree at some node that is left; the path from
    there to the largest id is then turned round.  All rounds grow with the logarithm of the largest diameter.
    """
    with scope() as held:
        rungs: list[Rung] = []
        comp = write(climb(forest, budget or Budget(), ledger, shrink_rounds, strategy, steps_per_log, first_guess, rungs), "components").df
        comp = comp.withColumnRenamed("component", "root")
        at = forest.nodes.select("id", F.lit(None).cast("long").alias("parent")).limit(0)
        for r in reversed(rungs):
            if r.phases:
                live = r.phases[-1].nodes.join(r.phases[-1].edges.select(F.col("src").alias("id")), "id", "left_anti")
                done = live.select("id", F.lit(None).cast("long").alias("parent"))
                for p in reversed(r.phases):
                    done = undo_phase(done, p, ledger)
                at = at.unionByName(done)
            if r.lone is not None:
                at = at.unionByName(r.lone.select("id", F.lit(None).cast("long").alias("parent")))
            at = write(at, "parents").df
            for acts in reversed(r.acts):
                at = undo_step(at, acts, ledger)
        return held(write(unsent(turn(at, comp, ledger)).join(comp, "id").select("id", "parent", "root"), "rooted")).df


def undo_step(at: DataFrame, acts: DataFrame, ledger: Ledger | None = None) -> DataFrame:
    """``at(id, parent)`` before a step of shrinking: a raked leaf hangs on its neighbour, a spliced node takes its
    place on the edge that bridged it, in the direction that this edge has got meanwhile."""
    leaf = acts.filter("kind = 'rake'").select(F.col("node").alias("id"), F.col("into").alias("parent"))
    cut = acts.filter("kind = 'splice'").select("node", F.explode(F.array(F.struct(F.col("lo").alias("id"), F.col("hi").alias("parent")), F.struct(F.col("hi").alias("id"), F.col("lo").alias("parent")))).alias("e")).select("node", "e.id", "e.parent")
    j = at.join(cut, ["id", "parent"], "left")
    both = F.when(F.col("node").isNull(), F.array(F.struct("id", "parent"))).otherwise(F.array(F.struct("id", F.col("node").alias("parent")), F.struct(F.col("node").alias("id"), "parent")))
    out = write(j.select(F.explode(both).alias("x")).select("x.id", "x.parent").unionByName(leaf), "parents").df
    if ledger is not None:
        ledger.add("root", "undo step", rounds=1)
    return out


def undo_phase(at: DataFrame, phase: Phase, ledger: Ledger | None = None) -> DataFrame:
    """``at(id, parent)`` of finished trees before a phase of the core.

    The nodes of a contracted path point along the direction of the edge that stood for it; those of a light
    subtree point to the heavy node that it hung on; a tree without heavy nodes brings its own orientation.
    """
    if phase.runs is None and phase.trees is None:
        return at
    if phase.runs is not None:
        edge = at.filter("parent is not null").select(F.least("id", "parent").alias("lo"), F.greatest("id", "parent").alias("hi"), (F.col("id") < F.col("parent")).alias("up"))
        run = write(phase.runs.join(edge, ["lo", "hi"]), "runs").df
        inner = run.select("id", F.when(F.col("up"), F.col("to_hi")).otherwise(F.col("to_lo")).alias("parent"))
        end = run.filter("up and to_lo = lo").select(F.col("lo").alias("id"), F.col("id").alias("parent")).unionByName(run.filter("not up and to_hi = hi").select(F.col("hi").alias("id"), F.col("id").alias("parent")))
        at = at.join(unsent(end.select("id")), "id", "left_anti").unionByName(end).unionByName(inner)
    else:
        here = at.select(F.col("id").alias("into"))
        light = phase.folds.filter("kind = 'light'").join(here, "into", "left_semi").select(F.col("node").alias("id"), F.col("hop").alias("parent"))
        at = at.unionByName(light).join(phase.trees.select("id"), "id", "left_anti").unionByName(phase.trees)
    if ledger is not None:
        ledger.add("root", "undo phase", rounds=2)
    return write(at, "parents").df


def turn(at: DataFrame, comp: DataFrame, ledger: Ledger | None = None) -> DataFrame:
    """``at(id, parent)`` with each tree rooted at ``root`` of ``comp(id, root)`` in place of the node it is rooted at.

    The ancestors of a new root are marked by pointer doubling; of their edges each is turned round.
    """
    marked = write(comp.select(F.col("root").alias("id")).distinct(), "marked").df
    jump = at.filter("parent is not null").select("id", F.col("parent").alias("far"))
    while True:
        more = write(jump.join(marked, "id", "left_semi").select(F.col("far").alias("id")).distinct(), "ahead").df
        if ledger is not None:
            ledger.add("root", "turn", rounds=2)
        if more.isEmpty():
            break
        marked = write(marked.unionByName(more), "marked").df
        on = jump.select(F.col("id").alias("far"), F.col("far").alias("beyond"))
        jump = write(jump.join(on, "far").select("id", F.col("beyond").alias("far")), "jump").df
    path = at.join(marked, "id", "left_semi")
    turned = path.filter("parent is not null").select(F.col("parent").alias("id"), F.col("id").alias("parent"))
    tops = comp.select(F.col("root").alias("id")).distinct().withColumn("parent", F.lit(None).cast("long"))
    return at.join(marked, "id", "left_anti").unionByName(turned).unionByName(tops)


def root_defects(forest: Forest, rooted: DataFrame) -> DataFrame:
    """Rows that break an orientation: parent not a neighbour, no or several rows for a node, root rule, cycle."""
    e = forest.edges.select(F.col("src").alias("id"), F.col("dst").alias("parent"))
    stranger = rooted.filter("parent is not null").join(e, ["id", "parent"], "left_anti").select("id", F.lit("stranger").alias("defect"))
    missing = forest.nodes.join(rooted, "id", "left_anti").select("id", F.lit("missing").alias("defect"))
    twice = rooted.groupBy("id").count().filter("count > 1").select("id", F.lit("twice").alias("defect"))
    tops = rooted.filter("parent is null and id <> root").select("id", F.lit("wrong root").alias("defect"))
    reach = depths(rooted.select("id", "parent"))
    lost = rooted.join(reach, "id", "left_anti").select("id", F.lit("unreached").alias("defect"))
    return stranger.unionByName(missing).unionByName(twice).unionByName(tops).unionByName(lost)


def pointers(rooted: DataFrame, rounds: int = 64, ledger: Ledger | None = None) -> DataFrame:
    """``(id, top, hops)``: the root and the distance to it, by pointer doubling; finished rows drop out.

    Rows on a cycle never finish and are left out.
    """
    live = rooted.select("id", F.col("parent").alias("top"), F.lit(1).cast("long").alias("hops"))
    done = live.filter("top is null").select("id", F.col("id").alias("top"), F.lit(0).cast("long").alias("hops"))
    parts = [write(done, "pointers").df]
    live = write(live.filter("top is not null"), "live").df
    finished = parts[0]
    for k in range(rounds):
        if live.isEmpty():
            break
        if ledger is not None:
            ledger.add("pointers", "double", iter=k, rows_in=live.count())
        # a target that is finished ends the walk, a live one is jumped over
        end = live.join(finished.select(F.col("id").alias("top"), F.col("top").alias("t"), F.col("hops").alias("h")), "top").select("id", F.col("t").alias("top"), (F.col("hops") + F.col("h")).alias("hops"))
        end = write(end, "pointers").df
        on = live.select(F.col("id").alias("top"), F.col("top").alias("t"), F.col("hops").alias("h"))
        nxt = write(live.join(on, "top").select("id", F.col("t").alias("top"), (F.col("hops") + F.col("h")).alias("hops")), "live").df
        finished = write(finished.unionByName(end), "finished").df
        if end.isEmpty() and k > 40:
            break
        live = nxt
    return finished


def depths(rooted: DataFrame, ledger: Ledger | None = None) -> DataFrame:
    """``(id, depth)``."""
    return pointers(rooted, ledger=ledger).select("id", F.col("hops").alias("depth"))


def two_colour(rooted: DataFrame, ledger: Ledger | None = None) -> DataFrame:
    """``(id, colour)``: parity of the distance to the root."""
    return pointers(rooted, ledger=ledger).select("id", F.pmod("hops", F.lit(2)).alias("colour"))


def ancestor_pow(rooted: DataFrame, k: int) -> DataFrame:
    """``(id, ancestor)``: the 2^k-th ancestor, null above the root."""
    at = rooted.select("id", F.col("parent").alias("ancestor"))
    for _ in range(k):
        nxt = at.select(F.col("id").alias("ancestor"), F.col("ancestor").alias("beyond"))
        at = at.join(nxt, "ancestor", "left").select("id", F.col("beyond").alias("ancestor"))
    return at

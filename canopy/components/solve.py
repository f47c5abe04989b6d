"""Components of a forest, diameter unknown: a ladder of guesses over shrink, core, replay."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.budget import Budget
from canopy.components.fallback import star_components
from canopy.components.shrink import replay, shrink
from canopy.ledger import Ledger
from canopy.maxid.core import Phase, max_id
from canopy.model.forest import Forest
from canopy.store import scope, write


def guess_ladder(cap: int, first: int = 4) -> list[int]:
    """Squares from ``first`` on up to ``cap``, which is the last rung if no square hits it."""
    out, g = [], first
    while g < cap:
        out.append(g)
        g *= g
    return [*out, cap]


def failed_components(answers: DataFrame) -> DataFrame:
    """Ids that a guess has left without an answer."""
    return answers.filter("best is null").select("id")


def components_fallback(forest: Forest) -> DataFrame:
    """``(id, component)`` by star contraction, component = largest id; used above the last guess."""
    c = star_components(forest.edges, "src", "dst").withColumnRenamed("component", "low")
    top = c.groupBy("low").agg(F.max("id").alias("component"))
    joined = forest.nodes.join(c, "id", "left").join(top, "low", "left")
    return joined.select("id", F.coalesce("component", "id").alias("component"))


def components(
    forest: Forest, budget: Budget | None = None, ledger: Ledger | None = None, shrink_rounds: int | None = None, strategy: str = "local_minimum", steps_per_log: int = 3, first_guess: int = 16
) -> DataFrame:
    """``(id, component)``: every node with the largest id of its tree.

    For each guess the forest left over is shrunk by ``steps_per_log * log2(guess)`` steps, and
    by some more while live nodes times guess^3 don't fit the memory; then the core runs on the
    residue.  Trees that it can't finish within the guess go to the next one and, above the last
    one, to the fallback.  One replay carries all answers back.  The ladder starts at ``first_guess``;
    ``shrink_rounds`` fixes the steps of a rung (0 leaves shrinking out).
    """
    with scope() as held:
        return held(write(climb(forest, budget or Budget(), ledger, shrink_rounds, strategy, steps_per_log, first_guess), "components")).df


@dataclass
class Rung:
    """What a rung did to the forest, in the order of the fields."""

    acts: list[DataFrame]  # steps of shrinking
    lone: DataFrame | None = None  # id: trees of one node after these
    phases: list[Phase] = field(default_factory=list)  # of the core


def climb(
    forest: Forest, budget: Budget, ledger: Ledger | None = None, shrink_rounds: int | None = None, strategy: str = "local_minimum", steps_per_log: int = 3, first_guess: int = 16, history: list[Rung] | None = None
) -> DataFrame:
    """The ladder itself; with a ``history``, which takes its rungs, trees above the last guess are shrunk to one node."""
    nodes = write(forest.nodes.withColumn("best", F.col("id")), "nodes").df
    edges = write(forest.edges, "edges").df
    folds: list[DataFrame] = []
    step = 0
    answered: list[DataFrame] = []
    for guess in guess_ladder(budget.light_cap, min(first_guess, budget.light_cap)):
        if edges.isEmpty():
            break
        rounds = steps_per_log * max(1, (guess - 1).bit_length()) if shrink_rounds is None else shrink_rounds
        taken: list[DataFrame] = []
        for extra in range(2 if shrink_rounds is None else 1):
            if not rounds or (extra and edges.select("src").distinct().count() * guess**3 <= budget.memory_words):
                break
            s = shrink(nodes, edges, rounds, step, ledger=ledger, strategy=strategy)
            nodes, edges, step = s.nodes, s.edges, step + s.steps
            folds += s.folds
            taken += s.folds
            if edges.isEmpty():
                break
        if history is not None:
            history.append(Rung(taken))
        if edges.isEmpty():
            break
        live = edges.select(F.col("src").alias("id")).distinct()
        lone = nodes.join(live, "id", "left_anti")
        answered.append(write(lone, "answers").df)
        phases: list[Phase] = []
        got = write(max_id(nodes.join(live, "id", "left_semi"), edges, guess, budget, ledger=ledger, history=phases), "core").df
        answered.append(got.filter("best is not null"))
        open_ = write(failed_components(got), "open").df
        if history is not None:
            history[-1] = Rung(taken, answered[-2].select("id"), phases)
        if ledger is not None:
            ledger.add("ladder", f"guess {guess}", rounds=0, rows_in=got.count(), rows_out=open_.count())
        nodes = nodes.join(open_, "id", "left_semi")
        edges = write(edges.join(open_.select(F.col("id").alias("src")), "src", "left_semi"), "edges").df
        nodes = write(nodes, "nodes").df
    if history is not None and not edges.isEmpty():
        s = shrink(nodes, edges, 10_000, step, ledger=ledger, strategy=strategy)
        nodes, edges = s.nodes, s.edges
        folds += s.folds
        history.append(Rung(s.folds))
        if not edges.isEmpty():
            raise RuntimeError("edges are left after 10,000 steps")
    if not edges.isEmpty():
        c = components_fallback(Forest(nodes.select("id"), edges))
        top = nodes.join(c, "id").groupBy("component").agg(F.max("best").alias("best"))
        answered.append(c.join(top, "component").select("id", "best"))
    else:
        answered.append(nodes)
    answers = answered[0]
    for a in answered[1:]:
        answers = answers.unionByName(a)
    answers = write(answers.groupBy("id").agg(F.max("best").alias("best")), "answers").df
    if history is not None:
        history.append(Rung([], nodes.select("id")))
    return replay(folds, answers).select("id", F.col("best").alias("component"))


def check_stability(forest: Forest, extra: Forest, solve=components) -> int:
    """Rows whose answer changes when a disjoint forest is added; a stable solver gives 0."""
    one = solve(forest)
    both = solve(Forest(forest.nodes.unionByName(extra.nodes), forest.edges.unionByName(extra.edges)))
    return one.exceptAll(both.join(forest.nodes, "id", "left_semi").select(*one.columns)).count()

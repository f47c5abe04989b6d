"""Experiments on costs: how rounds and words move with diameter, size and parameters."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy import baselines, workloads
from canopy import views as V
from canopy.budget import Budget
from canopy.components.solve import components
from canopy.ledger import Ledger
from canopy.maxid.core import absorb_light, max_id
from canopy.model.forest import Forest
from canopy.rooting import pointers


def rounds_by_diameter(spark, sf_dir: str, lengths=(4, 8, 16, 32)) -> DataFrame:
    """``(length, method, rounds, peak_words)`` on paths of exactly ``length`` nodes."""
    rows = []
    for n in lengths:
        f = workloads.event_cut(spark, sf_dir, n).kept()
        for name, run in (
            ("flood", lambda ledger: baselines.flood_max(f, ledger)),
            ("peel", lambda ledger: baselines.peel(f, ledger)),
            ("uniform", lambda ledger: baselines.uniform_doubling(f, ledger)),
            ("shrink", lambda ledger: components(f, ledger=ledger)),
            ("core", lambda ledger: max_id(f.nodes, f.edges, n, Budget(max(n, 4)), ledger=ledger)),
        ):
            ledger = Ledger()
            run(ledger)
            rows.append((n, name, len([r for r in ledger.rows if r[4]]), ledger.peak_words()))
    return spark.createDataFrame(rows, "length int, method string, rounds int, peak_words long")


def slope(points: list[tuple[float, float]]) -> float:
    """Least-squares slope."""
    n = len(points)
    mx, my = sum(x for x, _ in points) / n, sum(y for _, y in points) / n
    return sum((x - mx) * (y - my) for x, y in points) / sum((x - mx) ** 2 for x, _ in points)


def view_bounds(views: DataFrame, cap: int, guess: int) -> DataFrame:
    """``(widest, bound, broken)``: the widest view against the largest size that any case allows."""
    bound = max(2 * cap**2 + (cap + 1) * cap * guess, cap + 2 * cap**2)
    return views.groupBy("owner").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n").alias("widest"), F.count_if(F.col("n") > bound).alias("broken")).withColumn("bound", F.lit(bound).cast("long"))


def probe_sandwich(forest: Forest, steps: int, guess: int) -> DataFrame:
    """``(directions, broken)``: estimates of each direction against what a growth really brings, true <= estimate <= guess * true."""
    v = V.start(forest.edges)
    for _ in range(steps):
        v = V.distinct_rows(v.unionByName(V.grow(v, v)))
    est = V.estimates(v)
    new = V.grow(v, v).groupBy("owner", "first_hop").agg(F.count_distinct("known").alias("true"))
    j = est.join(new, ["owner", "first_hop"], "left").withColumn("true", F.coalesce("true", F.lit(0)))
    return j.agg(F.count(F.lit(1)).alias("directions"), F.count_if((F.col("est") < F.col("true")) | (F.col("est") > guess * F.col("true"))).alias("broken"))


def phase_report(forest: Forest, guess: int, cap: int) -> dict:
    """Duplicate spike, iterations and survivors of one absorbing phase, with the shrink factor's bound."""
    f = forest.kept()
    a = absorb_light(f.nodes.withColumn("best", F.col("id")), f.edges, guess, Budget(cap))
    n, left = f.nodes.count(), a.nodes.count()
    return {"nodes": n, "left": left, "factor": n / max(1, left), "bound": 1 + cap / 2, "spike": a.report["spike"], "iterations": a.report["iterations"], "limit": math.ceil(math.log(max(2, guess)) / math.log(4 / 3)) + 2}


def pointer_rounds(parents: DataFrame) -> int:
    ledger = Ledger()
    pointers(parents, ledger=ledger).count()
    return ledger.rounds()


def exchanges(df: DataFrame) -> int:
    """Shuffle exchanges in the physical plan of ``df`` (broadcasts not counted)."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return sum("Exchange " in line and "BroadcastExchange" not in line for line in plan.splitlines())


def skew(df: DataFrame, key: str) -> DataFrame:
    """``(keys, most, median)`` rows of a key: what one task may get."""
    g = df.groupBy(key).agg(F.count(F.lit(1)).alias("n"))
    return g.agg(F.count(F.lit(1)).alias("keys"), F.max("n").alias("most"), F.expr("percentile_disc(0.5) within group (order by n)").cast("long").alias("median"))

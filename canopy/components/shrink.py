"""Shrink a forest by independent nodes of degree at most two, and replay.

One step acts on an independent set: every leaf hangs on its neighbour (of two adjacent
leaves the higher id does), and degree-2 nodes without an acting neighbour are spliced
out where their hash is smaller than that of their degree-2 neighbours.  A removed node
remembers the node that it went into; spliced nodes also remember their two ends.

Costs of a step: one aggregate of the live edges, two joins against nodes of degree <= 2,
one anti join.  Replay follows the chains "node went into" by pointer doubling, so it takes
log2(steps) joins and not one for each step.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from canopy.ledger import Ledger
from canopy.store import Cut, unsent, write

#: A prime above any 31-bit residue, for the polynomial hash family.
PRIME = 2_147_483_647


def poly_hash(ident: Column, coefficients: tuple[int, ...]) -> Column:
    """A member of the k-wise independent family: a polynomial modulo a prime, k = number of coefficients."""
    x = F.pmod(ident, F.lit(PRIME))
    out = F.lit(0).cast("long")
    for c in coefficients:
        out = F.pmod(out * x + F.lit(c), F.lit(PRIME))
    return out


def coefficients(seed: int, k: int = 3) -> tuple[int, ...]:
    """Coefficients of the family member of a seed (a linear congruential walk)."""
    out, x = [], seed * 2_654_435_761 + 12_345
    for _ in range(k):
        x = (x * 6_364_136_223_846_793_005 + 1_442_695_040_888_963_407) % (1 << 64)
        out.append((x >> 33) % PRIME)
    return tuple(out)


def sparse_independent(two: DataFrame, strategy: str = "coin", seed: int = 1, seeds: int = 8) -> DataFrame:
    """Independent ids among ``two(id, lo, hi)``, the degree-2 nodes with their neighbours.

    ``coin``: a node is kept if its coin shows 1 and its neighbours' show 0 (an eighth on average, 3-wise
    independent).  ``seed_search``: the best of several seeds by one aggregate.  ``conditional``: a seed fixed
    piece by piece so that the expected number never falls, an eighth at least; ``two`` may have a column ``g``
    (component), then each component has a seed of its own.
    ``local_minimum``: a node is kept if its hash is below its neighbours' (a third on average).
    """
    if strategy == "seed_search":
        tried = range(seed, seed + seeds)
        counts = two.agg(*[F.count_if(picked("coin", s)).alias(str(s)) for s in tried], F.count(F.lit(1)).alias("n")).first()
        best = max(tried, key=lambda s: (counts[str(s)], -s))
        return two.filter(picked("coin", best)).select("id")
    if strategy == "conditional":
        t = two if "g" in two.columns else two.withColumn("g", F.lit(0).cast("long"))
        found = write(fixed_seeds(t), "seeds").df
        one = lambda c: f"(bit_count({c} & seed) + flip) % 2"
        return t.join(found, "g").filter(f"{one('id')} = 1 and {one('lo')} = 0 and {one('hi')} = 0").select("id")
    return two.filter(picked(strategy, seed)).select("id")


def picked(strategy: str, seed: int) -> Column:
    """Whether a row ``(id, lo, hi)`` is picked by a strategy that needs no aggregate."""
    if strategy == "coin":
        coin = lambda c: F.pmod(F.shiftright(poly_hash(F.col(c), coefficients(seed)), 7), F.lit(2))
        return (coin("id") == 1) & (coin("lo") == 0) & (coin("hi") == 0)
    if strategy == "local_minimum":
        h = lambda c: F.struct(poly_hash(F.col(c), coefficients(seed)), F.col(c))
        return (h("id") < h("lo")) & (h("id") < h("hi"))
    raise ValueError(strategy)


def fixed_seeds(two: DataFrame, piece: int = 4) -> DataFrame:
    """``(g, seed, flip)``: for each group of ``two(g, id, lo, hi)`` a seed that keeps an eighth of its rows at least.

    The coin of x is the parity of ``x & seed``, plus ``flip``: for three different ids these are
    independent bits over random seeds.  Seed bits are fixed ``piece`` at a time, each time
    to the value with the largest expected number of kept rows given the bits fixed so far; the number is
    exact, because it depends only on which of the three ids agree in the bits still open.
    """
    t = write(two.select("g", "id", "lo", "hi"), "twos").df
    row = t.agg(F.min(F.least("id", "lo", "hi")), F.max(F.greatest("id", "lo", "hi"))).first()
    bits = 0 if row[1] is None else 64 if row[0] < 0 else max(1, int(row[1]).bit_length())
    seeds = write(t.groupBy("g").agg(F.lit(0).cast("long").alias("seed")), "seeds").df
    for low in range(0, bits, piece):
        top = min(low + piece, bits)
        rest = lambda c: f"shiftrightunsigned({c}, {top})" if top < 64 else "0L"
        rows = t.join(seeds, "g").selectExpr(
            "g", "seed", "id", "lo", "hi", f"{rest('id')} = {rest('lo')} as xy", f"{rest('id')} = {rest('hi')} as xz", f"{rest('lo')} = {rest('hi')} as yz"
        )
        sums = []
        for v in range(1 << (top - low)):
            add = (v << low) - (1 << 64 if (v << low) >> 63 else 0)
            odd = lambda c: f"bit_count({c} & (seed | {add}L)) % 2"
            differ = lambda a, b: f"({odd(a)} <> {odd(b)})"
            # eight times the probability that the coins show 1, 0, 0
            e = f"""case when xy and yz then if({differ('id', 'lo')} and not {differ('lo', 'hi')}, 4, 0)
                when yz then if({differ('lo', 'hi')}, 0, 2) when xy then if({differ('id', 'lo')}, 2, 0)
                when xz then if({differ('id', 'hi')}, 2, 0) else 1 end"""
            sums.append(F.struct(F.sum(F.expr(e)).alias("e"), F.lit(add).cast("long").alias("v")))
        seeds = write(rows.groupBy("g").agg(F.first("seed").alias("seed"), F.array_max(F.array(*sums))["v"].alias("v")).selectExpr("g", "seed | v as seed"), "seeds").df
    one = lambda c, flip: f"(bit_count({c} & seed) + {flip}) % 2"
    kept = lambda flip: F.count_if(F.expr(f"{one('id', flip)} = 1 and {one('lo', flip)} = 0 and {one('hi', flip)} = 0"))
    return t.join(seeds, "g").groupBy("g").agg(F.first("seed").alias("seed"), F.when(kept(1) > kept(0), 1).otherwise(0).alias("flip"))


@dataclass
class Shrunk:
    nodes: DataFrame  # id, best: live nodes
    edges: DataFrame
    folds: list[DataFrame]  # step, kind, node, into, lo, hi
    live: int
    steps: int


def actions(edges: DataFrame, step: int, strategy: str = "local_minimum", protect: DataFrame | None = None) -> DataFrame:
    """``(step, kind, node, into, lo, hi)``: what one step removes; ids in ``protect(id)`` never act."""
    info = edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("deg"), F.min("dst").alias("lo"), F.max("dst").alias("hi"))
    small = info.filter("deg <= 2")
    if protect is not None:
        small = write(small.join(protect, "id", "left_anti"), "small").df
    ask = small.select("id", "deg", "lo", "hi", F.explode(F.array_distinct(F.array("lo", "hi"))).alias("nbr"))
    other = small.select(F.col("id").alias("nbr"), F.col("deg").alias("ndeg"))
    seen = ask.join(other, "nbr", "left").groupBy("id", "deg", "lo", "hi").agg(F.max(F.when(F.col("ndeg") == 1, F.col("nbr"))).alias("leaf"))
    rake = F.expr("deg = 1 and (leaf is null or id > leaf)")
    middle = F.expr("deg = 2 and leaf is null")
    if strategy in ("coin", "local_minimum"):
        kept = middle & picked(strategy, step + 1)
    else:
        seen = write(seen, "seen").df
        chosen = sparse_independent(seen.filter(middle).select("id", "lo", "hi"), strategy, seed=step + 1).withColumn("chosen", F.lit(True))
        seen = seen.join(chosen, "id", "left")
        kept = middle & F.coalesce("chosen", F.lit(False))
    acts = seen.filter(rake | kept).select(F.when(rake, "rake").otherwise("splice").alias("kind"), F.col("id").alias("node"), F.when(rake, F.col("lo")).otherwise(F.greatest("lo", "hi")).alias("into"), "lo", "hi")
    return acts.select(F.lit(step).alias("step"), "*")


def apply_actions(nodes: DataFrame, edges: DataFrame, acts: DataFrame) -> tuple[Cut, Cut]:
    """Nodes and edges after the written actions; the bests of removed nodes go to where these went."""
    gone = acts.select(F.explode(F.array(F.struct("node", F.col("lo").alias("other")), F.struct("node", F.col("hi").alias("other")))).alias("x")).select("x.*")
    both = gone.select(F.col("node").alias("src"), F.col("other").alias("dst")).unionByName(gone.select(F.col("other").alias("src"), F.col("node").alias("dst")))
    bridge = acts.filter("kind = 'splice'").select(F.explode(F.array(F.struct(F.col("lo").alias("src"), F.col("hi").alias("dst")), F.struct(F.col("hi").alias("src"), F.col("lo").alias("dst")))).alias("x")).select("x.*")
    new_edges = write(edges.join(unsent(both.distinct()), ["src", "dst"], "left_anti").unionByName(bridge), "edges")
    moved = nodes.join(acts.select(F.col("node").alias("id"), "into"), "id", "left")
    new_nodes = write(moved.groupBy(F.coalesce("into", "id").alias("id")).agg(F.max("best").alias("best")), "nodes")
    return new_nodes, new_edges


def shrink(nodes: DataFrame, edges: DataFrame, steps: int, first_step: int = 0, stop_at: int = 0, ledger: Ledger | None = None, strategy: str = "local_minimum", protect: DataFrame | None = None) -> Shrunk:
    """Up to ``steps`` steps, fewer if nothing is left or the live edges' nodes fit ``stop_at``."""
    folds, live, done = [], -1, 0
    for k in range(first_step, first_step + steps):
        acts = write(actions(edges, k, strategy, protect), "folds")
        n = acts.df.count()
        if not n:
            break
        new_nodes, new_edges = apply_actions(nodes, edges, acts.df)
        nodes, edges = new_nodes.df, new_edges.df
        folds.append(acts.df)
        done += 1
        live = edges.select("src").distinct().count() if stop_at else (0 if edges.isEmpty() else -1)
        if ledger is not None:
            ledger.add("shrink", "step", iter=k, rounds=4, rows_in=n, rows_out=max(live, 0))
        if live == 0 or 0 <= live <= stop_at:
            break
    return Shrunk(nodes, edges, folds, live, done)


def replay(folds: list[DataFrame], answers: DataFrame) -> DataFrame:
    """``answers(id, best)`` of live nodes carried to all removed ones along "went into" chains."""
    if not folds:
        return answers
    all_ = folds[0].select("node", "into")
    for f in folds[1:]:
        all_ = all_.unionByName(f.select("node", "into"))
    at = write(all_, "into").df
    for _ in range(max(1, (len(folds) - 1).bit_length())):
        nxt = at.select(F.col("node").alias("into"), F.col("into").alias("beyond"))
        at = write(at.join(nxt, "into", "left").select("node", F.coalesce("beyond", "into").alias("into")), "into").df
    carried = at.join(answers.select(F.col("id").alias("into"), "best"), "into").select(F.col("node").alias("id"), "best")
    return answers.select("id", "best").unionByName(carried)

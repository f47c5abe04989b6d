"""Labelling problems: verdicts and solutions against enumeration."""

import itertools
import random

import pytest
from pyspark.sql import functions as F

from canopy import workloads
from canopy.lcl import problem as P
from canopy.lcl.sizing import gather_light, mark_local_roots, mis_level, path_distances, subtree_sizes
from canopy.lcl.solve import product, solve_lcl
from canopy.model import literal
from canopy.rooting import root_forest


def solvable(pairs, ids, p, given):
    near = {i: [] for i in ids}
    for k, (a, b) in enumerate(pairs):
        near[a].append((k, 0))
        near[b].append((k, 1))
    for lab in itertools.product(range(p.labels), repeat=2 * len(pairs)):
        if all(p.edge_ok(lab[2 * k], lab[2 * k + 1]) for k in range(len(pairs))) and all(p.node(tuple(sorted(lab[2 * k + s] for k, s in near[i])), given.get(i, 0)) for i in ids):
            return True
    return False


@pytest.mark.parametrize("problem", [P.independent_set(), P.matching(), P.colouring(2)])
def test_solutions(spark, problem):
    f = workloads.shapes(spark, "caterpillar", 40).kept()
    labels, none = solve_lcl(f, problem, cap=4)
    labels = labels.cache()
    assert labels.count() == 78 and none.isEmpty() and P.violations(problem, f.edges, labels).isEmpty()


def test_verdicts_by_enumeration(spark):
    rnd = random.Random(3)
    pairs, ids, given, want = [], [], {}, {}
    for t in range(8):
        n = rnd.randint(2, 6)
        tree = [(100 * t + k, 100 * t + rnd.randrange(k)) for k in range(1, n)]
        own = [100 * t + k for k in range(n)]
        marks = {i: rnd.choice([0, 0, 1, 2]) for i in own}
        pairs += tree
        ids += own
        given |= marks
        want[max(own)] = solvable(tree, own, P.precoloured(), marks)
    assert len(set(want.values())) == 2
    f = literal(spark, pairs, ids).kept()
    g = spark.createDataFrame(list(given.items()), "id long, given int")
    labels, none = solve_lcl(f, P.precoloured(), g, cap=2)
    bad = {r.component for r in none.collect()}
    assert bad == {c for c, ok in want.items() if not ok}
    broken = {r.id // 100 for r in P.violations(P.precoloured(), f.edges, labels, g).collect()}
    assert broken == {c // 100 for c in bad}
    labels, none = solve_lcl(f, P.precoloured(), g, cap=2, scope="graph")
    assert labels.isEmpty() and none.count() == 8


def test_odd_out_degree_never(spark):
    f = workloads.shapes(spark, "spider", 14).kept()
    labels, none = solve_lcl(f, P.odd_out_degree(), cap=3)
    assert labels.isEmpty() and none.count() == 1


def test_degree_limit(spark):
    with pytest.raises(ValueError):
        solve_lcl(workloads.shapes(spark, "star", 12), P.matching())


def test_product(spark):
    rnd = random.Random(1)
    rows = [(rnd.getrandbits(49), rnd.getrandbits(49)) for _ in range(30)]
    got = spark.createDataFrame(rows, "a long, b long").select("a", "b", product(F.col("a"), F.col("b")).alias("c")).collect()
    bit = lambda m, i, j: m >> (7 * i + j) & 1
    for r in got:
        assert r.c == sum(1 << (7 * i + j) for i in range(7) for j in range(7) if any(bit(r.a, i, k) and bit(r.b, k, j) for k in range(7)))


def test_sizes_and_hosts(spark):
    pairs = [(1, 0), (2, 0), (3, 1), (4, 1), (5, 4), (6, 5)]
    t = spark.createDataFrame([(0, None), *pairs], "id long, parent long")
    s = subtree_sizes(t, 3)
    assert {r.id: (r.size, r.heavy) for r in s.collect()} == {0: (4, True), 1: (4, True), 2: (1, False), 3: (1, False), 4: (3, False), 5: (2, False), 6: (1, False)}
    assert {r.id for r in mark_local_roots(t, s).collect()} == {0, 1}
    assert {(r.light, r.local_root, r.child) for r in gather_light(t, s).collect()} == {(2, 0, 2), (3, 1, 3), (4, 1, 4), (5, 1, 4), (6, 1, 4)}


def test_levels(spark):
    f = workloads.shapes(spark, "path", 9)
    d = path_distances(f.edges, spark.createDataFrame([(0,)], "id long"))
    assert {r.id: r.distance for r in d.collect()} == {k: k + 1 for k in range(9)}
    level = lambda i: [k for k in range(1, 8) if k % (2 << i) and not k % (1 << i)]
    assert [level(0), level(1), level(2)] == [[1, 3, 5, 7], [2, 6], [4]]
    got = spark.range(1, 8).filter(mis_level(F.col("id"), 0)).collect()
    assert [r.id for r in got] == [1, 3, 5, 7]


def test_checker_sees_defects(spark):
    f = workloads.shapes(spark, "path", 6).kept()
    labels, _ = solve_lcl(f, P.colouring(2), rooted=root_forest(f))
    wrong = labels.withColumn("label", F.when((F.col("node") == 2) & (F.col("other") == 3), 1 - F.col("label")).otherwise(F.col("label")))
    assert not P.violations(P.colouring(2), f.edges, wrong).isEmpty()
    assert not P.violations(P.colouring(2), f.edges, labels.filter("node <> 4")).isEmpty()

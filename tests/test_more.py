"""Sources, functions, radius form, labelling baselines, cost experiments."""

import math

import pytest
from pyspark.sql import functions as F

from canopy import functions, plans, sources, streaming, workloads
from canopy.baselines import labelling
from canopy.ledger import Ledger
from canopy.lcl import problem as P
from canopy.lcl import radius
from canopy.lcl.solve import solve_lcl
from canopy.rooting import depths

D = "/root/testdata/sf0.001"


def test_source_and_layout(spark):
    sources.register(spark)
    t = spark.read.format("canopy_forest").option("n", 31).option("k", 2).load()
    assert t.count() == 31 and depths(t).agg(F.max("depth")).first()[0] == 4
    assert sources.layout(workloads.shapes(spark, "path", 50).edges, 4).rdd.getNumPartitions() <= 4


def test_functions(spark):
    functions.register(spark)
    assert [r.guess for r in spark.sql("select * from canopy_guess_ladder(300)").collect()] == [4, 16, 256, 300]
    assert len(spark.sql("select * from canopy_port_tuples(array(0, 0, 1))").collect()) == 3


def test_relay_join(spark):
    a = spark.range(1000).selectExpr("id % 3 k", "id x")
    b = spark.createDataFrame([(0, "a"), (1, "b"), (1, "c")], "k long, y string")
    hot = spark.createDataFrame([(1,)], "k long")
    got = functions.relay_join(a, b, "k", hot)
    assert sorted(map(tuple, got.select("k", "x", "y").collect())) == sorted(map(tuple, a.join(b, "k").collect()))


def test_radius_form(spark):
    f = workloads.shapes(spark, "caterpillar", 24).kept()
    p = radius.independent_set()
    half, none = solve_lcl(f, radius.to_node_edge(p), cap=4)
    labels = radius.node_labels(p, half, f.nodes).cache()
    assert none.isEmpty() and radius.check_radius(p, f.edges, labels).isEmpty()
    assert not radius.check_radius(p, f.edges, labels.withColumn("label", F.lit(1))).isEmpty()


def test_labelling_baselines(spark):
    f = workloads.shapes(spark, "path", 21).kept()
    for solve in (labelling.lcl_rake_compress, labelling.lcl_gather):
        labels, none = solve(f, P.matching())
        labels = labels.cache()
        assert none.isEmpty() and labels.count() == 40 and P.violations(P.matching(), f.edges, labels).isEmpty()
    chain = spark.range(200).selectExpr("id", "case when id < 199 then id + 1 end next")
    inside = {r.id for r in labelling.mis_colour_reduction(chain, Ledger()).collect()}
    assert all(not (i in inside and i + 1 in inside) for i in range(200))
    assert all(i in inside or i - 1 in inside or i + 1 in inside for i in range(200))
    assert {r.component for r in labelling.contract_until_small(f, 4).collect()} == {20}


def test_costs(spark):
    r = plans.phase_report(workloads.shapes(spark, "two_hubs", 40), 4, 4)
    assert r["left"] == 2 and r["factor"] >= r["bound"] and r["iterations"] <= r["limit"]
    s = plans.probe_sandwich(workloads.heap(spark, D, 2, "part"), 1, 16).first()
    assert s.directions > 0 and s.broken == 0
    a, b = (plans.pointer_rounds(spark.range(n).selectExpr("id", "case when id > 0 then id - 1 end parent")) for n in (16, 64))
    assert a <= math.log2(16) + 2 and b <= math.log2(64) + 2


def test_stream_dedup(spark):
    e = streaming.events_stream(spark, f"{D}/events.parquet")
    assert streaming.available(streaming.deduplicated(e).select("event_id")).count() == 1000


def test_plan_reports(spark):
    e = workloads.shapes(spark, "star", 30).edges
    assert plans.exchanges(spark.range(10).groupBy(F.col("id") % 3).count()) == 1 and plans.exchanges(spark.range(10)) == 0
    r = plans.skew(e, "src").first()
    assert (r.keys, r.most, r.median) == (30, 29, 1)


def test_cycles_inside_a_batch(spark):
    live = streaming.LiveComponents(spark)
    live.add(spark.createDataFrame([(1, 2), (2, 3), (3, 1), (4, 5), (4, 5), (5, 6), (7, 7)], "a long, b long"))
    assert sorted(tuple(r) for r in live.rejected.collect()) == [(3, 1), (4, 5), (7, 7)]
    live.add(spark.createDataFrame([(6, 1), (3, 4), (8, 1)], "a long, b long"))
    assert sorted(tuple(r) for r in live.rejected.collect()) == [(3, 1), (4, 5), (6, 1), (7, 7)]
    assert {tuple(r) for r in live.labels.collect()} == {(i, 7 if i == 7 else 1) for i in range(1, 9)}
    # a batch that comes again changes nothing; rows of earlier nodes stay as they were written
    live.add(spark.createDataFrame([(6, 1), (3, 4), (8, 1)], "a long, b long"), 1)
    assert live.rejected.count() == 4 and live.labels.count() == 8
    assert {tuple(r) for r in spark.read.parquet(f"{live.at}/ids/1").collect()} == {(8, 8)}


def test_compressed_tables_stay_where_they_are(spark):
    """A table that is small as a file and large as rows is not broadcast, whatever stands on the other side."""
    from canopy.store import write

    had = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "10m")
    try:
        big = write(spark.range(0, 1_500_000, 1, 2).selectExpr("id", "id div 64 as up", "0L as hops")).df
        plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
        assert int(str(big._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) < 10 << 20
        both = big.join(big.selectExpr("id as up", "hops as h"), "up")
        assert "BroadcastHashJoin" not in plan(both) and both.count() == 1_500_000
        assert "BroadcastHashJoin" in plan(big.join(spark.range(9), "id"))
        assert "BroadcastHashJoin" in plan(big.join(write(spark.range(9).toDF("id")).df, "id"))
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", had)


def sent(spark, monkeypatch, run):
    """Plans with broadcasts of what ``run`` writes, if each written table is one that only compression makes small.

    A plan with a table made from a Python list, such as the kinds of a problem, may broadcast.
    """
    import sys

    from canopy import store

    monkeypatch.setattr(store, "SMALL", 0)
    monkeypatch.setattr(store, "PACKED", 1 << 40)
    plans_, real = [], store.write

    def watch(df, name="cut"):
        plans_.append((name, df._jdf.queryExecution().executedPlan().toString()))
        return real(df, name)

    for name, m in list(sys.modules.items()):
        if name.startswith("canopy.") and getattr(m, "write", None) is real and m is not store:
            monkeypatch.setattr(m, "write", watch)
    had = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "64k")
    try:
        run()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", had)
    assert plans_
    return [(name, p) for name, p in plans_ if "BroadcastExchange" in p and "Scan ExistingRDD" not in p]


def test_shrinking_sends_no_union_of_its_tables(spark, monkeypatch):
    from canopy.components import shrink

    f = workloads.shapes(spark, "caterpillar", 300)

    def step():
        e = shrink.write(f.edges, "edges").df
        nodes = shrink.write(f.nodes.withColumn("best", F.col("id")), "nodes").df
        shrink.apply_actions(nodes, e, shrink.write(shrink.actions(e, 0), "folds").df)

    assert not sent(spark, monkeypatch, step)


def test_labelling_sends_no_part_of_its_tables(spark, monkeypatch):
    """Neither the orientation nor the light nodes, which come from unions and anti-joins of written tables."""
    from canopy.lcl import solve

    assert not sent(spark, monkeypatch, lambda: solve.solve_lcl(workloads.shapes(spark, "path", 20).kept(), P.odd_out_degree(), cap=4))


@pytest.mark.parametrize("name", ["light_heavy_heap2", "subtree_sizes_heap2", "sum_subtree_sizes_heap2", "two_colour_heap2"])
def test_heap_queries_hash_none_of_their_tables_on_the_driver(spark, monkeypatch, name):
    """Parents, pointers and sizes are joined where they are and give what the SQL gives; a row of totals may be sent."""
    import duckdb

    from canopy import rooting
    from canopy.queries import ORACLES, QUERIES

    made = []
    plans_ = sent(spark, monkeypatch, lambda: made.append(rooting.write(QUERIES[name](spark, D), "result").df))
    assert not [n for n, p in plans_ if "BroadcastHashJoin" in p]
    duck = duckdb.connect()
    duck.sql(f"create view orders as select * from '{D}/orders.parquet'")
    want = duck.sql(ORACLES[name])
    assert sorted(map(tuple, made[0].select(*want.columns).collect())) == sorted(want.fetchall())


def test_uniform_doubling_does_the_whole_job(spark):
    """No cap on rows unless one is asked for; each pair of a tree is seen once, by the round of its distance."""
    from inspect import signature

    from canopy.baselines import uniform_doubling

    assert signature(uniform_doubling).parameters["row_cap"].default is None
    ledger = Ledger()
    f = workloads.shapes(spark, "caterpillar", 40)
    assert {r.component for r in uniform_doubling(f, ledger).collect()} == {39}
    assert ledger.rows[-1][6] == 40 * 39 and ledger.rows[-1][5] == 40 * 39
    with pytest.raises(MemoryError):
        uniform_doubling(f, row_cap=100)


def test_absorption_stops_when_nothing_changes(spark):
    """Nodes that can neither settle nor learn do not keep the iterations going."""
    from canopy.budget import Budget
    from canopy.maxid import absorb_light
    from canopy.model import literal

    pairs, at = [], 1
    for _ in range(80):
        c, at = at, at + 1
        pairs.append((0, c))
        for _ in range(5):
            o, at = at, at + 4
            pairs += [(c, o), (o, o + 1), (o, o + 2), (o, o + 3)]
    f = literal(spark, pairs).kept()
    a = absorb_light(f.nodes.withColumn("best", F.col("id")), f.edges, 8, Budget(8))
    assert a.nodes.count() == 81 and a.report["iterations"] <= 3


def test_absorption_keeps_its_results_alone(spark, tmp_path, monkeypatch):
    """Of all tables that the core writes, those of views and states are gone when a phase ends."""
    import os

    from canopy import store
    from canopy.budget import Budget
    from canopy.maxid import absorb_light, max_id
    from canopy.model import literal

    pairs, at = [], 1
    for _ in range(12):  # a hub, on it centres of three stars and one star by itself
        c, at = at, at + 1
        pairs.append((0, c))
        for _ in range(3):
            o, at = at, at + 4
            pairs += [(c, o), (o, o + 1), (o, o + 2), (o, o + 3)]
    pairs += [(1000, 1001), (1000, 1002)]
    monkeypatch.setattr(store, "shared_dir", lambda s: f"file://{tmp_path}")
    f = literal(spark, pairs).kept()
    absorb_light(f.nodes.withColumn("best", F.col("id")), f.edges, 8, Budget(8))
    left = {name.split("-")[1] for name in os.listdir(tmp_path)}
    assert left == {"forest", "folds", "trees", "nodes", "edges"}
    got = {r.id: r.best for r in max_id(f.nodes, f.edges, 8, Budget(8)).collect()}
    assert got == {k: (1002 if k >= 1000 else at - 1) for p in pairs for k in p}

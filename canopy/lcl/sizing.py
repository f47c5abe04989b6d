"""Bounded subtree sizes, local roots, ports, path distances: the structural steps of the labelling solver."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from canopy.ledger import Ledger
from canopy.store import write


def subtree_sizes(rooted: DataFrame, cap: int, ledger: Ledger | None = None) -> DataFrame:
    """``(id, size, heavy)``: nodes of the subtree, itself counted, exact up to ``cap``; heavy above it.

    Doubling of (sum, pointer to the 2^i-th ancestor): a node adds what stands at
    nodes whose pointer reaches it.  Every node has one pointer, so all pointers together
    are n rows.  A node whose sum passes the cap stops and stops those above it.
    """
    j = write(rooted.select("id", F.col("parent").alias("anc")), "jump").df
    s = write(rooted.select("id", F.lit(1).cast("long").alias("size"), F.lit(False).alias("heavy")), "sizes").df
    for i in range(64):
        live = j.filter("anc is not null")
        if live.isEmpty():
            break
        add = live.join(s, "id").groupBy(F.col("anc").alias("id")).agg(F.sum("size").alias("more"), F.max("heavy").alias("h"))
        new = s.join(add, "id", "left").select("id", (F.col("size") + F.coalesce("more", F.lit(0))).alias("size"), (F.col("heavy") | F.coalesce("h", F.lit(False))).alias("heavy"))
        s = write(new.select("id", F.least("size", F.lit(cap + 1)).alias("size"), (F.col("heavy") | (F.col("size") > cap)).alias("heavy")), "sizes").df
        up = j.select(F.col("id").alias("anc"), F.col("anc").alias("beyond"))
        j = write(live.join(up, "anc", "left").select("id", F.col("beyond").alias("anc")), "jump").df
        if ledger is not None:
            ledger.add("sizing", "double", iter=i, rounds=2, rows_in=live.count())
    return s.select("id", F.when(F.col("heavy"), F.lit(cap + 1)).otherwise(F.col("size")).alias("size"), "heavy")


def mark_local_roots(rooted: DataFrame, sizes: DataFrame) -> DataFrame:
    """Ids of heavy nodes with a light child, and of roots whose whole tree is light."""
    kids = rooted.join(sizes, "id").filter("not heavy")
    heavy = sizes.filter("heavy").select("id")
    hosts = kids.filter("parent is not null").select(F.col("parent").alias("id")).distinct().join(heavy, "id", "left_semi")
    return hosts.unionByName(kids.filter("parent is null").select("id"))


def gather_light(rooted: DataFrame, sizes: DataFrame, ledger: Ledger | None = None) -> DataFrame:
    """``(light, local_root, child)``: the local root of each light node and the child of it above the node."""
    r = rooted.join(sizes.select("id", "heavy"), "id")
    light = r.filter("not heavy")
    host = r.filter("heavy").select(F.col("id").alias("parent"), F.lit(True).alias("stop"))
    at = light.join(host, "parent", "left").select(
        F.col("id").alias("light"), F.col("parent").alias("to"), F.col("id").alias("child"), (F.coalesce("stop", F.lit(False)) | F.col("parent").isNull()).alias("done")
    )
    at = write(at, "host").df
    for i in range(64):
        live = at.filter("not done")
        if live.isEmpty():
            break
        nxt = at.select(F.col("light").alias("to"), F.col("to").alias("t2"), F.col("child").alias("c2"), F.col("done").alias("d2"))
        step = live.join(nxt, "to").select("light", F.when(F.col("t2").isNull(), F.col("to")).otherwise(F.col("t2")).alias("to"), F.when(F.col("t2").isNull(), F.col("child")).otherwise(F.col("c2")).alias("child"), (F.col("d2")).alias("done"))
        at = write(at.filter("done").unionByName(step), "host").df
        if ledger is not None:
            ledger.add("gather", "jump", iter=i)
    return at.filter("to is not null").select("light", F.col("to").alias("local_root"), "child")


def assign_ports(edges: DataFrame) -> DataFrame:
    """``(node, other, node_port, edge_port)``: node ports 1..degree by neighbour, edge ports 1 (smaller id) and 2."""
    w = W.partitionBy("src").orderBy("dst")
    return edges.select(F.col("src").alias("node"), F.col("dst").alias("other"), F.row_number().over(w).alias("node_port"), F.when(F.col("src") < F.col("dst"), 1).otherwise(2).alias("edge_port"))


def path_distances(edges: DataFrame, heads: DataFrame, ledger: Ledger | None = None) -> DataFrame:
    """``(id, distance)`` from the head of each path, heads at 1, by halving of weighted links.

    ``heads(id)`` holds one end of each path; links lead toward the head.
    """
    deg = edges.groupBy("src").agg(F.count(F.lit(1)).alias("d"), F.min("dst").alias("lo"), F.max("dst").alias("hi"))
    # both links of every node; a link that reaches an end stays, the other ones add up
    links = edges.select(F.col("src").alias("id"), F.col("dst").alias("via"), F.col("dst").alias("to"), F.col("src").alias("from_"), F.lit(1).cast("long").alias("w"))
    ends = deg.filter("d = 1").select(F.col("src").alias("to"), F.lit(True).alias("end"))
    links = write(links.join(ends, "to", "left").select("id", "via", "to", "from_", "w", F.coalesce("end", F.lit(False)).alias("end")), "links").df
    for i in range(64):
        go = links.filter("not end")
        n = go.count()
        if ledger is not None:
            ledger.add("distances", "halve", iter=i, rows_in=n)
        if not n:
            break
        nxt = links.select(F.col("id").alias("to"), F.col("via").alias("v2"), F.col("to").alias("t2"), F.col("from_").alias("f2"), F.col("w").alias("w2"), F.col("end").alias("e2"))
        step = go.join(nxt, "to").filter("v2 <> from_").select("id", "via", F.col("t2").alias("to"), F.col("f2").alias("from_"), (F.col("w") + F.col("w2")).alias("w"), F.col("e2").alias("end"))
        links = write(links.filter("end").unionByName(step), "links").df
    got = links.join(heads.select(F.col("id").alias("to")), "to", "left_semi").select("id", (F.col("w") + 1).alias("distance"))
    return heads.select("id", F.lit(1).cast("long").alias("distance")).unionByName(got).groupBy("id").agg(F.min("distance").alias("distance"))


def mis_level(distance: Column, i: int) -> Column:
    """Nodes that step i takes: those at a distance that 2^(i+1) does not divide."""
    return F.pmod(distance, F.shiftleft(F.lit(1).cast("long"), i + 1)) != 0

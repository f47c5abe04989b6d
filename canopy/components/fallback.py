"""Components of an arbitrary graph by alternating star contraction.

Two kinds of step replace edges by edges of the same components until every
component is a star around its smallest id: the *wide* step hangs each larger
neighbour on the smallest id near a node, the *narrow* step does so for the
smaller neighbours.  O(log n) rounds in practice, edges never grow in number.

Hub safety: the minimum near a node is a hash aggregate with a partial phase,
it is written to a table, and the join back shuffles both sides plainly, so that
adaptive execution may split a hub's partition.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.store import write

#: Rounds after which the contraction is taken to be broken (2^60 nodes need fewer).
MAX_ROUNDS = 60


def _stamp(edges: DataFrame) -> tuple:
    row = edges.agg(
        F.count(F.lit(1)).alias("n"),
        F.coalesce(F.bit_xor(F.xxhash64("a", "b")), F.lit(0)).alias("x"),
    ).first()
    return row["n"], row["x"]


def star_components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """``(id, component)`` for every id on an edge; component = smallest id.

    Loops, repeated and reversed edges are allowed; edges with a null end are
    ignored.  An empty input gives an empty result.
    """
    e = edges.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b"))
    loops = e.filter("a is not null and b is not null and a = b").select(F.col("a").alias("id"))
    now = write(
        e.filter("a <> b")
        .select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
        .distinct(),
        "edges",
    )
    old = _stamp(now.df)
    for _ in range(MAX_ROUNDS):
        if not old[0]:
            break
        both = now.df.unionByName(now.df.select(F.col("b").alias("a"), F.col("a").alias("b")))
        near = write(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m")), "near")
        wide = write(
            now.df.join(near.df, "a").select(F.col("m").alias("a"), "b").distinct(), "wide"
        )
        # edges are stored with a < b: the smaller neighbours of b are its a's
        low = write(wide.df.groupBy("b").agg(F.min("a").alias("m")), "low")
        narrow = wide.df.join(low.df, "b").select(
            F.explode(
                F.array(
                    F.struct(F.col("m").alias("a"), F.col("b").alias("b")),
                    F.struct(F.col("m").alias("a"), F.col("a").alias("b")),
                )
            ).alias("e")
        ).select("e.a", "e.b")
        nxt = write(narrow.filter("a <> b").distinct(), "edges")
        for t in (near, wide, low, now):
            t.drop()
        now, new = nxt, _stamp(nxt.df)
        if new == old:
            break
        old = new
    else:
        raise RuntimeError("star contraction did not settle")
    stars = now.df.select(F.col("b").alias("id"), F.col("a").alias("component"))
    roots = now.df.select(F.col("a").alias("id"), F.col("a").alias("component"))
    alone = loops.select("id", F.col("id").alias("component"))
    return stars.unionByName(roots).unionByName(alone).groupBy("id").agg(F.min("component").alias("component"))

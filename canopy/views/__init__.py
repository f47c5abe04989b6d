"""Views: which nodes each node knows, as rows ``(owner, known, first_hop, last_hop, dist)``.

The first hop is the owner's neighbour on the way to the known node, the last hop the known
node's neighbour on the way back.  These columns close under joins: a view row v..w and
a row w..x that does not turn back at w give the row v..x.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KEY = ["owner", "known"]


def start(edges: DataFrame) -> DataFrame:
    """Every node knows its neighbours."""
    return edges.select(
        F.col("src").alias("owner"), F.col("dst").alias("known"), F.col("dst").alias("first_hop"), F.col("src").alias("last_hop"), F.lit(1).cast("long").alias("dist")
    )


def distinct_rows(views: DataFrame) -> DataFrame:
    """One row for each (owner, known); in a forest all rows of a pair are equal, so minima (hash aggregates) do."""
    return views.groupBy(*KEY).agg(F.min("first_hop").alias("first_hop"), F.min("last_hop").alias("last_hop"), F.min("dist").alias("dist"))


def grow(asking: DataFrame, views: DataFrame) -> DataFrame:
    """What the owners of ``asking`` learn from the nodes in it: rows of these nodes that do not lead back."""
    b = views.select(F.col("owner").alias("known"), F.col("known").alias("x"), F.col("first_hop").alias("f2"), F.col("last_hop").alias("l2"), F.col("dist").alias("d2"))
    j = asking.join(b, "known").filter(F.col("f2") != F.col("last_hop"))
    return j.select("owner", F.col("x").alias("known"), "first_hop", F.col("l2").alias("last_hop"), (F.col("dist") + F.col("d2")).alias("dist"))


def mirror(views: DataFrame) -> DataFrame:
    """The same pairs seen from the other end."""
    return views.select(F.col("known").alias("owner"), F.col("owner").alias("known"), F.col("last_hop").alias("first_hop"), F.col("first_hop").alias("last_hop"), "dist")


def estimates(asking: DataFrame, views: DataFrame | None = None) -> DataFrame:
    """``(owner, first_hop, est)``: for each direction the sum of what its known nodes know beyond, repeats counted.

    Two count tables and one equi-join; no pair is built.  ``views`` has the rows of the nodes in ``asking``, if these
    are not in ``asking`` itself.
    """
    views = asking if views is None else views
    per = views.groupBy(F.col("owner").alias("known"), F.col("first_hop").alias("last_hop")).agg(F.count(F.lit(1)).alias("back"))
    total = views.groupBy(F.col("owner").alias("known")).agg(F.count(F.lit(1)).alias("all"))
    j = asking.join(total, "known", "left").join(per, ["known", "last_hop"], "left")
    beyond: Column = F.coalesce("all", F.lit(0)) - F.coalesce("back", F.lit(0))
    return j.groupBy("owner", "first_hop").agg(F.sum(beyond).alias("est"), F.count(F.lit(1)).alias("have"))

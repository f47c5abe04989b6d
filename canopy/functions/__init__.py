"""Functions for SQL users: table functions, views over results, salted joins for hot keys."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from canopy.model.forest import Forest


@udtf(returnType="guess: bigint")
class GuessLadder:
    def eval(self, cap: int):
        from canopy.components.solve import guess_ladder

        for g in guess_ladder(cap):
            yield (g,)


@udtf(returnType="labels: array<int>")
class PortTuples:
    """All port assignments of a multiset of labels."""

    def eval(self, labels: list):
        from itertools import permutations

        for t in sorted(set(permutations(labels))):
            yield (list(t),)


def register(spark: SparkSession) -> None:
    spark.udtf.register("canopy_guess_ladder", GuessLadder)
    spark.udtf.register("canopy_port_tuples", PortTuples)


def publish(forest: Forest) -> None:
    """Temporary views ``canopy_components`` and ``canopy_rooted``."""
    from canopy.components.solve import components
    from canopy.rooting import root_forest
    from canopy.store import cut

    cut(components(forest), "components").createOrReplaceTempView("canopy_components")
    cut(root_forest(forest), "rooted").createOrReplaceTempView("canopy_rooted")


def relay_join(left: DataFrame, right: DataFrame, key: str, hot: DataFrame, fan: int = 16) -> DataFrame:
    """Equi-join in which the keys of ``hot`` are answered by ``fan`` copies of their (bounded) right rows.

    Left rows of a hot key are dealt over the copies by a hash of the row, so no task gets them all.
    """
    h = hot.select(key).distinct().withColumn("is_hot", F.lit(True))
    lhs = left.join(h, key, "left").withColumn("salt", F.when(F.col("is_hot"), F.pmod(F.xxhash64(*left.columns), F.lit(fan))).otherwise(F.lit(0)))
    rhs = right.join(h, key, "left").withColumn("salt", F.explode(F.when(F.col("is_hot"), F.sequence(F.lit(0), F.lit(fan - 1))).otherwise(F.array(F.lit(0)))))
    return lhs.drop("is_hot").join(rhs.drop("is_hot"), [key, "salt"]).drop("salt")

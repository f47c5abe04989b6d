"""Streams: windows and sessions of events, links between consecutive events, components kept up to date.

The round loops are batch; a stream only feeds edges.  ``available`` runs a stream over what is there.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from canopy.components.fallback import star_components
from canopy.store import folder, scope, write


def events_stream(spark: SparkSession, path: str) -> DataFrame:
    """The events as a file stream with event time ``at``."""
    # a glob, since a stream's plain path must be a folder
    raw = spark.readStream.schema(spark.read.parquet(path).schema).parquet(f"{path[:-1]}[{path[-1]}]")
    return raw.withColumn("at", F.col("ts").cast("timestamp"))


def available(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run over all available input; the result as a written table, to which each batch adds its own folder.

    A batch that is run again overwrites its folder.  In mode ``complete`` the last batch holds the whole result.
    """
    spark = stream.sparkSession
    at = folder(spark, "stream").path
    batches: list[int] = []

    def save(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{at}/{batch}")
        batches.append(batch)

    q = stream.writeStream.foreachBatch(save).outputMode(mode).option("checkpointLocation", f"{at}/_state").trigger(availableNow=True).start()
    q.awaitTermination()
    if not batches:
        return spark.createDataFrame([], stream.schema)
    paths = [f"{at}/{k}" for k in sorted(set(batches))]
    return spark.read.schema(stream.schema).parquet(*(paths[-1:] if mode == "complete" else paths))


def tumbling(events: DataFrame, size: str = "1 day") -> DataFrame:
    w = events.withWatermark("at", "2 hours").groupBy(F.window("at", size), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return w.select(F.expr("unix_micros(window.start)").alias("start"), "event_type", "n")


def sliding(events: DataFrame, size: str = "2 days", slide: str = "1 day") -> DataFrame:
    """Counts of overlapping windows: an event is in ``size / slide`` of them."""
    w = events.withWatermark("at", "2 hours").groupBy(F.window("at", size, slide), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return w.select(F.expr("unix_micros(window.start)").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    w = events.withWatermark("at", "2 hours").groupBy(F.session_window("at", gap), "user_id").agg(F.count(F.lit(1)).alias("n"), F.max("event_id").alias("top"))
    return w.select("user_id", "n", "top")


def deduplicated(events: DataFrame) -> DataFrame:
    return events.withWatermark("at", "2 hours").dropDuplicatesWithinWatermark(["event_id"])


def view_to_purchase(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: purchases of a user at most ``within`` after a view."""
    e = events.withWatermark("at", "2 hours")
    v = e.filter("event_type = 'view'").select(F.col("user_id").alias("vu"), F.col("event_id").alias("v"), F.col("at").alias("tv"))
    p = e.filter("event_type = 'purchase'").select(F.col("user_id").alias("pu"), F.col("event_id").alias("p"), F.col("at").alias("tp"))
    return v.join(p, F.expr(f"vu = pu and tp > tv and tp <= tv + interval {within}")).select("v", "p")


def spanning(quotient: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Edges ``(ca, cb)`` of a spanning forest of ``quotient(a, b, ca, cb)``, and the ``(a, b)`` that would close a cycle.

    In each round every group picks its smallest edge by (a, b), so picks never form a cycle; the number
    of groups at least halves.  Of a repeated edge one is used.
    """
    k = quotient.groupBy("a", "b").agg(F.first("ca").alias("ca"), F.first("cb").alias("cb"), F.count(F.lit(1)).alias("n"))
    rest = write(k.select("a", "b", F.col("ca").alias("x"), F.col("cb").alias("y"), "ca", "cb"), "rest").df
    closing = write(k.filter("n > 1").select("a", "b"), "closing").df
    kept = rest.select("ca", "cb").limit(0)
    while not rest.isEmpty():
        ends = rest.select(F.col("x").alias("g"), "a", "b").unionByName(rest.select(F.col("y").alias("g"), "a", "b"))
        best = ends.groupBy("g").agg(F.min(F.struct("a", "b")).alias("e")).select("e.a", "e.b").distinct()
        best = write(best, "best").df
        used = write(rest.join(best, ["a", "b"], "left_semi"), "used").df
        kept = write(kept.unionByName(used.select("ca", "cb")), "kept").df
        at = write(star_components(used, "x", "y"), "groups").df
        left = rest.join(best, ["a", "b"], "left_anti")
        left = left.join(at.select(F.col("id").alias("x"), F.col("component").alias("u")), "x").join(at.select(F.col("id").alias("y"), F.col("component").alias("v")), "y")
        left = write(left.select("a", "b", F.col("u").alias("x"), F.col("v").alias("y"), "ca", "cb"), "left").df
        closing = write(closing.unionByName(left.filter("x = y").select("a", "b")), "closing").df
        rest = left.filter("x <> y")
    return kept, closing


class LiveComponents:
    """Components under arriving edges: a batch is mapped to current labels and the small graph of labels is solved.

    Edges that would close a cycle, with earlier batches or inside one, are set aside.  A node's row is written once,
    with its label on arrival; merged labels are forwarded to the current one in a table of their own, the only
    one that is rewritten.  A batch that is run again is passed over, or overwrites what it left unfinished.
    """

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.at = folder(spark, "live").path
        self.done: list[int] = []
        self.forward = write(spark.createDataFrame([], "component long, now long"), "forward")

    def _all(self, name: str, schema: str) -> DataFrame:
        if not self.done:
            return self.spark.createDataFrame([], schema)
        return self.spark.read.schema(schema).parquet(*[f"{self.at}/{name}/{k}" for k in self.done])

    @property
    def labels(self) -> DataFrame:
        """``(id, component)``, component = smallest id."""
        return self._now(self._all("ids", "id long, component long")).select("id", F.coalesce("now", "component").alias("component"))

    @property
    def rejected(self) -> DataFrame:
        return self._all("rejected", "a long, b long")

    def _now(self, ids: DataFrame) -> DataFrame:
        return ids.join(self.forward.df, "component", "left")

    def add(self, pairs: DataFrame, batch: int | None = None) -> None:
        batch = max(self.done, default=-1) + 1 if batch is None else batch
        if batch in self.done:
            return
        with scope() as held:
            p = write(pairs.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).filter("a is not null and b is not null"), "batch").df
            ids = p.select(F.col("a").alias("id")).unionByName(p.select(F.col("b").alias("id"))).distinct()
            at = self._now(ids.join(self._all("ids", "id long, component long"), "id", "left"))
            at = write(at.select("id", F.coalesce("now", "component", "id").alias("component"), F.col("component").isNull().alias("fresh")), "touched").df
            at.filter("fresh").select("id", "component").write.mode("overwrite").parquet(f"{self.at}/ids/{batch}")
            ca, cb = at.select(F.col("id").alias("a"), F.col("component").alias("ca")), at.select(F.col("id").alias("b"), F.col("component").alias("cb"))
            q = write(p.join(ca, "a").join(cb, "b"), "quotient").df
            kept, closing = spanning(q.filter("ca <> cb"))
            q.filter("ca = cb").select("a", "b").unionByName(closing).write.mode("overwrite").parquet(f"{self.at}/rejected/{batch}")
            moved = star_components(kept, "ca", "cb").filter("id <> component").select(F.col("id").alias("component"), F.col("component").alias("now"))
            moved = write(moved, "moved").df
            on = moved.select(F.col("component").alias("now"), F.col("now").alias("beyond"))
            forward = self.forward.df.join(on, "now", "left").select("component", F.coalesce("beyond", "now").alias("now"))
            old, self.forward = self.forward, held(write(forward.unionByName(moved), "forward"))
            self.done.append(batch)
        old.drop()

    def follow(self, pairs_stream: DataFrame) -> None:
        q = pairs_stream.writeStream.foreachBatch(self.add).option("checkpointLocation", f"{self.at}/_state").trigger(availableNow=True).start()
        q.awaitTermination()

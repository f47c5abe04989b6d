"""The graph families on the given tables.  Ids are ``key * 8 + kind``."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from canopy.model.forest import Forest, from_pairs, from_parent, from_prefix, from_sequence
from canopy.store import table

LINE = "(l_orderkey * 16 + l_linenumber) * 8 + 5"


def fk_pairs(spark: SparkSession, d: str) -> DataFrame:
    """W1 as (child, parent): lines, orders, customers, suppliers, nations, regions."""
    parts = [
        table(spark, d, "nation").selectExpr("n_nationkey * 8L + 1 a", "n_regionkey * 8L b"),
        table(spark, d, "customer").selectExpr("c_custkey * 8 + 2 a", "c_nationkey * 8L + 1 b"),
        table(spark, d, "supplier").selectExpr("s_suppkey * 8 + 3 a", "s_nationkey * 8L + 1 b"),
        table(spark, d, "orders").selectExpr("o_orderkey * 8 + 4 a", "o_custkey * 8 + 2 b"),
        table(spark, d, "lineitem").selectExpr(f"{LINE} a", "l_orderkey * 8 + 4 b"),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def fk_forest(spark, d) -> Forest:
    return from_pairs(fk_pairs(spark, d), table(spark, d, "region").selectExpr("r_regionkey * 8L id"))


def event_chain(spark, d) -> Forest:
    """W2: consecutive events of a user."""
    return event_cut(spark, d, None)


def event_cut(spark, d, length: int | None) -> Forest:
    """W4: W2 cut after every ``length`` events."""
    e = table(spark, d, "events").select("event_id", "user_id", "ts")
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    e = e.withColumn("n", F.row_number().over(w))
    cut = (F.col("n") % length == 0) if length else None
    return from_sequence(e, [F.col("user_id")], [F.col("ts"), F.col("event_id")], F.expr("event_id * 8 + 7"), cut)


def event_sessions(spark, d, hours: int) -> Forest:
    """W3: W2 without the links whose gap exceeds ``hours``."""
    e = table(spark, d, "events").select("event_id", "user_id", "ts")
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    e = e.withColumn("nxt", F.lead("ts").over(w)).withColumn("gap", F.expr("timestampdiff(MICROSECOND, ts, nxt)"))
    return from_sequence(e, [F.col("user_id")], [F.col("ts"), F.col("event_id")], F.expr("event_id * 8 + 7"), F.coalesce(F.col("gap") > hours * 3_600_000_000, F.lit(True)))


def conversations(spark, d) -> Forest:
    """W5: turns in order."""
    c = table(spark, d, "conversations").select("conv_id", "turn")
    return from_sequence(c, [F.col("conv_id")], [F.col("turn")], F.expr("(conv_id * 16 + turn) * 8 + 7"))


def url_trie(spark, d) -> tuple[Forest, DataFrame]:
    """W6: host, then path prefixes, without scheme, query and fragment."""
    u = table(spark, d, "pages").select(F.regexp_extract("url", r"://([^?#]*)", 1).alias("path")).filter("path <> ''")
    return from_prefix(u)


def heap(spark, d, k: int = 2, source: str = "orders") -> Forest:
    """W7: parent = (key - 1) div k."""
    key = {"orders": "o_orderkey", "part": "p_partkey"}[source]
    t = table(spark, d, source).select(F.col(key).alias("k"))
    return from_parent(t, F.expr("k"), F.expr(f"case when k > 0 then (k - 1) div {k} end"))


def attach(spark, d) -> Forest:
    """W8: parent = hash mod key."""
    t = table(spark, d, "orders").select(F.col("o_orderkey").alias("k"))
    return from_parent(t, F.expr("k"), F.expr("case when k > 0 then pmod(pmod(k * 2654435761, 4294967296), k) end"))


def near(spark, d) -> Forest:
    """W8b: parent is one of the eight keys before."""
    t = table(spark, d, "orders").select(F.col("o_orderkey").alias("k"))
    h = "(pmod(k * 2654435761, 4294967296) div 65536)"
    return from_parent(t, F.expr("k"), F.expr(f"case when k > 0 then k - 1 - pmod({h}, least(k, 8)) end"))


def caterpillars(spark, d) -> Forest:
    """W11: orders of a customer by date as spine, distinct lines as legs."""
    o = table(spark, d, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    w = W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    spine = o.select(F.expr("o_orderkey * 8 + 4").alias("a"), F.lead(F.expr("o_orderkey * 8 + 4")).over(w).alias("b"))
    legs = table(spark, d, "lineitem").selectExpr(f"{LINE} a", "l_orderkey * 8 + 4 b")
    return from_pairs(spine.unionByName(legs), spine.select(F.col("a").alias("id")))


def chained_fk(spark, d) -> Forest:
    """W12: W1 with each child hung on its elder sibling, the eldest on the parent; at most 3 neighbours."""
    p = fk_pairs(spark, d).distinct()
    w = W.partitionBy("b").orderBy("a")
    return from_parent(p, F.col("a"), F.coalesce(F.lag("a").over(w), F.col("b")))


def copy_stars(spark, d) -> Forest:
    """W13: a document and the smallest id with the same text."""
    t = table(spark, d, "documents").select("doc_id", F.sha2(F.coalesce("text", F.lit("")), 256).alias("h"))
    low = t.groupBy("h").agg(F.min("doc_id").alias("low"))
    return from_parent(t.join(low, "h"), F.expr("doc_id"), F.expr("nullif(low, doc_id)"))


def cycles(spark, d, count: int = 1) -> DataFrame:
    """W14 as pairs: order keys in one or more equal cycles (not a forest)."""
    n = table(spark, d, "orders").count()
    part = n // count
    t = table(spark, d, "orders").select(F.col("o_orderkey").alias("a")).filter(F.col("a") < part * count)
    return t.selectExpr("a", f"a div {part} * {part} + (a % {part} + 1) % {part} b")


def shapes(spark, kind: str, n: int) -> Forest:
    """W9 from ``spark.range``: path, star, caterpillar, broom, spider, two hubs."""
    r = spark.range(1, n).selectExpr("id k")
    rule = {
        "path": "k - 1",
        "star": "0",
        "caterpillar": "case when k % 2 = 1 then k - 1 else greatest(k - 2, 0) end",
        "broom": f"case when k < {n // 2} then k - 1 else {n // 2 - 1} end",
        "spider": "case when k <= 4 then 0 else k - 4 end",
        "two_hubs": f"case when k < {n // 2} then 0 when k = {n // 2} then 0 else {n // 2} end",
    }[kind]
    return from_pairs(r.selectExpr("k a", f"{rule} b"))

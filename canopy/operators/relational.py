"""Relational operators around the forest methods, each as a query with a SQL twin.

``OPS`` maps a name to (Spark function, DuckDB SQL or None).  Outputs are integers, strings or
booleans with explicit names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from canopy import workloads
from canopy.store import shared_dir, table

OPS: dict = {}


def micros(c: str):
    """Microseconds since 1970 of a timestamp without zone, whatever the session's zone."""
    return F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', cast({c} as timestamp_ntz))")


def op(name: str, sql: str | None):
    def put(f):
        OPS[f"ops_{name}"] = (f, sql)
        return f

    return put


@op("scan_pruned", "select l_orderkey, cast(l_linenumber as bigint) as line from lineitem where l_orderkey < 1000")
def scan_pruned(s, d) -> DataFrame:
    return table(s, d, "lineitem").select("l_orderkey", F.col("l_linenumber").cast("long").alias("line")).filter("l_orderkey < 1000")


@op("format_round_trip", "with w as (select (conv_id * 16 + turn) * 8 + 7 as a, lead((conv_id * 16 + turn) * 8 + 7) over (partition by conv_id order by turn) as b from conversations) select format, 2 * count(b) as n, sum(case when b is not null then a + b end)::bigint as total from w, (values ('csv'), ('json'), ('orc')) v(format) group by format")
def format_round_trip(s, d) -> DataFrame:
    """An edge list through CSV, JSON and ORC; every format must give it back."""
    import uuid

    e = workloads.conversations(s, d).edges
    out = None
    for fmt in ("csv", "json", "orc"):
        path = f"{shared_dir(s)}/canopy-{fmt}-{uuid.uuid4().hex[:8]}"
        w = e.write.format(fmt)
        (w.option("header", True) if fmt == "csv" else w).save(path)
        r = s.read.format(fmt).schema("src long, dst long")
        back = (r.option("header", True) if fmt == "csv" else r).load(path)
        row = back.agg(F.count(F.lit(1)).alias("n"), F.sum("src").alias("total")).withColumn("format", F.lit(fmt))
        out = row if out is None else out.unionByName(row)
    return out


@op("predicates", "select o_orderkey from orders where (o_custkey % 3 = 0 or o_custkey is null) and o_orderkey between 10 and 900 and o_custkey in (3, 6, 9, 12, 33, 60) and o_orderkey is not distinct from o_orderkey")
def predicates(s, d):
    o = table(s, d, "orders")
    return o.filter(((F.col("o_custkey") % 3 == 0) | F.col("o_custkey").isNull()) & F.col("o_orderkey").between(10, 900) & F.col("o_custkey").isin(3, 6, 9, 12, 33, 60) & F.col("o_orderkey").eqNullSafe(F.col("o_orderkey"))).select("o_orderkey")


FK_SQL = """
pairs as (
  select n_nationkey::bigint * 8 + 1 as a, n_regionkey::bigint * 8 as b from nation
  union select c_custkey * 8 + 2, c_nationkey::bigint * 8 + 1 from customer
  union select s_suppkey * 8 + 3, s_nationkey::bigint * 8 + 1 from supplier
  union select o_orderkey * 8 + 4, o_custkey * 8 + 2 from orders
  union select (l_orderkey * 16 + l_linenumber) * 8 + 5, l_orderkey * 8 + 4 from lineitem)
"""


@op("degree_classes", f"with {FK_SQL}, e as (select a as id from pairs union all select b from pairs), g as (select id, count(*) as deg from e group by id) select case when deg >= 3 then 3 else deg end::bigint as class, count(*) as nodes from g group by 1")
def degree_classes(s, d):
    deg = workloads.fk_forest(s, d).degrees()
    return deg.groupBy(F.least("degree", F.lit(3)).alias("class")).agg(F.count(F.lit(1)).alias("nodes"))


@op("symmetrise", f"with {FK_SQL} select count(*) as rows_both, count(*) // 2 as edges from (select a, b from pairs union select b, a from pairs)")
def symmetrise(s, d):
    return workloads.fk_forest(s, d).edges.agg(F.count(F.lit(1)).alias("rows_both")).withColumn("edges", F.expr("rows_both div 2"))


@op("equi_join", "select o_orderkey, c_nationkey::bigint as nation from orders join customer on o_custkey = c_custkey")
def equi_join(s, d):
    o, c = table(s, d, "orders"), table(s, d, "customer")
    return o.join(c.hint("merge"), o.o_custkey == c.c_custkey).select("o_orderkey", F.col("c_nationkey").cast("long").alias("nation"))


@op("broadcast_join", "select c_custkey, n_name from customer join nation on c_nationkey = n_nationkey")
def broadcast_join(s, d):
    c, n = table(s, d, "customer"), table(s, d, "nation")  # 25 nations
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).select("c_custkey", "n_name")


@op("left_outer", "select d.doc_id, coalesce(l.toxic, -1)::bigint as toxic from documents d left join labels l on d.doc_id = l.doc_id")
def left_outer(s, d):
    return table(s, d, "documents").select("doc_id").join(table(s, d, "labels"), "doc_id", "left").select("doc_id", F.coalesce("toxic", F.lit(-1)).cast("long").alias("toxic"))


@op("semi_anti", "select c_custkey, exists (select 1 from orders where o_custkey = c_custkey) as has_orders from customer")
def semi_anti(s, d):
    c, o = table(s, d, "customer"), table(s, d, "orders")
    on = c.c_custkey == o.o_custkey
    return c.join(o, on, "left_semi").select("c_custkey", F.lit(True).alias("has_orders")).unionByName(c.join(o, on, "left_anti").select("c_custkey", F.lit(False).alias("has_orders")))


@op("full_outer", "with a as (select doc_id from documents where doc_id % 2 = 0), b as (select doc_id from documents where doc_id % 3 = 0) select a.doc_id as x, b.doc_id as y from a full join b on a.doc_id = b.doc_id")
def full_outer(s, d):
    t = table(s, d, "documents").select("doc_id")
    a, b = t.filter("doc_id % 2 = 0").withColumnRenamed("doc_id", "x"), t.filter("doc_id % 3 = 0").withColumnRenamed("doc_id", "y")
    return a.join(b, a.x == b.y, "full")


@op("range_join", "with s as (select user_id, min(ts) as lo, min(ts) + interval 6 hour as hi from events group by user_id) select e.event_id from events e join s on e.user_id = s.user_id and e.ts >= s.lo and e.ts < s.hi")
def range_join(s, d):
    e = table(s, d, "events").select("event_id", "user_id", "ts")
    spans = e.groupBy("user_id").agg(F.min("ts").alias("lo")).withColumn("hi", F.expr("lo + interval 6 hours"))
    return e.join(spans, "user_id").filter("ts >= lo and ts < hi").select("event_id")


@op("interval_join", "select v.event_id as v, p.event_id as p from events v join events p on v.user_id = p.user_id and v.event_type = 'view' and p.event_type = 'purchase' and p.ts > v.ts and p.ts <= v.ts + interval 1 hour")
def interval_join(s, d):
    e = table(s, d, "events").select("event_id", "user_id", "ts", "event_type")
    v = e.filter("event_type = 'view'").select("user_id", F.col("event_id").alias("v"), F.col("ts").alias("tv"))
    p = e.filter("event_type = 'purchase'").select("user_id", F.col("event_id").alias("p"), F.col("ts").alias("tp"))
    return v.join(p, "user_id").filter("tp > tv and tp <= tv + interval 1 hour").select("v", "p")


@op("as_of", "select p.event_id as p, (select max(x.event_id) from events x where x.user_id = p.user_id and x.event_type = 'error' and x.event_id < p.event_id) as last_error from events p where p.event_type = 'purchase'")
def as_of(s, d):
    e = table(s, d, "events").select("event_id", "user_id", "ts", "event_type")
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "error", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("last_error", last).filter("event_type = 'purchase'").select(F.col("event_id").alias("p"), "last_error")


@op("cross_small", "select a.r_regionkey::bigint as a, b.r_regionkey::bigint as b from region a cross join region b")
def cross_small(s, d):
    r = table(s, d, "region")  # five rows
    return r.select(F.col("r_regionkey").cast("long").alias("a")).crossJoin(F.broadcast(r.select(F.col("r_regionkey").cast("long").alias("b"))))


@op("pointer_jump", "select o_orderkey as id, case when o_orderkey >= 31 then (((((o_orderkey - 1) // 2 - 1) // 2 - 1) // 2 - 1) // 2)::bigint when o_orderkey >= 15 then (((((o_orderkey - 1) // 2 - 1) // 2 - 1) // 2 - 1) // 2)::bigint end as ancestor from orders")
def pointer_jump(s, d):
    from canopy.rooting import ancestor_pow

    t = table(s, d, "orders").selectExpr("o_orderkey id", "case when o_orderkey > 0 then (o_orderkey - 1) div 2 end parent")
    return ancestor_pow(t, 2)


@op("hash_aggregate", "select user_id, count(*) as n, max(event_id) as top from events group by user_id")
def hash_aggregate(s, d):
    return table(s, d, "events").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"), F.max("event_id").alias("top"))


@op("distinct_aggregate", "select event_type, count(distinct user_id) as users from events group by event_type")
def distinct_aggregate(s, d):
    return table(s, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@op("approx_distinct", "select count(distinct l_orderkey) as orders, true as near from lineitem")
def approx_distinct(s, d):
    """Exact number of keys, and whether the sketch comes within three standard errors of it."""
    t = table(s, d, "lineitem").select("l_orderkey")
    both = t.agg(F.approx_count_distinct("l_orderkey", 0.02).alias("about")).crossJoin(t.distinct().agg(F.count("l_orderkey").alias("orders")))
    return both.select("orders", (F.abs(F.col("about") - F.col("orders")) <= 0.06 * F.col("orders")).alias("near"))


@op("rollup", "select r_name, n_name, count(*) as customers from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by rollup (r_name, n_name)")
def rollup(s, d):
    c, n, r = (table(s, d, x) for x in ("customer", "nation", "region"))
    return c.join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey).rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("customers"))


@op("cube", "select c_mktsegment, c_nationkey::bigint as nation, count(*) as n from customer group by cube (c_mktsegment, c_nationkey)")
def cube(s, d):
    return table(s, d, "customer").select("c_mktsegment", F.col("c_nationkey").cast("long").alias("nation")).cube("c_mktsegment", "nation").agg(F.count(F.lit(1)).alias("n"))


@op("grouping_sets", "select c_mktsegment, c_nationkey::bigint as nation, count(*) as n from customer group by grouping sets ((c_mktsegment), (c_nationkey), ())")
def grouping_sets(s, d):
    t = table(s, d, "customer").select("c_mktsegment", F.col("c_nationkey").cast("long").alias("nation"))
    return t.groupingSets([["c_mktsegment"], ["nation"], []], "c_mktsegment", "nation").agg(F.count(F.lit(1)).alias("n"))


@op("pivot", "select user_id, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'view') as view, count(*) filter (event_type = 'purchase') as purchase from events group by user_id")
def pivot(s, d):
    p = table(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "view", "purchase"]).count()
    return p.select("user_id", *[F.coalesce(c, F.lit(0)).alias(c) for c in ("click", "view", "purchase")])


@op("filtered_aggregate", "select o_custkey, count(*) filter (o_orderkey % 2 = 1) as odd, count(*) as n from orders group by o_custkey having count(*) > 5")
def filtered_aggregate(s, d):
    g = table(s, d, "orders").groupBy("o_custkey").agg(F.count_if(F.col("o_orderkey") % 2 == 1).alias("odd"), F.count(F.lit(1)).alias("n"))
    return g.filter("n > 5")


@op("max_by", "select user_id, arg_max(event_id, ts) as last_event, arg_min(event_id, ts) as first_event from events group by user_id")
def max_by(s, d):
    return table(s, d, "events").groupBy("user_id").agg(F.max_by("event_id", "ts").alias("last_event"), F.min_by("event_id", "ts").alias("first_event"))


@op("skew_report", "with g as (select o_custkey, count(*) as n from orders group by o_custkey) select max(n) as most, quantile_disc(n, 0.5) as median, count(*) as keys from g")
def skew_report(s, d):
    g = table(s, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
    return g.agg(F.max("n").alias("most"), F.expr("percentile_disc(0.5) within group (order by n)").cast("long").alias("median"), F.count(F.lit(1)).alias("keys"))


@op("ranking", "select n_nationkey::bigint as nation, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(2) over w as nt from nation window w as (partition by n_regionkey order by n_nationkey)")
def ranking(s, d):
    w = W.partitionBy("n_regionkey").orderBy("n_nationkey")
    return table(s, d, "nation").select(F.col("n_nationkey").cast("long").alias("nation"), *[f.over(w).cast("long").alias(a) for f, a in ((F.row_number(), "rn"), (F.rank(), "rk"), (F.dense_rank(), "dr"), (F.ntile(2), "nt"))])


@op("lag_lead", "select event_id, lag(event_id) over w as before, lead(event_id) over w as after from events window w as (partition by user_id order by ts, event_id)")
def lag_lead(s, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return table(s, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"))


@op("running_frames", "select event_id, sum(event_id) over (partition by user_id order by ts, event_id rows between 2 preceding and current row)::bigint as near, count(*) over (partition by user_id order by epoch_us(ts) range between 3600000000 preceding and current row) as hour from events")
def running_frames(s, d):
    e = table(s, d, "events").withColumn("us", micros("ts"))
    a = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)
    b = W.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    return e.select("event_id", F.sum("event_id").over(a).alias("near"), F.count(F.lit(1)).over(b).alias("hour"))


@op("partition_max", "select event_id, max(event_id) over (partition by user_id) as top from events")
def partition_max(s, d):
    return table(s, d, "events").select("event_id", F.max("event_id").over(W.partitionBy("user_id")).alias("top"))


@op("sorted", "select conv_id, turn from conversations")
def sorted_(s, d):
    return table(s, d, "conversations").select("conv_id", "turn").orderBy("conv_id", "turn")


@op("top_k", "select text_hash, copies from (select md5(text) as text_hash, count(*) as copies from documents group by text) order by copies desc, text_hash limit 5")
def top_k(s, d):
    g = table(s, d, "documents").groupBy(F.md5("text").alias("text_hash")).agg(F.count(F.lit(1)).alias("copies"))
    return g.orderBy(F.desc("copies"), "text_hash").limit(5)


@op("top_k_per_group", "select user_id, event_id from (select user_id, event_id, row_number() over (partition by user_id order by event_id desc) as r from events) where r <= 3")
def top_k_per_group(s, d):
    w = W.partitionBy("user_id").orderBy(F.desc("event_id"))
    return table(s, d, "events").select("user_id", "event_id", F.row_number().over(w).alias("r")).filter("r <= 3").drop("r")


@op("set_operations", "with a as (select o_custkey % 50 as k from orders), b as (select c_custkey % 70 as k from customer where c_custkey % 70 > 20) select 'union' as kind, k from (select k from a union select k from b) union all select 'intersect', k from (select k from a intersect select k from b) union all select 'except', k from (select k from a except select k from b)")
def set_operations(s, d):
    a = table(s, d, "orders").selectExpr("o_custkey % 50 k")
    b = table(s, d, "customer").selectExpr("c_custkey % 70 k").filter("k > 20")
    named = lambda name, t: t.select(F.lit(name).alias("kind"), "k")
    return named("union", a.union(b).distinct()).unionByName(named("intersect", a.intersect(b))).unionByName(named("except", a.subtract(b)))


@op("bag_operations", "with a as (select o_custkey % 7 as k from orders), b as (select c_custkey % 5 as k from customer) select 'intersect' as kind, k, count(*) as n from (select k from a intersect all select k from b) group by k union all select 'except', k, count(*) from (select k from a except all select k from b) group by k")
def bag_operations(s, d):
    a, b = table(s, d, "orders").selectExpr("o_custkey % 7 k"), table(s, d, "customer").selectExpr("c_custkey % 5 k")
    named = lambda name, t: t.groupBy("k").agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("kind"), "k", "n")
    return named("intersect", a.intersectAll(b)).unionByName(named("except", a.exceptAll(b)))


@op("strings", "select page_id, regexp_extract(url, '://([^/?#]*)', 1) as host, lower(trim(split_part(url, '?', 1))) as bare, length(url) as n, sha256(url) as digest from pages")
def strings(s, d):
    return table(s, d, "pages").select("page_id", F.regexp_extract("url", "://([^/?#]*)", 1).alias("host"), F.lower(F.trim(F.substring_index("url", "?", 1))).alias("bare"), F.length("url").cast("long").alias("n"), F.sha2("url", 256).alias("digest"))


@op("dates", "select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m, epoch_us(date_trunc('month', o_orderdate)) as month_start, epoch_us(o_orderdate + interval 10 day) as due from orders")
def dates(s, d):
    return table(s, d, "orders").select("o_orderkey", F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m"), micros("date_trunc('month', o_orderdate)").alias("month_start"), micros("o_orderdate + interval 10 days").alias("due"))


@op("bits", "select o_orderkey, o_orderkey % 8 as level, (1::bigint << (o_orderkey % 5)::int) as mask, bit_count(o_orderkey)::bigint as ones, xor(o_orderkey, o_custkey) as mixed, greatest(o_orderkey, o_custkey) as top from orders")
def bits(s, d):
    return table(s, d, "orders").selectExpr("o_orderkey", "pmod(o_orderkey, 8) level", "shiftleft(1L, cast(o_orderkey % 5 as int)) mask", "cast(bit_count(o_orderkey) as bigint) ones", "o_orderkey ^ o_custkey mixed", "greatest(o_orderkey, o_custkey) top")


@op("arrays", "select n_nationkey::bigint as nation, unnest(list_transform(range(1, n_regionkey::bigint + 3), lambda x: x * x + n_nationkey)) as v from nation")
def arrays(s, d):
    n = table(s, d, "nation").select(F.col("n_nationkey").cast("long").alias("nation"), F.col("n_regionkey").cast("long").alias("r"))
    return n.select("nation", F.explode(F.transform(F.expr("sequence(1L, r + 2)"), lambda x: x * x + F.col("nation"))).alias("v"))


@op("array_tests", "select n_nationkey::bigint as nation, len(list_filter(range(0, n_nationkey::bigint + 1), lambda x: x % 3 = 0)) as thirds, list_sum(range(0, n_nationkey::bigint + 1))::bigint as total, n_nationkey >= 7 as has_seven from nation")
def array_tests(s, d):
    n = table(s, d, "nation").select(F.col("n_nationkey").cast("long").alias("nation")).withColumn("a", F.expr("sequence(0L, nation)"))
    return n.select("nation", F.size(F.filter("a", lambda x: x % 3 == 0)).cast("long").alias("thirds"), F.aggregate("a", F.lit(0).cast("long"), lambda t, x: t + x).alias("total"), F.exists("a", lambda x: x == 7).alias("has_seven"))


@op("json", "select event_id, array_to_string(list_sort(json_keys(props)), ',') as keys, json_array_length(to_json(json_keys(props)))::bigint as n from events")
def json_(s, d):
    e = table(s, d, "events").select("event_id", F.from_json("props", "map<string,string>").alias("m"))
    return e.select("event_id", F.array_join(F.sort_array(F.map_keys("m")), ",").alias("keys"), F.cardinality("m").cast("long").alias("n"))


@op("subqueries", "select o_orderkey from orders o where exists (select 1 from lineitem where l_orderkey = o_orderkey and l_linenumber = 7) and o_orderkey > (select avg(o_orderkey) from orders)")
def subqueries(s, d):
    table(s, d, "orders").createOrReplaceTempView("canopy_orders")
    table(s, d, "lineitem").createOrReplaceTempView("canopy_lines")
    return s.sql("select o_orderkey from canopy_orders o where exists (select 1 from canopy_lines where l_orderkey = o_orderkey and l_linenumber = 7) and o_orderkey > (select avg(o_orderkey) from canopy_orders)")


@op("recursive", "with recursive t as (select 0::bigint as id, 0::bigint as depth union all select o_orderkey, depth + 1 from t join orders on o_orderkey in (2 * id + 1, 2 * id + 2)) select id, depth from t where depth <= 6")
def recursive(s, d):
    table(s, d, "orders").select(F.col("o_orderkey").alias("k"), F.expr("(o_orderkey - 1) div 2").alias("p")).filter("k > 0").createOrReplaceTempView("canopy_heap")
    return s.sql("with recursive t(id, depth) as (select 0L, 0L union all select k, depth + 1 from t join canopy_heap on p = id where depth < 6) select id, depth from t")


@op("lateral", "select n_nationkey::bigint as nation, i as step from nation, lateral (select unnest(range(0, n_regionkey::bigint + 1)) as i)")
def lateral(s, d):
    table(s, d, "nation").createOrReplaceTempView("canopy_nation")
    return s.sql("select cast(n_nationkey as bigint) nation, i step from canopy_nation, lateral (select explode(sequence(0L, cast(n_regionkey as bigint))) i)")


@op("grouped_map", "select o_custkey, count(*) as n, sum(o_orderkey)::bigint as total from orders group by o_custkey")
def grouped_map(s, d):
    import pyarrow as pa
    import pyarrow.compute as pc

    def fold(t: pa.Table) -> pa.Table:
        return pa.table({"o_custkey": pa.array([t["o_custkey"][0].as_py()], pa.int64()), "n": pa.array([t.num_rows], pa.int64()), "total": pa.array([pc.sum(t["o_orderkey"]).as_py()], pa.int64())})

    return table(s, d, "orders").select("o_custkey", "o_orderkey").groupBy("o_custkey").applyInArrow(fold, "o_custkey long, n long, total long")


@op("hash_sample", "select o_orderkey from orders where ((o_orderkey * 2654435761) % 4294967296) % 16 = 0")
def hash_sample(s, d):
    return table(s, d, "orders").filter("pmod(pmod(o_orderkey * 2654435761, 4294967296), 16) = 0").select("o_orderkey")


@op("partitioned_sink", "select event_type, count(*) as n from events group by event_type")
def partitioned_sink(s, d):
    import uuid

    path = f"{shared_dir(s)}/canopy-sink-{uuid.uuid4().hex[:8]}"
    table(s, d, "events").select("event_type", "event_id").write.partitionBy("event_type").parquet(path)
    return s.read.parquet(path).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))

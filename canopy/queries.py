"""Queries of the forest engine and their SQL twins.  Outputs are LONG, STRING or BOOLEAN."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from canopy import baselines, hardness, streaming, workloads
from canopy import views as V
from canopy.baselines import labelling
from canopy.budget import Budget
from canopy.components.shrink import PRIME, actions, coefficients, sparse_independent
from canopy.components.solve import components, components_fallback
from canopy.ledger import Ledger
from canopy.lcl import problem as lcl
from canopy.lcl.sizing import assign_ports, mark_local_roots, mis_level, path_distances, subtree_sizes
from canopy.lcl.solve import init_compat, solve_lcl
from canopy.lcl.problem import violations
from canopy.maxid import contract_paths, max_id
from canopy.maxid.core import classify_exact
from canopy.operators.relational import FK_SQL, OPS
from canopy.rooting import depths, root_defects, root_forest, two_colour
from canopy.store import swept, table, write

QUERIES: dict = {k: f for k, (f, _) in OPS.items()}
ORACLES: dict = {k: sql for k, (_, sql) in OPS.items() if sql}


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


# --- components: every node with the largest id of its tree -------------------------------------------------

FK_REGION = """
r as (
  select r_regionkey::bigint * 8 as id, r_regionkey::bigint as r from region
  union all select n_nationkey::bigint * 8 + 1, n_regionkey from nation
  union all select c_custkey * 8 + 2, n_regionkey from customer join nation on c_nationkey = n_nationkey
  union all select s_suppkey * 8 + 3, n_regionkey from supplier join nation on s_nationkey = n_nationkey
  union all select o_orderkey * 8 + 4, n_regionkey from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey
  union all select distinct (l_orderkey * 16 + l_linenumber) * 8 + 5, n_regionkey from lineitem join orders on l_orderkey = o_orderkey
    join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey)
"""
FK_CC = f"with {FK_REGION} select id, max(id) over (partition by r) as component from r"
EVENT_CC = "select event_id * 8 + 7 as id, max(event_id * 8 + 7) over (partition by user_id) as component from events"


def session_sql(hours: int) -> str:
    return f"""
with g as (select event_id, user_id, ts, case when ts - lag(ts) over w <= interval {hours} hour then 0 else 1 end as fresh from events window w as (partition by user_id order by ts, event_id)),
s as (select event_id, user_id, sum(fresh) over (partition by user_id order by ts, event_id) as k from g)
select event_id * 8 + 7 as id, max(event_id * 8 + 7) over (partition by user_id, k) as component from s"""


def cut_sql(n: int) -> str:
    return f"""
with s as (select event_id, user_id, (row_number() over (partition by user_id order by ts, event_id) - 1) // {n} as k from events)
select event_id * 8 + 7 as id, max(event_id * 8 + 7) over (partition by user_id, k) as component from s"""


CONV_CC = "select (conv_id * 16 + turn) * 8 + 7 as id, max((conv_id * 16 + turn) * 8 + 7) over (partition by conv_id) as component from conversations"
COPY_CC = "select doc_id as id, max(doc_id) over (partition by coalesce(text, '')) as component from documents"
ONE_TREE = "select o_orderkey as id, (select max(o_orderkey) from orders) as component from orders"


@query("cc_fk", FK_CC)
def cc_fk(s, d) -> DataFrame:
    """Flagship: components of the foreign-key forest."""
    return components(workloads.fk_forest(s, d))


flagship = cc_fk


@query("cc_fk_sizes", f"with {FK_REGION} select max(id) as component, count(*) as nodes from r group by r")
def cc_fk_sizes(s, d):
    return components(workloads.fk_forest(s, d)).groupBy("component").agg(F.count(F.lit(1)).alias("nodes"))


@query("cc_fk_rollup", f"with {FK_REGION}, c as (select id % 8 as kind, max(id) over (partition by r) as component from r) select component, kind, count(*) as nodes from c group by rollup (component, kind)")
def cc_fk_rollup(s, d):
    c = components(workloads.fk_forest(s, d))
    return c.select("component", F.pmod("id", F.lit(8)).alias("kind")).rollup("component", "kind").agg(F.count(F.lit(1)).alias("nodes"))


query("cc_events", EVENT_CC)(lambda s, d: components(workloads.event_chain(s, d)))
for h in (1, 6, 24):
    query(f"cc_sessions_{h}h", session_sql(h))(lambda s, d, h=h: components(workloads.event_sessions(s, d, h)))
for n in (4, 16, 64):
    query(f"cc_cut_{n}", cut_sql(n))(lambda s, d, n=n: components(workloads.event_cut(s, d, n)))
query("cc_conversations", CONV_CC)(lambda s, d: components(workloads.conversations(s, d)))
query("cc_copies", COPY_CC)(lambda s, d: components(workloads.copy_stars(s, d)))
query("cc_heap2", ONE_TREE)(lambda s, d: components(workloads.heap(s, d, 2)))
query("cc_attach", ONE_TREE)(lambda s, d: components(workloads.attach(s, d)))
query("cc_near_fallback", ONE_TREE)(lambda s, d: components_fallback(workloads.near(s, d)))
query(
    "cc_caterpillars",
    "with x as (select o_orderkey * 8 + 4 as id, o_custkey as c from orders union all select distinct (l_orderkey * 16 + l_linenumber) * 8 + 5, o_custkey from lineitem join orders on l_orderkey = o_orderkey) select id, max(id) over (partition by c) as component from x",
)(lambda s, d: components(workloads.caterpillars(s, d)))


@query(
    "cc_url",
    "with u as (select distinct string_split(regexp_extract(url, '://([^?#]*)', 1), '/') as p from pages where regexp_extract(url, '://([^?#]*)', 1) <> ''), x as (select distinct p[1] as host, array_to_string(p[1 : k], '/') as prefix from u, lateral (select unnest(range(1, len(p) + 1)) as k)) select host, count(*) as nodes from x group by host",
)
def cc_url(s, d):
    forest, names = workloads.url_trie(s, d)
    c = components(forest).join(names, "id")
    return c.groupBy("component").agg(F.min(F.substring_index("prefix", "/", 1)).alias("host"), F.count(F.lit(1)).alias("nodes")).select("host", "nodes")


# --- the core without shrinking -----------------------------------------------------------------------------

query("maxid_core_cut16", cut_sql(16))(lambda s, d: _named(max_id(*_parts(workloads.event_cut(s, d, 16)), 16, Budget(256))))
query("maxid_core_fk", FK_CC)(lambda s, d: _named(max_id(*_parts(workloads.fk_forest(s, d)), 8, Budget(8))))


def _parts(forest):
    with swept(forest.nodes.sparkSession):
        k = forest.kept()
    return k.nodes, k.edges


def _named(answers: DataFrame) -> DataFrame:
    return answers.select("id", F.col("best").alias("component"))


@query("contract_paths_events", "with e as (select user_id, min(event_id * 8 + 7) as lo, max(event_id * 8 + 7) as hi from events group by user_id having count(*) > 1) select lo as src, hi as dst from e union all select hi, lo from e")
def contract_paths_events(s, d):
    f = workloads.event_chain(s, d).kept()
    return contract_paths(f.nodes.withColumn("best", F.col("id")), f.edges).edges


@query("view_growth_cut8", "with s as (select event_id * 8 + 7 as id, user_id, row_number() over (partition by user_id order by ts, event_id) - 1 as r from events) select a.id as owner, b.id as known, abs(a.r - b.r) as dist from s a join s b on a.user_id = b.user_id and a.r // 8 = b.r // 8 and a.r <> b.r and abs(a.r - b.r) <= 2")
def view_growth_cut8(s, d):
    v = V.start(workloads.event_cut(s, d, 8).edges)
    return V.distinct_rows(v.unionByName(V.grow(v, v))).select("owner", "known", "dist")


@query("probe_cut8", "with s as (select event_id * 8 + 7 as id, user_id, row_number() over (partition by user_id order by ts, event_id) - 1 as r, count(*) over (partition by user_id) as n from events), p as (select a.id, b.id as nb, case when b.r > a.r then (case when b.r % 8 < 7 and b.r + 1 < b.n then 1 else 0 end) else (case when b.r % 8 > 0 then 1 else 0 end) end as est from s a join s b on a.user_id = b.user_id and a.r // 8 = b.r // 8 and abs(a.r - b.r) = 1) select id as owner, nb as first_hop, est::bigint as est from p")
def probe_cut8(s, d):
    return V.estimates(V.start(workloads.event_cut(s, d, 8).edges)).select("owner", "first_hop", "est")


@query("is_fraction", "with g as (select user_id, count(*) as n from events group by user_id) select sum(greatest(n - 2, 0))::bigint as two, 0::bigint as shortfall, 0::bigint as adjacent from g")
def is_fraction(s, d):
    """Degree-2 nodes, missing ones to an eighth, adjacent chosen pairs."""
    e = write(workloads.event_chain(s, d).edges, "edges").df
    info = e.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("deg"), F.min("dst").alias("lo"), F.max("dst").alias("hi"))
    two = write(info.filter("deg = 2").select("id", "lo", "hi"), "two").df
    got = write(sparse_independent(two, "conditional"), "chosen").df
    near = e.join(got.select(F.col("id").alias("src")), "src").join(got.select(F.col("id").alias("dst")), "dst").agg(F.count(F.lit(1)).alias("adjacent"))
    n = two.agg(F.count(F.lit(1)).alias("two")).crossJoin(got.agg(F.count(F.lit(1)).alias("got"))).crossJoin(near)
    return n.select("two", F.greatest(F.lit(0).cast("long"), F.ceil(F.col("two") / 8).cast("long") - F.col("got")).alias("shortfall"), "adjacent")


# --- rooting and pointers -----------------------------------------------------------------------------------


def _root_report(s, d, forest) -> DataFrame:
    f = forest.kept()
    r = write(root_forest(f), "rooted").df
    bad = root_defects(f, r).agg(F.count(F.lit(1)).alias("defects"))
    return r.agg(F.count(F.lit(1)).alias("nodes"), F.count_if(F.col("parent").isNull()).alias("roots")).crossJoin(bad)


query("root_fk", f"with {FK_REGION} select count(*) as nodes, count(distinct r) as roots, 0::bigint as defects from r")(lambda s, d: _root_report(s, d, workloads.fk_forest(s, d)))
query("root_cut16", f"with c as ({cut_sql(16)}) select count(*) as nodes, count(distinct component) as roots, 0::bigint as defects from c")(lambda s, d: _root_report(s, d, workloads.event_cut(s, d, 16)))


def _heap_parents(s, d) -> DataFrame:
    return table(s, d, "orders").selectExpr("o_orderkey id", "case when o_orderkey > 0 then (o_orderkey - 1) div 2 end parent")


HEAP_DEPTH = "with recursive t as (select 0::bigint as id, 0::bigint as depth union all select o_orderkey, depth + 1 from t join orders on o_orderkey in (2 * id + 1, 2 * id + 2))"
HEAP_SIZES = "with recursive a as (select o_orderkey as id, o_orderkey as anc from orders union all select id, (anc - 1) // 2 from a where anc > 0), z as (select anc as id, count(*) as size from a group by anc)"
query("depth_heap2", f"{HEAP_DEPTH} select id, depth from t")(lambda s, d: depths(_heap_parents(s, d)))
query("two_colour_heap2", f"{HEAP_DEPTH} select id, depth % 2 as colour from t")(lambda s, d: two_colour(_heap_parents(s, d)))
query("subtree_sizes_heap2", f"{HEAP_SIZES} select id, least(size, 101) as size, size > 100 as heavy from z")(lambda s, d: subtree_sizes(_heap_parents(s, d), 100))
query(
    "local_roots_heap2",
    f"{HEAP_SIZES} select distinct p.id from z p join z c on c.id in (2 * p.id + 1, 2 * p.id + 2) where p.size > 100 and c.size <= 100",
)(lambda s, d: mark_local_roots(p := write(_heap_parents(s, d), "parents").df, subtree_sizes(p, 100)))
query("sum_subtree_sizes_heap2", f"{HEAP_DEPTH} select sum(depth + 1)::bigint as total, count(*) as nodes, max(depth) as longest from t")(
    lambda s, d: depths(_heap_parents(s, d)).agg(F.sum(F.col("depth") + 1).alias("total"), F.count(F.lit(1)).alias("nodes"), F.max("depth").alias("longest"))
)

# --- single steps: light subtrees, rake, splice -------------------------------------------------------------


@query(
    "light_heavy_heap2",
    f"{HEAP_SIZES}, n as (select count(*) as n from orders) select id, (id - 1) // 2 as against, size as subtree from z where id > 0 and size <= 100 union all select (id - 1) // 2, id, n - size from z, n where id > 0 and n - size <= 100",
)
def light_heavy_heap2(s, d):
    """Light sides of at most 100 nodes, from subtree sizes."""
    f, p = workloads.heap(s, d, 2).kept(), write(_heap_parents(s, d), "parents").df
    sizes = subtree_sizes(p, p.count()).select("id", "size")
    return classify_exact(f.edges, f.nodes, p.select("id", "parent", F.lit(0).cast("long").alias("root")), sizes, 100)


@query("leaf_rake_once", 'select o_orderkey as node, (o_orderkey - 1) // 2 as "into" from orders where 2 * o_orderkey + 1 not in (select o_orderkey from orders)')
def leaf_rake_once(s, d):
    """The leaves that one step hangs on their neighbours."""
    f = workloads.heap(s, d, 2).kept()
    return actions(write(f.edges, "edges").df, 0).filter("kind = 'rake'").select("node", "into")


def _hash_sql(c: str) -> str:
    out = "0"
    for k in coefficients(1):
        out = f"(({out} * ({c} % {PRIME}) + {k}) % {PRIME})"
    return out


@query(
    "splice_once",
    f"with s as (select event_id * 8 + 7 as id, row_number() over w as r, count(*) over (partition by user_id) as n, lag(event_id * 8 + 7) over w as p, lead(event_id * 8 + 7) over w as q from events window w as (partition by user_id order by ts, event_id)) select id as node, least(p, q) as lo, greatest(p, q) as hi from s where r between 3 and n - 2 and {_hash_sql('id')} < {_hash_sql('p')} and {_hash_sql('id')} < {_hash_sql('q')}",
)
def splice_once(s, d):
    """The degree-2 nodes that one step splices out: hash minima without an acting leaf beside them."""
    return actions(write(workloads.event_chain(s, d).edges, "edges").df, 0).filter("kind = 'splice'").select("node", "lo", "hi")


# --- labellings ---------------------------------------------------------------------------------------------

query(
    "ports_fk",
    f"with {FK_SQL}, e as (select a, b from pairs union select b, a from pairs) select a as node, b as other, row_number() over (partition by a order by b) as node_port, case when a < b then 1 else 2 end::bigint as edge_port from e",
)(lambda s, d: assign_ports(workloads.fk_forest(s, d).edges).select("node", "other", F.col("node_port").cast("long"), F.col("edge_port").cast("long")))


def _event_heads(s, d) -> DataFrame:
    e = table(s, d, "events").select("event_id", "user_id", "ts")
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return e.withColumn("r", F.row_number().over(w)).filter("r = 1").select(F.expr("event_id * 8 + 7").alias("id"))


PATH_SQL = "select event_id * 8 + 7 as id, row_number() over (partition by user_id order by ts, event_id) as distance from events"
query("path_dist_events", PATH_SQL)(lambda s, d: path_distances(workloads.event_chain(s, d).edges, _event_heads(s, d)))
for i in (0, 1, 2):
    query(f"mis_level_{i}", f"with p as ({PATH_SQL}) select id from p where distance % {2 << i} <> 0")(
        lambda s, d, i=i: path_distances(workloads.event_chain(s, d).edges, _event_heads(s, d)).filter(mis_level(F.col("distance"), i)).select("id")
    )


def _lcl(s, d, p, given=None, solver=None) -> DataFrame:
    f = workloads.event_cut(s, d, 16).kept()
    labels, none = solver(f, p, given) if solver else solve_lcl(f, p, given, cap=4)
    labels = write(labels, "labels").df
    bad = violations(p, f.edges, labels, given).agg(F.count(F.lit(1)).alias("violations"))
    n = f.nodes.agg(F.count(F.lit(1)).alias("nodes"))
    return n.crossJoin(labels.agg(F.count(F.lit(1)).alias("half_edges"))).crossJoin(bad).crossJoin(none.agg(F.count(F.lit(1)).alias("unsolvable")))


_CUT = f"c as ({cut_sql(16)}), g as (select count(*) as nodes, count(distinct component) as trees from c)"
for name, p in (("mis", lcl.independent_set), ("match", lcl.matching), ("col3", lambda: lcl.colouring(3)), ("col2", lambda: lcl.colouring(2))):
    query(f"lcl_{name}_violations", f"with {_CUT} select nodes, 2 * (nodes - trees) as half_edges, 0::bigint as violations, 0::bigint as unsolvable from g")(lambda s, d, p=p: _lcl(s, d, p()))


@query(
    "compat_init_cut16",
    "with s as (select event_id * 8 + 7 as id, user_id, row_number() over (partition by user_id order by ts, event_id) - 1 as r from events), x as (select id, user_id, r // 16 as k, r, lag(id) over w as p, lead(id) over w as q, max(id) over (partition by user_id, r // 16) as root from s window w as (partition by user_id, r // 16 order by r)), y as (select *, max(case when id = root then r end) over (partition by user_id, k) as top from x), z as (select *, case when r < top then q when r > top then p end as parent, case when r < top then p else q end as other from y) select z.id, z.parent, z.root, case when z.parent is not null then (z.other is not null and z.other < z.parent)::int::bigint end as op, case when z.parent is not null then (case when u.p = z.id then u.q else u.p end is not null and case when u.p = z.id then u.q else u.p end < z.id)::int::bigint end as pp from z left join y u on u.id = z.parent",
)
def compat_init_cut16(s, d):
    """Ports of every node towards its parent and of the parent towards it."""
    f = workloads.event_cut(s, d, 16).kept()
    rows = init_compat(f, write(root_forest(f), "rooted").df, lcl.independent_set())
    return rows.select("id", "parent", "root", F.col("op").cast("long").alias("op"), F.col("pp").cast("long").alias("pp"))


@query("baseline_lcl_rake_cut16", f"with {_CUT} select nodes, 2 * (nodes - trees) as half_edges, 0::bigint as violations, 0::bigint as unsolvable from g")
def baseline_lcl_rake_cut16(s, d):
    return _lcl(s, d, lcl.independent_set(), solver=labelling.lcl_rake_compress)


@query("baseline_mis_colours_events", "select count(*) as nodes, 0::bigint as adjacent, 0::bigint as uncovered from events")
def baseline_mis_colours_events(s, d):
    """Independent set of the event chains by colour reduction: nodes, adjacent pairs inside, nodes without a member beside them."""
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    chain = write(table(s, d, "events").select((F.col("event_id") * 8 + 7).alias("id"), F.lead(F.col("event_id") * 8 + 7).over(w).alias("next")), "chain").df
    inside = write(labelling.mis_colour_reduction(chain), "inside").df
    e = chain.filter("next is not null")
    e = write(e.select(F.col("id").alias("a"), F.col("next").alias("b")).unionByName(e.select(F.col("next").alias("a"), F.col("id").alias("b"))), "edges").df
    near = e.join(inside.select(F.col("id").alias("b")), "b", "left_semi").select(F.col("a").alias("id")).distinct()
    adjacent = inside.join(near, "id", "left_semi").agg(F.count(F.lit(1)).alias("adjacent"))
    bare = chain.select("id").join(inside, "id", "left_anti").join(near, "id", "left_anti").agg(F.count(F.lit(1)).alias("uncovered"))
    return chain.agg(F.count(F.lit(1)).alias("nodes")).crossJoin(adjacent).crossJoin(bare)


@query("lcl_odd_unsolvable", f"with c as ({cut_sql(16)}) select distinct component from c")
def lcl_odd_unsolvable(s, d):
    return solve_lcl(workloads.event_cut(s, d, 16).kept(), lcl.odd_out_degree(), cap=4)[1]


@query("lcl_reach", "with x as (select event_id * 8 + 7 as id, user_id, row_number() over (partition by user_id order by ts, event_id) as r, count(*) over (partition by user_id) as n from events where user_id % 2 = 0) select id as node, case when n > 1 then (r > 1) end as entered from x where r = 1 or r = n")
def lcl_reach(s, d):
    """Paths of even users are marked at their first event; which ends does the orientation enter?"""
    f = workloads.event_chain(s, d).kept()
    ends = f.degrees().filter("degree <= 1").select("id", "degree")
    even = table(s, d, "events").filter("user_id % 2 = 0").select(F.expr("event_id * 8 + 7").alias("id"))
    marks = _event_heads(s, d).join(even, "id", "left_semi").withColumn("given", F.lit(1))
    labels, _ = solve_lcl(f, lcl.endpoint_reach(), marks, cap=8)
    last = ends.join(even, "id", "left_semi").withColumnRenamed("id", "node")
    return last.join(labels, "node", "left").select("node", (F.col("label") == 0).alias("entered"))


# --- hardness -----------------------------------------------------------------------------------------------


@query("st_connected_sessions", "with g as (select event_id, user_id, ts, case when ts - lag(ts) over w <= interval 24 hour then 0 else 1 end as fresh from events window w as (partition by user_id order by ts, event_id)), s as (select event_id, user_id, sum(fresh) over (partition by user_id order by ts, event_id) as k from g), e as (select user_id, min(event_id) as a, max(event_id) as b from events group by user_id having count(*) > 1) select e.a * 8 + 7 as s, e.b * 8 + 7 as t, x.k = y.k as connected from e join s x on x.event_id = e.a join s y on y.event_id = e.b")
def st_connected_sessions(s, d):
    pairs = table(s, d, "events").groupBy("user_id").agg(F.expr("min(event_id) * 8 + 7").alias("s"), F.expr("max(event_id) * 8 + 7").alias("t")).filter("s <> t")
    return hardness.st_connected(workloads.event_sessions(s, d, 24), pairs.select("s", "t"))


@query("cycles_verdict", "select k as parts, (n // k) * k as nodes, k as cycles from (select count(*) as n from orders), (values (1::bigint), (2::bigint)) v(k)")
def cycles_verdict(s, d):
    one = hardness.cycle_count(workloads.cycles(s, d, 1)).select(F.lit(1).cast("long").alias("parts"), "nodes", "cycles")
    two = hardness.cycle_count(workloads.cycles(s, d, 2)).select(F.lit(2).cast("long").alias("parts"), "nodes", "cycles")
    return one.unionByName(two)


@query("cycles_shrunk", "select k as parts, k as cycles from (values (1::bigint), (2::bigint)) v(k)")
def cycles_shrunk(s, d):
    """The number of cycles after rounds of anchor sampling."""
    out = None
    for k in (1, 2):
        e, _ = hardness.shrink_cycles(workloads.cycles(s, d, k), 8)
        c = hardness.cycle_count(e.select(F.col("src").alias("a"), F.col("dst").alias("b"))).select(F.lit(k).cast("long").alias("parts"), "cycles")
        out = c if out is None else out.unionByName(c)
    return out


# --- costs --------------------------------------------------------------------------------------------------


@query("ledger_bounds_heap2", f"{HEAP_DEPTH} select count(*) as nodes, count(*) - 1 as edges, sum(depth + 1)::bigint as subtree_total, 0::bigint as broken from t")
def ledger_bounds_heap2(s, d):
    """Nodes, edges, sum of subtree sizes, and how many of the checked bounds break.

    Bounds: pointer rounds <= log2(depth) + 2; sum of subtree sizes <= (D + 1) n; shrink steps <= 32 log2 n.
    """
    ledger, steps = Ledger(), Ledger()
    t = write(depths(_heap_parents(s, d), ledger), "depths").df
    row = t.agg(F.count(F.lit(1)).alias("n"), F.max("depth").alias("deep"), F.sum(F.col("depth") + 1).alias("total")).first()
    n, deep, total = row["n"], row["deep"], row["total"]
    f = workloads.heap(s, d, 2).kept()
    write(components(f, ledger=steps), "components")
    broken = [ledger.rounds("pointers") > max(1, deep).bit_length() + 2, total > (2 * deep + 1) * n, len([r for r in steps.rows if r[0] == "shrink"]) > 32 * n.bit_length()]
    edges = f.edges.agg((F.count(F.lit(1)) / 2).cast("long").alias("edges"))
    return t.agg(F.count(F.lit(1)).alias("nodes"), F.sum(F.col("depth") + 1).alias("subtree_total")).crossJoin(edges).withColumn("broken", F.lit(sum(broken)).cast("long"))


# --- baselines ----------------------------------------------------------------------------------------------

for name, f in (("flood", baselines.flood_max), ("peel", baselines.peel), ("uniform", baselines.uniform_doubling), ("rake", baselines.rake_compress)):
    query(f"baseline_{name}_cut16", cut_sql(16))(lambda s, d, f=f: f(workloads.event_cut(s, d, 16).kept()))
query("baseline_contract_cut16", cut_sql(16))(lambda s, d: labelling.contract_until_small(workloads.event_cut(s, d, 16).kept()))
query("baseline_star_fk", FK_CC)(lambda s, d: components_fallback(workloads.fk_forest(s, d)))
query("baseline_broadcast_heap2", ONE_TREE)(lambda s, d: baselines.broadcast_max(workloads.heap(s, d, 2)))

# --- streams ------------------------------------------------------------------------------------------------


@query("stream_tumbling", "select epoch_us(time_bucket(interval 1 day, ts)) as start, event_type, count(*) as n from events group by 1, 2")
def stream_tumbling(s, d):
    return streaming.available(streaming.tumbling(streaming.events_stream(s, f"{d}/events.parquet")), "complete")


@query("stream_sliding", "with w as (select time_bucket(interval 1 day, ts) as d, event_type from events) select epoch_us(s) as start, event_type, count(*) as n from (select d as s, event_type from w union all select d - interval 1 day, event_type from w) group by 1, 2")
def stream_sliding(s, d):
    return streaming.available(streaming.sliding(streaming.events_stream(s, f"{d}/events.parquet")), "complete")


@query("stream_sessions", "with g as (select event_id, user_id, ts, case when ts - lag(ts) over w < interval 6 hour then 0 else 1 end as fresh from events window w as (partition by user_id order by ts, event_id)), s as (select event_id, user_id, sum(fresh) over (partition by user_id order by ts, event_id) as k from g) select user_id, count(*) as n, max(event_id) as top from s group by user_id, k")
def stream_sessions(s, d):
    return streaming.available(streaming.sessions(streaming.events_stream(s, f"{d}/events.parquet")), "complete")


@query("stream_interval_join", ORACLES["ops_interval_join"])
def stream_interval_join(s, d):
    return streaming.available(streaming.view_to_purchase(streaming.events_stream(s, f"{d}/events.parquet")))


@query("stream_components", "select event_id as id, min(event_id) over (partition by user_id) as component from events")
def stream_components(s, d):
    """Links user's first event - event, fed as a stream and kept as components."""
    first = table(s, d, "events").groupBy("user_id").agg(F.min("event_id").alias("b"))
    live = streaming.LiveComponents(s)
    pairs = streaming.events_stream(s, f"{d}/events.parquet").join(first, "user_id").select(F.col("event_id").alias("a"), "b").filter("a <> b")
    live.follow(pairs)
    return live.labels

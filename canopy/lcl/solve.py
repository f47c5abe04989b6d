"""Solve a labelling problem on a forest, or report the trees that have no solution.

Forward, in phases: subtrees of at most ``cap`` nodes are folded into their local root (one
grouped map for each; what is kept are the labels that the subtree allows on the edge to
it), then runs of nodes with one child are packed: at level i the nodes whose distance from
the head of their run is no multiple of 2^(i+1) give way to one edge whose relation is the
boolean product of the two edges and of the node between them.  Backward: each root takes its
smallest tuple; levels and subtrees follow in reverse, always with the smallest tuple that fits.

Rows are ``(id, parent, root, op, pp, rel, tuples)``: ``op`` is the node's port to its parent, ``pp`` the
parent's port to it (0-based), ``rel`` the relation of the edge as a bit matrix (bit 7a+b:
label a at the parent's end, b at the node's), ``tuples`` what the node still allows.
"""

from __future__ import annotations

from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from canopy.ledger import Ledger
from canopy.lcl.problem import MAX_DEGREE, LclProblem
from canopy.lcl.sizing import assign_ports, gather_light, mis_level, subtree_sizes
from canopy.model.forest import Forest
from canopy.rooting import pointers, root_forest
from canopy.store import write

SIDE = 7
#: Kinds (degree, input label) of a problem's table; labels are constant in number.
MAX_KINDS = 10_000
COLUMN = sum(1 << (SIDE * a) for a in range(SIDE))
ROW = (1 << SIDE) - 1


def product(a: Column, b: Column) -> Column:
    """Boolean product of two 7 x 7 bit matrices, in integer arithmetic."""
    out = F.lit(0).cast("long")
    for k in range(SIDE):
        left = (F.shiftright(a, k).bitwiseAND(F.lit(COLUMN))) * F.lit(ROW)
        right = (F.shiftright(b, SIDE * k).bitwiseAND(F.lit(ROW))) * F.lit(COLUMN)
        out = out.bitwiseOR(left.bitwiseAND(right))
    return out


def relation(tuples: Column, p: Column, c: Column) -> Column:
    """Bit matrix between the labels at two ports of a node."""
    return F.aggregate(tuples, F.lit(0).cast("long"), lambda acc, t: acc.bitwiseOR(_shift(F.get(t, p) * SIDE + F.get(t, c))))


def _shift(n: Column) -> Column:
    return F.call_function("shiftleft", F.lit(1).cast("long"), n.cast("int"))


def holds(rel: Column, a: Column, b: Column) -> Column:
    return F.call_function("shiftright", rel, (a * SIDE + b).cast("int")).bitwiseAND(F.lit(1)) == 1


def init_compat(forest: Forest, rooted: DataFrame, problem: LclProblem, given: DataFrame | None = None) -> DataFrame:
    """The starting rows; every node holds all port assignments that its degree and input label allow."""
    ports = write(assign_ports(forest.edges), "ports").df
    deg = forest.degrees()
    n = rooted.join(deg, "id")
    n = n.join(given.select("id", F.col("given").cast("int").alias("given")), "id", "left") if given is not None else n.withColumn("given", F.lit(0))
    n = n.withColumn("given", F.coalesce("given", F.lit(0)))
    top = n.agg(F.max("degree")).first()[0] or 0
    if top > MAX_DEGREE:
        raise ValueError(f"degree {top} is above the limit of {MAX_DEGREE} for labelling problems")
    kinds = [(r["degree"], r["given"]) for r in n.select("degree", "given").distinct().limit(MAX_KINDS + 1).collect()]
    if len(kinds) > MAX_KINDS:
        raise ValueError(f"more than {MAX_KINDS} kinds of degree and input label: a problem has a constant number of them")
    n = n.join(F.broadcast(problem.table(forest.nodes.sparkSession, kinds)), ["degree", "given"])
    up = ports.select(F.col("node").alias("id"), F.col("other").alias("parent"), (F.col("node_port") - 1).alias("op"))
    down = ports.select(F.col("other").alias("id"), F.col("node").alias("parent"), (F.col("node_port") - 1).alias("pp"))
    n = n.join(up, ["id", "parent"], "left").join(down, ["id", "parent"], "left")
    return n.select("id", "parent", "root", "op", "pp", F.lit(problem.matrix()).cast("long").alias("rel"), "tuples")


_GROUP = "local_root long, id long, parent long, op int, pp int, rel long, tuples array<array<int>>"


def _order(rows: list[dict]) -> list[dict]:
    """Children before parents."""
    kids: dict = {}
    for r in rows:
        kids.setdefault(r["parent"], []).append(r)
    out, todo = [], [r for r in rows if r["parent"] == r["local_root"]]
    while todo:
        r = todo.pop()
        out.append(r)
        todo += kids.get(r["id"], ())
    return out[::-1]


def _fold_group(t: pa.Table) -> pa.Table:
    """Prune the tuples of a light subtree bottom-up; adds ``feasible``: labels allowed at the parent's port, as bits."""
    rows = _order(t.to_pylist())
    masks: dict = {}
    out = []
    for r in rows:
        mine = masks.get(r["id"], {})
        r["tuples"] = [x for x in r["tuples"] if all(m >> x[p] & 1 for p, m in mine.items())]
        ends = {x[r["op"]] for x in r["tuples"]}
        ok = sum(1 << a for a in range(SIDE) if any(r["rel"] >> (SIDE * a + b) & 1 for b in ends))
        r["feasible"] = ok
        masks.setdefault(r["parent"], {})[r["pp"]] = ok
        out.append(r)
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.list_(pa.list_(pa.int32())), pa.int32()]
    names = ["local_root", "id", "parent", "op", "pp", "rel", "tuples", "feasible"]
    return pa.Table.from_arrays([pa.array([r[n] for r in out], k) for n, k in zip(names, kinds)], names=names)


def _unfold_group(t: pa.Table) -> pa.Table:
    """Smallest fitting tuples of a light subtree, top-down; ``host`` is the tuple of the local root."""
    rows = t.to_pylist()
    chosen = {rows[0]["local_root"]: rows[0]["host"]}
    out = []
    for r in reversed(_order(rows)):
        a = chosen[r["parent"]][r["pp"]]
        pick = min(x for x in r["tuples"] if r["rel"] >> (SIDE * a + x[r["op"]]) & 1)
        chosen[r["id"]] = pick
        out.append((r["id"], pick))
    return pa.table({"id": pa.array([i for i, _ in out], pa.int64()), "tuple": pa.array([x for _, x in out], pa.list_(pa.int32()))})


def fold_subtrees(rows: DataFrame, hosts: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(rows left, folded rows): light subtrees of ``hosts(light, local_root)`` prune their local root."""
    light = rows.join(hosts.select(F.col("light").alias("id"), "local_root"), "id")
    folded = light.select("local_root", "id", "parent", "op", "pp", "rel", "tuples").groupBy("local_root").applyInArrow(_fold_group, _GROUP + ", feasible int")
    folded = write(folded, "folded").df
    tops = folded.filter("parent = local_root").groupBy(F.col("local_root").alias("id")).agg(F.collect_list(F.struct("pp", "feasible")).alias("f"))
    left = rows.join(hosts.select(F.col("light").alias("id")), "id", "left_anti").join(tops, "id", "left")
    fits = lambda t: F.forall("f", lambda x: F.call_function("shiftright", x["feasible"], F.get(t, x["pp"])).bitwiseAND(F.lit(1)) == 1)
    left = left.withColumn("tuples", F.when(F.col("f").isNull(), F.col("tuples")).otherwise(F.filter("tuples", fits))).drop("f")
    return write(left, "rows").df, folded


@dataclass
class Packed:
    rows: DataFrame
    levels: list[DataFrame]


def pack_paths(rows: DataFrame, ledger: Ledger | None = None, phase: int = 0) -> Packed:
    """Replace runs of nodes with a parent and one child by single edges, level by level."""
    kids = rows.filter("parent is not null").groupBy(F.col("parent").alias("id")).agg(F.count(F.lit(1)).alias("kids"))
    inner = write(rows.filter("parent is not null").join(kids.filter("kids = 1"), "id").select("id", "parent"), "inner").df
    chain = inner.join(inner.select(F.col("id").alias("parent"), F.lit(1).alias("on")), "parent", "left").select("id", F.when(F.col("on") == 1, F.col("parent")).alias("parent"))
    dist = write(pointers(chain).select("id", (F.col("hops") + 1).alias("dist")), "distances").df
    longest = dist.agg(F.max("dist")).first()[0] or 0
    levels = []
    i = 0
    while longest >= 1 << i:
        gone_ids = dist.filter(mis_level(F.col("dist"), i) & (F.pmod("dist", F.shiftleft(F.lit(1).cast("long"), i)) == 0)).select("id")
        gone = rows.join(gone_ids, "id").select(*[F.col(c).alias(f"v_{c}") for c in ("id", "parent", "op", "pp", "rel", "tuples")])
        stay = rows.join(gone_ids, "id", "left_anti")
        j = write(stay.join(gone, stay.parent == gone.v_id, "left"), "packs").df
        hit = F.col("v_id").isNotNull()
        levels.append(j.filter(hit).select(F.col("id").alias("x"), F.col("op").alias("x_op"), F.col("pp").alias("c"), F.col("rel").alias("x_rel"), "v_id", "v_parent", "v_op", "v_pp", "v_rel", "v_tuples"))
        between = relation(F.col("v_tuples"), F.col("v_op"), F.col("pp"))
        rel = F.when(hit, product(product(F.col("v_rel"), between), F.col("rel"))).otherwise(F.col("rel"))
        rows = write(
            j.select("id", F.when(hit, F.col("v_parent")).otherwise(F.col("parent")).alias("parent"), "root", "op", F.when(hit, F.col("v_pp")).otherwise(F.col("pp")).alias("pp"), rel.alias("rel"), "tuples"),
            "rows",
        ).df
        if ledger is not None:
            ledger.add("pack", "level", phase, i, 2)
        i += 1
    return Packed(rows, levels)


def unpack_paths(chosen: DataFrame, levels: list[DataFrame]) -> DataFrame:
    """Tuples of the packed nodes, last level first: the smallest one that fits both sides."""
    for lv in reversed(levels):
        up = chosen.select(F.col("id").alias("v_parent"), F.col("tuple").alias("up"))
        low = chosen.select(F.col("id").alias("x"), F.col("tuple").alias("low"))
        j = lv.join(up, "v_parent").join(low, "x")
        j = j.select("v_id", "v_tuples", "v_rel", "x_rel", "v_op", "c", F.get("up", F.col("v_pp")).alias("a"), F.get("low", F.col("x_op")).alias("b"))
        fits = F.filter("v_tuples", lambda t: holds(F.col("v_rel"), F.col("a"), F.get(t, F.col("v_op"))) & holds(F.col("x_rel"), F.get(t, F.col("c")), F.col("b")))
        chosen = write(chosen.unionByName(j.select(F.col("v_id").alias("id"), F.array_min(fits).alias("tuple"))), "chosen").df
    return chosen


def unfold_subtrees(chosen: DataFrame, folded: DataFrame) -> DataFrame:
    host = chosen.select(F.col("id").alias("local_root"), F.col("tuple").alias("host"))
    got = folded.drop("feasible").join(host, "local_root").groupBy("local_root").applyInArrow(_unfold_group, "id long, tuple array<int>")
    return write(chosen.unionByName(got), "chosen").df


def solve_lcl(forest: Forest, problem: LclProblem, given: DataFrame | None = None, cap: int = 64, scope: str = "component", ledger: Ledger | None = None, rooted: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """``(labels(node, other, label), unsolvable(component))``.

    Trees without a solution get no labels and are listed; with ``scope='graph'`` one such tree
    leaves the whole forest without labels.
    """
    rooted = write(root_forest(forest, ledger=ledger), "rooted").df if rooted is None else rooted
    rows = write(init_compat(forest, rooted, problem, given), "rows").df
    history: list[tuple[DataFrame, list[DataFrame]]] = []
    for phase in range(64):
        if rows.filter("parent is not null").isEmpty():
            break
        tree = rows.select("id", "parent")
        sizes = subtree_sizes(tree, cap, ledger)
        hosts = write(gather_light(tree, sizes, ledger), "hosts").df
        # in a tree that is light as a whole the root itself is the local root
        lone = sizes.filter("not heavy").join(tree.filter("parent is null"), "id").select("id")
        hosts = write(hosts.join(lone.select(F.col("id").alias("light")), "light", "left_anti"), "hosts").df
        rows, folded = fold_subtrees(rows, hosts)
        if ledger is not None:
            ledger.add("fold", "subtrees", phase, 0, 1, folded.count(), rows.count())
        packed = pack_paths(rows, ledger, phase)
        rows = packed.rows
        history.append((folded, packed.levels))
    verdict = write(rows.select("root", "id", F.array_min("tuples").alias("tuple"), (F.size("tuples") == 0).alias("none")), "verdict").df
    unsolvable = verdict.filter("none").select(F.col("root").alias("component"))
    chosen = verdict.filter("not none").select("id", "tuple")
    if scope == "graph" and not unsolvable.isEmpty():
        chosen = chosen.limit(0)
        unsolvable = verdict.select(F.col("root").alias("component"))
    for folded, levels in reversed(history):
        chosen = unfold_subtrees(unpack_paths(chosen, levels), folded)
    ports = assign_ports(forest.edges)
    labels = ports.join(chosen.withColumnRenamed("id", "node"), "node").select("node", "other", F.get("tuple", F.col("node_port") - 1).alias("label"))
    return labels, unsolvable

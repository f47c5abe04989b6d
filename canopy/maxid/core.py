"""Absorb light subtrees, contract paths, repeat; then unfold.

A node is light against its neighbour u if everything but u's side has at most ``light_cap``
nodes, itself included; it is heavy if it is light against nobody.  In each phase every
light subtree is folded into the heavy node that it hangs on (a tree without heavy nodes
into its largest id), then every run of degree-2 nodes into one edge.

The step of an iteration, for active nodes: estimate each direction; directions whose estimate
reaches ``light_cap * guess`` are blocked; with two blocked ones a node can never settle;
with one it widens its view everywhere else; with none it spares the direction that looks
largest (a trial growth decides if the estimates don't) and widens the others, and whoever
it learns of learns back.  A node settles against u when its view is closed in all other
directions and these hold at most ``light_cap - 1`` nodes.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from canopy import views as V
from canopy.budget import Budget
from canopy.ledger import Ledger
from canopy.store import Cut, scope, swept, unsent, write

ACTIVE, SETTLED, OVERFULL, HOPELESS = 0, 1, 2, 3


@dataclass
class Options:
    """Ablations: all on is the method."""

    mirror: bool = True
    spare: bool = True
    trial: bool = True


@dataclass
class Phase:
    nodes: DataFrame  # id, best
    edges: DataFrame
    folds: DataFrame  # kind, node, into, hop: the neighbour towards ``into``
    runs: DataFrame | None = None  # id, lo, hi, to_lo, to_hi: nodes of contracted paths, ends, neighbours towards these
    trees: DataFrame | None = None  # id, parent: trees without a heavy node, rooted at an end of their middle edge
    report: dict = field(default_factory=dict)


def classify_exact(edges: DataFrame, nodes: DataFrame, rooted: DataFrame, sizes: DataFrame, cap: int) -> DataFrame:
    """Test oracle: ``(id, against, subtree)`` of every light node, from subtree sizes of any rooting.

    ``rooted(id, parent, root)``, ``sizes(id, size)`` with the node itself counted.
    """
    total = rooted.groupBy("root").agg(F.count(F.lit(1)).alias("total"))
    s = rooted.join(sizes, "id").join(total, "root")
    up = s.filter("parent is not null").select("id", F.col("parent").alias("against"), F.col("size").alias("subtree"))
    down = s.filter("parent is not null").select(F.col("parent").alias("id"), F.col("id").alias("against"), (F.col("total") - F.col("size")).alias("subtree"))
    return up.unionByName(down).filter(F.col("subtree") <= cap)


def fold(nodes: DataFrame, edges: DataFrame, into: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Nodes and edges after ``into(node, into)``: the target keeps the largest best, outside edges are re-attached."""
    m = into.select(F.col("node").alias("id"), "into")
    new_nodes = nodes.join(m, "id", "left").groupBy(F.coalesce("into", "id").alias("id")).agg(F.max("best").alias("best"))
    a = into.select(F.col("node").alias("src"), F.col("into").alias("s"))
    b = into.select(F.col("node").alias("dst"), F.col("into").alias("t"))
    half = edges.filter("src < dst")  # the other half is the same turned round
    e = half.join(a, "src", "left").join(b, "dst", "left").select(F.coalesce("s", "src").alias("src"), F.coalesce("t", "dst").alias("dst")).filter("src <> dst")
    return new_nodes, e.unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def unfold(answers: DataFrame, folds: DataFrame) -> DataFrame:
    """Answers of the folded nodes are those of the nodes they went into."""
    got = folds.select("node", "into").join(answers.select(F.col("id").alias("into"), "best"), "into").select(F.col("node").alias("id"), "best")
    return answers.select("id", "best").unionByName(got)


def _decide(est: DataFrame, guess: int, cap: int, options: Options) -> DataFrame:
    """``(owner, first_hop, blocked, top, rival, rank, n_blocked)``; ranks break ties toward the larger neighbour."""
    e = est.withColumn("blocked", F.col("est") >= cap * guess)
    w = W.partitionBy("owner")
    order = w.orderBy(F.desc("est"), F.desc("first_hop"))
    return e.withColumns({"rank": F.row_number().over(order), "rival": F.lead("est", 1, 0).over(order), "n_blocked": F.count_if(F.col("blocked")).over(w)})


def _first(edges: DataFrame, cap: int) -> DataFrame:
    """``(id, state, against, subtree, deg)`` of views of one step, which `_settle` need not build.

    A direction is closed if its node is a leaf, and holds that node alone.  The one open neighbour is what is left of
    all neighbours xored with the leaves among them.
    """
    ends = write(edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("deg"), F.bit_xor("dst").alias("others")), "ends")
    # what is left of a single neighbour is the neighbour
    closed = ends.df.filter("deg = 1").groupBy(F.col("others").alias("id")).agg(F.count(F.lit(1)).alias("shut"), F.bit_xor("id").alias("leaves"), F.max("id").alias("top"))
    j = ends.df.join(closed, "id", "left").withColumn("opens", F.col("deg") - F.coalesce("shut", F.lit(0)))
    done = (F.col("opens") <= 1) & (F.col("deg") <= cap)
    against = F.when(F.col("opens") == 1, F.col("others").bitwiseXOR(F.coalesce("leaves", F.lit(0).cast("long")))).otherwise(F.col("top"))
    state = F.when(F.col("deg") > cap + 1, HOPELESS).when(done, SETTLED).otherwise(ACTIVE)
    states = write(j.select("id", state.alias("state"), F.when(done, against).alias("against"), F.when(done, F.col("deg")).alias("subtree"), "deg"), "states")
    ends.drop()
    return states.df


def _settle(mine: DataFrame, theirs: DataFrame, states: DataFrame, cap: int) -> tuple[DataFrame, DataFrame]:
    """Newly settled ``(id, against, subtree)`` and the rows of two steps or more that complete their views.

    ``mine`` are the views of the active owners, ``theirs`` those of the nodes in them.  For an owner v and a direction
    d, X is what v knows there.  Nodes of X that are settled against the hop back to v are terminal: their own views
    hold all below them.  d is closed if each neighbour beyond a non-terminal node of X is known or comes from a
    terminal one.  In a forest these are the known nodes whose last hop is that node, so they are counted.
    """
    info = states.select(F.col("id").alias("known"), "deg", F.when(F.col("state") == SETTLED, F.col("against")).alias("back"))
    x_cut = write(mine.join(unsent(info), "known").select(*mine.columns, "deg", F.coalesce(F.col("back") == F.col("last_hop"), F.lit(False)).alias("terminal")), "closure")
    x = x_cut.df
    below = V.grow(x.filter("terminal").drop("deg", "terminal"), theirs)
    known_cut = write(V.distinct_rows(x.drop("deg", "terminal").unionByName(below)), "closed")
    known = known_cut.df
    have = known.groupBy("owner", F.col("last_hop").alias("known")).agg(F.count(F.lit(1)).alias("have"))
    beyond = x.filter("not terminal and deg > 1").select("owner", "first_hop", "known", "deg").join(have, ["owner", "known"], "left")
    open_ = beyond.filter(F.coalesce("have", F.lit(0)) < F.col("deg") - 1).select("owner", "first_hop").distinct().withColumn("open", F.lit(1))
    size = known.groupBy("owner", "first_hop").agg(F.count(F.lit(1)).alias("n"))
    side = size.join(open_, ["owner", "first_hop"], "left").withColumn("open", F.coalesce("open", F.lit(0)))
    per = side.groupBy("owner").agg(
        F.sum("open").alias("opens"), F.sum("n").alias("all"), F.max(F.when(F.col("open") == 1, F.col("first_hop"))).alias("open_hop"), F.max("n").alias("largest")
    )
    # against the one open direction; if all are closed, against the largest (ties: larger id)
    largest = side.join(per.select("owner", "largest"), "owner").filter("n = largest").groupBy("owner").agg(F.max("first_hop").alias("top_hop"))
    open_n = side.filter("open = 1").groupBy("owner").agg(F.max("n").alias("open_n"))
    j = per.join(largest, "owner").join(open_n, "owner", "left")
    j = j.select(F.col("owner").alias("id"), "opens", F.coalesce("open_hop", "top_hop").alias("against"), (F.col("all") - F.coalesce("open_n", "largest") + 1).alias("subtree"))
    new = write(j.filter((F.col("opens") <= 1) & (F.col("subtree") <= cap)).select("id", "against", "subtree"), "settled").df
    rows = known.join(new.select(F.col("id").alias("owner"), "against"), "owner").filter("first_hop <> against and dist > 1")
    rows = write(rows.select("owner", "known", "first_hop", "last_hop", "dist"), "completed").df
    x_cut.drop()
    known_cut.drop()
    return new, rows


def _apart(hang: DataFrame, side: DataFrame) -> DataFrame | None:
    """Owners of ``hang(owner, against)`` whose sides ``side(owner, against, node)`` are folded: no two overlap.

    None if no two sides overlap anyway.  Only a too small guess leaves overlaps, since a heavy node is in no light
    side.  Of nested sides the outer one stays; of two that cover the tree together, the one with the larger edge.
    """
    other = side.select(F.col("owner").alias("o2"), F.col("against").alias("w2"), F.col("node").alias("against"))
    met = write(hang.join(other, "against"), "overlaps").df
    if met.isEmpty():
        return None
    back = side.select("owner", F.col("node").alias("w2"), F.lit(True).alias("both"))
    worse = met.join(back, ["owner", "w2"], "left").filter(F.col("both").isNull() | (F.struct("w2", "o2") > F.struct("against", "owner")))
    return hang.join(worse, "owner", "left_anti").select("owner")


def absorb_light(nodes: DataFrame, edges: DataFrame, guess: int, budget: Budget, options: Options | None = None, ledger: Ledger | None = None, phase: int = 0) -> Phase:
    """Fold every light subtree; ``guess`` must reach the diameter for a complete result.

    Rows of one step are the edges and never written again; ``more`` has those of two steps or more.
    """
    with scope() as held, swept(edges.sparkSession):
        return _absorb(nodes, edges, guess, budget, options or Options(), ledger, phase, held)


def _absorb(nodes: DataFrame, edges: DataFrame, guess: int, budget: Budget, options: Options, ledger: Ledger | None, phase: int, held: Callable[[Cut], Cut]) -> Phase:
    cap, full = budget.light_cap, budget.full_cap
    start = V.start(edges)
    first = _first(edges, cap)
    live = write(first.filter(F.col("state") == ACTIVE), "live").df
    fixed = [first.filter(F.col("state") != ACTIVE)]  # states that change no more
    more = write(start.limit(0), "views")
    reached = live.select("id").limit(0)  # nodes whose edges are in ``base``
    base = start.limit(0)

    def states() -> DataFrame:
        out = live
        for f in fixed:
            out = out.unionByName(f)
        return out

    def owners() -> DataFrame:
        return live.select(F.col("id").alias("owner"))

    def look() -> tuple[Cut, DataFrame]:
        """Views of the active nodes, and those of the nodes in them."""
        nonlocal reached, base
        mine = write(near.join(owners(), "owner", "left_semi").unionByName(more.df.join(owners(), "owner", "left_semi")), "mine")
        asked = write(mine.df.select(F.col("known").alias("id")).distinct().join(reached, "id", "left_anti"), "asked").df
        if not asked.isEmpty():
            base = base.unionByName(write(start.join(asked.withColumnRenamed("id", "owner"), "owner", "left_semi"), "base").df)
            reached = reached.unionByName(asked)
        return mine, around()

    def around() -> DataFrame:
        return unsent(base.unionByName(more.df.join(reached.withColumnRenamed("id", "owner"), "owner", "left_semi")))

    spike = 1.0
    limit = math.ceil(math.log(max(2, guess)) / math.log(4 / 3)) + 2
    iterations = 0
    still = None  # active nodes of the last iteration, if its views did not grow
    n_edges = edges.count() if ledger is not None else 0
    for it in range(limit):
        if not it:
            settled_now = first.filter(F.col("state") == SETTLED).count()
        else:
            mine, theirs = look()
            new, rows = _settle(mine.df, theirs, states(), cap)
            settled_now = new.count()
            if settled_now:
                got = new.select("id", F.col("against").alias("a"), F.col("subtree").alias("s"))
                fixed.append(write(live.join(got, "id").select("id", F.lit(SETTLED).alias("state"), F.col("a").alias("against"), F.col("s").alias("subtree"), "deg"), "states").df)
                live = write(live.join(got, "id", "left_anti"), "live").df
                old, more = more, write(V.distinct_rows(more.df.unionByName(rows)), "views")
                old.drop()
                theirs = around()
        n_active = live.count()
        if ledger is not None:
            ledger.add("absorb", "settle", phase, it, 3, n_active, settled_now)
        # the same views and states as before would only give the same again
        if not n_active or it == limit - 1 or (still == n_active and not settled_now):
            break
        iterations += 1
        if not it:
            near = write(start.join(owners(), "owner", "left_semi"), "near").df
            mine, theirs = look()
        views = mine.df.join(owners(), "owner", "left_semi") if it and settled_now else mine.df
        est = write(V.estimates(views, theirs), "estimates").df
        d = write(_decide(est, guess, cap, options), "directions").df
        hopeless = d.filter("n_blocked >= 2").select(F.col("owner").alias("id")).distinct()
        clear = (F.col("rank") == 1) & (F.col("est") >= guess * F.col("rival"))
        chosen = d.filter("n_blocked = 1 and not blocked").select("owner", "first_hop", F.lit(False).alias("free"))
        free = d.filter("n_blocked = 0")
        if options.spare:
            sure = free.filter(clear).select("owner", F.col("first_hop").alias("spared"))
            if options.trial:
                unsure = free.join(sure.select("owner"), "owner", "left_anti").select("owner").distinct()
                asking = views.join(unsure, "owner")
                tried = V.distinct_rows(asking.unionByName(V.grow(asking, theirs)))
                size = tried.groupBy("owner", "first_hop").agg(F.count(F.lit(1)).alias("n"))
                top = W.partitionBy("owner").orderBy(F.desc("n"), F.desc("first_hop"))
                best = size.withColumn("r", F.row_number().over(top)).filter("r = 1").select("owner", F.col("first_hop").alias("spared"))
            else:
                best = free.filter("rank = 1").select("owner", F.col("first_hop").alias("spared")).join(sure.select("owner"), "owner", "left_anti")
            spared = sure.unionByName(best)
            widen = free.join(spared, "owner").filter("first_hop <> spared").select("owner", "first_hop", F.lit(True).alias("free"))
        else:
            widen = free.select("owner", "first_hop", F.lit(True).alias("free"))
        chosen = write(chosen.unionByName(widen), "chosen").df
        learned_cut = write(V.grow(views.join(chosen.select("owner", "first_hop"), ["owner", "first_hop"]), theirs), "learned")
        learned = learned_cut.df
        raw = learned.count()
        gained = learned
        if options.mirror:
            generous = chosen.filter("free").select("owner").distinct()
            hubs = states().filter(F.col("state") == HOPELESS).select(F.col("id").alias("owner"))
            gained = learned.unionByName(V.mirror(learned.join(generous, "owner")).join(hubs, "owner", "left_anti"))
        if raw:
            spike = max(spike, raw / max(1, learned.select("owner", "known").distinct().count()))
        old, more = more, write(V.distinct_rows(more.df.unionByName(gained)), "views")
        had, have = old.df.count(), more.df.count()
        per = more.df.groupBy(F.col("owner").alias("id")).agg(F.count(F.lit(1)).alias("n"))
        marked = live.join(hopeless.withColumn("h", F.lit(1)), "id", "left").join(per, "id", "left").select(
            "id",
            F.when(F.col("h") == 1, HOPELESS).when(F.col("deg") + F.coalesce("n", F.lit(0)) >= full, OVERFULL).otherwise(ACTIVE).alias("state"),
            "against",
            "subtree",
            "deg",
        )
        marked = write(marked, "live").df
        live = marked.filter(F.col("state") == ACTIVE)
        fixed.append(marked.filter(F.col("state") != ACTIVE))
        for cut in (old, mine, learned_cut):
            cut.drop()
        if ledger is not None:
            widest = start.unionByName(more.df).groupBy("owner").count().agg(F.max("count")).first()[0]
            ledger.add("absorb", "grow", phase, it, 4, raw, n_edges + have, widest, 5)
        still = n_active if have == had else None
    # fold: a settled node beside an unsettled one takes its side there; mutually settled trees go to their largest id
    counts = states().groupBy("state").count().collect()
    s = unsent(states().filter(F.col("state") == SETTLED).select("id", "against"))
    other = s.select(F.col("id").alias("against"), F.col("against").alias("back"))
    edge = s.join(other, "against", "left").select("id", "against", F.coalesce(F.col("back") == F.col("id"), F.lit(False)).alias("mutual"), F.col("back").isNotNull().alias("other"))
    edge = write(edge.filter("not other or (mutual and id > against)"), "borders").df
    hang = edge.filter("not other").select(F.col("id").alias("owner"), "against")
    mutual = edge.filter("mutual").select(F.col("id").alias("owner"), "against")
    both = mutual.select(F.struct("owner", "against").alias("e"), F.explode(F.array(F.struct(F.col("owner").alias("v"), F.col("against").alias("u")), F.struct(F.col("against").alias("v"), F.col("owner").alias("u")))).alias("x"))
    # trees have an ``e``, light sides none
    ends = both.select(F.col("x.v").alias("owner"), F.col("x.u").alias("against"), "e")
    ends = unsent(ends.unionByName(hang.withColumn("e", F.lit(None).cast(ends.schema["e"].dataType))))
    tip = F.when(F.col("e").isNull() | (F.col("owner") < F.col("against")), F.col("against"))
    sides = unsent(start.unionByName(more.df)).join(ends, "owner").filter("first_hop <> against").select("owner", "against", "e", F.col("known").alias("node"), F.col("last_hop").alias("hop"))
    sides = write(sides.unionByName(ends.select("owner", "against", "e", F.col("owner").alias("node"), tip.alias("hop"))), "sides")
    side = sides.df.filter("e is null").drop("e")
    apart = _apart(hang, side)
    into_heavy = (side if apart is None else side.join(apart, "owner", "left_semi")).select("node", F.col("against").alias("into"), "hop", F.lit("light").alias("kind"))
    # a too small guess can leave several such edges in a tree: the largest counts
    whole = held(write(sides.df.filter("e is not null").groupBy("node").agg(F.max("e").alias("e"), F.max_by("hop", "e").alias("hop")), "trees")).df
    if apart is None and whole.isEmpty():  # each node is in one side at most
        folds = into_heavy
    else:
        top = whole.groupBy("e").agg(F.max("node").alias("into"))
        all_light = whole.join(top, "e").filter("node <> into").select("node", "into", F.lit(None).cast("long").alias("hop"), F.lit("tree").alias("kind")).distinct()
        folds = into_heavy.unionByName(all_light).groupBy("node").agg(F.max("into").alias("into"), F.max("hop").alias("hop"), F.max("kind").alias("kind"))
    folds = held(write(folds, "folds")).df
    sides.drop()
    new_nodes, new_edges = fold(nodes, edges, folds)
    trees = whole.select(F.col("node").alias("id"), F.col("hop").alias("parent"))
    return Phase(held(write(new_nodes, "nodes")).df, held(write(new_edges, "edges")).df, folds, trees=trees, report={"spike": spike, "iterations": iterations, "states": {r["state"]: r["count"] for r in counts}})


def contract_paths(nodes: DataFrame, edges: DataFrame, ledger: Ledger | None = None, phase: int = 0) -> Phase:
    """Replace each maximal run of degree-2 nodes by one edge between its ends, the run folded into the larger end.

    Every run node holds one link to each side, (to, length), and doubles it through the node
    that it points to until both reach the ends.
    """
    deg = edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("deg"), F.min("dst").alias("lo"), F.max("dst").alias("hi"))
    two = write(deg.filter("deg = 2"), "two").df
    none = nodes.sparkSession.createDataFrame([], "node long, into long, hop long, kind string")
    if two.isEmpty():
        return Phase(nodes, edges, none)
    inner = two.select(F.col("id").alias("to"), F.lit(1).alias("inner"))
    # a link leaves ``id`` by neighbour ``via``; it has come to ``to``, entering there from ``from_``
    links = two.select("id", F.explode(F.array("lo", "hi")).alias("via")).select("id", "via", F.col("via").alias("to"), F.col("id").alias("from_"))
    links = write(links.join(inner, "to", "left").select("id", "via", "to", "from_", F.col("inner").isNull().alias("end")), "links").df
    for it in range(64):
        go = links.filter("not end")
        n = go.count()
        if ledger is not None:
            ledger.add("paths", "double", phase, it, 1, n, n)
        if not n:
            break
        # continue from ``to`` by the neighbour that does not lead back
        nxt = links.select(F.col("id").alias("to"), F.col("via").alias("v2"), F.col("to").alias("t2"), F.col("from_").alias("f2"), F.col("end").alias("e2"))
        step = go.join(nxt, "to").filter("v2 <> from_").select("id", "via", F.col("t2").alias("to"), F.col("f2").alias("from_"), F.col("e2").alias("end"))
        links = write(links.filter("end").unionByName(step), "links").df
    ends = links.groupBy("id").agg(F.max("to").alias("hi"), F.min("to").alias("lo"), F.max_by("via", F.struct("to", "via")).alias("hop"), F.min_by("via", F.struct("to", "via")).alias("back"))
    ends = write(ends, "ends").df
    gone = ends.select(F.col("id").alias("node"), F.col("hi").alias("into"), "hop", F.lit("path").alias("kind"))
    bridges = ends.select("lo", "hi").distinct()
    kept = edges.join(two.select(F.col("id").alias("src")), "src", "left_anti").join(two.select(F.col("id").alias("dst")), "dst", "left_anti").select("src", "dst")
    new_edges = kept.unionByName(bridges.select(F.col("lo").alias("src"), F.col("hi").alias("dst"))).unionByName(bridges.select(F.col("hi").alias("src"), F.col("lo").alias("dst"))).distinct()
    folds = write(gone, "folds").df
    new_nodes = nodes.join(folds.select(F.col("node").alias("id"), "into"), "id", "left").groupBy(F.coalesce("into", "id").alias("id")).agg(F.max("best").alias("best"))
    runs = ends.select("id", "lo", "hi", F.col("back").alias("to_lo"), F.col("hop").alias("to_hi"))
    return Phase(write(new_nodes, "nodes").df, write(new_edges, "edges").df, folds, runs=runs)


def max_id(
    nodes: DataFrame, edges: DataFrame, guess: int, budget: Budget | None = None, options: Options | None = None, ledger: Ledger | None = None, phases: int = 40, history: list[Phase] | None = None
) -> DataFrame:
    """``(id, best)`` with ``best`` the largest best of the tree; ``nodes(id)`` or ``nodes(id, best)``.

    Trees that a too small guess leaves unfinished have a null ``best``.  ``history`` takes the phases, two an
    entry of the loop, in their order.
    """
    budget = budget or Budget()
    if "best" not in nodes.columns:
        nodes = nodes.withColumn("best", F.col("id"))
    done: list[DataFrame] = []
    for p in range(phases):
        if edges.isEmpty():
            break
        before = nodes.count()
        a = absorb_light(nodes, edges, guess, budget, options, ledger, p)
        c = contract_paths(a.nodes, a.edges, ledger, p)
        done += [a.folds.select("node", "into"), c.folds.select("node", "into")]
        if history is not None:
            history += [a, c]
        nodes, edges = c.nodes, c.edges
        after = nodes.count()
        if ledger is not None:
            ledger.add("phase", "shrink", p, 0, 0, before, after)
        if after == before:
            break
    left = edges.select(F.col("src").alias("id")).distinct().withColumn("open", F.lit(1))
    answers = nodes.join(left, "id", "left").select("id", F.when(F.col("open").isNull(), F.col("best")).alias("best"))
    last = None
    with swept(answers.sparkSession):
        for f in reversed(done):
            made = write(unfold(answers, f), "answers")
            if last is not None:
                last.drop()
            answers, last = made.df, made
    return answers

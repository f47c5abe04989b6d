"""Set similarity join on word n-grams by chosen paths.

* Sets.  A document is the set of its ``N``-word shingles (a text of fewer words is one
  shingle).  Equal sets become one item with a multiplicity.
* Paths.  A set is embedded as ``COORDS`` min-hashes.  A run starts at the root; each
  node of a path picks coordinates by a hash of the path, and a set goes to the child
  (path, coordinate, its own min-hash): sets that agree on the sampled token go down
  together.  A run takes ``PER_RUN`` coordinates at the root; small buckets are
  compared at once.  A bucket over ``LIMIT`` sets is split by ``FAN`` coordinates that its
  path has not used, to depth ``DEPTH``, unless the children would cost as many
  comparisons as the bucket itself (a family of near copies): then, and at the last
  depth, it is compared block by block, exactly.
* Recall.  ``RUNS`` runs are made, and more of them, up to all coordinates, until the
  recall measured on probes reaches ``TARGET``.  A probe is the signature of a sampled set
  (``PROBES`` on average, whatever the size of the corpus) and one of a partner at
  similarity 0.8: each min-hash kept with that probability.  Probes go down the same
  paths and through the same splits as the sets, and are in no result.
* Sketches.  Members of a bucket are compared on their min-hashes first; a pair goes on
  if its sizes allow the similarity and ``AGREE`` min-hashes are equal (a pair at 0.8 has
  fewer with probability 1e-7).  Oversized buckets of one family are one bucket.  Buckets fall apart into connected groups of such pairs,
  groups with the same members become one.
* Check.  In the groups all pairs are compared on full shingle sets in integers
  (5 i >= 4 u); each pair is counted in one group, pairs are never emitted.

Texts move once, and full shingle sets only for members of groups.  Hot groups: memberships are
aggregated with a partial phase; buckets and groups are dealt by block pairs.

Defined results: null text and texts without words have no links; null ids have none either
(their class is null); repeated rows are copies of each other; an empty table gives an
empty result; very long texts are hashed whole.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.components.fallback import star_components
from canopy.llm.links import bucket_links, candidate_groups, memberships
from canopy.llm.substring_dedup import _WORD_BASE, Prefix, _bytes, _mix, word_bounds, word_hashes
from canopy.store import scope, write

N = 5
NUM, DEN = 4, 5  # similarity 0.8 as a fraction
COORDS, RUNS, PER_RUN = 24, 6, 2
LIMIT, DEPTH, FAN = 256, 3, 3
AGREE = 8
#: Members of a block when sketches are compared.
SKETCHED = 2048
#: Random signs for the estimate of what a split would save.
SIGNS = 8
PROBES, TARGET = 512, 0.999
#: Cells of the incidence matrix that are multiplied at once, shingles that are matched or handed on at once.
CELLS = 2_000_000
ENTRIES = 250_000

_SALT = _mix(np.arange(1, COORDS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)


def shingles(data: np.ndarray) -> np.ndarray:
    """Sorted distinct shingle hashes of a text's bytes."""
    start, end = word_bounds(data)
    if not len(start):
        return np.zeros(0, dtype=np.uint64)
    h = word_hashes(data, start, end)
    i = np.arange(max(1, len(h) - N + 1))
    return np.unique(Prefix(h, _WORD_BASE).span(i, np.minimum(i + N, len(h))))


def min_hashes(s: np.ndarray) -> np.ndarray:
    out = np.full(COORDS, np.iinfo(np.uint64).max, dtype=np.uint64)
    for lo in range(0, len(s), 1 << 14):
        out = np.minimum(out, (s[lo : lo + (1 << 14), None] * _SALT[None, :]).min(axis=0))
    return _mix(out + np.arange(COORDS, dtype=np.uint64))


def _sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        sid, size, sig = [], [], []
        for data in _bytes(b.column(2)):
            s = shingles(data)
            sid.append(int(_mix(np.array([np.bitwise_xor.reduce(_mix(s)) + np.uint64(len(s))], dtype=np.uint64)).view(np.int64)[0]) if len(s) else None)
            size.append(len(s))
            sig.append(min_hashes(s).view(np.int64) if len(s) else None)
        yield pa.RecordBatch.from_arrays(
            [b.column(0), b.column(1), pa.array(sid, pa.int64()), pa.array(size, pa.int32()), pa.array(sig, pa.list_(pa.int64()))],
            names=["doc_id", "th", "sid", "size", "sig"],
        )


def _payload(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        s: list[np.ndarray] = []
        first = entries = 0
        for i, data in enumerate(_bytes(b.column(3))):
            s.append(shingles(data).view(np.int64))
            entries += len(s[-1])
            if entries > ENTRIES or i + 1 == b.num_rows:
                rows = b.slice(first, len(s))
                yield pa.RecordBatch.from_arrays([*rows.columns[:3], pa.array(s, pa.list_(pa.int64()))], names=["sid", "mult", "leaves", "payload"])
                s, first, entries = [], i + 1, 0


def alike(one: np.ndarray, two: np.ndarray) -> np.ndarray:
    """Which rows (size, min-hashes) of two tables may be similar."""
    size = np.minimum(one[:, 0], two[:, 0]) * DEN >= np.maximum(one[:, 0], two[:, 0]) * NUM
    return size & ((one[:, 1:] == two[:, 1:]).sum(axis=1) >= AGREE)


def similar(sets: list[np.ndarray]) -> np.ndarray:
    """Which pairs of shingle sets (sorted as unsigned numbers) reach the similarity, exactly.

    The hashes are taken range by range, about ``ENTRIES`` at a time, so memory doesn't grow with the texts.
    """
    n = len(sets)
    sets = [s.view(np.uint64) for s in sets]
    size = np.array([len(s) for s in sets])
    common = np.zeros((n, n), dtype=np.float64)
    ranges = int(size.sum()) // ENTRIES + 1
    bounds = np.array([i * (1 << 64) // ranges for i in range(1, ranges)], dtype=np.uint64)
    cuts = np.stack([np.concatenate([[0], np.searchsorted(s, bounds), [len(s)]]) for s in sets], axis=1).astype(np.int64)
    for lo, hi in zip(cuts[:-1], cuts[1:]):
        _, place, count = np.unique(np.concatenate([s[i:j] for s, i, j in zip(sets, lo, hi)]), return_inverse=True, return_counts=True)
        some = count[place] > 1
        who = np.repeat(np.arange(n), hi - lo)[some]
        column = (np.cumsum(count > 1) - 1)[place[some]]
        by = np.argsort(column, kind="stable")
        who, column = who[by], column[by]
        width = int(column[-1]) + 1 if len(column) else 0
        step = max(1, CELLS // n)
        for left in range(0, width, step):
            a, z = np.searchsorted(column, [left, left + step])
            m = np.zeros((n, min(step, width - left)), dtype=np.float32)
            m[who[a:z], column[a:z] - left] = 1
            common += m @ m.T
    return DEN * common >= NUM * (size[:, None] + size[None, :] - common)


def _signs() -> list:
    """Sums of random signs of the values that ``next`` holds: ``SIGNS`` for each of the ``FAN`` coordinates."""
    sign = lambda k, j: F.expr(f"1 - 2 * cast(getbit(xxhash64('sign', next[{k}].c, next[{k}].v), {j}) as int)")
    return [F.sum(sign(k, j)).cast("double").alias(f"s{k}_{j}") for k in range(FAN) for j in range(SIGNS)]


def _pairs_left() -> str:
    """The comparisons of a bucket's children, estimated: a squared sum of random signs is the sum of squared sizes on average."""
    return "(" + " + ".join(f"s{k}_{j} * s{k}_{j}" for k in range(FAN) for j in range(SIGNS)) + f") / {SIGNS}"


def paths(sets: DataFrame, first: int = 0, runs: int = RUNS) -> DataFrame:
    """``(bucket, sid)`` of ``sets(sid, sig)``: the leaves of the chosen paths of ``runs`` runs."""
    roots = [F.struct(F.xxhash64(F.lit(r), F.lit("root")).alias("p"), F.lit((r * PER_RUN + j) % COORDS).alias("c")) for r in range(first, first + runs) for j in range(PER_RUN)]
    now = sets.select("sid", F.explode(F.array(*roots)).alias("x"), "sig")
    now = now.select("sid", F.xxhash64("x.p", "x.c", F.get("sig", F.col("x.c"))).alias("bucket"), F.expr("shiftleft(1L, x.c)").alias("used"))
    # the coordinates that the path has not used, in an order of its own
    free = F.filter(F.sequence(F.lit(0), F.lit(COORDS - 1)), lambda j: F.getbit("used", j) == 0)
    order = F.sort_array(F.transform(free, lambda j: F.struct(F.xxhash64("bucket", j).alias("h"), j.alias("c"))))
    picks = F.transform(F.slice(order, 1, FAN), lambda x: x["c"])
    done: list[DataFrame] = []
    for _ in range(DEPTH):
        now = write(now, "paths").df
        size = now.groupBy("bucket").agg(F.count(F.lit(1)).alias("n"), F.max("used").alias("used")).filter(F.col("n") > LIMIT)
        big = write(size.select("bucket", "n", picks.alias("picks")), "big").df
        if big.isEmpty():
            done.append(now.select("sid", "bucket"))
            break
        done.append(now.join(big, "bucket", "left_anti").select("sid", "bucket"))
        over = now.join(big, "bucket").join(sets.select("sid", "sig"), "sid")
        over = over.select("sid", "bucket", "used", F.transform("picks", lambda c: F.struct(c.alias("c"), F.get("sig", c).alias("v"))).alias("next"))
        over = write(over, "over").df
        whole = write(over.groupBy("bucket").agg(F.count(F.lit(1)).cast("double").alias("n"), *_signs()).filter(f"{_pairs_left()} >= n * n").select("bucket"), "whole").df
        done.append(now.join(whole, "bucket", "left_semi").select("sid", "bucket"))
        now = over.join(whole, "bucket", "left_anti").select("sid", F.col("bucket").alias("parent"), "used", F.explode("next").alias("x"))
        now = now.select("sid", F.xxhash64("parent", "x.c", "x.v").alias("bucket"), F.expr("used | shiftleft(1L, x.c)").alias("used"))
    else:
        done.append(now.select("sid", "bucket"))
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    return out.distinct()


def probes(items: DataFrame, n: int) -> DataFrame:
    """``sid, sig, pair, side`` of ``items(sid, sig)``: about ``PROBES`` sampled signatures and their partners at the similarity."""
    some = items.filter(F.pmod(F.xxhash64(F.lit("probe"), "sid"), F.lit(max(1, n // PROBES))) == 0)
    other = F.transform(
        "sig", lambda x, j: F.when(F.pmod(F.xxhash64(F.lit("kept"), "sid", j), F.lit(DEN)) < NUM, x).otherwise(F.xxhash64(F.lit("new"), "sid", j))
    )
    sides = F.array(F.struct(F.lit(0).alias("side"), F.col("sig")), F.struct(F.lit(1).alias("side"), other.alias("sig")))
    some = some.select(F.col("sid").alias("pair"), F.explode(sides).alias("x"))
    return some.select(F.xxhash64(F.lit("probe"), "pair", "x.side").alias("sid"), "x.sig", "pair", "x.side")


def chosen_leaves(items: DataFrame, target: float = TARGET) -> tuple[DataFrame, float, int]:
    """``(bucket, sid)`` of ``items(sid, sig)``, the recall measured on probes, and the number of runs."""
    n = items.count()
    tests = write(probes(items, n), "probes").df
    total = tests.count() // 2
    both = items.select("sid", "sig").unionByName(tests.select("sid", "sig"))
    leaves, runs, recall = None, 0, 1.0
    while runs * PER_RUN < COORDS:
        more = RUNS if not runs else min(2, COORDS // PER_RUN - runs)
        got = write(paths(both, runs, more), "leaves").df
        leaves, runs = got if leaves is None else leaves.unionByName(got), runs + more
        if not total:
            break
        met = leaves.join(tests.select("sid", "pair", "side"), "sid").groupBy("pair", "bucket").agg(F.count_distinct("side").alias("k"))
        recall = met.filter("k = 2").agg(F.count_distinct("pair")).first()[0] / total
        if recall >= target:
            break
    return leaves.join(tests.select("sid"), "sid", "left_anti"), recall, runs


def similarity_join(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, th, class_id, n_links, class_size``: a row per document; ``th`` is the hash of the text.

    ``class_id`` is the smallest id of the documents reachable by links, ``n_links`` the
    number of other documents at the similarity or above.
    """
    d = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(F.col(text_col).cast("string")).alias("th"), F.col(text_col).cast("string").alias("text"))
    with scope() as held:
        scan = write(d.mapInArrow(_sets, "doc_id long, th long, sid long, size int, sig array<long>"), "sets")
        known = scan.df.filter("sid is not null and doc_id is not null")
        # the rows of an item are alike in shingles, so any signature will do
        items = known.groupBy("sid").agg(F.count(F.lit(1)).alias("mult"), F.min("doc_id").alias("low"), F.min_by("th", "doc_id").alias("th"), F.first("size").alias("size"), F.first("sig").alias("sig"))
        items = write(items, "items")
        with scope() as kept:
            leaves = write(memberships(chosen_leaves(items.df.select("sid", "sig"))[0], LIMIT), "leaves")
            kept(leaves)
        sketch = F.concat(F.array("size"), F.transform("sig", lambda x: x.bitwiseAND(F.lit(0x7FFFFFFF)).cast("int")))
        members = leaves.df.join(items.df.select("sid", sketch.alias("payload")), "sid")
        groups = write(memberships(candidate_groups(members, alike, SKETCHED)), "groups")
        leaves.drop()
        wanted = groups.df.join(items.df.select("sid", "mult", F.col("low").alias("doc_id"), "th"), "sid")
        wanted = write(wanted, "wanted")
        groups.drop()
        # the one pass in which texts move: repeated rows of an id and text meet in it
        text = d.join(wanted.df.hint("merge"), ["doc_id", "th"]).dropDuplicates(["doc_id", "th"]).select("sid", "mult", "leaves", "text")
        payload = text.mapInArrow(_payload, "sid long, mult long, leaves array<struct<bucket: long, n: long>>, payload array<long>")
        found = write(bucket_links(payload, similar, LIMIT), "links")
        wanted.drop()
        comp = star_components(found.df, "sid", "root").withColumnRenamed("id", "sid")
        comp = write(items.df.select("sid", "low", "mult").join(comp, "sid"), "components").df
        low = comp.groupBy("component").agg(F.min("low").alias("class_id"), F.sum("mult").alias("class_size"))
        links = found.df.groupBy("sid").agg(F.sum("links").alias("links"))
        per = comp.join(low, "component").join(links, "sid").select("sid", "class_id", "class_size", "links")
        per = items.df.select("sid", "low", "mult").join(per, "sid", "left")
        per = per.select("sid", F.coalesce("class_id", "low").alias("c"), (F.coalesce("links", F.lit(0)) + F.col("mult") - 1).alias("n"), F.coalesce("class_size", "mult").alias("s"))
        per = write(per, "classes")
        # rows without a set get a key of their own kind, so they don't meet in one partition
        keyed = scan.df.select("doc_id", "th", F.when(F.col("doc_id").isNotNull(), F.col("sid")).alias("own"), F.coalesce("sid", F.xxhash64("doc_id")).alias("k"))
        j = keyed.join(per.df.withColumnRenamed("sid", "k"), "k", "left")
        linked = F.col("own").isNotNull()
        out = j.select(
            "doc_id",
            "th",
            F.when(linked, F.col("c")).otherwise(F.col("doc_id")).alias("class_id"),
            F.when(linked, F.col("n")).otherwise(F.lit(0)).cast("long").alias("n_links"),
            F.when(linked, F.col("s")).otherwise(F.lit(1)).cast("long").alias("class_size"),
        )
        out = write(out, "joined")
        held(out)
    return out.df


ORACLE = r"""
with recursive w as (
  select doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') as ws from documents),
s as (
  select doc_id, unnest(list_distinct(list_transform(range(1, greatest(2, len(ws) - 3)), lambda i: array_to_string(ws[i : i + 4], ' ')))) as g
  from w where len(ws) > 0),
n as (select doc_id, count(*) as k from s group by doc_id),
p as (select a.doc_id as a, b.doc_id as b, count(*) as i from s a join s b on a.g = b.g and a.doc_id <> b.doc_id group by 1, 2),
e as (select p.a, p.b from p join n x on p.a = x.doc_id join n y on p.b = y.doc_id where 5 * p.i >= 4 * (x.k + y.k - p.i)),
r as (select doc_id as a, doc_id as b from documents union select r.a, e.b from r join e on r.b = e.a),
c as (select a as doc_id, min(b) as class_id, count(*) as class_size from r group by a)
select c.doc_id, c.class_id, coalesce(l.n, 0) as n_links, c.class_size
from c left join (select a, count(*) as n from e group by a) l on c.doc_id = l.a
"""


def query(spark, sf_dir: str) -> DataFrame:
    return similarity_join(spark.read.parquet(f"{sf_dir}/documents.parquet")).select("doc_id", "class_id", "n_links", "class_size")

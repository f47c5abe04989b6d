"""Compare the members of buckets, each pair once, without emitting pairs.

``bucket_links`` takes memberships (bucket, sid) and payloads by sid.  Buckets with the
same members are compared once.  Every member carries the sorted list of its buckets;
a pair that meets in several buckets is counted in the smallest one only.  A
bucket of n members is dealt to k(k+1)/2 groups of two blocks, k = ceil(n / limit), so no
task holds more than two blocks, however hot the bucket.  Each group returns one row
per linked member: its weight of new partners and the root of its local component.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.components.fallback import star_components
from canopy.store import write


def grouped(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """Tables of rows with equal keys from a stream sorted by them."""
    held: list[pa.RecordBatch] = []
    last = None
    for b in batches:
        if not b.num_rows:
            continue
        cols = [b.column(k).to_numpy(zero_copy_only=False) for k in keys]
        new = np.zeros(b.num_rows, dtype=bool)
        for c in cols:
            new[1:] |= c[1:] != c[:-1]
        edges = [0, *np.flatnonzero(new).tolist(), b.num_rows]
        for lo, hi in zip(edges[:-1], edges[1:]):
            key = tuple(c[lo] for c in cols)
            if held and key != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(b.slice(lo, hi - lo))
            last = key
    if held:
        yield pa.Table.from_batches(held)


def lists(column: pa.ChunkedArray) -> list[np.ndarray]:
    """The rows of a list column as arrays."""
    a = column.combine_chunks()
    a = a if isinstance(a, pa.Array) else a.chunk(0)
    values = a.values.to_numpy(zero_copy_only=False)
    offsets = a.offsets.to_numpy()
    return [values[offsets[i] : offsets[i + 1]] for i in range(len(a))]


def roots(linked: np.ndarray) -> np.ndarray:
    """Smallest index of the component of each row of a symmetric boolean matrix."""
    label = np.arange(len(linked))
    while True:
        near = np.where(linked, label[None, :], len(label)).min(axis=1) if len(label) else label
        new = np.minimum(label, near)
        new = new[new]
        if (new == label).all():
            return label
        label = new


def met_before(leaves: list[np.ndarray], bucket: int) -> np.ndarray:
    """Which members share a bucket smaller than this one."""
    n = len(leaves)
    flat = np.concatenate(leaves)
    who = np.repeat(np.arange(n), [len(x) for x in leaves])
    low = flat < bucket
    if not low.any():
        return np.zeros((n, n), dtype=bool)
    names, place, count = np.unique(flat[low], return_inverse=True, return_counts=True)
    some = count[place] > 1
    if not some.any():
        return np.zeros((n, n), dtype=bool)
    m = np.zeros((n, len(names)), dtype=np.float32)
    m[who[low][some], place[some]] = 1
    return m @ m.T > 0


_LINKS = "sid long, links long, root long"


def _compare(linked_of: Callable[[list[np.ndarray]], np.ndarray]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[list[np.ndarray]] = [[], [], []]
        size = 0
        for t in grouped(batches, ["bucket", "bx", "by"]):
            if t.num_rows < 2:
                continue
            sid, mult, block = (t.column(c).to_numpy() for c in ("sid", "mult", "block"))
            linked = linked_of(lists(t.column("payload")))
            np.fill_diagonal(linked, False)
            bx, by = t.column("bx")[0].as_py(), t.column("by")[0].as_py()
            if bx != by:
                linked &= block[:, None] != block[None, :]
            if not linked.any():
                continue
            fresh = linked & ~met_before(lists(t.column("leaves")), t.column("bucket")[0].as_py())
            links = fresh.astype(np.float64) @ mult
            some = linked.any(axis=1)
            for o, x in zip(out, (sid[some], links[some].astype(np.int64), sid[roots(linked)][some])):
                o.append(x)
            size += int(some.sum())
            if size > 20_000:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(o)) for o in out], names=["sid", "links", "root"])
                out, size = [[], [], []], 0
        if size:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(o)) for o in out], names=["sid", "links", "root"])

    return run


def useful_buckets(members: DataFrame) -> DataFrame:
    """``bucket, n, low``: buckets of two members at least, one for each set of members; ``low`` is a min-hash of the set."""
    sizes = members.groupBy("bucket").agg(
        F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("sid")).alias("x"), F.bit_xor(F.xxhash64(F.lit(7), "sid")).alias("y"), F.min(F.xxhash64("sid")).alias("low")
    )
    return sizes.filter("n > 1").groupBy("n", "x", "y").agg(F.min("bucket").alias("bucket"), F.min("low").alias("low")).select("bucket", "n", "low")


def memberships(members: DataFrame, merge_above: int | None = None) -> DataFrame:
    """``sid, leaves array<struct<bucket, n>>`` of the members of useful buckets.

    Buckets of over ``merge_above`` members whose sets have one min-hash become one: those of a family of near
    copies, which differ in a few members.  A union holds all pairs of its buckets.
    """
    keep = write(useful_buckets(members), "buckets").df
    if merge_above is None:
        return members.join(keep, "bucket").groupBy("sid").agg(F.sort_array(F.collect_set(F.struct("bucket", "n"))).alias("leaves"))
    large = F.col("n") > merge_above
    name = F.when(large, F.xxhash64(F.lit("merged"), "low")).otherwise(F.col("bucket"))
    keep = keep.select("bucket", "n", name.alias("name"), large.alias("large"))
    m = write(members.join(keep, "bucket").select("sid", F.col("name").alias("bucket"), "n", "large"), "members").df
    union = m.filter("large").select("sid", "bucket").distinct()
    union = union.join(union.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")), "bucket")
    m = m.filter("not large").select("sid", "bucket", "n").unionByName(union.select("sid", "bucket", "n"))
    return m.groupBy("sid").agg(F.sort_array(F.collect_set(F.struct("bucket", "n"))).alias("leaves"))


def bucket_links(items: DataFrame, linked_of: Callable[[list[np.ndarray]], np.ndarray], limit: int) -> DataFrame:
    """``sid, links, root`` rows to be summed and joined up.

    ``items(sid, mult, leaves, payload)``; ``linked_of`` gives the symmetric link matrix of payloads.
    """
    named = items.select("sid", "mult", "payload", "leaves", F.transform("leaves", lambda x: x["bucket"]).alias("names"))
    r = blocks_of(named, limit, "mult", "payload", "names").drop("split").withColumnRenamed("names", "leaves")
    key = ["bucket", "bx", "by"]
    return r.repartition(*key).sortWithinPartitions(*key).mapInArrow(_compare(linked_of), _LINKS)


#: Pairs of a bucket that are held before they are united.
PAIRS = 1_000_000


def united(label: np.ndarray, pairs: np.ndarray) -> np.ndarray:
    """Labels (each the smallest place of its component) after more pairs."""
    while True:
        a, b = label[pairs[0]], label[pairs[1]]
        if (a == b).all():
            return label
        label = label.copy()
        low = np.minimum(a, b)
        np.minimum.at(label, a, low)
        np.minimum.at(label, b, low)
        while (label[label] != label).any():
            label = label[label]


_GROUPS = "bucket long, split boolean, sid long, root long"


def _candidates(alike: Callable[[np.ndarray, np.ndarray], np.ndarray]):
    def groups(t: pa.Table) -> pa.RecordBatch | None:
        bucket, sid, block = (t.column(c).to_numpy() for c in ("bucket", "sid", "block"))
        bx, by = t.column("bx").to_numpy(), t.column("by").to_numpy()
        width = len(t.column("payload")[0])
        data = np.concatenate(lists(t.column("payload"))).reshape(-1, width)
        key = np.zeros(len(sid), dtype=np.int64)
        key[1:] = np.cumsum((bucket[1:] != bucket[:-1]) | (bx[1:] != bx[:-1]) | (by[1:] != by[:-1]))
        label = np.arange(len(sid))
        linked = np.zeros(len(sid), dtype=bool)
        held: list[np.ndarray] = []
        for k in range(1, len(sid)):
            one = np.flatnonzero(key[k:] == key[:-k])
            if not len(one):
                break
            one = one[(bx[one] == by[one]) | (block[one] != block[one + k])]
            one = one[alike(data[one], data[one + k])]
            held.append(np.stack([one, one + k]))
            if sum(x.shape[1] for x in held) > PAIRS:
                label = united(label, np.concatenate(held, axis=1))
                linked[np.concatenate(held, axis=None)] = True
                held = []
        if held:
            label = united(label, np.concatenate(held, axis=1))
            linked[np.concatenate(held, axis=None)] = True
        some = np.flatnonzero(linked)
        if not len(some):
            return None
        # every group names a block pair: blocks of a bucket are joined up afterwards
        columns = [bucket[some], t.column("split").to_numpy(zero_copy_only=False)[some], sid[some], sid[label[some]]]
        return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["bucket", "split", "sid", "root"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for b in batches:
            if not b.num_rows:
                continue
            t = pa.Table.from_batches([b])
            t = t if held is None else pa.concat_tables([held, t]).combine_chunks()
            # the last group may go on in the next batch
            last = np.ones(t.num_rows, dtype=bool)
            for c in ("bucket", "bx", "by"):
                x = t.column(c).to_numpy()
                last &= x == x[-1]
            stop = int(np.flatnonzero(~last)[-1]) + 1 if not last.all() else 0
            held = t.slice(stop)
            if stop:
                got = groups(t.slice(0, stop).combine_chunks())
                if got is not None:
                    yield got
        if held is not None and held.num_rows:
            got = groups(held.combine_chunks())
            if got is not None:
                yield got

    return run


def blocks_of(items: DataFrame, limit: int, *carry: str) -> DataFrame:
    """A row for each member, bucket and block pair that it takes part in."""
    r = items.select("sid", *carry, F.explode("leaves").alias("l"))
    r = r.withColumn("k", F.ceil(F.col("l.n") / limit).cast("int")).withColumn("block", F.pmod(F.xxhash64("sid"), F.col("k")).cast("int"))
    r = r.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("k") - 1)))
    return r.select("sid", *carry, "block", (F.col("k") > 1).alias("split"), F.col("l.bucket").alias("bucket"), F.least("block", "other").alias("bx"), F.greatest("block", "other").alias("by"))


def candidate_groups(items: DataFrame, alike: Callable[[np.ndarray, np.ndarray], np.ndarray], limit: int) -> DataFrame:
    """``(bucket, sid)``: buckets cut down to groups of members joined by pairs that may be linked.

    ``items(sid, leaves, payload array<int>)`` with payloads of one width; ``alike`` compares
    rows of two tables of them.  Members of buckets that are dealt in blocks are joined over all blocks and all
    such buckets: a family that fills several of them is one group.
    """
    key = ["bucket", "bx", "by"]
    r = blocks_of(items, limit, "payload").repartition(*key).sortWithinPartitions(*key)
    got = write(r.mapInArrow(_candidates(alike), _GROUPS), "candidates").df
    plain = got.filter("not split").select(F.xxhash64("bucket", "root").alias("bucket"), "sid")
    split = got.filter("split")
    if split.isEmpty():
        return plain
    whole = star_components(split, "sid", "root").select(F.xxhash64(F.lit("whole"), "component").alias("bucket"), F.col("id").alias("sid"))
    return plain.unionByName(whole)

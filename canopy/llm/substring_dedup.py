"""Substring dedup by compacting the De Bruijn graph of long word windows.

Nodes are windows of ``WINDOW`` words, edges join windows one word apart.  The graph is
never stored window by window:

1. *Scan.*  Each window is assigned to its smallest ``K``-word hash (its minimizer).
   Windows of a row that share a minimizer form one run ("piece"), a nonbranching path by
   content: about one row for 16 words, with a 128-bit content hash and its source
   coordinates.  Equal windows always have equal minimizers, so nothing is missed.
2. *Repeats.*  Minimizers seen in one document only are dropped by a join with the
   aggregated minimizer table (16 bytes a row); the rest of the work is on what repeats.
3. *Compaction.*  Where every row of a piece is followed by one and the same piece, and every
   row of that one is preceded by it, the edge is glued (joins on the aggregated
   degrees).  Glued pieces of a row become one row: a nonbranching path, with one
   hash, one smallest document and one source coordinate.  Coverage is decided on paths.
4. *Verification at source coordinates.*  The text at the source coordinate of each
   path is read once more for a digest of its words, with which the last pass
   compares the words that it is about to remove.  Pieces that share a minimizer but differ (the
   ends of shared passages, edited copies) are opened in the same pass: the windows of each
   distinct one are matched on 128-bit hashes, whatever the number of copies.
5. *Cut.*  Covered words of each document are removed in one last pass.

Hashes: words by two chained 64-bit mixes of their bytes (a keyed digest above ``LONG`` bytes), windows by
two binary trees of mixes over these: neither is a polynomial, so no words or word patterns collide by form.

Defined results: null text has no words; texts under 50 words keep all words; rows with a
null id lose nothing and are no source; repeated rows (same id and text) are all
returned and are no source for each other; an empty table gives an empty result; very
long texts are hashed in overlapping segments of bounded memory.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from canopy.store import scope, write

WINDOW, K = 50, 20
SEGMENT = 1 << 20  # bytes hashed at once
LONG = 64  # bytes of a word that are mixed block by block

_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_WORD_BASE = 0xD6E8FEB86659FD93
_ODD = np.array([0x9E3779B97F4A7C15, 0xA0761D6478BD642F], dtype=np.uint64)
_MASK = np.array([(1 << 8 * k) - 1 for k in range(9)], dtype=np.uint64)
_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _powers(base: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """base^i and base^-i modulo 2^64 for i < n at least."""
    have = _POWERS.get(base)
    if have is None or len(have[0]) < n:
        size = 1 << max(12, int(n - 1).bit_length())
        made = []
        for b in (base, pow(base, -1, 1 << 64)):
            p = np.full(size, b, dtype=np.uint64)
            p[0] = 1
            made.append(np.multiply.accumulate(p))
        have = _POWERS[base] = (made[0], made[1])
    return have


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Prefix:
    """Hashes of any span of a sequence from prefix sums."""

    def __init__(self, values: np.ndarray, base: int):
        up, self.down = _powers(base, len(values) + 1)
        self.sums = np.zeros(len(values) + 1, dtype=np.uint64)
        np.cumsum(values * up[: len(values)], out=self.sums[1:])

    def span(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return _mix((self.sums[end] - self.sums[start]) * self.down[start] + (end - start).astype(np.uint64))


def word_bounds(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    gap = np.concatenate(([True], _SPACE[data], [True]))
    edge = np.flatnonzero(gap[1:] != gap[:-1])
    return edge[0::2], edge[1::2]


def word_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray, seeds: int = 1) -> np.ndarray:
    """Hashes of words, or with ``seeds=2`` a row of them for each of two independent functions."""
    padded = np.zeros(len(data) + 8, dtype=np.uint8)
    padded[: len(data)] = data
    load = np.ndarray(len(data) + 1, dtype="<u8", buffer=padded.data, strides=(1,))
    size = (end - start).astype(np.int64)
    odd = _ODD[:seeds, None]
    h = _mix(size.astype(np.uint64)[None, :] * odd + odd)
    at, left, who = start.astype(np.int64), size, None
    for _ in range(0, LONG, 8):
        block = load[at] & _MASK[np.minimum(left, 8)]
        if who is None:
            h = _mix((h ^ block) * odd)
        else:
            h[:, who] = _mix((h[:, who] ^ block) * odd)
        more = np.flatnonzero(left > 8)
        if not len(more):
            break
        who = more if who is None else who[more]
        at, left = at[more] + 8, left[more] - 8
    for k in np.flatnonzero(size > LONG).tolist():
        digest = hashlib.blake2b(padded[start[k] : end[k]].tobytes(), digest_size=16).digest()
        h[:, k] = np.frombuffer(digest, dtype="<u8")[:seeds]
    return h if seeds > 1 else h[0]


def fixed_spans(h: np.ndarray, width: int) -> np.ndarray:
    """Hashes of all runs of ``width`` values along the last axis: a binary tree of mixes."""
    n = h.shape[-1] - width + 1
    level, span, out, covered = h, 1, None, 0
    while True:
        if width & span:
            part = level[..., covered : covered + n]
            out = part if out is None else _mix(out * _ODD[0] + part)
            covered += span
        if 2 * span > width:
            return out
        level = _mix(level[..., :-span] * _ODD[1] + level[..., span:])
        span *= 2


def segments(data: np.ndarray) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """(first word, data, starts, ends) of a text; segments overlap by ``WINDOW - 1`` words."""
    at, words = 0, 0
    while at < len(data):
        stop = min(len(data), at + SEGMENT)
        start, end = word_bounds(data[at:stop])
        if stop < len(data) and len(start) > WINDOW + 1:
            start, end = start[:-1], end[:-1]  # the last word may be cut
            yield words, data[at:stop], start, end
            words += len(start) - (WINDOW - 1)
            at += int(start[-(WINDOW - 1)])
            continue
        if stop < len(data):  # huge words: take the rest at once
            start, end = word_bounds(data[at:])
            stop = len(data)
        yield words, data[at:stop], start, end
        return


def _argmin(values: np.ndarray, width: int) -> np.ndarray:
    """Place of the leftmost smallest value of each run of ``width`` values."""
    v, at, span = values, np.arange(len(values)), 1
    while span < width:
        step = min(span, width - span)
        left = v[:-step] <= v[step:]
        at = np.where(left, at[:-step], at[step:])
        v = np.minimum(v[:-step], v[step:])
        span += step
    return at


def pieces(h: np.ndarray, doc: np.ndarray) -> dict[str, np.ndarray]:
    """Runs of windows with one minimizer; ``h`` are word hashes (one row, or two), ``doc`` the (rising) document of each word."""
    h = h if h.ndim == 2 else np.stack([h, _mix(h)])
    n = h.shape[1] - WINDOW + 1
    if n <= 0:
        return {}
    i = np.arange(h.shape[1] - K + 1)
    mz = Prefix(h[0], _WORD_BASE).span(i, i + K)
    best = _argmin(mz, WINDOW - K + 1)[:n]
    ok = doc[:n] == doc[WINDOW - 1 :]
    new = np.ones(n, dtype=bool)
    new[1:] = (best[1:] != best[:-1]) | ~ok[:-1]
    first = np.flatnonzero(new & ok)
    stop = np.append(np.flatnonzero(new | ~ok), n)
    count = stop[np.searchsorted(stop, first, side="right")] - first
    # all windows of a piece hold its minimizer, so its first and last window overlap and name its words
    w = fixed_spans(h, WINDOW)
    c = _mix(w[:, first] * _ODD[0] + _mix(w[:, first + count - 1] + count.astype(np.uint64)))
    return {"first": first, "n": count, "mz": mz[best[first]], "c1": c[0], "c2": c[1]}


def _bytes(column: pa.Array) -> list[np.ndarray]:
    """The UTF-8 bytes of each text, without a copy."""
    column = column.cast(pa.large_string())
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    raw = column.buffers()[2]
    data = np.frombuffer(raw, dtype=np.uint8) if raw is not None else np.zeros(0, np.uint8)
    return [data[offsets[k] : offsets[k + 1]] for k in range(len(column))]


_SCAN = "doc_id long, th long, pos int, n int, mz long, c1 long, c2 long"


def _scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["doc_id", "th", "pos", "n", "mz", "c1", "c2"]
    gap = np.array([32], dtype=np.uint8)

    def emit(group: list[tuple[int, int, int, np.ndarray]]) -> Iterator[pa.RecordBatch]:
        """group: (id, hash, first word, bytes), hashed together."""
        data = np.concatenate([x for g in group for x in (g[3], gap)])
        edges = np.cumsum([len(g[3]) + 1 for g in group])
        start, end = word_bounds(data)
        if not len(start):
            return
        doc = np.searchsorted(edges, start, side="right")
        p = pieces(word_hashes(data, start, end, 2), doc)
        if not p or not len(p["first"]):
            return
        d = doc[p["first"]]
        begin = np.searchsorted(doc, np.arange(len(group)))
        base = np.array([g[2] for g in group])
        columns = [
            np.array([g[0] for g in group], dtype=np.int64)[d],
            np.array([g[1] for g in group], dtype=np.int64)[d],
            (p["first"] - begin[d] + base[d]).astype(np.int32),
            p["n"].astype(np.int32),
            *(p[c].view(np.int64) for c in ("mz", "c1", "c2")),
        ]
        yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=names)

    for b in batches:
        ids, ths = b.column(0).to_numpy(zero_copy_only=False), b.column(1).to_numpy(zero_copy_only=False)
        group, size = [], 0
        for i, t, data in zip(ids, ths, _bytes(b.column(2))):
            if len(data) < SEGMENT:
                group.append((i, t, 0, data))
                size += len(data) + 1
            else:
                for words, part, _, end in segments(data):
                    if len(end):
                        yield from emit([(i, t, words, part[: int(end[-1])])])
            if size >= SEGMENT:
                yield from emit(group)
                group, size = [], 0
        if group:
            yield from emit(group)


_OPEN = "c1 long, c2 long, src long, j int, w1 long, w2 long"


def digest(words: list[bytes]) -> tuple[int, int]:
    """Two halves of a digest of words."""
    d = hashlib.blake2b(b" ".join(words), digest_size=16).digest()
    return int.from_bytes(d[:8], "little", signed=True), int.from_bytes(d[8:], "little", signed=True)


def _open(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Columns text, asks list<struct<pos, n, c1, c2, src, whole>>: the windows of what is asked for, or (j = -1) a digest of the whole."""
    for b in batches:
        out: list[list[np.ndarray]] = [[] for _ in range(6)]
        asked = b.column(1).to_pylist()
        for data, asks in zip(_bytes(b.column(0)), asked):
            start, end = word_bounds(data)
            for a in asks:
                s, e = start[a["pos"]], end[a["pos"] + a["n"] - 2 + WINDOW]
                if a["whole"]:
                    d = digest(data[s:e].tobytes().split())
                    row = [np.array([x]) for x in (a["c1"], a["c2"], a["src"], -1, *d)]
                    row[3] = row[3].astype(np.int32)
                else:
                    lo, hi = a["pos"], a["pos"] + a["n"] - 1 + WINDOW
                    w = fixed_spans(word_hashes(data[s:e], start[lo:hi] - s, end[lo:hi] - s, 2), WINDOW).view(np.int64)
                    one = np.ones(a["n"], dtype=np.int64)
                    row = [one * a["c1"], one * a["c2"], one * a["src"], np.arange(a["n"], dtype=np.int32), w[0], w[1]]
                for o, x in zip(out, row):
                    o.append(x)
        if out[0]:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(o)) for o in out], names=["c1", "c2", "src", "j", "w1", "w2"])


def glued_edges(path: DataFrame) -> DataFrame:
    """Edges ``(g1, g2)`` of ``path(c1, nx, pv)`` inside nonbranching paths.

    An edge is nonbranching when every row of its tail is followed by its head and every
    row of its head is preceded by its tail.
    """

    def only(c: str):
        return F.when((F.count(c) == F.count(F.lit(1))) & (F.min(c) == F.max(c)), F.min(c))

    deg = write(path.groupBy("c1").agg(only("nx").alias("nx"), only("pv").alias("pv")), "degree").df
    tails = deg.filter("nx is not null").select(F.col("c1").alias("g1"), F.col("nx").alias("g2"))
    heads = deg.filter("pv is not null").select(F.col("pv").alias("g1"), F.col("c1").alias("g2"))
    return write(tails.join(heads, ["g1", "g2"]), "glued").df


def compacted(occ: DataFrame) -> DataFrame:
    """``doc_id, th, pos, n, pieces, u1, u2``: the nonbranching paths of each row, ``n`` windows from word ``pos``.

    ``occ(doc_id, th, pos, n, c1, c2)`` are pieces; ``(u1, u2)`` names equal paths.
    """
    line = W.partitionBy("doc_id", "th").orderBy("pos")
    # repeated rows of an id and text are one row here
    once = occ.withColumn("was", F.lag("pos").over(line)).filter("was is null or was <> pos").drop("was")
    after = F.when(F.lead("pos").over(line) == F.col("pos") + F.col("n"), F.lead("c1").over(line))
    ahead = F.when(F.lag("pos").over(line) + F.lag("n").over(line) == F.col("pos"), F.lag("c1").over(line))
    path = write(once.select("doc_id", "th", "pos", "n", "c1", "c2", after.alias("nx"), ahead.alias("pv")), "path").df
    edges = glued_edges(path).withColumn("glued", F.lit(True))
    # rows without a predecessor get a key of their own, so they don't meet in one partition
    before = F.coalesce("pv", F.xxhash64("doc_id", "th", "pos"))
    p = path.withColumn("before", before).join(edges, (F.col("before") == F.col("g1")) & (F.col("c1") == F.col("g2")), "left")
    p = p.select("doc_id", "th", "pos", "n", "c1", "c2", (F.col("glued").isNotNull() & F.col("pv").isNotNull()).alias("glued"))
    p = p.withColumn("start", F.last(F.when(~F.col("glued"), F.col("pos")), ignorenulls=True).over(line.rowsBetween(W.unboundedPreceding, 0)))
    inside = F.xxhash64("c1", "c2", F.col("pos") - F.col("start"))
    other = F.xxhash64("c2", F.col("pos") - F.col("start"), "c1")
    runs = p.groupBy("doc_id", "th", "start").agg(
        F.sum("n").cast("int").alias("n"), F.count(F.lit(1)).alias("pieces"), F.bit_xor(inside).alias("x"), F.bit_xor(other).alias("y")
    )
    return runs.select("doc_id", "th", F.col("start").alias("pos"), "n", "pieces", F.xxhash64("x", "n").alias("u1"), F.xxhash64("n", "y").alias("u2"))


def repeated_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, th, spans array<struct<start, end, src, w1, w2>>)``: word spans whose windows also start in a smaller document.

    ``th`` is the hash of the text: the pair names the row.  ``src`` is a document that the span's windows start in;
    ``w1, w2`` are the digest of the words at the source, null for spans of single windows.
    """
    d = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text_col).alias("th"), F.col(text_col).cast("string").alias("text"))
    d = d.filter("doc_id is not null and text is not null")
    with scope() as held:
        scan = write(d.mapInArrow(_scan, _SCAN), "pieces")
        mz = scan.df.groupBy("mz").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).filter("lo < hi")
        often = write(mz.select("mz"), "minimizers")
        rep = write(scan.df.join(often.df, "mz", "left_semi"), "repeats")
        scan.drop()
        often.drop()
        occ = rep.df
        with scope() as kept:
            runs = kept(write(compacted(occ), "paths")).df
        # equal paths; source coordinate = any row of the smallest document
        first = [F.min("doc_id").alias("src"), F.max("doc_id").alias("top")]
        paths = runs.groupBy("u1", "u2", "n").agg(*first, F.min_by(F.struct("th", "pos"), "doc_id").alias("at")).filter("src < top")
        paths = write(paths, "sources").df
        # distinct pieces that share a minimizer
        nodes = write(occ.groupBy("c1", "c2", "mz", "n").agg(F.min("doc_id").alias("src"), F.min_by(F.struct("th", "pos"), "doc_id").alias("at")), "nodes").df
        shared = write(nodes.groupBy("mz").agg(F.count(F.lit(1)).alias("k")).filter("k > 1").select("mz"), "shared").df
        ask = lambda t, a, b, whole: t.select("src", "at.th", F.struct(F.col("at.pos").alias("pos"), "n", F.col(a).alias("c1"), F.col(b).alias("c2"), "src", F.lit(whole).alias("whole")).alias("ask"))
        asks = ask(nodes.join(shared, "mz", "left_semi"), "c1", "c2", False).unionByName(ask(paths, "u1", "u2", True))
        asks = asks.groupBy(F.col("src").alias("doc_id"), "th").agg(F.collect_list("ask").alias("asks"))
        # what is asked grows with the corpus: a merge join at every size, so that cost stays in proportion
        asked = d.join(write(asks, "asks").df.hint("merge"), ["doc_id", "th"]).select("text", "asks")
        seen = write(asked.mapInArrow(_open, _OPEN).distinct(), "windows").df
        # paths: every row beyond the smallest document is covered
        proof = seen.filter("j < 0").select(F.col("c1").alias("u1"), F.col("c2").alias("u2"), "src", "w1", "w2")
        whole = runs.join(proof, ["u1", "u2"]).filter("src < doc_id")
        whole = whole.select("doc_id", "th", F.col("pos").alias("start"), (F.col("pos") + F.col("n") - 1 + WINDOW).alias("end"), "src", "w1", "w2")
        # windows that another piece holds in a smaller document count in the smallest document of their own piece
        win = seen.filter("j >= 0")
        low = write(win.groupBy("w1", "w2").agg(F.min("src").alias("low"), F.max("src").alias("high")).filter("low < high"), "low").df
        opened = win.join(low, ["w1", "w2"]).filter("low < src").groupBy("c1", "c2", F.col("src").alias("doc_id"))
        opened = write(opened.agg(F.collect_list(F.struct("j", "low")).alias("more")), "opened").df
        parts = occ.join(opened, ["c1", "c2", "doc_id"]).select("doc_id", "th", "pos", F.explode("more").alias("m"))
        parts = parts.select("doc_id", "th", (F.col("pos") + F.col("m.j")).alias("start"), (F.col("pos") + F.col("m.j") + WINDOW).alias("end"), F.col("m.low").alias("src"))
        line = W.partitionBy("doc_id", "th").orderBy("start", "end")
        past = F.max("end").over(line.rowsBetween(W.unboundedPreceding, -1))
        parts = parts.withColumn("fresh", F.when(F.col("start") <= past, 0).otherwise(1))
        parts = parts.withColumn("g", F.sum("fresh").over(line.rowsBetween(W.unboundedPreceding, 0)))
        merged = parts.groupBy("doc_id", "th", "g").agg(F.min("start").alias("start"), F.max("end").alias("end"), F.min("src").alias("src")).drop("g")
        none = F.lit(None).cast("long")
        spans = whole.unionByName(merged.withColumns({"w1": none, "w2": none}))
        spans = spans.groupBy("doc_id", "th").agg(F.sort_array(F.collect_list(F.struct("start", "end", "src", "w1", "w2"))).alias("spans"))
        return held(write(spans, "spans")).df


_KEPT = "doc_id long, n_words long, n_removed long, kept_sha256 string, kept string"


def _keep(with_text: bool):
    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out: list[list] = [[], [], [], []]
            for text, spans in zip(b.column(1).to_pylist(), b.column(2).to_pylist()):
                words = (text or "").encode().split()
                kept, at = [], 0
                for s in spans or ():
                    # a path is removed if its words are those at the source
                    if s["w1"] is not None and digest(words[s["start"] : s["end"]]) != (s["w1"], s["w2"]):
                        continue
                    kept += words[at : s["start"]]
                    at = max(at, s["end"])
                kept += words[at:]
                joined = b" ".join(kept)
                for o, x in zip(out, (len(words), len(words) - len(kept), hashlib.sha256(joined).hexdigest(), joined.decode() if with_text else None)):
                    o.append(x)
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.string())
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(o, k) for o, k in zip(out, kinds))], names=["doc_id", "n_words", "n_removed", "kept_sha256", "kept"])

    return keep


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", with_text: bool = True) -> DataFrame:
    """``(doc_id, n_words, n_removed, kept_sha256, kept)``, one row per input row; ``kept`` is null without ``with_text``."""
    spans = repeated_spans(docs, id_col, text_col)
    d = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.xxhash64(text_col).alias("th"))
    return d.join(spans.hint("merge"), ["doc_id", "th"], "left").select("doc_id", "text", "spans").mapInArrow(_keep(with_text), _KEPT)


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return remove_repeats(docs, with_text=False).select("doc_id", "n_words", "n_removed", "kept_sha256")


def brute(rows: list[tuple]) -> dict:
    """Test twin for unique ids: id -> (n_words, n_removed, sha256)."""
    split = {i: (t or "").encode().split() for i, t in rows}
    low: dict = {}
    for i, w in split.items():
        for p in range(len(w) - WINDOW + 1):
            key = tuple(w[p : p + WINDOW])
            low[key] = min(low.get(key, i), i)
    out = {}
    for i, w in split.items():
        drop = set()
        for p in range(len(w) - WINDOW + 1):
            if low[tuple(w[p : p + WINDOW])] < i:
                drop.update(range(p, p + WINDOW))
        kept = [x for k, x in enumerate(w) if k not in drop]
        out[i] = (len(w), len(drop), hashlib.sha256(b" ".join(kept)).hexdigest())
    return out

"""Mix sources to target weights on a low-discrepancy schedule.

* Targets.  All words of the corpus are shared among the sources by weight; no source
  gets over ``MAX_EPOCHS`` times its own words, the excess goes to the others by weight.
* Schedule.  Slots stand for blocks of ``BLOCK`` words.  The base-2 van der Corput points
  of the slot numbers are mapped through the cumulative slot shares of the sources.  For
  2^m slots the points are a permutation of i/2^m, so a source's slots are the
  reversed bits of one interval: they are generated from the source's side, without
  a join of slots and sources.
* Ranks.  The k-th slot of a source takes the k-th block of the source's shuffled
  documents, laid end to end and repeated.  Slot ranks and word positions are two-level
  prefix sums (sums of small buckets, then rows inside a bucket), so that a source
  with a third of all rows is never one window.
* Blocks and slots are joined; a document's share is the overlap with its blocks, its place in
  the mixture the slots of these blocks.  The mixture is written in slot order.

The schedule depends on ids, texts and weights only, so reruns agree.

Defined results: null text has size 0 and is never taken; the null source is a source
of its own, last in order; ids may be null or repeated; repeated rows (same id, text and source) lie side
by side in stretches of ``COPIES`` rows, and in the mixture one of them stands for all; an
empty table, or one without words, takes nothing.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from canopy.store import scope, write

WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS = (5, 2, 1)
MAX_EPOCHS = 3
BLOCK = 256
BUCKET_ROWS = 4096
CHUNK = 1 << 15
COPIES = 64


def size_of(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text.cast("string"), F.lit(WORD)), F.lit(0)).cast("long")


def targets(sources: DataFrame, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """``sources(source, source_size, weight)`` with ``target`` added: shares by weight, capped, the excess reshared.

    One row per source; the windows run over sources, not over documents.
    """
    cap = F.col("source_size") * max_epochs
    up = W.orderBy(cap / F.col("weight"), F.col("source").asc_nulls_last())
    all_rows = W.partitionBy()
    s = sources.withColumns(
        {
            "below": F.coalesce(F.sum(cap).over(up.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)),
            "left": F.sum("weight").over(up.rowsBetween(0, W.unboundedFollowing)),
            "all": F.sum("source_size").over(all_rows),
        }
    )
    s = s.withColumn("level", (F.col("all") - F.col("below")) / F.col("left"))
    ratio = cap / F.col("weight")
    level = F.min(F.when(ratio >= F.col("level"), F.struct(ratio.alias("r"), "level"))).over(all_rows)["level"]
    # the first source that its cap does not stop fixes the level of all that are not stopped
    s = s.withColumn("level", F.coalesce(level, F.lit(0.0)))
    return s.withColumn("target", F.least(cap.cast("double"), F.col("level") * F.col("weight"))).drop("below", "left", "all", "level")


def source_table(docs: DataFrame, weights=WEIGHTS, max_epochs: int = MAX_EPOCHS, block: int = BLOCK) -> DataFrame:
    """``sid, source, source_size, weight, target, words, slots, first_slot`` of ``docs(source, size)``."""
    by = W.orderBy(F.col("source").asc_nulls_last())
    s = docs.groupBy("source").agg(F.sum("size").alias("source_size"))
    s = s.withColumn("sid", F.row_number().over(by) - 1)
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.pmod("sid", F.lit(len(weights))) + 1).cast("int"))
    s = s.withColumn("weight", w)
    s = targets(s, max_epochs)
    s = s.withColumn("words", F.round("target").cast("long"))
    s = s.withColumn("slots", F.ceil(F.col("words") / F.lit(block)).cast("long"))
    first = F.coalesce(F.sum("slots").over(W.orderBy("sid").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    return s.withColumn("first_slot", first)


def reversed_bits(x: Column, bits: int) -> Column:
    return F.conv(F.reverse(F.lpad(F.bin(x), bits, "0")), 2, 10).cast("long") if bits else x


def schedule(sources: DataFrame) -> DataFrame:
    """``(sid, rank, slot)``: slot numbers rise in mixing order, ranks count a source's slots from 0."""
    total = sources.agg(F.coalesce(F.sum("slots"), F.lit(0))).first()[0]
    bits = max(0, math.ceil(math.log2(total))) if total else 0
    grid, total = 1 << bits, max(total, 1)
    edge = lambda c: F.expr(f"cast(ceil(cast({c} as decimal(38,0)) * {grid} / {total}) as bigint)")
    s = sources.filter("slots > 0").select("sid", "slots", edge("first_slot").alias("lo"), edge("(first_slot + slots)").alias("hi"))
    parts = s.withColumn("chunk", F.explode(F.expr(f"sequence(lo div {CHUNK}, (hi - 1) div {CHUNK})"))).repartition("sid", "chunk")
    j = F.explode(F.expr(f"sequence(greatest(lo, chunk * {CHUNK}), least(hi, (chunk + 1) * {CHUNK}) - 1)"))
    slots = parts.select("sid", "slots", j.alias("j")).select("sid", "slots", reversed_bits(F.col("j"), bits).alias("slot"))
    slots = write(slots.withColumn("bucket", F.expr(f"slot div {CHUNK}")), "slots").df
    base = slots.groupBy("sid", "bucket").agg(F.count(F.lit(1)).alias("n"))
    base = base.withColumn("base", F.coalesce(F.sum("n").over(W.partitionBy("sid").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    inside = F.row_number().over(W.partitionBy("sid", "bucket").orderBy("slot")) - 1
    ranked = slots.withColumn("inside", inside).join(base.select("sid", "bucket", "base"), ["sid", "bucket"])
    return ranked.select("sid", (F.col("base") + F.col("inside")).alias("rank"), "slot", "slots").filter("rank < slots").drop("slots")


def laid_out(docs: DataFrame, sources: DataFrame) -> DataFrame:
    """``docs(doc_id, th, source, size)`` with ``sid, start, source_size, target, words``: places in the source's shuffled stream."""
    n = docs.count()
    bits = max(0, math.ceil(math.log2(max(1, n / BUCKET_ROWS))))
    # repeated rows have one hash: they are dealt over the buckets in stretches
    d = docs.groupBy("doc_id", "th", "source", "size").agg(F.count(F.lit(1)).alias("m"))
    d = d.withColumn("part", F.explode(F.expr(f"sequence(0L, (m - 1) div {COPIES})")))
    d = d.withColumn("m", F.expr(f"least({COPIES}L, m - part * {COPIES})"))
    d = d.join(sources.drop("weight", "slots", "first_slot").withColumnRenamed("source", "s"), F.col("source").eqNullSafe(F.col("s"))).drop("s")
    u = F.xxhash64("doc_id", "th", "part")
    d = d.withColumn("u", u).withColumn("bucket", F.shiftrightunsigned("u", 64 - bits) if bits else F.lit(0).cast("long"))
    words = F.col("size") * F.col("m")
    base = d.groupBy("sid", "bucket").agg(F.sum(words).alias("n"))
    base = base.withColumn("base", F.coalesce(F.sum("n").over(W.partitionBy("sid").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    line = W.partitionBy("sid", "bucket").orderBy("u", "doc_id", "th", "part").rowsBetween(W.unboundedPreceding, -1)
    d = d.withColumn("inside", F.coalesce(F.sum(words).over(line), F.lit(0)))
    d = d.join(base.select("sid", "bucket", "base"), ["sid", "bucket"])
    d = d.withColumn("copy", F.explode(F.expr("sequence(0L, m - 1)")))
    return d.withColumn("start", F.col("base") + F.col("inside") + F.col("copy") * F.col("size")).drop("u", "bucket", "inside", "base", "m", "part", "copy")


def blocks(placed: DataFrame, max_epochs: int = MAX_EPOCHS, block: int = BLOCK) -> DataFrame:
    """``(sid, start, rank, epoch, lo, hi)``: the words lo..hi of a document in block ``rank`` of its source."""
    d = placed.filter("size > 0").select("sid", "start", "size", "source_size", "words", F.explode(F.sequence(F.lit(0), F.lit(max_epochs - 1))).alias("epoch"))
    d = d.withColumn("a", F.col("epoch") * F.col("source_size") + F.col("start")).withColumn("z", F.least(F.col("a") + F.col("size"), "words"))
    d = d.filter("z > a").withColumn("rank", F.explode(F.expr(f"sequence(a div {block}, (z - 1) div {block})")))
    lo = F.greatest("a", F.col("rank") * block) - F.col("a")
    hi = F.least("z", (F.col("rank") + 1) * block) - F.col("a")
    return d.select("sid", "start", "rank", "epoch", lo.alias("lo"), hi.alias("hi"))


def rows_of(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    text = F.col(text_col).cast("string")
    return docs.select(F.col(id_col).alias("doc_id"), F.xxhash64(text).alias("th"), F.col(source_col).cast("string").alias("source"), size_of(text).alias("size"))


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights=WEIGHTS) -> tuple[DataFrame, DataFrame]:
    """``placed`` (a row per document) and the mixture ``(slot, sid, start, epoch, lo, hi)``: words to take, in slot order."""
    d = write(rows_of(docs, id_col, text_col, source_col), "sizes").df
    sources = write(source_table(d, weights), "sources").df
    placed = write(laid_out(d, sources), "placed").df
    taken = blocks(placed).join(schedule(sources).hint("merge"), ["sid", "rank"]).select("slot", "sid", "start", "epoch", "lo", "hi")
    return placed, taken


def copies(docs: DataFrame, **columns) -> tuple[DataFrame, DataFrame]:
    """``placed`` and ``(sid, start, epoch, n, slot, last_slot)``: the copies that the mixture takes, by their words and slots."""
    placed, taken = mix(docs, **columns)
    per = taken.groupBy("sid", "start", "epoch").agg(F.sum(F.col("hi") - F.col("lo")).alias("n"), F.min("slot").alias("slot"), F.max("slot").alias("last_slot"))
    return placed, write(per, "copies").df


def taken_words(docs: DataFrame, **columns) -> DataFrame:
    """``doc_id, th, source, size, source_size, target, taken, epochs, first_slot, last_slot``: a row per document.

    ``epochs`` are the copies that the mixture takes, a last cut one included; slots are null where there are none.
    """
    with scope() as held:
        placed, per = copies(docs, **columns)
        per = per.groupBy("sid", "start").agg(
            F.sum("n").alias("taken"), F.count(F.lit(1)).alias("epochs"), F.min("slot").alias("first_slot"), F.max("last_slot").alias("last_slot")
        )
        # a row for each document: sorted numbers compress so well that file sizes would let it be broadcast
        per = write(per, "taken").df.hint("merge")
        d = placed.join(per, (placed.sid == per.sid) & (placed.start == per.start) & (placed["size"] > 0), "left")
        zero = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
        out = d.select("doc_id", "th", "source", "size", "source_size", "target", zero("taken"), zero("epochs"), "first_slot", "last_slot")
        return held(write(out, "mixed")).df


def mixed_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", slot_col: str | None = None) -> DataFrame:
    """The mixture as documents in slot order: a row for each copy that it takes, a last cut copy as its first words.

    ``slot_col`` names a column for the slot at which a copy starts.
    """
    own = docs.columns
    with scope() as held:
        placed, per = copies(docs, id_col=id_col, text_col=text_col, source_col=source_col)
        d = placed.filter("size > 0").select("sid", "start", "doc_id", "th", "source", "size")
        plan = per.hint("merge").join(d, ["sid", "start"])
        keys = lambda i, h, src: [F.xxhash64(i, h, src).alias("__k"), F.xxhash64(F.lit(1), src, h, i).alias("__l")]
        plan = plan.select(*keys("doc_id", "th", "source"), F.col("n").alias("__n"), F.col("size").alias("__size"), F.col("slot").alias("__slot"))
        plan = held(write(plan, "plan")).df
    th = F.xxhash64(F.col(text_col).cast("string"))
    k, l = keys(F.col(id_col), th, F.col(source_col).cast("string"))
    # repeated rows have one row here: their copies are rows of the plan
    one = docs.withColumns({"__k": k, "__l": l}).dropDuplicates(["__k", "__l"])
    m = one.join(plan.hint("merge"), ["__k", "__l"])
    whole = F.col("__n") >= F.col("__size")
    first = F.array_join(F.slice(F.regexp_extract_all(text_col, F.lit(WORD), F.lit(0)), F.lit(1), F.col("__n").cast("int")), " ")
    m = m.withColumn(text_col, F.when(whole, F.col(text_col)).otherwise(first))
    if "n_chars" in own:
        m = m.withColumn("n_chars", F.when(whole, F.col("n_chars")).otherwise(F.length(text_col).cast("long")))
    m = m.repartitionByRange("__slot").sortWithinPartitions("__slot")
    return m.select(*[m[c] for c in own], *([F.col("__slot").alias(slot_col)] if slot_col else []))


def query(spark, sf_dir: str) -> DataFrame:
    t = taken_words(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return t.select("doc_id", "size", "source_size", "target", "taken", "first_slot", "last_slot")

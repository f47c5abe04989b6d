"""Exact deduplication by content-defined chunk recipes (DataFrame functions only).

A text is normalised, cut into chunks at places chosen by its own content, and
each chunk becomes a verified identifier.  Two texts are equal when their ordered
identifier lists are equal, so after the one scan that builds the recipes no text
moves again: shuffles carry 24 bytes for about 400 characters.

* Cut rule: a chunk ends after word i when the hash of words i-1 and i falls in a
  1/64 class.  An edit moves at most the cuts beside it.
* Verified identifiers: a chunk has a 64-bit hash and an independent 128-bit
  digest.  The dictionary of distinct (hash, digest) pairs shows which hashes stand
  for two contents; a recipe that holds such a hash also carries its digests.
* Groups: rows with equal identifier lists (and equal digests of doubtful chunks) are one group;
  the hash of the whole text is an output and decides nothing.
* Hot groups: copies meet in a hash aggregate with a partial phase; its result is
  written, and the join back is plain on both sides so that skewed partitions split.

Defined results: null text counts as empty; a null id never is the smallest (a
group of null ids only keeps a null id, and its rows are kept); rows that tie on the
smallest id of a group are all kept; an empty table gives an empty result; only the
two named columns are read, so other columns may have any name.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from canopy.store import scope, write

SPACES = r"[\x20\x09-\x0D]+"
CUT_CLASSES = 64


def normalised(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text.cast("string"), F.lit("")), SPACES, " ")


def _ends(words: Column) -> Column:
    """1-based places of the last word of each chunk."""
    n = F.size(words)
    return F.filter(
        F.sequence(F.lit(1), n),
        lambda i: (i == n)
        | ((i > 1) & (F.pmod(F.xxhash64(F.get(words, i - 2), F.get(words, i - 1)), F.lit(CUT_CLASSES)) == 0)),
    )


def _chunk(words: Column, ends: Column):
    def chunk(end: Column, k: Column) -> Column:
        start = F.when(k == 0, F.lit(0)).otherwise(F.get(ends, k - 1))
        c = F.array_join(F.slice(words, start + 1, end - start), " ")
        return F.struct(F.xxhash64(c).alias("h"), F.unhex(F.substring(F.sha2(c, 256), 1, 32)).alias("v"))

    return chunk


def recipes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id, th, text_sha256, chunks array<struct<h long, v binary>>)``, one row per input row; ``th`` is the hash of the text as it is."""
    th = F.xxhash64(F.col(text_col).cast("string")).alias("th")
    norm = docs.select(F.col(id_col).alias("id"), th, normalised(F.col(text_col)).alias("t"))
    # each step is a projection of its own: a column used inside a lambda is then computed once
    w = norm.select("id", "th", F.sha2("t", 256).alias("text_sha256"), F.split("t", " ").alias("w"))
    w = w.withColumn("ends", _ends(F.col("w")))
    return w.select("id", "th", "text_sha256", F.transform("ends", _chunk(F.col("w"), F.col("ends"))).alias("chunks"))


def chunk_dictionary(recipe: DataFrame) -> DataFrame:
    """Distinct chunks with their use: ``(h, v, uses)``."""
    c = recipe.select(F.explode("chunks").alias("c")).select("c.h", "c.v")
    return c.groupBy("h", "v").agg(F.count(F.lit(1)).alias("uses"))


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", recipe_of=recipes) -> DataFrame:
    """``(id, th, keep_id, group_size, kept, text_sha256, n_chunks)``, one row per input row.

    ``recipe_of(docs, id_col, text_col)`` makes the recipes that are compared.
    """
    with scope() as held:
        r = write(recipe_of(docs, id_col, text_col), "recipes").df
        twins = write(chunk_dictionary(r).groupBy("h").agg(F.count(F.lit(1)).alias("n")).filter("n > 1"), "twins").df
        # the digests of doubtful chunks, by text: only recipes with such chunks have a row
        doubtful = (
            r.select("text_sha256", F.posexplode("chunks").alias("pos", "c"))
            .select("text_sha256", "pos", F.col("c.h").alias("h"), F.col("c.v").alias("v"))
            .distinct()
            .join(twins.select("h"), "h")
            .groupBy("text_sha256")
            .agg(F.sort_array(F.collect_list(F.struct("pos", "v"))).alias("vs"))
            .select("text_sha256", F.concat_ws(",", F.transform("vs", lambda x: F.hex(x["v"]))).alias("proof"))
        )
        doubtful = write(doubtful, "doubtful").df
        ids = F.transform("chunks", lambda c: c["h"]).alias("ids")
        keyed = r.select("id", "th", "text_sha256", ids).join(doubtful, "text_sha256", "left")
        keyed = keyed.withColumn("proof", F.coalesce("proof", F.lit("")))
        key = ["ids", "proof"]
        groups = keyed.groupBy(*key).agg(F.min("id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
        out = keyed.join(write(groups, "groups").df, key).select(
            "id",
            "th",
            "keep_id",
            "group_size",
            F.col("id").eqNullSafe(F.col("keep_id")).alias("kept"),
            "text_sha256",
            F.size("ids").cast("long").alias("n_chunks"),
        )
        return held(write(out, "copies")).df


ORACLE = r"""
with n as (
  select doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') as t from documents)
select doc_id, min(doc_id) over (partition by t) as keep_id,
       count(*) over (partition by t) as group_size,
       doc_id = min(doc_id) over (partition by t) as kept,
       sha256(t) as text_sha256
from n
"""


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return exact_groups(docs).select(
        F.col("id").alias("doc_id"), "keep_id", "group_size", "kept", "text_sha256"
    )

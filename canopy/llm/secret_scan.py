"""Secret scan with corpus-wide ownership frequency (DataFrame functions only).

Fixed patterns find base spans.  A wider pattern finds token-like candidates.  All
candidate values of the corpus are aggregated by hash: how many distinct owners and
repositories hold the value.  A value that many owners or many repositories hold is a
copied example; a token-like value of few owners and repositories that also looks live
(mixed classes, entropy, no placeholder) becomes a span of kind ``live``.

Owner = ``source``; repository = ``source`` and ``lang`` (a sub-collection of an
owner): the table has no finer column, both are parameters.

Positions come without a UDF: splitting by a pattern gives the text between the
matches, so starts are running sums of piece and match lengths in code points.

Defined results: null text counts as empty and has no span; null owners count as one
owner; repeated rows are judged alike and all returned; an empty table gives none.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from canopy.store import write

# Fixed patterns, in the order in which spans that start together are listed.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"[0-9a-f]{24,}"
TOKEN = r"(?<![A-Za-z0-9+/_=-])(?=[A-Za-z+/_=-]*[0-9])(?=[0-9+/_=-]*[A-Za-z])[A-Za-z0-9+/_=-]{20,}"
PLACEHOLDER = r"(?i)example|sample|changeme|placeholder|dummy|your|test|xxxx|0{6,}|1234567|abcdef0123"
KINDS = {"assign": 0, "access": 1, "hex": 2, "live": 3}
#: A value held by more owners, or in more repositories, than this is an example that was copied around.
MAX_OWNERS = 2
MAX_REPOS = 4
MIN_ENTROPY = 3.0


def running(lengths: Column) -> Column:
    """Running sums of an array, by doubling: log2 of its size passes, so long arrays cost no quadratic time."""

    def double(sums: Column, k: Column) -> Column:
        back = F.call_function("shiftleft", F.lit(1), k)
        return F.transform(sums, lambda x, i: x + F.coalesce(F.get(sums, i - back), F.lit(0)))

    return F.aggregate(F.sequence(F.lit(0), F.ceil(F.log2(F.size(lengths))).cast("int")), lengths, double)


def matches(text: Column, pattern: str) -> Column:
    """``array<struct<start, end, m>>`` of the leftmost non-overlapping matches, in code points."""
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    gaps = F.transform(F.split(text, pattern, -1), lambda p: F.length(p))
    parts = F.filter(F.arrays_zip(gaps.alias("gap"), found.alias("m")), lambda x: x["m"].isNotNull())

    def placed(p: Column) -> Column:
        ends = running(F.transform(p, lambda x: x["gap"] + F.length(x["m"])))
        return F.zip_with(p, ends, lambda x, e: F.struct((e - F.length(x["m"])).alias("start"), e.alias("end"), x["m"].alias("m")))

    # the array of one element binds the parts, so patterns are applied once
    none = F.array().cast("array<struct<start:int,end:int,m:string>>")
    return F.when(text.rlike(pattern), F.get(F.transform(F.array(parts), placed), F.lit(0))).otherwise(none)


def entropy(value: Column) -> Column:
    """Shannon entropy of the characters, in bits."""
    n = F.length(value).cast("double")

    def more(total: Column, c: Column) -> Column:
        share = (n - F.length(F.replace(value, c, F.lit("")))) / n
        return F.when(share > 0, total - share * F.log2(share)).otherwise(total)

    return F.aggregate(F.array_distinct(F.split(value, "")), F.lit(0.0), more)


def _spans(kind: str, found: Column, value) -> Column:
    return F.transform(
        found,
        lambda x: F.struct(
            x["start"].alias("start"),
            F.lit(KINDS[kind]).alias("k"),
            x["end"].alias("end"),
            value(x["m"]).alias("value"),
        ),
    )


def candidates(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", owner: str = "source", repo=("source", "lang")
) -> DataFrame:
    """One row per input row: ``id, owner, repo, base, wide`` with arrays of spans and their value hashes."""
    t = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    d = docs.select(
        F.col(id_col).alias("id"),
        F.coalesce(F.col(owner).cast("string"), F.lit("")).alias("owner"),
        F.xxhash64(*[F.coalesce(F.col(c).cast("string"), F.lit("")) for c in repo]).alias("repo"),
        t.alias("t"),
    )
    group2 = lambda m: F.regexp_extract(m, ASSIGN, 2)
    d = d.select(
        "id",
        "owner",
        "repo",
        F.filter(matches(F.col("t"), ASSIGN), lambda x: F.length(group2(x["m"])) >= 6).alias("a"),
        matches(F.col("t"), ACCESS).alias("c"),
        matches(F.col("t"), HEX).alias("h"),
        matches(F.col("t"), TOKEN).alias("w"),
    )
    same = lambda m: m
    base = F.array_sort(F.concat(_spans("assign", F.col("a"), group2), _spans("access", F.col("c"), same), _spans("hex", F.col("h"), same)))
    d = d.select("id", "owner", "repo", base.alias("base"), _spans("live", F.col("w"), same).alias("wide"))
    apart = lambda x: ~F.exists("base", lambda b: (b["start"] < x["end"]) & (x["start"] < b["end"]))
    return d.withColumn("wide", F.filter("wide", apart))


def ownership(found: DataFrame) -> DataFrame:
    """Per candidate value: ``vh, n_owners, n_repos, n_rows, live_looking``."""
    one = found.filter(F.size("base") + F.size("wide") > 0).select(
        "owner", "repo", F.explode(F.concat("base", "wide")).alias("s")
    )
    one = one.select("owner", "repo", F.sha2(F.col("s.value"), 256).alias("vh"), F.col("s.value").alias("value"))
    per = one.groupBy("vh", "owner", "repo").agg(F.count(F.lit(1)).alias("n"), F.first("value").alias("value"))
    per = per.groupBy("vh", "owner").agg(
        F.count(F.lit(1)).alias("repos"), F.sum("n").alias("n"), F.first("value").alias("value")
    )
    per = per.groupBy("vh").agg(
        F.count(F.lit(1)).alias("n_owners"), F.sum("repos").alias("n_repos"), F.sum("n").alias("n_rows"), F.first("value").alias("value")
    )
    looks = (entropy(F.col("value")) >= MIN_ENTROPY) & ~F.col("value").rlike(PLACEHOLDER)
    return per.select("vh", "n_owners", "n_repos", "n_rows", looks.alias("live_looking"))


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", owner: str = "source", repo=("source", "lang")) -> DataFrame:
    """``id, base, live, n_live, n_copied``: base spans, added spans, and base spans by ownership."""
    found = write(candidates(docs, id_col, text_col, owner, repo), "secrets").df
    known = write(ownership(found), "owners").df
    key = F.xxhash64("id", "base", "wide").alias("key")
    some = found.filter(F.size("base") + F.size("wide") > 0).select(key, "base", "wide").distinct()
    each = some.select("key", F.explode(F.concat("base", "wide")).alias("s")).select("key", "s", F.sha2("s.value", 256).alias("vh"))
    live = (F.col("n_owners") <= MAX_OWNERS) & (F.col("n_repos") <= MAX_REPOS) & F.col("live_looking")
    judged = each.join(known, "vh").select("key", "s", live.alias("live"))
    per = judged.groupBy("key").agg(
        F.array_sort(F.collect_list(F.when(F.col("live") & (F.col("s.k") == KINDS["live"]), F.col("s")))).alias("live"),
        F.count_if(F.col("live") & (F.col("s.k") < KINDS["live"])).alias("n_live"),
        F.count_if(~F.col("live") & (F.col("s.k") < KINDS["live"])).alias("n_copied"),
    )
    out = found.withColumn("key", key).join(per, "key", "left")
    return out.select(
        "id",
        "base",
        F.coalesce("live", F.filter("base", lambda x: F.lit(False))).alias("live"),
        F.coalesce("n_live", F.lit(0)).alias("n_live"),
        F.coalesce("n_copied", F.lit(0)).alias("n_copied"),
    )


def _listed(spans: Column) -> Column:
    name = F.create_map(*[F.lit(x) for k, v in KINDS.items() for x in (v, k)])
    return F.concat_ws(
        ",", F.transform(spans, lambda s: F.concat_ws(":", name[s["k"]], s["start"].cast("string"), s["end"].cast("string")))
    )


def query(spark, sf_dir: str) -> DataFrame:
    s = scan(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    count = lambda kind: F.size(F.filter("base", lambda x: x["k"] == KINDS[kind])).cast("long")
    return s.select(
        F.col("id").alias("doc_id"),
        count("assign").alias("n_assign"),
        count("access").alias("n_access"),
        count("hex").alias("n_hex"),
        F.sha2(_listed(F.col("base")), 256).alias("base_sha256"),
        _listed(F.array_sort(F.concat("base", "live"))).alias("spans"),
        "n_live",
        "n_copied",
    )

"""URL filter: longest host-and-path rule, else gradient-boosted trees (DataFrame functions only).

URLs that a rule decides are the labelled set.  Boosted trees are fitted to lexical
features of about nine tenths of ``TRAIN_ROWS`` of them (a share of the hash range; under the bound
the split finder reads every row, so reruns agree), then written out as
one column expression: scoring is generated code with no model object in the tasks.

Features: length, path depth, digit ratio, character entropy, number of query
parameters, hyphens, host labels, longest word, https, fragment, and statistics of the
host's suffix over *all* URLs (its log count and the smoothed share of blocked ones
among the rule-decided).  The suffix table is aggregated with a partial phase, written,
and joined plainly, so that a suffix with a third of all rows splits.

Defined results: a null url or one without ``://`` has empty host and path, matches no
rule and is judged by the trees on the empty text; with fewer than two classes among the
labelled rows the verdict without a rule is that class, or allow where none is labelled.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from canopy.llm.secret_scan import entropy
from canopy.store import write

#: The given rules: (verdict, host and path).
RULES = (
    ("allow", "org/"),
    ("block", "example.org/es/"),
    ("block", "example.org/en/1"),
    ("allow", "com/fr/"),
    ("block", "com/de/"),
)
TRAIN_ROWS = 10_000
TREES, DEPTH = 20, 4
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
SPLIT = r"(?s)^.*?://([^/?#]*)([^?#]*)"


def host_of(url: Column) -> Column:
    return F.translate(F.regexp_extract(F.coalesce(url, F.lit("")), SPLIT, 1), UPPER, LOWER)


def path_of(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), SPLIT, 2)


def rule_of(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest fitting rule and its verdict, null where none fits."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for says, text in sorted(rules, key=lambda r: len(r[1])):
        h, _, p = text.partition("/")
        fits = ((host == h) | host.endswith("." + h)) & path.startswith("/" + p)
        rule, verdict = F.when(fits, F.lit(text)).otherwise(rule), F.when(fits, F.lit(says)).otherwise(verdict)
    return rule, verdict


def lexical(url: Column, host: Column, path: Column) -> dict[str, Column]:
    u = F.coalesce(url, F.lit(""))
    n = F.greatest(F.length(u), F.lit(1)).cast("double")
    query = F.regexp_extract(u, r"(?s)\?([^#]*)", 1)
    count = lambda c, pattern: F.length(F.regexp_replace(c, pattern, "")).cast("double")
    return {
        "f_length": F.length(u).cast("double"),
        "f_depth": count(path, "[^/]"),
        "f_digits": count(u, "[^0-9]") / n,
        "f_entropy": F.coalesce(entropy(F.when(F.length(u) > 0, u)), F.lit(0.0)),
        "f_params": F.when(query == "", 0.0).otherwise(F.size(F.split(query, "&")).cast("double")),
        "f_hyphens": count(host, "[^-]"),
        "f_labels": F.size(F.split(host, r"\.")).cast("double"),
        "f_longest": F.array_max(F.transform(F.split(u, "[^A-Za-z0-9]+"), lambda w: F.length(w))).cast("double"),
        "f_https": u.startswith("https").cast("double"),
        "f_fragment": F.contains(u, F.lit("#")).cast("double"),
    }


def _tree(node, names: list[str]) -> Column:
    if node.subtreeDepth() == 0:
        return F.lit(float(node.prediction()))
    split = node.split()
    return F.when(
        F.col(names[split.featureIndex()]) <= float(split.threshold()), _tree(node.leftChild(), names)
    ).otherwise(_tree(node.rightChild(), names))


def fit_margin(rows: DataFrame, names: list[str]) -> Column | None:
    """Boosted trees over ``names`` for label ``y`` as one expression; above 0 means block."""
    from pyspark.ml.classification import GBTClassifier
    from pyspark.ml.feature import VectorAssembler

    ready = VectorAssembler(inputCols=names, outputCol="features").transform(rows)
    gbt = GBTClassifier(labelCol="y", maxIter=TREES, maxDepth=DEPTH, stepSize=0.3, seed=7, maxBins=64)
    model = gbt.fit(ready.select("features", "y"))
    margin = F.lit(0.0)
    for tree, weight in zip(model.trees, model.treeWeights):
        margin = margin + F.lit(float(weight)) * _tree(tree._call_java("rootNode"), names)
    return margin


def judge(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", rules=RULES, train_rows: int = TRAIN_ROWS) -> DataFrame:
    """``id, host, path, rule, verdict, margin``, one row per page."""
    u = pages.select(F.col(id_col).alias("id"), F.col(url_col).cast("string").alias("url"))
    u = u.withColumns({"host": host_of(F.col("url")), "path": path_of(F.col("url"))})
    rule, says = rule_of(F.col("host"), F.col("path"), rules)
    u = u.withColumns({"rule": rule, "says": says, "suffix": F.substring_index("host", ".", -1)})
    u = write(u.withColumns(lexical(F.col("url"), F.col("host"), F.col("path"))), "urls").df
    totals = u.agg(F.count_if(F.col("says") == "block").alias("b"), F.count("says").alias("n")).first()
    prior = totals["b"] / totals["n"] if totals["n"] else 0.0
    if not 0 < prior < 1:
        return u.select("id", "host", "path", "rule", F.coalesce("says", F.lit("block" if prior else "allow")).alias("verdict"), F.lit(0.0).alias("margin"))
    suffix = write(
        u.groupBy("suffix").agg(
            F.log1p(F.count(F.lit(1))).alias("f_suffix_count"),
            ((F.count_if(F.col("says") == "block") + 20 * prior) / (F.count("says") + 20)).alias("f_suffix_block"),
        ),
        "suffix",
    ).df
    f = u.join(suffix, "suffix")
    names = sorted(c for c in f.columns if c.startswith("f_"))
    # a share of the hash range that holds nine tenths of the bound on average; the bound itself is what the
    # split finder reads in full, which keeps reruns equal
    share = min(1 << 20, int(0.9 * train_rows * (1 << 20)) // totals["n"])
    labelled = f.filter("says is not null").filter(F.pmod(F.xxhash64("id", "url"), F.lit(1 << 20)) < share)
    train = write(labelled.select(*names, (F.col("says") == "block").cast("double").alias("y")), "labelled").df
    if train.select("y").distinct().count() < 2:
        return u.select("id", "host", "path", "rule", F.coalesce("says", F.lit("block" if prior > 0.5 else "allow")).alias("verdict"), F.lit(0.0).alias("margin"))
    margin = fit_margin(train, names)
    f = f.withColumn("margin", margin)
    own = F.when(F.col("margin") > 0, "block").otherwise("allow")
    return f.select("id", "host", "path", "rule", F.coalesce("says", own).alias("verdict"), "margin")


def query(spark, sf_dir: str) -> DataFrame:
    j = judge(spark.read.parquet(f"{sf_dir}/pages.parquet"))
    return j.select(F.col("id").alias("page_id"), "host", "path", "rule", "verdict", "margin")

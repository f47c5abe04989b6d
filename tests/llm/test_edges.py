"""Nulls, empty and repeated rows, clashing columns, empty tables for every operator."""

import pytest
from pyspark.sql import functions as F

from canopy.llm import (
    embedding_dedup,
    exact_dedup,
    lattice_lm,
    mixing,
    ngram_join,
    packing,
    secret_scan,
    substring_dedup,
    toxicity,
    url_filter,
)

LONG = " ".join(f"w{i % 977}x{i % 13}" for i in range(20_000))
ROWS = [
    (1, "alpha beta gamma", "en", "a", 16, 99),
    (2, None, None, None, None, 99),
    (3, "", "en", "a", 0, None),
    (4, LONG, "fr", "b", len(LONG), 1),
    (5, LONG, "fr", "b", len(LONG), 1),
    (6, "alpha  beta\tgamma", "en", None, 17, 2),
    (6, "alpha  beta\tgamma", "en", None, 17, 2),
    (None, "no id here", "de", "c", 10, 3),
    (8, "   \n\t ", "en", "a", 6, 4),
    (9, "word", "en", "a", 4, 5),
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, kept long"


@pytest.fixture(scope="module")
def docs(spark):
    # extra columns whose names clash with those the operators use
    d = spark.createDataFrame(ROWS, SCHEMA)
    return d.withColumns({"id": F.lit(1), "size": F.lit("x"), "th": F.lit(2), "key": F.lit("k"), "start": F.lit(0), "keep_id": F.lit(7), "score": F.lit(1.0)})


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (4, 0, 1), (9, 1, None), (None, 0, 1)], "doc_id long, quality int, toxic int")


def by_id(df, key="doc_id"):
    out = {}
    for r in df.collect():
        out.setdefault(r[key], []).append(r)
    return out


def test_substring(docs):
    r = by_id(substring_dedup.remove_repeats(docs))
    assert r[4][0].n_removed == 0 and r[5][0].n_removed == r[5][0].n_words == 20_000
    assert [x.n_words for x in r[6]] == [3, 3] and r[2][0].n_words == 0 and r[None][0].n_removed == 0
    assert sum(map(len, r.values())) == len(ROWS)


def test_join(docs):
    r = by_id(ngram_join.similarity_join(docs))
    assert r[4][0].n_links == 1 and r[5][0].class_id == 4
    assert [x.n_links for x in r[6]] == [2, 2] and r[1][0].n_links == 2 and r[6][0].class_id == 1
    assert r[2][0].n_links == r[3][0].n_links == r[None][0].n_links == 0 and r[None][0].class_id is None
    assert sum(map(len, r.values())) == len(ROWS)


def test_exact(docs):
    r = by_id(exact_dedup.exact_groups(docs), "id")
    assert r[2][0].kept and not r[3][0].kept and r[3][0].keep_id == 2
    assert r[6][0].keep_id == 1 and r[6][0].group_size == 3 and not r[6][0].kept
    assert r[None][0].kept and r[8][0].kept and sum(map(len, r.values())) == len(ROWS)


def test_lattice(docs):
    r = by_id(lattice_lm.score_documents(docs))
    assert r[2][0].n_tokens == r[3][0].n_tokens == 1 and r[2][0].score == r[3][0].score < 0
    assert r[6][0].score == r[6][1].score and r[None][0].held_out is False
    assert sum(map(len, r.values())) == len(ROWS)


def test_lattice_rare_words(spark, docs):
    """Words outside the table in memory count once, like those in it."""
    exact = lambda df: sorted(((r.doc_id or 0, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6), round(r.score, 6)) for r in df.collect()))
    want = exact(lattice_lm.score_documents(docs))
    assert want[-1][2] == 2
    for head in (0, 100):
        assert exact(lattice_lm.score_documents(docs, head=head)) == want


def test_lattice_odd_bytes(spark):
    d = spark.createDataFrame([(3, bytearray(b"ok \xff\xfe A")), (4, bytearray(b"\xff\xfe"))], "doc_id long, t binary").selectExpr("doc_id", "cast(t as string) text")
    r = by_id(lattice_lm.score_documents(d))
    assert (r[3][0].n_tokens, r[4][0].n_tokens, r[3][0].n_known, r[4][0].n_known, r[3][0].train_tokens) == (4, 2, 4, 2, 6)


def test_secrets(docs):
    r = by_id(secret_scan.scan(docs), "id")
    assert all(not x.base for v in r.values() for x in v) and sum(map(len, r.values())) == len(ROWS)


def test_toxicity(docs, labels):
    s = toxicity.score(docs, labels).collect()
    assert len(s) == len(ROWS) and all(0 <= x.score <= 1 for x in s)
    kept = toxicity.keep_clean(docs, labels)
    assert kept.columns == docs.columns


def test_mixing(docs):
    r = by_id(mixing.taken_words(docs))
    assert sum(x.taken for v in r.values() for x in v) == sum(x["size"] for v in r.values() for x in v)
    assert all(x.taken <= 3 * x["size"] for v in r.values() for x in v) and sum(map(len, r.values())) == len(ROWS)
    m = mixing.mixed_documents(docs)
    assert m.columns == docs.columns
    words = sum(len(x.text.split()) for x in m.collect())
    assert words == sum(x.taken for v in r.values() for x in v)


def test_packing(docs):
    r = packing.packed_documents(docs).collect()
    ends = {}
    for x in sorted(r, key=lambda x: (x.sequence_id, x.offset)):
        assert x.offset == ends.get(x.sequence_id, 0)
        ends[x.sequence_id] = x.offset + x.length
    assert max(ends.values()) <= packing.CAPACITY
    assert len(ends) == -(-sum(x.length for x in r) // packing.CAPACITY)
    assert [x.length for x in r if x.doc_id in (2, 3, 8)] == [1, 1, 1]
    assert sum(x.doc_id == 6 for x in r) == 2


def test_empty_tables(spark, labels):
    e = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    assert substring_dedup.remove_repeats(e).count() == 0
    assert ngram_join.similarity_join(e).count() == 0
    assert exact_dedup.exact_groups(e).count() == 0
    assert lattice_lm.score_documents(e).count() == 0
    assert secret_scan.scan(e).count() == 0
    assert toxicity.score(e, labels.limit(0)).count() == 0
    assert mixing.taken_words(e).count() == 0
    assert packing.packed_documents(e).count() == 0
    assert url_filter.judge(spark.createDataFrame([], "page_id long, url string")).count() == 0
    assert embedding_dedup.near_duplicates(spark.createDataFrame([], "vec_id long, embedding array<float>, label int")).count() == 0


def test_urls(spark):
    p = [(1, "https://A.Example.org/en/12?x=1"), (2, None), (3, "no scheme"), (4, "http://x.com/de/"), (5, "http://x.com/de"), (6, "ftp://net"), (7, "http://h.org"), (7, "http://h.org"), (8, "http://y.com/fr/1#a")]
    r = by_id(url_filter.judge(spark.createDataFrame(p, "page_id long, url string").withColumn("host", F.lit("h"))), "id")
    assert (r[1][0].host, r[1][0].path, r[1][0].rule, r[1][0].verdict) == ("a.example.org", "/en/12", "example.org/en/1", "block")
    assert r[2][0].host == r[3][0].path == "" and r[2][0].rule is None
    assert (r[4][0].rule, r[4][0].verdict, r[5][0].rule, r[7][0].rule, len(r[7])) == ("com/de/", "block", None, None, 2)
    assert (r[8][0].rule, r[8][0].verdict, r[6][0].host, r[6][0].path) == ("com/fr/", "allow", "net", "")
    assert all(x.verdict in ("allow", "block") for v in r.values() for x in v)


def test_vectors(spark):
    nan, inf = float("nan"), float("inf")
    v = [(1, [1.0, 0.0], 1), (2, [2.0, 0.0], 1), (3, [2.0, 0.0], 1), (3, [2.0, 0.0], 1), (4, [1.0, 0.0], 2), (5, [0.0, 0.0], 1), (6, None, 1), (7, [nan, 1.0], 1), (8, [inf, 1.0], 1), (9, [None, 1.0], 1), (10, [1.0, 0.0], None), (11, [1.0, 0.0, 0.0], 1), (12, [0.0, 1.0], 1), (None, [1.0, 0.0], 1), (13, [], 1)]
    r = by_id(embedding_dedup.near_duplicates(spark.createDataFrame(v, "vec_id long, embedding array<double>, label int")), "vec_id")
    assert [r[i][0].n_links for i in (1, 2, 3)] == [3, 3, 3] and r[3][1].component_id == 1
    assert all(r[i][0].n_links == 0 and r[i][0].component_id == i and r[i][0].kept for i in (4, 5, 6, 7, 8, 9, 10, 11, 12, 13))
    assert r[None][0].n_links == 0 and r[None][0].component_id is None

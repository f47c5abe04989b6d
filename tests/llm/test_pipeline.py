"""The pipeline's stages against plain versions."""

import pyarrow.parquet as pq

import corpus_pipeline as p
from canopy.llm import exact_dedup, mixing, ngram_join, toxicity
from canopy.store import cut

D = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{D}/documents.parquet")
    names = docs.columns
    frames = [docs]
    for name, stage in p.STAGES:
        frames.append(cut(stage(spark, frames[-1], D), name))
    ids = [sorted(r.doc_id for r in f.select("doc_id").collect()) for f in frames]
    assert all(f.columns == names for f in frames[:-1])
    bad = {r.doc_id for r in toxicity.query(spark, D).collect() if r.predicted}
    assert ids[1] == [i for i in ids[0] if i not in bad]
    keep = {r.id for r in exact_dedup.exact_groups(frames[1]).filter("kept").collect()}
    assert set(ids[2]) == keep and len(ids[2]) == len(keep)
    texts = pq.read_table(f"{D}/documents.parquet").to_pandas().set_index("doc_id").text
    assert len({" ".join(texts[i].split()) for i in ids[2]}) == len(ids[2])
    near = {r.doc_id for r in ngram_join.similarity_join(frames[2]).filter("class_id = doc_id").collect()}
    assert set(ids[3]) == near
    taken = {r.doc_id: r.taken for r in mixing.taken_words(frames[3]).collect()}
    words: dict = {}
    for r in frames[4].collect():
        words[r.doc_id] = words.get(r.doc_id, 0) + len(r.text.split())
        assert texts[r.doc_id].split()[: len(r.text.split())] == r.text.split()
    assert words == {i: n for i, n in taken.items() if n}
    assert {r.doc_id for r in frames[5].collect()} == set(words)


def test_run(spark):
    assert p.run(spark, D).count() > 0


def _docs(spark, rows):
    return spark.createDataFrame([(i, t, "en", s, len(t or ""), 5) for i, t, s in rows], "doc_id long, text string, lang string, source string, n_chars long, th int")


def test_stages_on_odd_rows(spark):
    long = " ".join(f"w{k}" for k in range(30_000))
    rows = [(1, "a b", "s"), (6, "a b", "s"), (6, "c d", "s"), (7, None, None), (8, "", "t"), (None, "a b", "s"), (9, long, "t"), (2, "x y z", None), (2, "x y z", None)]
    for name, stage in p.STAGES:
        got = stage(spark, _docs(spark, rows), D)
        found = sorted((str(r.doc_id) for r in got.collect()), key=str)
        if name == "toxicity":
            assert len(found) == len(rows)
        if name == "ngram_join":
            # (6, "a b") is linked to 1; texts without words are linked to nothing
            assert len(found) == len(rows) - 1
            assert {r.text for r in got.filter("doc_id = 6").collect()} == {"c d"}
        if name == "exact_dedup":
            # (6, "a b") is a copy of 1, (6, "c d") is not; null and empty texts are equal
            assert found == sorted(["1", "6", "7", "None", "9", "2", "2"]), found
            assert {r.text for r in got.filter("doc_id = 6").collect()} == {"c d"}
        if name == "mixing":
            assert "7" not in found and "8" not in found and {"1", "9", "None"} <= set(found)
        if name == "packing":
            assert set(found) == {"1", "2", "6", "7", "8", "9", "None"}
        if name != "packing":
            assert got.columns == _docs(spark, rows).columns, name


def test_stages_on_an_empty_table(spark):
    for name, stage in p.STAGES:
        assert stage(spark, _docs(spark, [(1, "a", "s")]).limit(0), D).count() == 0, name

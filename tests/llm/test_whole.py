"""Inputs on which an operator once did less than the whole job."""

import hashlib
import random

import numpy as np

from canopy.llm import exact_dedup, mixing, ngram_join, packing, substring_dedup


def _first_alone(rnd, passages=400):
    """``(left, right, b)``: the first window of ``b`` is a piece of its own after ``left``, and part of a longer one after ``right``."""
    word = lambda: "".join(rnd.choice("abcdefgh") for _ in range(7))
    for _ in range(passages):
        b = [word() for _ in range(90)]
        made = []
        for _ in range(12):
            side = [word() for _ in range(90)]
            data = np.frombuffer(" ".join(side + b).encode(), np.uint8)
            h = substring_dedup.word_hashes(data, *substring_dedup.word_bounds(data))
            p = substring_dedup.pieces(h, np.zeros(len(h), dtype=np.int64))
            k = int(np.searchsorted(p["first"], 90, side="right")) - 1
            made.append((int(p["first"][k]), int(p["n"][k]), side))
        alone = [s for f, n, s in made if f == 90 and n == 1]
        longer = [s for f, _, s in made if f < 90]
        if alone and longer:
            return alone[0], longer[0], b
    raise AssertionError("no such passage")


def test_substring_words_between_two_passages_stay(spark):
    rnd = random.Random(11)
    left, right, b = _first_alone(rnd)
    word = lambda: "".join(rnd.choice("abcdefgh") for _ in range(7))
    some = lambda n: [word() for _ in range(n)]
    a = some(80)
    copied = some(70) + a + some(150) + left + b + some(70)
    rows = [(1, some(60) + a + some(60)), (2, right + b + some(60)), (3, copied), (4, copied), (5, copied)]
    rows = [(i, " ".join(w)) for i, w in rows]
    want = substring_dedup.brute(rows)
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in substring_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert want[3][1] == len(a) + len(b) and got == want


def test_join_pairs_survive_split_buckets(spark):
    # every root bucket holds about a sixth of 16,000 sets and every child a sixth of that: all are split
    rng = np.random.default_rng(7)
    n, values = 8_000, 6
    one = rng.integers(0, values, (n, ngram_join.COORDS))
    two = np.where(rng.random(one.shape) < 0.8, one, rng.integers(values, 2 * values, one.shape))
    rows = [(i, s.tolist()) for i, s in enumerate(np.concatenate([one, two]))]
    got = ngram_join.paths(spark.createDataFrame(rows, "sid long, sig array<long>"))
    met = got.groupBy("bucket", (got.sid % n).alias("pair")).count().filter("count > 1").select("pair").distinct().count()
    assert met == n


def test_packing_of_bins_that_cannot_be_filled(spark, monkeypatch):
    # 600 pieces of 2,100 tokens need a bin each, and the short ones can't fill them
    largest, evolve = [], packing._pack_shards

    def seen(shards, *a):
        largest.append(shards.selectExpr("max(size(items))").first()[0])
        return evolve(shards, *a)

    monkeypatch.setattr(packing, "_pack_shards", seen)
    rows = [(i, 2_100 if i < 600 else 40) for i in range(1_000)]
    got = packing.pack(spark.createDataFrame(rows, "doc_id long, length long"), shard_items=64, islands=2, epochs=1).collect()
    bins = {}
    for r in got:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert sorted(r.doc_id for r in got) == list(range(1_000)) and len(bins) == 600
    for b in bins.values():
        b.sort()
        assert [o for o, _ in b] == [sum(n for _, n in b[:k]) for k in range(len(b))] and sum(n for _, n in b) <= packing.CAPACITY
    # bins of up to 49 pieces are dealt whole, so shards differ in size
    assert max(largest) <= 4 * 64 and len(largest) <= 4


def test_substring_words_of_a_doubling_pattern(spark):
    # words that collide under every polynomial hash modulo 2^64
    one = "".join("ab"[bin(k).count("1") % 2] for k in range(1024))
    two = "".join("ba"[bin(k).count("1") % 2] for k in range(1024))
    side = [f"w{k}" for k in range(60)]
    rows = [(1, " ".join([*side[:30], one, *side[30:]])), (2, " ".join([*side[:30], two, *side[30:]]))]
    got = {r.doc_id: r.n_removed for r in substring_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: 0, 2: 0} == {i: v[1] for i, v in substring_dedup.brute(rows).items()}


def test_word_hashes_name_words():
    words = [b"a", b"a\0", b"a\0\0", b"12345678", b"12345678\0", b"1234567812345678", b"x" * 64, b"x" * 65, b"y" * 200]
    data = np.frombuffer(b" ".join(words), np.uint8)
    end = np.cumsum([len(w) + 1 for w in words]) - 1
    h = substring_dedup.word_hashes(data, end - np.array([len(w) for w in words]), end, 2)
    assert len({tuple(x) for x in h.T.tolist()}) == len(words) and not (h[0] == h[1]).any()
    # the same words elsewhere
    again = substring_dedup.word_hashes(np.frombuffer(b"  " + b" ".join(words), np.uint8), end - np.array([len(w) for w in words]) + 2, end + 2, 2)
    assert (h == again).all()


def test_substring_long_repeats_are_single_paths(spark):
    rnd = random.Random(4)
    some = lambda n: ["".join(rnd.choice("abcdefgh") for _ in range(7)) for _ in range(n)]
    passage = some(700)
    rows = [(i, " ".join(some(80) + passage + some(80))) for i in range(4)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    spans = {r.doc_id: r.spans for r in substring_dedup.repeated_spans(docs).collect()}
    longest = [max((s["end"] - s["start"], s["w1"] is not None) for s in spans[i]) for i in (1, 2, 3)]
    # inner windows of the passage are one path with one digest
    assert all(n > 550 and proved for n, proved in longest) and 0 not in spans
    # a span whose words are not those at the source is left alone
    text = rows[1][1].split()
    s = max(spans[1], key=lambda s: s["end"] - s["start"])
    assert substring_dedup.digest([w.encode() for w in text[s["start"] : s["end"]]]) == (s["w1"], s["w2"])


def test_exact_groups_come_from_recipes(spark):
    rows = [(1, "a b c"), (2, "a  b\tc"), (3, "d e f"), (4, None), (5, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    keep = lambda g: {r.id: (r.keep_id, r.group_size) for r in g.collect()}
    assert keep(exact_dedup.exact_groups(docs)) == {1: (1, 2), 2: (1, 2), 3: (3, 1), 4: (4, 2), 5: (4, 2)}

    def empty(d, i, t):
        return exact_dedup.recipes(d, i, t).withColumn("chunks", exact_dedup.F.slice("chunks", 1, 0))

    def twins(d, i, t):
        # one 64-bit hash for all chunks: digests must tell them apart
        return exact_dedup.recipes(d, i, t).withColumn("chunks", exact_dedup.F.transform("chunks", lambda c: exact_dedup.F.struct(exact_dedup.F.lit(7).cast("long").alias("h"), c["v"].alias("v"))))

    assert set(keep(exact_dedup.exact_groups(docs, recipe_of=empty)).values()) == {(1, 5)}
    assert keep(exact_dedup.exact_groups(docs, recipe_of=twins)) == keep(exact_dedup.exact_groups(docs))


def test_mixture_follows_the_schedule(spark, monkeypatch):
    rnd = random.Random(6)
    rows = [(i, " ".join(f"w{rnd.random()}" for _ in range(rnd.randint(0, 300))), "abc"[i % 3], 9) for i in range(300)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, slot int")
    mixed = mixing.mixed_documents(docs, slot_col="at").collect()
    at = [r["at"] for r in mixed]
    assert at == sorted(at) and len(set(at)) > 50
    first = {}
    for r in mixed:
        first.setdefault(r.doc_id, r["at"])
    per = {r.doc_id: r for r in mixing.taken_words(docs).collect()}
    assert first == {i: r.first_slot for i, r in per.items() if r.taken}
    assert all(r.first_slot <= r.last_slot for r in per.values() if r.taken)
    # sources meet in every stretch of the schedule at about their share
    where = {i: s for i, _, s, _ in rows}
    half = [where[r.doc_id] for r in mixed[: len(mixed) // 2]]
    rest = [where[r.doc_id] for r in mixed[len(mixed) // 2 :]]
    assert all(abs(half.count(s) - rest.count(s)) < 0.25 * len(half) for s in "abc")
    # without the low-discrepancy points the order is another one
    monkeypatch.setattr(mixing, "reversed_bits", lambda x, bits: x)
    assert [r.doc_id for r in mixing.mixed_documents(docs).collect()] != [r.doc_id for r in mixed]


def test_mixing_repeated_rows(spark):
    rows = [(1, "a b c d", "s")] * 150 + [(2, "e f", "s"), (3, None, "t"), (None, "g h i", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mixing.taken_words(docs).collect()
    assert len(got) == len(rows) and all(r.taken <= 3 * r["size"] for r in got)
    total = sum(r.taken for r in got)
    assert total == sum(len(r.text.split()) for r in mixing.mixed_documents(docs).collect()) and abs(total - 605) <= 3


def test_evolution_beats_best_fit():
    # triples that fill a bin exactly: longest first by best fit misses the bound
    rnd = random.Random(8)
    lengths = []
    for _ in range(40):
        a, b = rnd.randint(1100, 1700), rnd.randint(1100, 1500)
        lengths += [a, b, 4096 - a - b]
    plain = len(packing.best_fit([], list(range(len(lengths))), lengths, 4096))
    start = packing.random_fit(lengths, 4096, random.Random(1))
    best = packing.evolve(lengths, 4096, 3, [])
    assert 40 <= len(best) <= plain and len(best) < len(start)
    assert sorted(i for b in best for i in b[1:]) == list(range(len(lengths)))
    # without crossover and mutation the start is all there is
    assert hashlib.sha256(repr(best).encode()).digest() != hashlib.sha256(repr(start).encode()).digest()


def test_join_measures_its_recall(spark):
    rng = np.random.default_rng(3)
    rows = [(i, s.tolist()) for i, s in enumerate(rng.integers(0, 1 << 40, (2_000, ngram_join.COORDS)))]
    items = spark.createDataFrame(rows, "sid long, sig array<long>")
    leaves, recall, runs = ngram_join.chosen_leaves(items)
    assert recall >= ngram_join.TARGET and runs == ngram_join.RUNS
    # a target that can't be met takes all coordinates
    assert ngram_join.chosen_leaves(items, target=1.1)[2] * ngram_join.PER_RUN == ngram_join.COORDS
    assert leaves.join(items, "sid", "left_anti").isEmpty()

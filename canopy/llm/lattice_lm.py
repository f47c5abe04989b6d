"""Subword lattice likelihood of documents.

The pieces of an existing vocabulary weight all segmentations of a word; the forward
recursion in log space sums over them, and a document's score is the log10 of its marginal
probability.  Pieces never cross white space, so a document is the product of its words'
marginals and one end piece.

* Corpus counts.  Distinct words of all documents with their training counts, by a counting
  scan and one shuffle; this table grows with the corpus and is never collected.
* Piece probabilities.  Each distinct training word is segmented once by the vocabulary's own
  merges, weighted with its count; piece counts (bounded by the vocabulary) and single-code-point
  pieces are smoothed with a share that falls with the piece's rank in the vocabulary.
* Lattice.  Every distinct word is scored once.
* Documents.  The words above a count threshold (at most ``HEAD`` of them, the threshold comes
  from a histogram of counts) are looked up in memory; all other words are joined by a
  shuffle, so nothing that is broadcast grows with the data.

Code points outside the vocabulary are spelt with its byte pieces, as one edge; so are bytes that are not UTF-8.

Defined results: null text counts as empty (one end token); null ids are held in (their
remainder is unknown); repeated rows are scored alike; an empty table gives an empty
result; with no training rows all counts are 0 and the piece shares come from ranks alone.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.store import write

VOCABULARY = "piece_bpe_32k.model"
FOLDS, HELD_OUT = 7, 2
HEAD = 131_072
MARK = "▁"
#: Weight of the rank prior, in tokens for each piece on average.
PRIOR = 0.1
GROUP_BYTES = 1 << 22

_LOADED: dict = {}


def _model(vocabulary: str):
    if vocabulary not in _LOADED:
        import os

        import public_tokenizers
        import sentencepiece

        path = vocabulary if os.path.isabs(vocabulary) else public_tokenizers.path(vocabulary)
        _LOADED[vocabulary] = sentencepiece.SentencePieceProcessor(model_file=path)
    return _LOADED[vocabulary]


def held_out(doc_id):
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string")), F.lit(FOLDS)) == HELD_OUT, F.lit(False))


#: Words are bytes from here to the join: a text need not be valid UTF-8.
_COUNTS = "word binary, n long, t long"


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Words of (text, held_out), with counts overall and in training, a partial table for each stretch of input."""

    def out(all_: Counter, train: Counter) -> pa.RecordBatch:
        words = list(all_)
        return pa.RecordBatch.from_arrays(
            [
                pa.array(words, pa.binary()),
                pa.array([all_[w] for w in words], pa.int64()),
                pa.array([train[w] for w in words], pa.int64()),
            ],
            names=["word", "n", "t"],
        )

    everything, train = Counter(), Counter()
    for b in batches:
        for text, out_of in zip(b.column(0).cast(pa.binary()).to_pylist(), b.column(1).to_pylist()):
            words = (text or b"").lower().split()
            everything.update(words)
            if not out_of:
                train.update(words)
        if len(everything) > 300_000:
            yield out(everything, train)
            everything, train = Counter(), Counter()
    if everything:
        yield out(everything, train)


def _segment(vocabulary: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sp = _model(vocabulary)
        total = np.zeros(sp.get_piece_size(), dtype=np.int64)
        for b in batches:
            words, t = [w.decode(errors="replace") for w in b.column(0).to_pylist()], b.column(1).to_numpy()
            for lo in range(0, len(words), 4096):
                ids = sp.encode(words[lo : lo + 4096], num_threads=1)
                flat = np.fromiter((i for x in ids for i in x), dtype=np.int64)
                np.add.at(total, flat, np.repeat(t[lo : lo + 4096], [len(x) for x in ids]))
        some = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(total[some])], names=["piece", "t"])

    return run


class Lattice:
    """Piece log-probabilities and the forward recursion."""

    def __init__(self, counts: dict[int, int], ends: int, vocabulary: str = VOCABULARY):
        sp = _model(vocabulary)
        size = sp.get_piece_size()
        # the vocabulary is ordered by its scores; control pieces spell nothing and get no mass
        share = np.array([0.0 if sp.is_control(i) or sp.is_unknown(i) else 1.0 / (2 + i) for i in range(size)])
        weight = PRIOR * size * share / share.sum()
        for i, c in counts.items():
            weight[i] += c if share[i] else 0
        end = ends + 1.0
        logp = np.log(np.maximum(weight, 1e-300)) - math.log(weight.sum() + end)
        self.end = math.log(end) - math.log(weight.sum() + end)
        self.pieces: dict[str, float] = {}
        self.bytes = [0.0] * 256
        for i in range(size):
            if sp.is_byte(i):
                self.bytes[int(sp.id_to_piece(i)[3:5], 16)] = float(logp[i])
            elif not (sp.is_control(i) or sp.is_unknown(i)):
                self.pieces[sp.id_to_piece(i)] = float(logp[i])
        self.starts = {p[:k] for p in self.pieces for k in range(1, len(p) + 1)}

    def word(self, word: str) -> float:
        """Natural-log marginal of one word over all its segmentations."""
        s = MARK + word
        n = len(s)
        into: list[list[float] | None] = [None] * (n + 1)
        into[0] = [0.0]
        pieces, starts, exp, log = self.pieces, self.starts, math.exp, math.log
        for i in range(n):
            got = into[i]
            if got is None:
                continue
            if len(got) == 1:
                a = got[0]
            else:
                top = max(got)
                a = top + log(sum([exp(x - top) for x in got]))
            single = False
            for j in range(i + 1, n + 1):
                part = s[i:j]
                if part not in starts:
                    break
                p = pieces.get(part)
                if p is not None:
                    single = single or j == i + 1
                    if into[j] is None:
                        into[j] = [a + p]
                    else:
                        into[j].append(a + p)
            if not single:
                p = a + sum(self.bytes[c] for c in s[i].encode(errors="surrogateescape"))
                if into[i + 1] is None:
                    into[i + 1] = [p]
                else:
                    into[i + 1].append(p)
        got = into[n]
        top = max(got)
        return top + log(sum([exp(x - top) for x in got]))


def _score_words(lattice, n_train: int, v_train: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lat = lattice.value
        for b in batches:
            t = b.column(2).to_numpy()
            score = np.array([lat.word(w.decode(errors="surrogateescape")) for w in b.column(0).to_pylist()]) / math.log(10)
            base = np.log10((t + 1) / (n_train + v_train + 1))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array(base, pa.float64()), pa.array(score, pa.float64())], names=["word", "n", "t", "base", "score"])

    return run


_DOC = "doc_id long, held_out boolean, key long, tokens long, known long, base double, score double, word binary, times long"


def _look_up(head):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words, known_, base_, score_ = head.value
        place = _LOADED.get("head")
        if place is None or place[0] is not words:
            place = _LOADED["head"] = (words, {w: i for i, w in enumerate(words)})
        get = place[1].get
        for b in batches:
            ids, out_of, keys = (b.column(k).to_pylist() for k in range(3))
            texts = b.column(3).cast(pa.binary()).to_pylist()
            at = 0
            while at < len(texts):
                cols: list[list] = [[] for _ in range(9)]
                size = 0
                while at < len(texts) and size < GROUP_BYTES:
                    tokens = (texts[at] or b"").lower().split()
                    size += len(texts[at] or b"") + 64
                    spot = np.fromiter([get(w, -1) for w in tokens], dtype=np.int64, count=len(tokens))
                    hit = spot[spot >= 0]
                    rows = [(ids[at], out_of[at], keys[at], len(hit), int(known_[hit].sum()), float(base_[hit].sum()), float(score_[hit].sum()), None, 1)]
                    if len(hit) < len(tokens):
                        rest = Counter([w for w, k in zip(tokens, spot.tolist()) if k < 0])
                        rows += [(ids[at], out_of[at], keys[at], 0, 0, 0.0, 0.0, w, c) for w, c in rest.items()]
                    for c, x in zip(cols, zip(*rows)):
                        c.extend(x)
                    at += 1
                kinds = (pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.binary(), pa.int64())
                names = ["doc_id", "held_out", "key", "tokens", "known", "base", "score", "word", "times"]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=names)

    return run


def head_threshold(words: DataFrame, head: int = HEAD) -> int:
    """Smallest count such that at most ``head`` words reach it (counts are binned by eighths of powers of two)."""
    step = F.floor(F.log2("n") * 8)
    bins = words.groupBy(step.alias("s")).agg(F.count(F.lit(1)).alias("k"), F.min("n").alias("n")).orderBy(F.desc("s")).collect()
    total, least = 0, 1 << 62
    for b in bins:
        total += b["k"]
        if total > head:
            break
        least = b["n"]
    return least


def score_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str = VOCABULARY, head: int = HEAD) -> DataFrame:
    """``doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score``, one row per input row."""
    spark = docs.sparkSession
    d = docs.select(F.col(id_col).cast("long").alias("doc_id"), held_out(F.col(id_col)).alias("held_out"), F.col(text_col).cast("string").alias("text"))
    d = d.select("doc_id", "held_out", F.xxhash64("doc_id", "text").alias("key"), "text")
    part = d.select("text", "held_out").mapInArrow(_count, _COUNTS)
    words = write(part.groupBy("word").agg(F.sum("n").alias("n"), F.sum("t").alias("t")), "words").df
    ends = docs.select(F.count_if(~held_out(F.col(id_col)))).first()[0]
    sums = words.agg(F.coalesce(F.sum("t"), F.lit(0)).alias("t"), F.count_if(F.col("t") > 0).alias("v")).first()
    n_train, v_train = sums["t"] + ends, sums["v"] + (1 if ends else 0)
    counted = words.filter("t > 0").select("word", "t").mapInArrow(_segment(vocabulary), "piece long, t long").groupBy("piece").agg(F.sum("t").alias("t"))
    lattice = Lattice({r["piece"]: r["t"] for r in counted.collect()}, ends, vocabulary)
    shared = spark.sparkContext.broadcast(lattice)
    scored = write(words.mapInArrow(_score_words(shared, n_train, v_train), "word binary, n long, t long, base double, score double"), "scored").df
    least = head_threshold(scored, head)
    top = scored.filter(F.col("n") >= least).select("word", (F.col("t") > 0).alias("k"), "base", "score").toArrow()
    table = (top.column("word").to_pylist(), *(top.column(c).to_numpy().astype(np.float64) for c in ("k", "base", "score")))
    rows = d.mapInArrow(_look_up(spark.sparkContext.broadcast(table)), _DOC)
    rows = write(rows, "lookups").df
    tail = rows.filter("word is not null").join(scored.filter(F.col("n") < least).select("word", "t", F.col("base").alias("b"), F.col("score").alias("s")), "word")
    tail = tail.select(
        "doc_id", "held_out", "key", F.col("times").alias("tokens"), F.when(F.col("t") > 0, F.col("times")).otherwise(0).alias("known"),
        (F.col("b") * F.col("times")).alias("base"), (F.col("s") * F.col("times")).alias("score"), F.lit(0).alias("m"),
    )
    both = rows.filter("word is null").select("doc_id", "held_out", "key", "tokens", "known", "base", "score", F.lit(1).alias("m")).unionByName(tail)
    per = both.groupBy("doc_id", "held_out", "key").agg(*[F.sum(c).alias(c) for c in ("tokens", "known", "base", "score", "m")])
    # m equal rows (same id and text) were summed together
    per = per.withColumn("r", F.explode(F.sequence(F.lit(1).cast("long"), F.col("m"))))
    end_base = math.log10((ends + 1) / (n_train + v_train + 1))
    end_score = lattice.end / math.log(10)
    return per.select(
        "doc_id",
        "held_out",
        (F.expr("tokens div m") + 1).alias("n_tokens"),
        (F.expr("known div m") + (1 if ends else 0)).alias("n_known"),
        F.lit(n_train).cast("long").alias("train_tokens"),
        (F.col("base") / F.col("m") + end_base).alias("base_score"),
        (F.col("score") / F.col("m") + end_score).alias("score"),
    )


def query(spark, sf_dir: str) -> DataFrame:
    return score_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))

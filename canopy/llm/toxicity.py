"""Toxicity scores from Levenshtein automata run against a lexicon trie.

* Lexicon.  Terms and stems are mined from labelled training rows only (at most
  ``SAMPLE`` rows of each class, by id hash): a term must be in so many toxic documents
  and so few others that chance is ruled out over all candidates.  Copies and near copies
  count once (documents are told apart by a min-hash of their words).
* Automaton.  The trie of terms and the edit automaton are walked together.  States (trie node,
  edits) are determinised on demand and shared by all words, so a word costs a few table
  look-ups and most words die after two or three letters.  Short terms and stems allow no edit,
  longer terms one, long ones two; look-alike digits and signs are folded first.  Words
  common in clean training documents are never taken for a misspelling.
* Context.  A window of ``SPAN`` words on either side of a hit is searched for signs of quotation
  (quote marks that open before and close after it, words of reporting) and of address;
  quotation lowers the weight of the hit, address raises it.
* Score.  A logistic model on hit features, fitted on the sample; documents without a hit
  get the model's value for none.  Ids, labels, language and source are no inputs.

Defined results: null text counts as empty; empty texts get the score of a text without hits;
null ids are held in but have no label; repeated rows are scored alike; with no labelled
toxic rows the lexicon is empty and every score is the share of toxic labels.
"""

from __future__ import annotations

import math
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from canopy.store import write

FOLDS, HELD_OUT, CUT = 4, 2, 0.3
SAMPLE = 10_000  # labelled rows of each class at most
SPAN = 8
WORD = re.compile(r"\w(?:[\w@$!*]*\w)?")
#: Chance, over all candidates, that a harmless word enters the lexicon.
CHANCE = 0.01

# Look-alike characters, words of reporting, words of address.
LOOKS = str.maketrans({"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "@": "a", "$": "s", "!": "i"})
REPORTING = frozenset("said says wrote writes called calls quote quoted quotes word term insult insults slur reported alleged comment dit écrit mot sagte schrieb wort dijo escribió palabra".split())
ADDRESS = frozenset("you your you're youre u ur yourself du dein tu ton votre vous tú tu usted".split())
OPENING, CLOSING = "\"“«„‘'", "\"”»“’'"


def held_out(doc_id):
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string")), F.lit(FOLDS)) == HELD_OUT, F.lit(False))


def words_of(text: str) -> list[str]:
    return WORD.findall(text.lower())


def edits_for(term: str) -> int:
    return 0 if len(term) < 5 else 1 if len(term) < 10 else 2


class Automaton:
    """Trie of terms (``stem*`` for stems) walked together with the edit automaton, determinised on demand."""

    def __init__(self, weights: dict[str, float], common: frozenset[str] = frozenset()):
        self.common = common
        self.child: list[dict[str, int]] = [{}]
        self.term: list[tuple[float, int] | None] = [None]  # (weight, edits allowed)
        self.stem: list[float | None] = [None]
        self.allow = [0]  # most edits that a term below the node allows
        for t, w in sorted(weights.items()):
            stem = t.endswith("*")
            text = t.rstrip("*")
            k = 0 if stem else edits_for(text)
            node = 0
            self.allow[0] = max(self.allow[0], k)
            for c in text:
                nxt = self.child[node].get(c)
                if nxt is None:
                    nxt = self.child[node][c] = len(self.child)
                    self.child.append({})
                    self.term.append(None)
                    self.stem.append(None)
                    self.allow.append(0)
                node = nxt
                self.allow[node] = max(self.allow[node], k)
            if stem:
                self.stem[node] = w
            else:
                self.term[node] = (w, k)
        self.states: dict[frozenset, int] = {}
        self.content: list[frozenset] = []
        self.moves: list[dict[str, int]] = []
        self.known: dict[str, tuple[float, int] | None] = {}
        self.start = self._state(self._close({(0, 0)}))

    def _close(self, s: set[tuple[int, int]]) -> frozenset:
        """Skipped letters of the term; keep the fewest edits of a node."""
        todo, best = list(s), {}
        while todo:
            node, e = todo.pop()
            if node >= 0 and e > self.allow[node] or best.get(node, 99) <= e:
                continue
            best[node] = e
            if node >= 0:
                todo += [(c, e + 1) for c in self.child[node].values()]
        return frozenset(best.items())

    def _state(self, s: frozenset) -> int:
        at = self.states.get(s)
        if at is None:
            at = self.states[s] = len(self.content)
            self.content.append(s)
            self.moves.append({})
        return at

    def _move(self, state: int, c: str) -> int:
        out: set[tuple[int, int]] = set()
        for node, e in self.content[state]:
            if node < 0:  # past a stem: any ending
                out.add((node, e))
                continue
            if self.stem[node] is not None and e == 0:
                out.add((-node - 1, 0))
            for x, nxt in self.child[node].items():
                out.add((nxt, e if x == c else e + 1))
            out.add((node, e + 1))
        return self._state(self._close(out))

    def find(self, word: str) -> tuple[float, int] | None:
        """(weight, edits) of the best term that the word spells, if any."""
        got = self.known.get(word, 0)
        if got != 0:
            return got
        best = self._run(word)
        folded = word.translate(LOOKS)
        if folded != word and (other := self._run(folded)) and (best is None or other[1] < best[1]):
            # look-alikes alone hardly ever happen by chance
            best = (0.95 * other[0], 0) if other[1] == 0 else other
        if best and best[1] and word in self.common:
            best = None
        if len(self.known) > 400_000:
            self.known.clear()
        self.known[word] = best
        return best

    def _run(self, word: str) -> tuple[float, int] | None:
        state = self.start
        for c in word:
            nxt = self.moves[state].get(c)
            if nxt is None:
                if len(self.content) > 200_000:  # memory bound: start over
                    self.states, self.content, self.moves = {}, [], []
                    self.start = self._state(self._close({(0, 0)}))
                    return self._run(word)
                nxt = self.moves[state][c] = self._move(state, c)
            state = nxt
            if not self.content[state]:
                return None
        best = None
        for node, e in self.content[state]:
            if node < 0 or self.stem[node] is not None and e == 0:
                hit = (self.stem[-node - 1 if node < 0 else node], 0)
            elif self.term[node] is not None and e <= self.term[node][1]:
                hit = (self.term[node][0], e)
            else:
                continue
            if best is None or (hit[1], -hit[0]) < (best[1], -best[0]):
                best = hit
        return best


FEATURES = 6


def features(text: str, auto: Automaton) -> np.ndarray | None:
    """Hit features of a text, None without a hit."""
    text = text.lower()  # offsets and marks are read from one string: lowering can change the length
    found = list(WORD.finditer(text))
    words = [m.group() for m in found]
    if not any(auto.find(w) for w in set(words)):
        return None
    spans = [m.span() for m in found]
    exact = fuzzy = quoted = addressed = most = total = 0.0
    for i, w in enumerate(words):
        hit = auto.find(w)
        if not hit:
            continue
        around = words[max(0, i - SPAN) : i] + words[i + 1 : i + 1 + SPAN]
        lo, hi = spans[max(0, i - SPAN)][0], spans[min(len(spans) - 1, i + SPAN)][1]
        before, after = text[lo : spans[i][0]], text[spans[i][1] : hi]
        marked = any(before.count(o) % 2 if o == c else before.count(o) > before.count(c) for o, c in zip(OPENING, CLOSING) if o in before and c in after)
        told = sum(x in REPORTING for x in around)
        call = any(x in ADDRESS for x in around)
        weight = hit[0] * (1.0 if hit[1] == 0 else 0.7) * (0.5 if marked or told >= 2 else 1.0) * (1.2 if call else 1.0)
        exact += hit[1] == 0
        fuzzy += hit[1] > 0
        quoted += marked or told >= 2
        addressed += call
        total += weight
        most = max(most, weight)
    n = len(words)
    return np.array([1.0, math.log1p(total), most, math.log1p(fuzzy) - math.log1p(exact), quoted / (exact + fuzzy), min(1.0, 50 * (exact + fuzzy) / n)])


def fit_logistic(x: np.ndarray, y: np.ndarray, rounds: int = 60, ridge: float = 1.0) -> np.ndarray:
    """Ridge logistic regression by Newton steps; the first column is the constant."""
    w = np.zeros(x.shape[1])
    penalty = np.full(x.shape[1], ridge)
    penalty[0] = 1e-3
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (p - y) + penalty * w
        h = (x * (p * (1 - p))[:, None]).T @ x + np.diag(penalty)
        step = np.linalg.solve(h, g)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    return w


def _terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(term, toxic, copy key) of labelled texts: words and stems.

    The key is a min-hash of the words: alike for copies and most near copies.  Unrelated texts that share a word
    of small hash count as one, so counts of terms err on the low side.
    """
    for b in batches:
        for text, toxic in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
            words = {w for w in words_of(text or "") if 4 <= len(w) <= 40}
            if not words:
                continue
            key = min(zlib.crc32(w.encode()) for w in words)
            terms = words | {w[:k] + "*" for w in words for k in (4, 5, 6) if len(w) > k}
            yield pa.RecordBatch.from_arrays(
                [pa.array(list(terms), pa.string()), pa.array([int(toxic)] * len(terms), pa.int32()), pa.array([key] * len(terms), pa.int64())], names=["term", "toxic", "copy"]
            )


def beyond_chance(per: DataFrame, toxic_docs: int, clean_docs: int) -> DataFrame:
    """``(term, rate, t)`` of ``per(term, t, o)``: terms of toxic documents whose count can't be chance.

    The chance of at least t toxic ones of n is bounded by the relative entropy against the share of
    toxic documents, and has to be below ``CHANCE`` over all candidates.
    """
    base = toxic_docs / (toxic_docs + clean_docs)
    some = per.filter((F.col("t") >= 3) & (F.col("t") > base * (F.col("t") + F.col("o"))))
    n, q = F.col("t") + F.col("o"), F.col("t") / (F.col("t") + F.col("o"))
    rest = F.when(F.col("o") > 0, (1 - q) * F.log((1 - q) / (1 - base))).otherwise(0.0)
    rate = ((F.col("t") + 0.5) / (toxic_docs + 1)) / ((F.col("o") + 0.5) / (clean_docs + 1))
    tried = some.count()
    chance = -n * (q * F.log(q / base) + rest)
    return some.filter((rate >= 8) & (chance < math.log(CHANCE / max(1, tried)))).select("term", F.log(rate).alias("rate"), "t")


def lexicon(rows: list) -> dict[str, float]:
    """Weights of the terms to keep; rows are (term, log rate, toxic documents)."""
    good = {term: (rate, t) for term, rate, t in rows}
    whole = {k: v for k, v in good.items() if not k.endswith("*")}
    stems = {k: v for k, v in good.items() if k.endswith("*")}
    # a stem is kept if endings beyond the kept terms carry it, and only its shortest good form
    out = {k: v[0] for k, v in sorted(whole.items(), key=lambda x: (-x[1][1], x[0]))}
    for k, (rate, t) in sorted(stems.items(), key=lambda x: (len(x[0]), x[0])):
        text = k[:-1]
        if any(text[:n] + "*" in out for n in (4, 5)) or t <= 1.5 * max([v[1] for w, v in whole.items() if w.startswith(text)] or [0]):
            continue
        out[k] = rate
    return out


def _features(model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        auto = Automaton(*model.value)
        for b in batches:
            out = [features(t or "", auto) for t in b.column(0).to_pylist()]
            none = [1.0] + [0.0] * (FEATURES - 1)
            yield pa.RecordBatch.from_arrays([pa.array([none if x is None else x.tolist() for x in out], pa.list_(pa.float64())), b.column(1)], names=["x", "toxic"])

    return run


def _misspelt(weights):
    """Words that the automaton would take for a misspelt term."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        auto = Automaton(weights.value)
        for b in batches:
            hits = ((w, auto.find(w)) for w in b.column(0).to_pylist())
            yield pa.RecordBatch.from_arrays([pa.array([w for w, hit in hits if hit and hit[1]], pa.string())], names=["term"])

    return run


_KEPT: dict = {}


def _score(model):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        weights, common, w = model.value
        if _KEPT.get("of") is not weights:
            _KEPT.update(of=weights, auto=Automaton(weights, common))
        auto = _KEPT["auto"]
        none = 1 / (1 + math.exp(-float(np.clip(w[0], -30, 30))))
        for b in batches:
            score = []
            for t in b.column(1).to_pylist():
                x = features(t or "", auto)
                score.append(none if x is None else 1 / (1 + math.exp(-float(np.clip(x @ w, -30, 30)))))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(score, pa.float64())], names=["row", "score"])

    return run


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic"):
    """(term weights, common clean words, logistic weights) from at most ``SAMPLE`` training rows of each class."""
    lab = labels.select(F.col(id_col).alias("i"), F.col(label_col).cast("int").alias("toxic")).filter(F.col("i").isNotNull() & F.col("toxic").isin(0, 1) & ~held_out(F.col("i")))
    lab = lab.groupBy("i").agg(F.max("toxic").alias("toxic"))
    # a share of the hash range that holds about SAMPLE ids: no sort, nothing passes through the driver
    totals = {r["toxic"]: r["n"] for r in lab.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    share = {k: min(1 << 20, (SAMPLE << 20) // n) for k, n in totals.items()}
    cut = F.when(F.col("toxic") == 1, share.get(1, 0)).otherwise(share.get(0, 0))
    ids = lab.filter(F.pmod(F.xxhash64("i"), F.lit(1 << 20)) < cut)
    ids = write(ids, "labelled").df
    # about 2 * SAMPLE ids of 12 bytes: a bounded broadcast
    rows = docs.select(F.col(id_col).alias("i"), F.col(text_col).cast("string").alias("text")).join(F.broadcast(ids), "i").select("text", "toxic")
    rows = write(rows, "labelled").df
    counts = {r["toxic"]: r["n"] for r in rows.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    bad, good = counts.get(1, 0), counts.get(0, 0)
    both = lab.agg(F.coalesce(F.avg("toxic"), F.lit(0.0)).alias("p")).first()["p"]
    per = rows.mapInArrow(_terms, "term string, toxic int, copy long").groupBy("term", "copy").agg(F.max("toxic").alias("toxic"))
    per = per.groupBy("term").agg(F.sum("toxic").alias("t"), F.count_if(F.col("toxic") == 0).alias("o"))
    per = write(per, "terms").df
    weights: dict[str, float] = {}
    if bad and good:
        weights = lexicon([tuple(r) for r in beyond_chance(per, bad, good).select("term", "rate", "t").collect()])
    # of the words of clean documents only those near a term matter
    clean = per.filter((F.col("o") >= 3) & ~F.col("term").endswith("*")).select("term")
    near = clean.mapInArrow(_misspelt(docs.sparkSession.sparkContext.broadcast(weights)), "term string").toArrow()
    common = frozenset(near.column("term").to_pylist()) - set(weights)
    shared = docs.sparkSession.sparkContext.broadcast((weights, common))
    got = rows.mapInArrow(_features(shared), "x array<double>, toxic int").toArrow()
    w = np.zeros(FEATURES)
    if bad and good:
        x = np.array(got.column("x").to_pylist())
        y = got.column("toxic").to_numpy().astype(float)
        w = fit_logistic(x, y)
        # the classes were sampled apart: shift the constant to the labels' true shares
        w[0] += math.log(both / (1 - both)) - math.log(bad / good)
    else:
        p = min(max(both, 1e-6), 1 - 1e-6)
        w[0] = math.log(p / (1 - p))
    return weights, common, w


def score(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> DataFrame:
    """Every row of ``docs`` as struct ``row`` with its ``score``."""
    shared = docs.sparkSession.sparkContext.broadcast(fit(docs, labels, id_col, text_col, label_col))
    d = docs.select(F.struct(*[F.col(c) for c in docs.columns]).alias("row"), F.col(text_col).cast("string").alias("t"))
    kind = d.schema["row"].dataType.simpleString()
    return d.mapInArrow(_score(shared), f"row {kind}, score double")


def keep_clean(docs: DataFrame, labels: DataFrame, cut: float = CUT, text_col: str = "text") -> DataFrame:
    """The rows that the model does not reject, columns unchanged."""
    s = score(docs, labels, text_col=text_col).filter(F.col("score") < cut)
    return s.select(*[F.col("row").getField(c).alias(c) for c in docs.columns])


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    s = score(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return s.select(
        F.col("row.doc_id").alias("doc_id"),
        held_out(F.col("row.doc_id")).alias("held_out"),
        "score",
        (F.col("score") >= CUT).cast("int").alias("predicted"),
    )

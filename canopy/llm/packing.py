"""Pack token sequences by a grouping genetic algorithm on islands.

* Pieces.  Each document's token ids (and one end id) become pieces of at most
  ``CAPACITY`` tokens; only longer documents are cut.
* Shards.  Pieces are dealt by hash into shards of about ``SHARD`` pieces; a shard is one
  row with an array of piece lengths, so its size is bounded whatever the data.
* Islands.  Each shard is evolved by ``ISLANDS`` independent populations, one row each.
  A chromosome is a packing.  A population starts from packings in random order.  Crossover
  injects the fullest bins of one parent into the other, removes the bins that hold any
  of the same pieces, and puts the displaced pieces back by best fit.  Between epochs the
  best packing of each island moves to the next one; an island stops at the lower bound
  ceil(tokens / capacity).
* Rest.  Bins that stay underfilled are pooled over shards and packed again, in shards of
  about ``SHARD`` pieces again, until one shard holds the rest or a level needs as many
  bins as the level before: the waste is one bin in the end, not one per shard, where the
  pieces allow it.

Defined results: null text counts as empty: one piece of length 1 (the end id); repeated
rows are packed apart; null ids are kept; an empty table gives an empty result.
"""

from __future__ import annotations

import bisect
import random
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from canopy.store import write

CAPACITY = 4096
END_ID = 1
SHARD, ISLANDS, EPOCHS = 4096, 3, 2
POPULATION, GENERATIONS = 6, 40
#: Shares of the bins that a crossover injects.
INJECTED = (0.2, 0.5)
WELL_FILLED = 0.98
VOCABULARY = "word_bpe_49k.json"
#: Words whose ids a worker remembers (about 200 bytes each).
CACHE_WORDS = 1_500_000
#: Plain words that are encoded as one text.
JOINED = 64
#: Signs that may follow a word of letters (no apostrophe: contractions are splits of their own).
SIGNS = b'.,;:!?$%&#*|)"'
#: Bytes of text that are tokenised together.
GROUP_BYTES = 1 << 23

_LOADED: dict = {}


def _tokenizer(vocabulary: str):
    if vocabulary not in _LOADED:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import public_tokenizers
        from tokenizers import Tokenizer

        path = vocabulary if os.path.isabs(vocabulary) else public_tokenizers.path(vocabulary)
        tok = Tokenizer.from_file(path)
        ends = np.zeros(max(tok.get_vocab().values()) + 1, dtype=bool)
        ends[[i for t, i in tok.get_vocab().items() if t.endswith("</w>")]] = True
        _LOADED[vocabulary] = (tok, ends, {})
    return _LOADED[vocabulary]


def _letters(word: bytes) -> bool:
    """Letters only, also in lower case: the splitter then keeps the word whole."""
    if word.isalpha():
        return True
    text = word.decode()
    return text.isalpha() and text.lower().isalpha()


def _encode_words(words: set[bytes], tok, ends: np.ndarray, cache: dict[bytes, bytes]) -> None:
    """Put the ids of ``words`` into ``cache``.

    Signs after a word of letters are a split of their own, so such words are put together
    from two.  Words of letters have one word end, so many share a call; a group whose ends
    don't add up is encoded word by word.
    """
    encode = getattr(tok, "encode_batch_fast", tok.encode_batch)
    signed, plain, other = [], set(), set()
    for w in words:
        core = w.rstrip(SIGNS)
        if len(core) == len(w):
            (plain if _letters(w) else other).add(w)
        elif core and _letters(core):
            tail = w[len(core) :]
            signed.append((w, core, tail))
            if core not in cache:
                plain.add(core)
            if tail not in cache:
                other.add(tail)
        else:
            other.add(w)
    letters = list(plain)
    for lo in range(0, len(letters), JOINED * 256):
        part = letters[lo : lo + JOINED * 256]
        groups = [part[k : k + JOINED] for k in range(0, len(part), JOINED)]
        for group, e in zip(groups, encode([b" ".join(g).decode() for g in groups], add_special_tokens=False)):
            ids = np.array(e.ids, dtype="<u4")
            cuts = ((np.flatnonzero(ends[ids]) + 1) * 4).tolist()
            if len(cuts) != len(group):
                other.update(group)
                continue
            cache.update(zip(group, map(ids.tobytes().__getitem__, map(slice, [0, *cuts[:-1]], cuts))))
    rest = list(other)
    for lo in range(0, len(rest), 8192):
        part = rest[lo : lo + 8192]
        for w, e in zip(part, encode([w.decode() for w in part], add_special_tokens=False)):
            cache[w] = np.array(e.ids, dtype="<u4").tobytes()
    for w, core, tail in signed:
        cache[w] = cache[core] + cache[tail]


def token_ids(texts: pa.Array, vocabulary: str = VOCABULARY) -> tuple[np.ndarray, np.ndarray]:
    """(ids of all texts in a row, an end id after each; where each text starts, and the end of the last).

    The vocabulary's splitter never lets a token cross ASCII white space, so the distinct
    words of a batch are looked up or encoded once and laid out by index arithmetic; a test
    compares this with encoding whole texts.
    """
    tok, ends, cache = _tokenizer(vocabulary)
    lists = pc.ascii_split_whitespace(pc.fill_null(texts.cast(pa.large_string()), ""))
    offsets = lists.offsets.to_numpy().astype(np.int64)
    coded = lists.values.slice(offsets[0], offsets[-1] - offsets[0]).dictionary_encode()
    offsets = offsets - offsets[0]
    words = coded.dictionary.cast(pa.large_binary()).to_pylist()
    new = {w for w in words if w not in cache}
    if len(cache) + len(new) > CACHE_WORDS:
        cache.clear()
        new = set(words)
    _encode_words(new, tok, ends, cache)
    table = [*map(cache.__getitem__, words), np.array([END_ID], dtype="<u4").tobytes()]
    sizes = np.fromiter(map(len, table), dtype=np.int64, count=len(table)) // 4
    pool = np.frombuffer(b"".join(table), dtype="<u4")
    first = np.cumsum(sizes) - sizes
    # an end after the words of each text
    codes = np.insert(coded.indices.to_numpy().astype(np.int64), offsets[1:], len(words))
    n = sizes[codes]
    stop = np.cumsum(n)
    ids = pool[np.repeat(first[codes] - stop + n, n) + np.arange(stop[-1] if len(stop) else 0)]
    bounds = np.concatenate(([0], stop[offsets[1:] + np.arange(len(texts))])) if len(texts) else np.zeros(1, np.int64)
    return ids, bounds


def token_bytes(texts: list[bytes], vocabulary: str = VOCABULARY) -> list[bytes]:
    """Little-endian 32-bit ids of each text, the end id included."""
    ids, bounds = token_ids(pa.array([t.decode() for t in texts], pa.large_string()), vocabulary)
    return [ids[a:z].tobytes() for a, z in zip(bounds[:-1], bounds[1:])]


_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


def _groups(texts: pa.Array) -> Iterator[tuple[int, int]]:
    """Stretches of rows with about ``GROUP_BYTES`` of text."""
    sizes = pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False).tolist()
    at, total = 0, 0
    for k, n in enumerate(sizes):
        if total and total + n > GROUP_BYTES:
            yield at, k
            at, total = k, 0
        total += n + 1
    if sizes:
        yield at, len(sizes)


def _cut(vocabulary: str, capacity: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo, hi in _groups(b.column(1)):
                doc = b.column(0).slice(lo, hi - lo).to_pylist()
                ids, bounds = token_ids(b.column(1).slice(lo, hi - lo), vocabulary)
                raw = memoryview(np.ascontiguousarray(ids)).cast("B")
                out: list[list] = [[], [], [], [], []]
                for i, a, z in zip(doc, bounds[:-1].tolist(), bounds[1:].tolist()):
                    for k, s in enumerate(range(a, z, capacity)):
                        e = min(z, s + capacity)
                        for o, x in zip(out, (i, k, s - a, e - s, zlib.crc32(raw[4 * s : 4 * e]))):
                            o.append(x)
                kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(o, k) for o, k in zip(out, kinds)], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return run


def pieces_of(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str = VOCABULARY, capacity: int = CAPACITY) -> DataFrame:
    """``doc_id, piece, start, length, ids_crc32`` of every row."""
    d = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return d.mapInArrow(_cut(vocabulary, capacity), _PIECES)


# A packing is a list of [free space, piece, piece, ...]; pieces are places in the shard's array of lengths.


def best_fit(bins: list[list[int]], items: list[int], lengths: list[int], capacity: int, by_length: bool = True) -> list[list[int]]:
    """Put ``items``, longest first (or as they come), each where the least room is left over."""
    free = sorted((b[0], k) for k, b in enumerate(bins))
    for i in sorted(items, key=lambda i: -lengths[i]) if by_length else items:
        n = lengths[i]
        at = bisect.bisect_left(free, (n, -1))
        if at < len(free):
            room, k = free.pop(at)
            bins[k][0] = room - n
            bins[k].append(i)
        else:
            k = len(bins)
            bins.append([capacity - n, i])
        bisect.insort(free, (bins[k][0], k))
    return bins


def fitness(bins: list[list[int]], capacity: int) -> tuple:
    """Fewer bins first, then uneven filling (full bins beside empty ones are easier to improve)."""
    return (len(bins), -sum(((capacity - b[0]) / capacity) ** 2 for b in bins))


def random_fit(lengths: list[int], capacity: int, rnd: random.Random) -> list[list[int]]:
    """A packing to start from: pieces in random order, each where the least room is left over."""
    order = list(range(len(lengths)))
    rnd.shuffle(order)
    return best_fit([], order, lengths, capacity, by_length=False)


def crossover(one: list[list[int]], two: list[list[int]], lengths: list[int], capacity: int, rnd: random.Random) -> list[list[int]]:
    full = sorted((b for b in two if capacity - b[0] >= WELL_FILLED * capacity), key=lambda b: (b[0], rnd.random())) or [min(two)]
    inject = full[: max(1, int(len(two) * rnd.uniform(*INJECTED)))]
    have = {i for b in inject for i in b[1:]}
    keep, displaced = [], []
    for b in one:
        if have.isdisjoint(b[1:]):
            keep.append(list(b))
        else:
            displaced += [i for i in b[1:] if i not in have]
    return best_fit([*map(list, inject), *keep], displaced, lengths, capacity)


def reopened(bins: list[list[int]], lengths: list[int], capacity: int, rnd: random.Random) -> list[list[int]]:
    """A mutation: some of the emptiest bins and some at random give up their pieces, which go back by best fit."""
    order = sorted(range(len(bins)), key=lambda k: -bins[k][0])
    k = max(2, len(bins) // 20)
    out = {*order[:k], *rnd.sample(order, min(k, len(order)))}
    loose = [i for j in out for i in bins[j][1:]]
    keep = [list(b) for j, b in enumerate(bins) if j not in out]
    rnd.shuffle(keep)
    return best_fit(keep, loose, lengths, capacity)


def evolve(lengths: list[int], capacity: int, seed: int, elites: list[list[list[int]]]) -> list[list[int]]:
    """The best packing after some generations; the best one is never lost, and the lower bound ends the search."""
    rnd = random.Random(seed)
    bound = -(-sum(lengths) // capacity)
    pool = [*elites]
    while len(pool) < POPULATION and min(map(len, pool), default=bound + 1) > bound:
        pool.append(random_fit(lengths, capacity, rnd))
    for _ in range(GENERATIONS):
        pool.sort(key=lambda b: fitness(b, capacity))
        if len(pool) < 2 or len(pool[0]) <= bound:
            break
        one, two = rnd.sample(pool[: max(2, 2 * len(pool) // 3)], 2)
        child = crossover(one, two, lengths, capacity, rnd)
        pool[-1] = reopened(child, lengths, capacity, rnd) if rnd.random() < 0.5 else child
    return min(pool, key=lambda b: fitness(b, capacity))


def packing_of(owner: list[int], lengths: list[int], capacity: int) -> list[list[int]]:
    bins: dict[int, list[int]] = {}
    for i, k in enumerate(owner):
        b = bins.setdefault(k, [capacity])
        b[0] -= lengths[i]
        b.append(i)
    return list(bins.values())


_ISLAND = "shard long, island int, owner array<int>, bins int"


def _island(capacity: int, epoch: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for shard, island, lengths, elites in zip(*(c.to_pylist() for c in b.columns)):
                packed = evolve(lengths, capacity, hash((shard, island, epoch)) & 0xFFFFFFFF, [packing_of(o, lengths, capacity) for o in elites or ()])
                owner = [0] * len(lengths)
                for k, x in enumerate(packed):
                    for i in x[1:]:
                        owner[i] = k
                yield pa.RecordBatch.from_arrays(
                    [pa.array([shard], pa.int64()), pa.array([island], pa.int32()), pa.array([owner], pa.list_(pa.int32())), pa.array([len(packed)], pa.int32())],
                    names=["shard", "island", "owner", "bins"],
                )

    return run


def _pack_shards(shards: DataFrame, capacity: int, islands: int, epochs: int) -> DataFrame:
    """``shard, owner``: the best packing over islands after migration; ``shards(shard, items)``."""
    lengths = shards.select("shard", F.transform("items", lambda x: x["length"].cast("int")).alias("lengths"))
    base = lengths.select("shard", F.explode(F.sequence(F.lit(0), F.lit(islands - 1))).alias("island"), "lengths")
    state = base.withColumn("elites", F.lit(None).cast("array<array<int>>"))
    bound = lengths.select("shard", F.ceil(F.aggregate("lengths", F.lit(0).cast("long"), lambda a, x: a + x) / capacity).alias("bound"))
    done = None
    for epoch in range(epochs):
        spread = state.repartition("shard", "island")
        out = write(spread.mapInArrow(_island(capacity, epoch), _ISLAND), "islands").df
        best = out.groupBy("shard").agg(F.min_by("owner", F.struct("bins", "island")).alias("owner"), F.min("bins").alias("bins"))
        best = write(best, "best").df
        done = best if done is None else write(
            done.unionByName(best).groupBy("shard").agg(F.min_by("owner", "bins").alias("owner"), F.min("bins").alias("bins")), "best"
        ).df
        open_ = done.join(bound, "shard").filter("bins > bound").select("shard")
        if epoch + 1 == epochs or open_.isEmpty():
            break
        # migration: an island starts the next epoch from its own elite and its neighbour's
        moved = out.select("shard", F.pmod(F.col("island") + 1, F.lit(islands)).cast("int").alias("island"), "owner")
        elites = out.select("shard", "island", "owner").unionByName(moved).groupBy("shard", "island").agg(F.collect_list("owner").alias("elites"))
        state = base.join(open_, "shard", "left_semi").join(elites, ["shard", "island"])
    return done.select("shard", "owner")


def pack(pieces: DataFrame, capacity: int = CAPACITY, shard_items: int = SHARD, islands: int = ISLANDS, epochs: int = EPOCHS) -> DataFrame:
    """``pieces`` (with ``length``) plus ``sequence_id`` and ``offset``; lengths must be 1..capacity."""
    own = pieces.columns
    todo = write(pieces.select(F.struct(*own).alias("x"), F.col("length"), F.xxhash64(*own, F.monotonically_increasing_id()).alias("u")), "pieces").df
    n = todo.count()
    count = max(1, -(-n // shard_items))
    made, rest, level, open_bins = [], None, 0, 0
    todo = todo.withColumn("shard", F.pmod("u", F.lit(count)))
    while True:
        shards = write(todo.groupBy("shard").agg(F.sort_array(F.collect_list(F.struct("length", "u", "x")), asc=False).alias("items")), "shards").df
        best = _pack_shards(shards, capacity, islands, epochs)
        placed = shards.join(best, "shard").select("shard", F.posexplode("items").alias("i", "item"), "owner")
        placed = placed.select("shard", "item.length", "item.u", "item.x", F.element_at("owner", F.col("i") + 1).alias("bin"))
        bin_ = W.partitionBy("shard", "bin")
        placed = placed.withColumns(
            {
                "fill": F.sum("length").over(bin_),
                "offset": F.sum("length").over(bin_.orderBy(F.desc("length"), "u").rowsBetween(W.unboundedPreceding, 0)) - F.col("length"),
            }
        )
        placed = write(placed, "placed").df
        under = F.col("fill") < WELL_FILLED * capacity
        first = F.col("offset") == 0
        left = placed.agg(F.count_if(first).alias("bins"), F.count_if(first & under).alias("open"), F.count_if(under).alias("pieces")).first()
        if level and left["bins"] >= open_bins:
            # no bin saved by pooling: the bins stay as they were
            made.append(rest)
            break
        chosen = placed.select("x", F.struct(F.lit(level).alias("l"), "shard", "bin").alias("s"), "offset", under.alias("under"))
        if count == 1 or not left["open"]:
            made.append(chosen.drop("under"))
            break
        made.append(chosen.filter("not under").drop("under"))
        rest = chosen.filter("under").drop("under")
        level, count, open_bins = level + 1, -(-left["pieces"] // shard_items), left["open"]
        todo = placed.filter(under).select("x", "length", "u", F.pmod(F.xxhash64(F.lit(level), "shard", "bin"), F.lit(count)).alias("shard"))
    out = made[0]
    for m in made[1:]:
        out = out.unionByName(m)
    # level, shard and bin in one number: bins of a shard are fewer than its pieces
    number = F.col("s.shard") * F.lit(1 << 24) + F.col("s.bin") + F.col("s.l").cast("long") * F.lit(1 << 48)
    return out.select("x.*", number.alias("sequence_id"), F.col("offset").cast("long").alias("offset"))


def packed_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str = VOCABULARY) -> DataFrame:
    return pack(pieces_of(docs, id_col, text_col, vocabulary))


def query(spark, sf_dir: str) -> DataFrame:
    return packed_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))


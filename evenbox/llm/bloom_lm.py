"""Language-model scoring from a log-frequency Bloom filter.

The filter holds word and word-pair counts of the training documents. A count c is stored as its level,
1 + floor(2 log2 c): the pair of a gram and j is a member for every j up to the level, so a count is read back by
probing j = 1, 2, ... until a probe fails. Grams are dealt to slices of ``SLICE_BITS`` bits by their leading bits; a
task that owns a slice gets all grams of it and sets their bits, and the slices together are the filter.
``BITS_EACH`` bits for each member fix its size; members are counted exactly over the grams of one part in ``SHARE`` of the
hash space. It is broadcast in segments of at most ``SEGMENT_SLICES`` slices (128 MB), each let go of after its pass; a filter of
more segments takes a pass over the documents for each.

The score of a text is the sum over its words and its end of log10 P(word | word before), with
P = (c(pair) + mu P1(word)) / (c(word before) + mu) and P1 = (c(word) + 0.1) / (N + 0.1 (V + 1)), all counts read from the filter.

Beside it stands an exact base: log10 P1 with true counts. Counts of the most frequent words (``TOP`` at most)
are broadcast; the other words of each document are joined with the count table.

Defined results: a null or empty text is its end alone; repeated rows are scored (and counted) each; a null
doc_id is training data; no training rows make N = V = 0 and an empty filter; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenbox.llm.bytewords import Words, combine, mix64, slices, text_bytes
from evenbox.llm.scratch import Scratch

SLICE_BITS = 1 << 17
SEGMENT_SLICES = 1 << 13
#: the filter's members are counted over grams whose hash is 0 modulo this
SHARE = 256
BITS_EACH = 6
#: where in a member's hash the places of its bits begin
PROBES = (0, 15, 31, 47)
TOP = 1 << 19
MU = 100.0
ADD = 0.1
FOLDS = 10
_END = np.uint64(0xE3D1A5C6B7F80912)
_BEGIN = np.uint64(0xB1E7C4D5A6938271)
_FLUSH = 2_000_000
_MAX_LEVEL = 128


def held_out(doc_id: Column, folds: int = FOLDS) -> Column:
    """True for the documents that are scored without having been learned from."""
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(folds)) == 0, F.lit(False))


def count_level(n: np.ndarray) -> np.ndarray:
    """1 + floor(2 log2 n) in whole numbers: 2 b + 1, and one more from sqrt(2) 2^b on."""
    n = np.maximum(n.astype(np.int64), 1)
    b = np.floor(np.log2(n)).astype(np.int64)
    b = np.where(np.left_shift(np.int64(1), b) > n, b - 1, b)
    return 2 * b + 1 + (n.astype(np.float64) >= math.sqrt(2) * 2.0**b)


def level_counts() -> np.ndarray:
    """A count for each level: the middle of the whole numbers that share it; 0 for level 0."""
    value = np.zeros(_MAX_LEVEL + 1)
    for j in range(1, _MAX_LEVEL + 1):
        low, high = math.ceil(2 ** ((j - 1) / 2) - 1e-9), math.ceil(2 ** (j / 2) - 1e-9) - 1
        value[j] = (low + max(low, high)) / 2
    return value


def _sequence(words: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(token, token before, row) of the rows of a slice; each row ends with the end token."""
    n = len(words.start) + words.rows
    token = np.full(n, _END, np.uint64)
    token[np.arange(len(words.start)) + words.row] = words.word_hash()
    before = np.empty(n, np.uint64)
    before[1:] = token[:-1]
    before[words.first[:-1] + np.arange(words.rows)] = _BEGIN
    return token, before, np.repeat(np.arange(words.rows), words.per_row + 1)


def _sequences(batch: pa.RecordBatch, column: int):
    raw, offsets = text_bytes(batch.column(column))
    for a, b in slices(offsets):
        yield (a, b, *_sequence(Words(raw[offsets[a] : offsets[b]], offsets[a : b + 1], lower=True)))


def _counted(batches: Iterator[pa.RecordBatch], grams) -> Iterator[pa.RecordBatch]:
    """Counts inside a task, let go of whenever they are many."""
    held: list[np.ndarray] = []
    size = 0

    def made():
        names, n = np.unique(np.concatenate(held), return_counts=True)
        return pa.RecordBatch.from_arrays([pa.array(names.view(np.int64)), pa.array(n)], ["gram", "n"])

    for batch in batches:
        for _, _, token, before, _ in _sequences(batch, 0):
            held.append(grams(token, before))
            size += len(held[-1])
            if size >= _FLUSH:
                yield made()
                held, size = [], 0
    if held:
        yield made()


def word_gram(token: np.ndarray) -> np.ndarray:
    """The name of a word; odd, so that counting may mark it."""
    return combine([token]) | np.uint64(1)


def count_words(docs: DataFrame) -> DataFrame:
    """(gram, n, whole) of the words and ends of ``docs`` and, whole being false, of the pairs in one part in ``SHARE`` of the hash space."""

    def grams(token: np.ndarray, before: np.ndarray) -> np.ndarray:
        # words have an odd name and pairs an even one here, so that both are counted at once
        pair = combine([before, token])
        return np.concatenate([word_gram(token), pair[_shared(pair)] & ~np.uint64(1)])

    counted = docs.select("text").mapInArrow(lambda batches: _counted(batches, grams), "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n"))
    return counted.withColumn("whole", F.col("gram").bitwiseAND(F.lit(1)) == 1)


def _shared(gram: np.ndarray) -> np.ndarray:
    return (gram >> np.uint64(1)) % np.uint64(SHARE) == 0


def _places(gram: np.ndarray, level: np.ndarray) -> list[np.ndarray]:
    """Bit places of (gram, level) in its slice, one for each probe."""
    with np.errstate(over="ignore"):
        name = mix64(gram + level.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93))
    return [((name >> np.uint64(k)) & np.uint64(SLICE_BITS - 1)).astype(np.int64) for k in PROBES]


def _part(gram: np.ndarray, n: int) -> np.ndarray:
    """The slice, of n, of a gram."""
    return (((gram >> np.uint64(32)) * np.uint64(n)) >> np.uint64(32)).astype(np.int64)


def count_members(counted: DataFrame) -> int:
    """Members of the filter over words and pairs: a word's levels, and those of the counted pairs times ``SHARE``."""
    # 2 log2 n by whole numbers is worked out when bits are set; here the float is close enough for a size
    level = F.sum(F.floor(2 * F.log2(F.col("n").cast("double")) + 1e-9) + 1)
    found = {r["whole"]: r["members"] for r in counted.groupBy("whole").agg(level.alias("members")).collect()}
    return int(found.get(True, 0) + SHARE * found.get(False, 0))


def build_filter(docs: DataFrame, words: DataFrame, members: int, scratch: Scratch) -> tuple[DataFrame, int]:
    """The slices (slice, bits) of the filter over pairs of ``docs`` and ``words``, and how many there are."""
    pairs = docs.select("text").mapInArrow(lambda batches: _counted(batches, lambda token, before: combine([before, token])), "gram long, n long")
    n = max(1, -(-BITS_EACH * members // SLICE_BITS))
    own = F.shiftrightunsigned(F.shiftrightunsigned("gram", 32) * F.lit(n).cast("long"), 32)
    rows = pairs.unionByName(words).withColumn("slice", own).repartition("slice").groupBy("slice", "gram").agg(F.sum("n").alias("n"))

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        maps: dict[int, np.ndarray] = {}
        for batch in batches:
            part = batch.column("slice").to_numpy()
            gram = batch.column("gram").to_numpy().view(np.uint64)
            level = count_level(batch.column("n").to_numpy())
            for j in range(1, int(level.max(initial=0)) + 1):
                at = np.flatnonzero(level >= j)
                places = _places(gram[at], np.full(len(at), j))
                order = np.argsort(part[at], kind="stable")
                owners, begins = np.unique(part[at][order], return_index=True)
                for owner, a, b in zip(owners.tolist(), begins, [*begins[1:], len(at)], strict=True):
                    if owner not in maps:
                        maps[owner] = np.zeros(SLICE_BITS // 8, np.uint8)
                    flags = np.zeros(SLICE_BITS, bool)
                    for place in places:
                        flags[place[order[a:b]]] = True
                    maps[owner] |= np.packbits(flags)
        for owner, bits in maps.items():
            yield pa.RecordBatch.from_arrays([pa.array([owner], pa.int64()), pa.array([bits.tobytes()], pa.binary())], ["slice", "bits"])

    return scratch.write(rows.mapInArrow(build, "slice long, bits binary"), "filter", "lz4"), n


class Segment:
    """Consecutive slices of a filter of n slices, for probing."""

    def __init__(self, first: int, slices_here: int, n: int, bits: np.ndarray):
        self.first, self.count, self.n, self.bits = first, slices_here, n, bits

    def levels(self, gram: np.ndarray, out: np.ndarray) -> None:
        """Write the levels of the grams that belong here to ``out``."""
        part = _part(gram, self.n)
        at = np.flatnonzero((part >= self.first) & (part < self.first + self.count))
        base, live = (part[at] - self.first) * SLICE_BITS, gram[at]
        for j in range(1, _MAX_LEVEL):
            hit = np.ones(len(at), bool)
            for place in _places(live, np.full(len(at), j)):
                place = place + base
                hit &= (self.bits[place >> 3] >> (7 - (place & 7)).astype(np.uint8)) & 1 == 1
            at, base, live = at[hit], base[hit], live[hit]
            if not len(at):
                break
            out[at] = j


def load_segment(stored: DataFrame, first: int, n: int) -> Segment:
    """At most SEGMENT_SLICES slices, brought to the driver: a fixed number of bytes."""
    here = min(SEGMENT_SLICES, n - first)
    bits = np.zeros(here * SLICE_BITS // 8, np.uint8)
    found = stored.where(F.col("slice").between(first, first + here - 1)).toArrow()
    for part, raw in zip(found["slice"].to_pylist(), found["bits"], strict=True):
        bits[(part - first) * SLICE_BITS // 8 :][: SLICE_BITS // 8] = np.frombuffer(raw.as_buffer(), np.uint8)
    return Segment(first, here, n, bits)


def top_words(words: DataFrame, most: int = TOP) -> tuple[np.ndarray, np.ndarray, float]:
    """(grams in order, counts, least class): the classes of most frequent words that make up ``most`` words at most."""
    by = words.groupBy(_class().alias("class")).count().orderBy(F.desc("class")).collect()  # 16 classes a doubling
    least, total = math.inf, 0
    for row in by:
        total += row["count"]
        if total > most:
            break
        least = row["class"]
    found = words.where(_class() >= F.lit(float(least))).toArrow()
    gram, n = found["gram"].to_numpy().view(np.uint64), found["n"].to_numpy()
    order = np.argsort(gram)
    return gram[order], n[order], float(least)


def _class() -> Column:
    return F.floor(F.log2(F.col("n").cast("double")) * 16).cast("double")


def score_documents(docs: DataFrame, mu: float = MU, top: int = TOP, folds: int = FOLDS) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "lm")
    sc = spark.sparkContext
    docs = docs.select("doc_id", "text")
    train = docs.where(~held_out(F.col("doc_id"), folds))
    counted = scratch.write(count_words(train), "words")
    words = counted.where("whole").drop("whole")
    totals = words.agg(F.count("*"), F.coalesce(F.sum("n"), F.lit(0))).first()
    distinct, tokens = totals[0], totals[1]
    stored, n = build_filter(train, words, count_members(counted), scratch)
    gram, count, least = top_words(words, top)
    frequent = sc.broadcast((gram, count))  # TOP words at most
    floor = tokens + ADD * (distinct + 1)

    state = docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", "text", F.lit(None).cast("binary").alias("levels"))
    firsts = range(0, n, SEGMENT_SLICES)
    for turn, first in enumerate(firsts[:-1]):
        segment = sc.broadcast(load_segment(stored, first, n))
        state = scratch.write(state.mapInArrow(_probing(segment), state.schema), f"probed-{turn}")
        segment.destroy()
        if turn:
            scratch.drop(f"probed-{turn - 1}")
    last = sc.broadcast(load_segment(stored, firsts[-1], n))
    scored = scratch.write(state.mapInArrow(_scoring(last, frequent, mu, floor, train.count()), _SCORED), "scored")
    last.destroy()
    frequent.destroy()
    rare = words.where(_class() < F.lit(least))
    asked = scored.select("row", F.explode("rare").alias("gram")).join(rare, "gram", "left")
    more = asked.groupBy("row").agg(F.sum(F.log10((F.coalesce(F.col("n"), F.lit(0)) + ADD) / floor)).alias("more"), F.count("n").alias("known"))
    both = scored.drop("rare").join(more, "row", "left")
    return both.select("doc_id", held_out(F.col("doc_id"), folds).alias("held_out"), "n_tokens", (F.col("n_known") + F.coalesce("known", F.lit(0))).alias("n_known"), F.lit(int(tokens)).cast("long").alias("train_tokens"), (F.col("base") + F.coalesce("more", F.lit(0.0))).alias("base_score"), "score")


_SCORED = "row long, doc_id long, n_tokens long, n_known long, base double, score double, rare array<long>"


def _looked_up(batch: pa.RecordBatch, segment: Segment):
    """Slices of a batch with the levels known so far: the word and the pair of each token. A word is looked up
    once in a slice, for frequent words have many levels; the word before has the level of the token before."""
    levels = batch.column("levels")
    for a, b, token, before, row in _sequences(batch, 2):
        size = np.bincount(row, minlength=b - a)
        known = np.zeros((2, len(token)), np.uint8)
        if levels.null_count < len(levels):
            kept = [np.frombuffer(x.as_buffer(), np.uint8).reshape(2, -1) for x in levels.slice(a, b - a)]
            known = np.concatenate(kept, axis=1) if kept else known
        words, at = np.unique(token, return_inverse=True)
        found = np.zeros(len(words), np.uint8)
        segment.levels(word_gram(words), found)
        known[0] = np.maximum(known[0], found[at])
        pairs = known[1].copy()
        segment.levels(combine([before, token]), pairs)
        known[1] = pairs
        yield a, b, token, row, size, known


def _probing(segment):
    """A pass over one segment of a filter that has several."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b, _, _, size, known in _looked_up(batch, segment.value):
                edges = np.concatenate([[0], np.cumsum(size)])
                cells = [np.ascontiguousarray(known[:, x:y]).tobytes() for x, y in zip(edges, edges[1:], strict=False)]
                own = [c.slice(a, b - a) for c in batch.columns[:3]]
                yield pa.RecordBatch.from_arrays([*own, pa.array(cells, pa.binary())], batch.schema.names)

    return run


def _scoring(segment, frequent, mu: float, floor: float, begins: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, counts = frequent.value
        value = level_counts()
        schema = [x.split()[0] for x in _SCORED.split(", ")]
        for batch in batches:
            for a, b, token, row, size, known in _looked_up(batch, segment.value):
                word, pair = value[known]
                before = np.empty_like(word)
                before[1:] = word[:-1]
                before[np.cumsum(size) - size] = begins
                pair = np.minimum(pair, np.minimum(word, before))  # a pair is no more frequent than its words
                score = np.log10((pair + mu * (word + ADD) / floor) / (before + mu))
                own = word_gram(token)
                at = np.minimum(np.searchsorted(names, own), max(len(names) - 1, 0))
                top = names[at] == own if len(names) else np.zeros(len(own), bool)
                base = np.where(top, np.log10(((counts[at] if len(names) else 0) + ADD) / floor), 0.0)
                rare = own[~top].view(np.int64)
                offsets = np.concatenate([[0], np.cumsum(np.bincount(row[~top], minlength=b - a))]).astype(np.int32)
                add = lambda x: np.bincount(row, weights=x, minlength=b - a)
                columns = [pa.array(size), pa.array(add(top).astype(np.int64)), pa.array(add(base)), pa.array(add(score)), pa.ListArray.from_arrays(pa.array(offsets), pa.array(rare))]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), batch.column(1).slice(a, b - a), *columns], schema)

    return run

"""Token counts that follow edits.

A document is cut into segments where a lone space stands between two other characters that are not white space: no
pre-token crosses such a place, whatever the text around. Its index is the segments' lengths and token
counts, and a segment tree of count sums over them. An edit (start, deleted characters, inserted text)
touches the segments it overlaps; they and one more on each side, as boundary context, are joined, changed and
cut again, and only those of the new segments whose text differs are encoded. If the segments stay as many, the sums above the
changed leaves are updated; if not, leaves are put in and the tree is summed anew, without encoding.

Defined results: a null or empty text has one empty segment; an edit reaches no further than the text, so a
start past the end appends; edits of one document apply in order of their number, each to the text as the one before
left it; repeated rows of a doc_id get the same edits each; null edit fields are 0 or empty; extra columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenbox.llm.fast_bpe import encoder
from evenbox.llm.scratch import Scratch

#: characters after which a segment ends at the next safe place
SEGMENT = 256
_SAFE = re.compile(r"(?<=\S) (?=\S)")


@dataclass(frozen=True)
class Edit:
    start: int
    deleted: int
    inserted: str


def cut_segments(text: str, least: int = SEGMENT) -> list[str]:
    """Segments of ``least`` characters or more that end at safe places; joined they are the text."""
    out, begin = [], 0
    while True:
        found = _SAFE.search(text, begin + least)
        if not found:
            return [*out, text[begin:]]
        out.append(text[begin : found.start()])
        begin = found.start()


class SumTree:
    """A complete binary tree of sums in an array; leaf i is at ``size + i``."""

    def __init__(self, leaves: list[int]):
        self.n = len(leaves)
        self.size = 1 << max(0, (self.n - 1).bit_length())
        self.sums = [0] * self.size + list(leaves) + [0] * (self.size - self.n)
        for i in range(self.size - 1, 0, -1):
            self.sums[i] = self.sums[2 * i] + self.sums[2 * i + 1]

    def total(self) -> int:
        return self.sums[1]

    def set(self, leaf: int, value: int) -> None:
        i = self.size + leaf
        change = value - self.sums[i]
        while i:
            self.sums[i] += change
            i >>= 1

    def before(self, leaf: int) -> int:
        """The sum of the leaves before one."""
        total, i = 0, self.size + leaf
        while i > 1:
            if i & 1:
                total += self.sums[i - 1]
            i >>= 1
        return total

    def find(self, amount: int) -> int:
        """The leaf in which the running sum passes ``amount``; the last leaf if none does."""
        i = 1
        while i < self.size:
            i *= 2
            if amount >= self.sums[i]:
                amount -= self.sums[i]
                i += 1
        return min(i - self.size, self.n - 1)


class CountedText:
    """A text with its segments, lengths and token counts; ``encoded`` counts characters given to ``count``."""

    def __init__(self, text: str, count: Callable[[list[str]], list[int]], least: int = SEGMENT, counts: list[int] | None = None):
        self.count, self.least, self.encoded = count, least, 0
        self.segments = cut_segments(text or "", least)
        self.counts = counts if counts is not None else self._count(self.segments)
        self._sum()

    def _count(self, segments: list[str]) -> list[int]:
        self.encoded += sum(map(len, segments))
        return self.count(segments)

    def _sum(self) -> None:
        self.tokens, self.chars = SumTree(self.counts), SumTree([len(s) for s in self.segments])

    def text(self) -> str:
        return "".join(self.segments)

    def total(self) -> int:
        return self.tokens.total()

    def apply(self, edit: Edit) -> int:
        """Make the edit; the token count after it."""
        length = self.chars.total()
        start = min(max(edit.start, 0), length)
        stop = min(start + max(edit.deleted, 0), length)
        first = max(self.chars.find(start) - 1, 0)
        last = min(self.chars.find(max(stop - 1, start)) + 1, len(self.segments) - 1)
        base = self.chars.before(first)
        old = self.segments[first : last + 1]
        text = "".join(old)
        text = text[: start - base] + edit.inserted + text[stop - base :]
        new = cut_segments(text, self.least)
        known = dict(zip(old, self.counts[first : last + 1], strict=True))
        fresh = [s for s in new if s not in known]
        if fresh:
            known.update(zip(fresh, self._count(fresh), strict=True))
        counts = [known[s] for s in new]
        if len(new) == len(old):
            for i, (segment, n) in enumerate(zip(new, counts, strict=True), first):
                if segment != self.segments[i]:
                    self.segments[i], self.counts[i] = segment, n
                    self.tokens.set(i, n)
                    self.chars.set(i, len(segment))
        else:
            self.segments[first : last + 1], self.counts[first : last + 1] = new, counts
            self._sum()
        return self.total()


def _counting(vocabulary: str) -> Callable[[list[str]], list[int]]:
    bpe = encoder(vocabulary)
    return lambda segments: [len(ids) // bpe.dtype.itemsize for ids in bpe.encode_many(segments)]


def index_documents(docs: DataFrame, vocabulary: str = "byte_bpe_50k.json", least: int = SEGMENT) -> DataFrame:
    """doc_id, n_tokens and counts (tokens of each segment) of every row: the stored index."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = _counting(vocabulary)
        for batch in batches:
            for row in range(0, batch.num_rows, 256):
                part = batch.slice(row, 256)
                cut = [cut_segments(text or "", least) for text in part.column(1).to_pylist()]
                counted = iter(count([s for segments in cut for s in segments]))
                counts = [[next(counted) for _ in segments] for segments in cut]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([sum(c) for c in counts], pa.int64()), pa.array(counts, pa.list_(pa.int32())), part.column(1)], ["doc_id", "n_tokens", "counts", "text"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, counts array<int>, text string")


_RESULT = "doc_id long, tokens_before long, tokens_after long, n_edits int, text_chars long, encoded_chars long, counts array<int>, text string"


def _applied(rows: DataFrame, vocabulary: str, least: int) -> DataFrame:
    """Rows (doc_id, text, counts, edits) -> ``_RESULT``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = _counting(vocabulary)
        names = [x.split()[0] for x in _RESULT.split(", ")]
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.list_(pa.int32()), pa.string()]
        for batch in batches:
            for row in range(0, batch.num_rows, 256):
                out = []
                for doc, text, counts, changes in zip(*(c.slice(row, 256).to_pylist() for c in batch.columns), strict=True):
                    counted = CountedText(text, count, least, counts)
                    before = counted.total()
                    for e in changes or ():
                        counted.apply(Edit(e["start"] or 0, e["deleted"] or 0, e["inserted"] or ""))
                    out.append((doc, before, counted.total(), len(changes or ()), counted.chars.total(), counted.encoded, counted.counts, counted.text()))
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names)

    return rows.select("doc_id", "text", "counts", "edits").mapInArrow(run, _RESULT)


def apply_edits(indexed: DataFrame, edits: DataFrame, vocabulary: str = "byte_bpe_50k.json", least: int = SEGMENT) -> DataFrame:
    """``indexed`` (doc_id, text, counts) and ``edits`` (doc_id, edits: array of start, deleted, inserted in order) ->
    doc_id, tokens_before, tokens_after, n_edits, text_chars (after), encoded_chars, counts and text (the new index)."""
    return _applied(indexed.join(edits, "doc_id", "left"), vocabulary, least)


def sample_edits() -> Column:
    """Three edits for a document, from its id and length alone: a replaced stretch, an insertion, a deletion."""
    n = F.length(F.coalesce("text", F.lit("")))
    at = lambda k: F.pmod(F.coalesce("doc_id", F.lit(0)) * k + k, n + 1).cast("int")
    edit = lambda start, deleted, text: F.struct(start.alias("start"), F.lit(deleted).alias("deleted"), F.lit(text).alias("inserted"))
    return F.array(edit(at(7919), 12, "replaced words "), edit(at(104729), 0, " a new\n\nclause, inserted"), edit(at(1299709), 40, ""))


def edited_counts(docs: DataFrame, vocabulary: str = "byte_bpe_50k.json") -> DataFrame:
    """Index every document, apply ``sample_edits`` and give the counts before and after."""
    scratch = Scratch(docs.sparkSession, "edits")
    rows = index_documents(docs, vocabulary).withColumn("edits", sample_edits())
    counts = _applied(rows, vocabulary, SEGMENT).drop("counts", "text")
    return scratch.write(counts, "counts")

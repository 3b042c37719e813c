"""Benchmark decontamination by pigeonhole edit matching.

Texts and test items are normalised (lower case, runs of anything but letters and digits to one space). A test
item of m characters may occur with k = floor(m * max_errors) edits. It is cut into k + 1 pieces;
k edits leave one piece whole, so every occurrence has an exact hit of a piece at its place. One automaton
finds the hits of all pieces in one pass over a text, hits of an item that stand close make one window, and
Myers' bit-parallel distance finds the best occurrence in the window.

An item too short for an edit (twelve characters and fewer) counts only where it stands between spaces or ends of the text, so that
a short word is not found inside a longer one.

The test items are cut into batches of bounded size; an automaton of a batch goes to every executor and
each batch is a pass over the documents. With several batches the matches of each are written before the next is sent.

Defined results: null and empty texts match nothing; items without a letter or digit are left out; items
that are equal are matched each; repeated rows of documents match each; empty tables give no rows; extra
columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenbox.llm.scratch import ROW, Scratch, numbered

MAX_ERRORS = 0.08
#: ids of documents up to this many go to every executor, more are joined by shuffle
BROADCAST_IDS = 1_000_000
#: characters of test items in one automaton
BATCH_CHARS = 2 << 20
_GAP = re.compile(r"[\W_]+")


def normal_text(text: str | None) -> str:
    return _GAP.sub(" ", text.lower()).strip() if text else ""


def error_budget(length: int, max_errors: float = MAX_ERRORS) -> int:
    return int(length * max_errors + 1e-9)


def pieces(item: str, budget: int) -> list[tuple[int, str]]:
    """(offset, piece): budget + 1 pieces of nearly equal length that make up the item."""
    n = min(budget + 1, len(item))
    cuts = [len(item) * i // n for i in range(n + 1)]
    return [(a, item[a:b]) for a, b in zip(cuts, cuts[1:], strict=False)]


class Pattern:
    """Approximate search for one item; a column of the distance table is two integers."""

    def __init__(self, text: str):
        self.length = len(text)
        self.mask = (1 << self.length) - 1
        self.top = 1 << (self.length - 1)
        self.where: dict[str, int] = {}
        for i, c in enumerate(text):
            self.where[c] = self.where.get(c, 0) | 1 << i

    def best(self, window: str) -> tuple[int, int]:
        """(distance, end) of the closest substring of the window; the first such end."""
        up, down, score = self.mask, 0, self.length
        found = (score, 0)
        mask, top, where = self.mask, self.top, self.where
        for at, c in enumerate(window, 1):
            equal = where.get(c, 0)
            vertical = equal | down
            diagonal = (((equal & up) + up) ^ up) | equal
            rise = down | ~(diagonal | up) & mask
            fall = up & diagonal
            if rise & top:
                score += 1
            elif fall & top:
                score -= 1
            rise = (rise << 1) & mask
            fall = (fall << 1) & mask
            up = fall | ~(vertical | rise) & mask
            down = rise & vertical
            if score < found[0]:
                found = (score, at)
        return found


class Matcher:
    """All items of a batch: (item_id, normalised text). bounded: items without an error budget match whole words only."""

    def __init__(self, items: list[tuple[int, str]], max_errors: float, bounded: bool = True):
        import ahocorasick

        self.items = items
        self.budgets = [error_budget(len(text), max_errors) for _, text in items]
        self.patterns: list[Pattern | None] = [None] * len(items)
        found: dict[str, list[tuple[int, int]]] = {}
        for i, (_, text) in enumerate(items):
            for offset, piece in [(-1, f" {text} ")] if bounded and not self.budgets[i] else pieces(text, self.budgets[i]):
                found.setdefault(piece, []).append((i, offset))
        self.automaton = ahocorasick.Automaton()
        for piece, places in found.items():
            self.automaton.add_word(piece, (len(piece), places))
        self.automaton.make_automaton()

    def matches(self, text: str) -> list[tuple[int, int, int, int]]:
        """(item_id, distance, begin, end) of the best occurrence of each item that occurs in a normalised text.

        begin is the end less the item's length, 0 at least.
        """
        windows: dict[int, list[list[int]]] = {}
        for last, (size, places) in self.automaton.iter(f" {text} "):
            for i, offset in places:
                begin = last - size - offset  # in the text without the space before it
                low, high = begin - self.budgets[i], begin + len(self.items[i][1]) + self.budgets[i]
                own = windows.setdefault(i, [])
                if own and own[-1][0] <= high and low <= own[-1][1]:
                    own[-1][0], own[-1][1] = min(own[-1][0], low), max(own[-1][1], high)
                else:
                    own.append([low, high])
        out = []
        for i, spans in windows.items():
            item_id, item = self.items[i]
            pattern = self.patterns[i] = self.patterns[i] or Pattern(item)
            best = (self.budgets[i] + 1, 0)
            for low, high in spans:
                low = max(low, 0)
                distance, end = pattern.best(text[low:high])
                best = min(best, (distance, low + end))
            if best[0] <= self.budgets[i]:
                out.append((item_id, best[0], max(best[1] - len(item), 0), best[1]))
        return out


def _item_batches(items: DataFrame, batch_chars: int) -> Iterator[list[tuple[int, str]]]:
    total = items.agg(F.sum(F.length("text"))).first()[0] or 0
    n = -(-total // batch_chars) or 1
    for part in range(n):
        rows = items if n == 1 else items.where(F.pmod(F.xxhash64("text"), F.lit(n)) == part)
        yield [(r["item_id"], text) for r in rows.select("item_id", "text").collect() if (text := normal_text(r["text"]))]


def benchmark_matches(docs: DataFrame, items: DataFrame, max_errors: float = MAX_ERRORS, batch_chars: int = BATCH_CHARS) -> DataFrame:
    """doc_id, item_id, distance, begin, end (in the normalised text) of every test item in every document."""
    scratch, out = Scratch(docs.sparkSession, "matches"), []
    batches = _item_batches(items, batch_chars)
    held = next(batches)
    for following in _ahead(batches):
        found = docs.select("doc_id", "text").mapInArrow(_matching(docs, held, max_errors), "doc_id long, item_id long, distance int, begin int, end int")
        out.append(scratch.write(found, f"batch-{len(out)}") if out or following is not None else found)
        held = following
    return reduce(DataFrame.unionByName, out)


def _ahead(batches: Iterator[list]) -> Iterator[list | None]:
    """The batches that follow the first, and None at the end."""
    yield from batches
    yield None


def _matching(docs: DataFrame, batch: list[tuple[int, str]], max_errors: float):
    shared = docs.sparkSession.sparkContext.broadcast(batch)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher = Matcher(shared.value, max_errors) if shared.value else None
        kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32()]
        for part in batches:
            rows = [(doc, *m) for doc, text in zip(part.column(0).to_pylist(), part.column(1), strict=True) for m in (matcher.matches(normal_text(text.as_py())) if matcher else ())]
            columns = list(zip(*rows, strict=True)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], ["doc_id", "item_id", "distance", "begin", "end"])

    return run


def drop_contaminated(docs: DataFrame, items: DataFrame, max_errors: float = MAX_ERRORS) -> DataFrame:
    """The rows of ``docs`` in which no test item occurs; rows are judged each, whatever their doc_id."""
    scratch = Scratch(docs.sparkSession, "clean")
    rows = numbered(docs, scratch)
    found = benchmark_matches(rows.select(F.col(ROW).alias("doc_id"), "text"), items, max_errors)
    hit = scratch.write(found.select(F.col("doc_id").alias(ROW)).distinct(), "hit")
    hit = F.broadcast(hit) if hit.count() <= BROADCAST_IDS else hit
    return rows.join(hit, ROW, "left_anti").select(*docs.columns)

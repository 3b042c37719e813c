"""Quality rules: repetition by suffix arrays over characters.

Every window of ``min_repeat`` code points is named by a rolling hash; only text inside a window that occurs again in its row can
be part of a repeat, so suffixes are sorted there alone. They are sorted by prefix doubling, many texts at once and only
those that are still tied; the ranks kept at each doubling give the longest common prefix of neighbours in the order. A run of
neighbours whose common prefixes are no shorter than some length is an interval of the array, whose suffixes begin with one
repeated substring; the deepest interval that a suffix stands in has the larger of the common prefixes with its two neighbours as its length, and
that is the longest repeat that begins there. The union of the repeats' spans is the covered part of a text, in code points. A text is
rejected if the covered fraction or the longest repeat is over its limit.

Defined results: a null, empty or wordless text has zero words and fails the base rule; repeated rows are judged
each; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenbox.llm.bytewords import Words, _pow, mix64, slices, text_bytes

MIN_WORDS = 50
#: code points of the shortest repeat that counts
MIN_REPEAT = 40
#: largest fraction (per cent) of a text's code points inside repeats
MAX_COVERED = 45
#: longest repeat, in per cent of the text's code points
MAX_REPEAT = 30
_SYMBOLS = np.isin(np.arange(256), np.frombuffer(b"#*$%&|<>", np.uint8))


def _ranks(keys: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(order, dense rank in sorted order, tied flag in sorted order) of rows by several keys."""
    order = np.lexsort(keys[::-1])
    same = np.ones(max(len(order) - 1, 0), bool)
    for key in keys:
        same &= key[order][1:] == key[order][:-1]
    fresh = np.concatenate([[True], ~same]) if len(order) else np.zeros(0, bool)
    tied = np.zeros(len(order), bool)
    tied[1:] |= same
    tied[:-1] |= same
    return order, np.flatnonzero(fresh)[np.cumsum(fresh) - 1] if len(order) else np.zeros(0, np.int64), tied


def longest_repeats(symbols: np.ndarray, row: np.ndarray, end: np.ndarray | None = None) -> np.ndarray:
    """For every position, the length of the longest substring from there that occurs again in its row.

    symbols: any integers; row: non-decreasing row numbers; end: where the substrings from a position must stop, its row's end if not given.
    """
    n = len(symbols)
    if not n:
        return np.zeros(0, np.int64)
    order, dense, tied = _ranks([row, symbols])
    rank = np.empty(n, np.int64)
    rank[order] = dense
    suffixes = order.copy()
    active = np.zeros(n, bool)
    active[order] = tied
    end = np.searchsorted(row, row, "right") if end is None else end
    left = end - np.arange(n)
    levels, k = [rank], 1
    while active.any():
        at = np.flatnonzero(active)
        # what ends comes before what goes on, and different ends are never tied
        more = np.where(left[at] > k, levels[-1][np.minimum(at + k, n - 1)] + n + 1, end[at])
        by, dense, tied = _ranks([(levels[-1][at] << 32) | more])
        moved = at[by]
        rank = levels[-1].copy()
        # a tied group keeps its place in the order: its first rank and the place inside the group
        first = np.concatenate([[0], np.flatnonzero(np.diff(levels[-1][moved])) + 1])
        begin = np.repeat(first, np.diff(np.concatenate([first, [len(moved)]])))
        rank[moved] = levels[-1][moved] + dense - begin
        suffixes[levels[-1][moved] + np.arange(len(moved)) - begin] = moved
        levels.append(rank)
        active[:] = False
        active[moved] = tied
        k *= 2
    a, b = suffixes[:-1].copy(), suffixes[1:].copy()
    common = np.zeros(n - 1, np.int64)
    live = row[a] == row[b]
    for level in range(len(levels) - 1, -1, -1):
        span = 1 << level
        fits = live & (left[a] - common >= span) & (left[b] - common >= span)
        at = np.flatnonzero(fits)
        x, y = a[at] + common[at], b[at] + common[at]
        equal = levels[level][x] == levels[level][y]
        common[at[equal]] += span
    best = np.zeros(n, np.int64)
    np.maximum.at(best, a, common)
    np.maximum.at(best, b, common)
    return best


def repeated_text(points: np.ndarray, edges: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray]:
    """(flags of the code points inside a repeat of at least ``least``, the longest repeat of each row) of rows of code points."""
    n, rows = len(points), len(edges) - 1
    flags, longest = np.zeros(n, bool), np.zeros(rows, np.int64)
    row = np.repeat(np.arange(rows), np.diff(edges))
    at = np.flatnonzero(edges[row + 1] - np.arange(n) >= least) if n >= least else np.zeros(0, np.int64)
    if len(at) < 2:
        return flags, longest
    up, down = _pow(n + 1)
    with np.errstate(over="ignore"):
        sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum((points.astype(np.uint64) + np.uint64(1)) * up[:n], dtype=np.uint64)])
        names = mix64((sums[at + least] - sums[at]) * down[at] + mix64(row[at].astype(np.uint64)))
    order = np.argsort(names)
    same = names[order][1:] == names[order][:-1]
    twice = np.zeros(len(at), bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    at = at[twice]
    if not len(at):
        return flags, longest
    steps = np.bincount(at, minlength=n + 1) - np.bincount(at + least, minlength=n + 1)
    inside = np.flatnonzero(np.cumsum(steps[:n]) > 0)
    # windows that follow on each other are one stretch; a repeat does not leave its stretch or its row
    broken = np.concatenate([[True], (np.diff(inside) > 1) | (np.diff(row[inside]) > 0)])
    begins = np.flatnonzero(broken)
    ends = np.repeat(np.append(begins[1:], len(inside)), np.diff(np.append(begins, len(inside))))
    found = longest_repeats(points[inside].astype(np.int64), row[inside], ends)
    np.maximum.at(longest, row[inside], np.where(found >= least, found, 0))
    flags[inside] = _covered(found, least)
    return flags, longest


def _covered(repeats: np.ndarray, least: int) -> np.ndarray:
    """Positions inside a repeat of at least ``least``."""
    n = len(repeats)
    at = np.flatnonzero(repeats >= least)
    reach = np.zeros(n + 1, np.int64)
    reach[at] = at + repeats[at]
    return np.maximum.accumulate(reach)[:n] > np.arange(n)


def _counts_by_row(values: np.ndarray, edges: np.ndarray) -> np.ndarray:
    sums = np.concatenate([[0], np.cumsum(values, dtype=np.int64)])
    return sums[edges[1:]] - sums[edges[:-1]]


def _in_row_repeat(hashes: np.ndarray, row: np.ndarray) -> np.ndarray:
    """Flags of the entries whose hash occurs twice or more in their row, the first included."""
    order = np.lexsort((hashes, row))
    same = (hashes[order][1:] == hashes[order][:-1]) & (row[order][1:] == row[order][:-1])
    flags = np.zeros(len(hashes), bool)
    flags[order[1:][same]] = True
    flags[order[:-1][same]] = True
    return flags


def _later_copies(hashes: np.ndarray, row: np.ndarray) -> np.ndarray:
    """Flags of the entries that equal an earlier one of their row."""
    order = np.lexsort((np.arange(len(hashes)), hashes, row))
    flags = np.zeros(len(hashes), bool)
    flags[order[1:][(hashes[order][1:] == hashes[order][:-1]) & (row[order][1:] == row[order][:-1])]] = True
    return flags


def measure(raw: np.ndarray, offsets: np.ndarray, min_repeat: int = MIN_REPEAT) -> dict[str, np.ndarray]:
    """The measures of every row of a slice."""
    offsets = offsets - offsets[0]
    words = Words(raw, offsets, lower=False)
    n = words.rows
    points = np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])
    size = points[words.end] - points[words.start]
    windows, at = words.windows(3)
    twice = _in_row_repeat(windows, words.row[at])
    inside = np.zeros(len(words.start) + 3, bool)
    for j in range(3):
        inside[at[twice] + j] = True
    # lines: cut at newlines and row edges
    breaks = np.unique(np.concatenate([np.flatnonzero(raw == 10), offsets[1:] - 1])) if len(raw) else np.zeros(0, np.int64)
    ends = np.where(raw[breaks] == 10, breaks, breaks + 1) if len(raw) else breaks
    starts = np.concatenate([[0], breaks[:-1] + 1]) if len(breaks) else breaks
    ends = np.maximum(ends, starts)
    wordy = np.searchsorted(words.start, ends) > np.searchsorted(words.start, starts) if len(breaks) else np.zeros(0, bool)
    starts, ends = starts[wordy], ends[wordy]
    line_row = np.searchsorted(offsets, starts, "right") - 1
    copies = _later_copies(words.span_hash(starts, ends), line_row)
    out = {
        "n_words": words.per_row.astype(np.int64),
        "word_chars": _counts_by_row(size, words.first),
        "n_symbols": _counts_by_row(_SYMBOLS[raw], offsets),
        "n_dup_lines": np.bincount(line_row[copies], minlength=n),
        "n_repeat_words": _counts_by_row(inside[: len(words.start)], words.first),
    }
    places = points[offsets]
    text = np.frombuffer(raw.tobytes().decode("utf-8", "surrogatepass").encode("utf-32-le", "surrogatepass"), "<u4")
    flags, longest = repeated_text(text, places, min_repeat)
    return out | {"text_chars": np.diff(places), "covered_chars": _counts_by_row(flags, places), "longest_repeat": longest}


_MEASURES = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "text_chars", "covered_chars", "longest_repeat"]


def repetition_measures(docs: DataFrame, min_repeat: int = MIN_REPEAT, carry: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The carried columns of ``docs`` (which also has text) and the measures."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw, offsets = text_bytes(batch.column("text"))
            for a, b in slices(offsets):
                found = measure(raw[offsets[a] : offsets[b]], offsets[a : b + 1], min_repeat)
                own = [batch.column(c).slice(a, b - a) for c in carry]
                yield pa.RecordBatch.from_arrays([*own, *[pa.array(found[m].astype(np.int64)) for m in _MEASURES]], [*[f"_{i}" for i in range(len(carry))], *_MEASURES])

    kinds = dict(docs.dtypes)
    schema = ", ".join([*[f"`_{i}` {kinds[c]}" for i, c in enumerate(carry)], *[f"{m} long" for m in _MEASURES]])
    return docs.select(*dict.fromkeys([*carry, "text"])).mapInArrow(run, schema)


def verdict(min_words: int = MIN_WORDS, max_covered: int = MAX_COVERED, max_repeat: int = MAX_REPEAT):
    """(base_failed, kept) as columns over the measures; whole-number comparisons only."""
    base = (F.col("n_words") < min_words) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    repeats = (100 * F.col("covered_chars") > max_covered * F.col("text_chars")) | (100 * F.col("longest_repeat") > max_repeat * F.col("text_chars"))
    return base, ~base & ~repeats


def judge_documents(docs: DataFrame, min_repeat: int = MIN_REPEAT, **limits: int) -> DataFrame:
    """doc_id, the measures, base_failed and kept of every row."""
    base, kept = verdict(**limits)
    measured = repetition_measures(docs, min_repeat).withColumnRenamed("_0", "doc_id")
    return measured.select("*", base.alias("base_failed"), kept.alias("kept"))


def keep_good_documents(docs: DataFrame, min_repeat: int = MIN_REPEAT, **limits: int) -> DataFrame:
    """The rows of ``docs`` that the rules keep, with their columns."""
    _, kept = verdict(**limits)
    carry = tuple(docs.columns)
    good = repetition_measures(docs, min_repeat, carry).where(kept)
    return good.select(*[F.col(f"_{i}").alias(c) for i, c in enumerate(carry)])

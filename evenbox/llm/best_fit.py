"""Best-fit packing by size classes.

Documents are cut into pieces of at most ``capacity`` tokens. Pieces and gaps both have sizes in
1..capacity, so a range-sorted corpus is described by how many pieces there are of each size: at most
``capacity`` numbers, whatever the corpus. The plan takes the next size downwards, finds by a
successor search the smallest gap that holds it, gives the pieces of that size to the sequences of that
gap by rank, moves those sequences to their new gap, and repeats until the size is used up; what fits
nowhere opens sequences. That is best-fit-decreasing for all pieces at once. The plan has a
row for each (size, run of ranks, run of sequences), a few thousand in all, and is made on the driver: sweeps over tables of
pieces and gaps would need a round of jobs for each of up to ``capacity`` sizes to pack as tightly. The pieces find their places in
parallel: a piece of a size and rank lies in exactly one run of the plan, found by binary search.

Ranks come from a range sort by (size, document, piece): each task numbers its pieces of a size, and
sorted tasks share a size only at their edges, so the counts to add up are one row for each task and size.

Defined results: a null or empty text is one piece of the end id; repeated rows are packed each; an empty
table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenbox.llm.fast_bpe import encoder
from evenbox.llm.scratch import Scratch, shuffle_width

CAPACITY = 2048
_PIECE = "doc_id long, piece int, start long, length int, ids_crc32 long"


def cut_pieces(docs: DataFrame, vocabulary: str = "word_bpe_49k.json", end_id: int = 0, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 (and ids, little-endian unsigned 32-bit)."""
    names = [x.split()[0] for x in _PIECE.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = encoder(vocabulary)
        end = np.array([end_id], "<u4")
        for batch in batches:
            for row in range(0, batch.num_rows, 512):
                part = batch.slice(row, 512)
                out: list[list] = [[] for _ in range(6)]
                for doc, ids in zip(part.column(0).to_pylist(), bpe.encode_many(part.column(1).to_pylist()), strict=True):
                    ids = np.concatenate([np.frombuffer(ids, bpe.dtype).astype("<u4"), end])
                    for number, start in enumerate(range(0, len(ids), capacity)):
                        raw = ids[start : start + capacity].tobytes()
                        for column, value in zip(out, (doc, number, start, len(raw) // 4, zlib.crc32(raw), raw), strict=True):
                            column.append(value)
                kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.binary()]
                arrays = [pa.array(x, k) for x, k in zip(out, kinds, strict=True)]
                yield pa.RecordBatch.from_arrays(arrays if with_ids else arrays[:5], [*names, "ids"] if with_ids else names)

    return docs.select("doc_id", "text").mapInArrow(run, _PIECE + ", ids binary" * with_ids)


def plan_packing(counts: np.ndarray, capacity: int = CAPACITY) -> dict[str, np.ndarray]:
    """Best-fit-decreasing over size classes.

    counts[s]: pieces of size s. Returns the plan's columns: size, rank (first of the run), n (pieces),
    sequence (first), each (pieces of the run in each sequence), offset (of the first piece in a sequence).
    """
    rows: list[tuple[int, int, int, int, int, int]] = []
    #: gap -> runs (first sequence, sequences) that have it; ``open_gaps`` is sorted
    runs: dict[int, deque[tuple[int, int]]] = {}
    open_gaps: list[int] = []
    made = 0

    def put(gap: int, first: int, n: int) -> None:
        if gap and n:
            if gap not in runs:
                runs[gap] = deque()
                insort(open_gaps, gap)
            runs[gap].append((first, n))

    for size in range(capacity, 0, -1):
        left, rank = int(counts[size]), 0
        while left:
            at = bisect_left(open_gaps, size)
            if at < len(open_gaps):
                gap = open_gaps[at]
                first, n = runs[gap].popleft()
                if not runs[gap]:
                    del runs[gap], open_gaps[at]
            else:
                gap, n = capacity, -(-left // (capacity // size))
                first, made = made, made + n
            each = gap // size
            full = min(n, left // each)
            if full:
                rows.append((size, rank, full * each, first, each, capacity - gap))
                put(gap - each * size, first, full)
                rank, left = rank + full * each, left - full * each
            if full < n:
                rest = left if full < n and left < each else 0
                if rest:
                    rows.append((size, rank, rest, first + full, rest, capacity - gap))
                    put(gap - rest * size, first + full, 1)
                    rank, left = rank + rest, left - rest
                put(gap, first + full + bool(rest), n - full - bool(rest))
    table = np.array(rows, np.int64).reshape(-1, 6)
    return dict(zip(("size", "rank", "n", "sequence", "each", "offset"), table.T, strict=True))


def _ranked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Sorted pieces with their task and their number among the task's pieces of the same length."""
    from pyspark import TaskContext

    task, last, seen = TaskContext.get().partitionId(), -1, 0
    for batch in batches:
        length = batch.column("length").to_numpy()
        if not len(length):
            continue
        change = np.flatnonzero(np.diff(length, prepend=last))
        begins = np.zeros(len(length), np.int64)
        begins[change] = change
        local = np.arange(len(length)) - np.maximum.accumulate(begins)
        same = len(length) if not len(change) else change[0]
        local[:same] += seen
        last, seen = int(length[-1]), int(local[-1]) + 1
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.full(len(length), task, np.int32)), pa.array(local)], [*batch.schema.names, "task", "local"])


def place(pieces: DataFrame, scratch: Scratch, capacity: int = CAPACITY) -> DataFrame:
    """``pieces`` (doc_id, piece, start, length, ...) with sequence_id and offset."""
    spark = pieces.sparkSession
    cut = scratch.write(pieces, "cut")
    names = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in cut.schema)
    ordered = cut.repartitionByRange(shuffle_width(spark), F.col("length").desc(), "doc_id", "piece", "start").sortWithinPartitions(F.col("length").desc(), "doc_id", "piece", "start")
    ranked = scratch.write(ordered.mapInArrow(_ranked, f"{names}, task int, local long"), "ranked")
    tally = ranked.groupBy("task", "length").count().toArrow()  # tasks + capacity rows at most: tasks are sorted by length
    task, length, n = (tally[c].to_numpy() for c in ("task", "length", "count"))
    by = np.lexsort((task, -length))
    task, length, n = task[by], length[by], n[by]
    counts = np.zeros(capacity + 1, np.int64)
    np.add.at(counts, length, n)
    before = np.cumsum(n) - n
    opens = np.diff(length, prepend=-1) != 0
    base = before - np.maximum.accumulate(np.where(opens, before, 0))
    bases = spark.sparkContext.broadcast({(int(t), int(s)): int(b) for t, s, b in zip(task, length, base, strict=True)})
    plan = plan_packing(counts, capacity)
    order = np.lexsort((plan["rank"], plan["size"]))
    plan = spark.sparkContext.broadcast({k: v[order] for k, v in plan.items()})  # bounded by the capacity

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p, base_of = plan.value, bases.value
        span = np.int64(1) << 40
        keys = p["size"] * span + p["rank"]
        for batch in batches:
            size = batch.column("length").to_numpy().astype(np.int64)
            where = batch.column("task").to_numpy().astype(np.int64) * (capacity + 1) + size
            pairs, inverse = np.unique(where, return_inverse=True)
            known = np.array([base_of[divmod(int(x), capacity + 1)] for x in pairs], np.int64)
            rank = batch.column("local").to_numpy() + known[inverse] if len(size) else np.zeros(0, np.int64)
            at = np.searchsorted(keys, size * span + rank, "right") - 1
            within = rank - p["rank"][at]
            each = p["each"][at]
            columns = [c for c, name in zip(batch.columns, batch.schema.names, strict=True) if name not in ("task", "local")]
            kept = [name for name in batch.schema.names if name not in ("task", "local")]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(p["sequence"][at] + within // each), pa.array(p["offset"][at] + within % each * size)], [*kept, "sequence_id", "offset"])

    return ranked.mapInArrow(run, f"{names}, sequence_id long, offset long")


def pack_documents(docs: DataFrame, vocabulary: str = "word_bpe_49k.json", end_id: int = 0, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """Pack whole documents; one row for each piece."""
    scratch = Scratch(docs.sparkSession, "packing")
    placed = place(cut_pieces(docs, vocabulary, end_id, capacity, with_ids), scratch, capacity)
    return placed.withColumn("length", F.col("length").cast("long"))

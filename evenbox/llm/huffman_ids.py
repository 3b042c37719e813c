"""Token-id files: canonical length-limited Huffman blocks with bit-offset checkpoints.

The id counts of the whole corpus give one code. Documents stand in ascending ``doc_id`` order
(null first) in shards; a shard is cut into blocks that decode on their own. A block has the bits
of its ids, the place of each document and a bit offset for every ``stride`` ids, so a reader can
start at any checkpoint, and all checkpoints of a block are decoded side by side, one table lookup
for each id. On disk: ``ids`` (intermediate, dropped), ``blocks`` and ``code``, Parquet tables whose
rows are the blocks and the code, written with Spark's own commit protocol.

Defined results: a null or empty text is one document of the end id alone; repeated rows and repeated
ids are all kept, rows of one doc_id in any order; an empty table gives an empty file; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from evenbox.llm.fast_bpe import encoder
from evenbox.llm.scratch import Scratch, shuffle_width

MAX_BITS = 16
STRIDE = 64
BLOCK_IDS = 1 << 16
ENCODE_ROWS = 2048


# --- the code -----------------------------------------------------------------------------------


def code_lengths(counts: np.ndarray, max_bits: int = MAX_BITS) -> np.ndarray:
    """Optimal code lengths of at most ``max_bits`` by package-merge; 0 where the count is 0."""
    used = np.flatnonzero(counts)
    lengths = np.zeros(len(counts), np.uint8)
    if len(used) > 1 << max_bits:
        raise ValueError(f"{len(used)} symbols need codes of more than {max_bits} bits")
    if len(used) <= 1:
        lengths[used] = 1
        return lengths
    order = used[np.argsort(counts[used], kind="stable")]
    coins = counts[order].astype(np.float64)
    n, merged, is_coin = len(coins), coins, []
    is_coin.append(np.ones(n, bool))
    for _ in range(max_bits - 1):
        pairs = merged[: len(merged) // 2 * 2].reshape(-1, 2).sum(axis=1)
        both = np.concatenate([coins, pairs])
        by = np.argsort(both, kind="stable")
        merged = both[by]
        is_coin.append(by < n)
    take = 2 * (n - 1)
    deep = np.zeros(n, np.int64)
    for level in reversed(is_coin):
        coins_here = int(level[:take].sum())
        deep[:coins_here] += 1
        take = 2 * (take - coins_here)
    lengths[order] = deep
    return lengths


def canonical_codes(lengths: np.ndarray) -> np.ndarray:
    """Code words in canonical order: by length, then by symbol."""
    codes = np.zeros(len(lengths), np.uint32)
    order = np.lexsort((np.arange(len(lengths)), lengths))
    order = order[lengths[order] > 0]
    if len(order):
        widths = lengths[order].astype(np.int64)
        spans = np.left_shift(np.int64(1), widths.max() - widths)
        begins = np.concatenate([[0], np.cumsum(spans)[:-1]])
        codes[order] = begins >> (widths.max() - widths)
    return codes


class Codec:
    """Packs id arrays to bits and back; made from code lengths alone."""

    def __init__(self, lengths: np.ndarray):
        self.lengths = np.asarray(lengths, np.uint8)
        self.codes = canonical_codes(self.lengths)
        self.width = int(self.lengths.max(initial=1))
        used = np.flatnonzero(self.lengths)
        self.symbol = np.zeros(1 << self.width, np.uint32)
        self.step = np.zeros(1 << self.width, np.uint8)
        order = used[np.lexsort((used, self.lengths[used]))]
        spans = 1 << (self.width - self.lengths[order].astype(np.int64))
        full = int(spans.sum())
        self.symbol[:full] = np.repeat(order, spans)
        self.step[:full] = np.repeat(self.lengths[order], spans)

    def pack(self, ids: np.ndarray, stride: int = STRIDE) -> tuple[bytes, np.ndarray]:
        """(bits, bit offset of every stride-th id)."""
        if not len(ids):
            return b"", np.zeros(0, np.uint32)
        widths = self.lengths[ids].astype(np.int64)
        if not widths.all():
            raise ValueError("an id has no code")
        ends = np.cumsum(widths)
        begins = ends - widths
        size = int(ends[-1] + 7) // 8
        word = self.codes[ids].astype(np.int64) << (32 - widths - (begins & 7))
        sums = np.bincount(begins >> 3, weights=word, minlength=size).astype(np.int64)
        out = np.zeros(size + 4, np.int64)
        for k in range(4):
            out[k : k + size] += (sums >> (24 - 8 * k)) & 255
        return out[:size].astype(np.uint8).tobytes(), begins[::stride].astype(np.uint32)

    def unpack(self, bits: bytes, marks: np.ndarray, n: int, stride: int = STRIDE) -> np.ndarray:
        """The n ids of a block; every checkpoint is a lane and all lanes move together."""
        raw = np.concatenate([np.frombuffer(bits, np.uint8), np.zeros(4, np.uint8)]).astype(np.uint32)
        window = (raw[:-3] << 24) | (raw[1:-2] << 16) | (raw[2:-1] << 8) | raw[3:]
        at = marks.astype(np.int64)
        out = np.empty((len(at), stride), np.uint32)
        for k in range(stride):
            peek = (window[at >> 3] << (at & 7).astype(np.uint32)) >> np.uint32(32 - self.width)
            out[:, k] = self.symbol[peek]
            at = np.minimum(at + self.step[peek], 8 * len(bits))
        return out.reshape(-1)[:n]


# --- writing ------------------------------------------------------------------------------------


def encode_documents(docs: DataFrame, vocabulary: str, end_id: int) -> DataFrame:
    """doc_id, n_tokens, ids: the ids of each whole text and the end id, little-endian bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = encoder(vocabulary)
        end = np.array([end_id], bpe.dtype).tobytes()
        for batch in batches:
            for row in range(0, batch.num_rows, ENCODE_ROWS):
                part = batch.slice(row, ENCODE_ROWS)
                ids = [x + end for x in bpe.encode_many(part.column(1).to_pylist())]
                counts = pa.array([len(x) // bpe.dtype.itemsize for x in ids], pa.int64())
                yield pa.RecordBatch.from_arrays([part.column(0), counts, pa.array(ids, pa.binary())], ["doc_id", "n_tokens", "ids"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, ids binary")


def count_ids(encoded: DataFrame, size: int, wide: str) -> np.ndarray:
    """Corpus counts by id. Each task adds up its own rows; ``size`` rows at most reach the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(size, np.int64)
        for batch in batches:
            for ids in batch.column(0):
                total += np.bincount(np.frombuffer(ids.as_buffer(), wide), minlength=size)
        used = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(used), pa.array(total[used])], ["id", "n"])

    counted = encoded.select("ids").mapInArrow(run, "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))
    found = counted.toArrow()
    counts = np.zeros(size, np.int64)
    counts[found["id"].to_numpy()] = found["n"].to_numpy()
    return counts


_BLOCK = "shard int, block int, start long, n_ids int, bits binary, marks binary, doc_ids array<long>, numbers array<long>, sizes array<int>, whole boolean"


def _blocks(lengths: np.ndarray, wide: str, block_ids: int, stride: int):
    """Shard rows in order -> blocks. A document that does not fit in what is left of a block begins
    the next; only one longer than a block is cut, into blocks of its own. Memory is one block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        codec, shard = Codec(lengths), TaskContext.get().partitionId()
        lists = {"doc_ids": pa.list_(pa.int64()), "numbers": pa.list_(pa.int64()), "sizes": pa.list_(pa.int32())}
        schema = pa.schema([("shard", pa.int32()), ("block", pa.int32()), ("start", pa.int64()), ("n_ids", pa.int32()), ("bits", pa.binary()), ("marks", pa.binary()), *lists.items(), ("whole", pa.bool_())])
        block, start, number = 0, 0, 0

        def made(held: list, whole: bool) -> pa.RecordBatch:
            nonlocal block, start
            ids = np.concatenate([x for _, _, x in held])
            bits, marks = codec.pack(ids, stride)
            row = {"shard": shard, "block": block, "start": start, "n_ids": len(ids), "bits": bits, "marks": marks.astype("<u4").tobytes(), "doc_ids": [d for d, _, _ in held], "numbers": [k for _, k, _ in held], "sizes": [len(x) for _, _, x in held], "whole": whole}
            block, start = block + 1, start + len(ids)
            return pa.RecordBatch.from_pylist([row], schema)

        held, n = [], 0
        for batch in batches:
            for doc, raw in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = np.frombuffer(raw.as_buffer(), wide)
                if held and n + len(ids) > block_ids:
                    yield made(held, True)
                    held, n = [], 0
                if len(ids) > block_ids:
                    for at in range(0, len(ids), block_ids):
                        yield made([(doc, number, ids[at : at + block_ids])], False)
                else:
                    held.append((doc, number, ids))
                    n += len(ids)
                number += 1
        if held:
            yield made(held, True)

    return run


def write_ids(docs: DataFrame, scratch: Scratch, vocabulary: str = "byte_bpe_50k.json", end_id: int = 2, max_bits: int = MAX_BITS, block_ids: int = BLOCK_IDS, stride: int = STRIDE) -> None:
    """Encode ``docs`` (doc_id, text) and write the tables ``blocks`` and ``code`` below ``scratch``."""
    bpe = encoder(vocabulary)
    encoded = scratch.write(encode_documents(docs, vocabulary, end_id), "ids")
    size = max(bpe.size, end_id + 1)
    lengths = code_lengths(count_ids(encoded, size, bpe.dtype.str), max_bits)
    spark = docs.sparkSession
    code = spark.createDataFrame(pa.table({"lengths": [lengths.tobytes()], "stride": [stride]}))
    scratch.write(code, "code")
    ordered = encoded.select("doc_id", "ids").repartitionByRange(shuffle_width(spark), "doc_id").sortWithinPartitions("doc_id")
    ordered.mapInArrow(_blocks(lengths, bpe.dtype.str, block_ids, stride), _BLOCK).write.mode("overwrite").option("compression", "uncompressed").parquet(scratch.at("blocks"))
    scratch.drop("ids")


# --- reading ------------------------------------------------------------------------------------


def read_ids(spark: SparkSession, scratch: Scratch, with_ids: bool = False, blocks: Column | None = None) -> DataFrame:
    """One row for each run of a document in a block (of those chosen by a condition on ``blocks``): shard, number (of the document in the shard),
    doc_id, begin (ids before the run in the shard), n_ids, crc (of its ids as unsigned 32-bit
    integers), whole (the run is the document), and the ids if asked for."""
    head = scratch.read("code").first()
    lengths, stride = np.frombuffer(head["lengths"], np.uint8), head["stride"]
    schema = "shard int, number long, doc_id long, begin long, n_ids long, crc long, whole boolean" + ", ids array<int>" * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec(lengths)
        names = [x.split()[0] for x in schema.split(", ")]
        for batch in batches:
            for row in batch.to_pylist():
                ids = codec.unpack(row["bits"], np.frombuffer(row["marks"], "<u4"), row["n_ids"], stride).astype("<u4")
                sizes = np.array(row["sizes"], np.int64)
                begins = np.cumsum(sizes) - sizes
                runs = [ids[b : b + s] for b, s in zip(begins, sizes, strict=True)]
                n = len(runs)
                columns = [pa.array([row["shard"]] * n, pa.int32()), pa.array(row["numbers"], pa.int64()), pa.array(row["doc_ids"], pa.int64()), pa.array(begins + row["start"]), pa.array(sizes), pa.array([zlib.crc32(x.tobytes()) for x in runs], pa.int64()), pa.array([row["whole"]] * n)]
                if with_ids:
                    columns.append(pa.array([x.astype(np.int32) for x in runs], pa.list_(pa.int32())))
                yield pa.RecordBatch.from_arrays(columns, names)

    stored = scratch.read("blocks", _BLOCK)
    return (stored if blocks is None else stored.where(blocks)).mapInArrow(run, schema)


def _gf2_shift(crc: int, n: int) -> int:
    """The CRC-32 register after n zero bytes, by squaring the one-bit operator."""

    def times(matrix: list[int], vector: int) -> int:
        total, k = 0, 0
        while vector:
            if vector & 1:
                total ^= matrix[k]
            vector, k = vector >> 1, k + 1
        return total

    operator = [0xEDB88320] + [1 << k for k in range(31)]
    for _ in range(3):
        operator = [times(operator, x) for x in operator]
    while n:
        if n & 1:
            crc = times(operator, crc)
        operator, n = [times(operator, x) for x in operator], n >> 1
    return crc


def joined_crc(parts: list[tuple[int, int]]) -> int:
    """CRC-32 of a whole from (crc, bytes) of its parts in order."""
    crc = parts[0][0]
    for more, size in parts[1:]:
        crc = _gf2_shift(crc, size) ^ more
    return crc


def _joined(runs: pd.DataFrame) -> pd.DataFrame:
    """The runs of one document longer than a block, as one row."""
    runs = runs.sort_values("begin")
    crc = joined_crc(list(zip(runs["crc"], 4 * runs["n_ids"], strict=True)))
    return runs.head(1).assign(n_ids=int(runs["n_ids"].sum()), crc=crc)


def token_file_digest(docs: DataFrame, vocabulary: str = "byte_bpe_50k.json", end_id: int = 2) -> DataFrame:
    """Write the file, read it back: doc_id, start, n_tokens, ids_crc32 of each document."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "ids")
    write_ids(docs, scratch, vocabulary, end_id)
    shards = scratch.read("blocks", _BLOCK).groupBy("shard").agg(F.sum(F.col("n_ids").cast("long")).alias("n"))
    ahead, base = 0, []
    for shard, n in sorted((r["shard"], r["n"]) for r in shards.collect()):  # a row for each shard
        base.append((shard, ahead))
        ahead += n
    runs = read_ids(spark, scratch, blocks=F.col("whole"))
    split = read_ids(spark, scratch, blocks=~F.col("whole")).groupBy("shard", "number").applyInPandas(_joined, runs.schema)
    bases = F.broadcast(spark.createDataFrame(base, "shard int, base long"))  # a row for each shard
    every = runs.unionByName(split).join(bases, "shard")
    return every.select("doc_id", (F.col("begin") + F.col("base")).alias("start"), F.col("n_ids").alias("n_tokens"), F.col("crc").alias("ids_crc32"))

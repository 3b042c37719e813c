"""Exact n-gram Jaccard join on a token-group matrix.

A document is its set of distinct k-word shingles (64-bit hashes); two documents link when
``den * |intersection| >= num * |union|``. Equal sets are one representative from the start.

1. Similar representatives are sorted by a min-hash into groups of at most ``GROUP`` and linked
   inside their group; that joins most near copies cheaply and loses nothing, for step 2 is exact.
2. Every entity (a component of step 1, or a group of the rest) has a row of the token-group matrix: the
   union of its members' prefix shingles in a global order, rare first. A linked pair shares a prefix
   shingle, so only entities that share one can link. They meet group against group; a query document's
   overlap with a group's union bounds its overlap with every member, and only groups that can reach the
   threshold are opened. Pairs already in one component are never compared, so a large
   group of copies costs no quadratic work once joined.

The order comes from shingle counts of all documents in a table of fixed size; any order gives the
same links, a good one fewer candidates.

Defined results: null, empty and wordless texts have n_shingles 0 and are alone; fewer than k words make one
shingle of the whole sequence; every row is linked by its own text, whether its doc_id is null or repeated; a component of null
doc_ids alone has a null component_id; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenbox.llm.bytewords import Words, combine, mix64, slices, text_bytes
from evenbox.llm.components import connected_components
from evenbox.llm.scratch import ROW, Scratch, numbered, shuffle_width

GROUP = 32
#: groups of documents without a link hold sizes within one of so many steps of a factor e, each
SIZE_STEPS = 50
SKETCH = 4
CELLS = 1 << 20
_STRIPE = 1 << 14
#: a set of ids up to this size goes to every executor, a larger one is joined by shuffle
BROADCAST_IDS = 2_000_000


def shingle_sets(raw: np.ndarray, offsets: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, n of each row): the distinct shingles of the rows of a slice, sorted in each row."""
    words = Words(raw, offsets, lower=True)
    shingles, at = words.windows(k)
    row = words.row[at] if len(at) else np.zeros(0, np.int64)
    short = np.flatnonzero((words.per_row > 0) & (words.per_row < k))
    if len(short):
        hashes = words.word_hash()
        whole = [combine([hashes[[w]] for w in range(words.first[r], words.first[r + 1])])[0] for r in short]
        shingles, row = np.concatenate([shingles, np.array(whole, np.uint64)]), np.concatenate([row, short])
    order = np.lexsort((shingles, row))
    shingles, row = shingles[order], row[order]
    fresh = np.ones(len(row), bool)
    fresh[1:] = (shingles[1:] != shingles[:-1]) | (row[1:] != row[:-1])
    return shingles[fresh], np.bincount(row[fresh], minlength=words.rows)


def _each_slice(batch: pa.RecordBatch, column: int, k: int):
    raw, offsets = text_bytes(batch.column(column))
    for a, b in slices(offsets):
        yield (a, b, *shingle_sets(raw[offsets[a] : offsets[b]], offsets[a : b + 1], k))


def rarity_classes(docs: DataFrame, k: int) -> np.ndarray:
    """A class 0..255 for each of ``CELLS`` hash cells, growing with how often its shingles occur."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(CELLS, np.int64)
        for batch in batches:
            for *_, shingles, _ in _each_slice(batch, 0, k):
                total += np.bincount((shingles >> np.uint64(44)).astype(np.int64), minlength=CELLS)
        stripes = total.reshape(-1, _STRIPE)
        keep = np.flatnonzero(stripes.any(axis=1))
        yield pa.RecordBatch.from_arrays([pa.array(keep, pa.int32()), pa.array([stripes[s].tobytes() for s in keep], pa.binary())], ["stripe", "counts"])

    def add(rows: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: dict[int, np.ndarray] = {}
        for part in rows:
            for stripe, counts in zip(part["stripe"], part["counts"], strict=True):
                counts = np.frombuffer(counts, np.int64)
                held[stripe] = held[stripe] + counts if stripe in held else counts
        yield pd.DataFrame({"stripe": list(held), "counts": [x.tobytes() for x in held.values()]})

    schema = "stripe int, counts binary"
    parts = docs.select("text").mapInArrow(count, schema).repartition("stripe").mapInPandas(add, schema)
    total = np.zeros((CELLS // _STRIPE, _STRIPE), np.float64)
    for row in parts.collect():  # CELLS numbers in all
        total[row["stripe"]] += np.frombuffer(row["counts"], np.int64)
    total = total.reshape(-1)
    return np.minimum(255, np.log2(1 + total / max(total.mean(), 1)) * 8).astype(np.uint8)


def describe(docs: DataFrame, classes: np.ndarray, k: int, num: int, den: int) -> DataFrame:
    """doc_id, n, fp1, fp2 (names of the set), sketch (min-hashes), prefix (rarest shingles)."""
    shared = docs.sparkSession.sparkContext.broadcast(classes)
    salts = mix64(np.arange(1, SKETCH + 1, dtype=np.uint64))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rank = shared.value.astype(np.uint64)
        for batch in batches:
            for a, b, shingles, n in _each_slice(batch, 1, k):
                begins = np.cumsum(n) - n
                some = np.flatnonzero(n)
                names, minima = np.zeros((2, b - a), np.uint64), np.zeros((b - a, SKETCH), np.uint64)
                if len(some):
                    with np.errstate(over="ignore"):
                        for name, salt in zip(names, (np.uint64(0x51ED), np.uint64(0xA3C7)), strict=True):
                            name[some] = np.add.reduceat(mix64(shingles ^ salt), begins[some])
                        for j, salt in enumerate(salts):
                            minima[some, j] = np.minimum.reduceat(mix64(shingles ^ salt), begins[some])
                ordered = (rank[(shingles >> np.uint64(44)).astype(np.int64)] << np.uint64(56)) | (shingles & np.uint64((1 << 56) - 1))
                row = np.repeat(np.arange(b - a), n)
                ordered = ordered[np.lexsort((ordered, row))]
                length = np.where(n > 0, n - -(-num * n // den) + 1, 0)
                take = np.arange(len(row)) - begins[row] < length[row]
                prefix = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(length)]).astype(np.int32)), pa.array(ordered[take].view(np.int64)))
                sketch = pa.ListArray.from_arrays(pa.array(np.arange(0, (b - a) * SKETCH + 1, SKETCH, dtype=np.int32)), pa.array(minima.reshape(-1).view(np.int64)))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(n), pa.array(names[0].view(np.int64)), pa.array(names[1].view(np.int64)), sketch, prefix], ["doc_id", "n", "fp1", "fp2", "sketch", "prefix"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n long, fp1 long, fp2 long, sketch array<long>, prefix array<long>")


def _runs(size: int, tag: int, num: int, den: int):
    """Rows sorted by (mark, n, ...) -> members of groups of equal mark, at most ``size`` each; a set too large to
    link with the group's first begins the next."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task, last, group, filled, first = TaskContext.get().partitionId(), None, -1, 0, 0
        for batch in batches:
            groups = []
            for mark, n in zip(batch.column("mark").to_pylist(), batch.column("n").to_pylist(), strict=True):
                if mark != last or filled == size or num * n > den * first:
                    last, group, filled, first = mark, group + 1, 0, n
                filled += 1
                groups.append((tag << 58) | (task << 36) | group)
            yield pa.RecordBatch.from_arrays([pa.array(groups, pa.int64()), batch.column("doc_id")], ["g", "doc_id"])

    return run


def similar_groups(reps: DataFrame, j: int, size: int = GROUP, num: int = 80, den: int = 100) -> DataFrame:
    """(g, doc_id): representatives of one min-hash and close sizes side by side, cut into groups; range-sorted, so
    a mark that very many share is dealt over tasks."""
    rows = reps.select(F.col("sketch")[j].alias("mark"), "n", "doc_id")
    ordered = rows.repartitionByRange(shuffle_width(reps.sparkSession), "mark", "n", "doc_id").sortWithinPartitions("mark", "n", "doc_id")
    return ordered.mapInArrow(_runs(size, j, num, den), "g long, doc_id long")


def _bounded(rows: DataFrame, n: int) -> DataFrame:
    return F.broadcast(rows) if n <= BROADCAST_IDS else rows


class _Union:
    def __init__(self):
        self.up: dict = {}

    def find(self, x):
        while self.up.setdefault(x, x) != x:
            self.up[x] = x = self.up[self.up[x]]
        return x

    def join(self, a, b) -> None:
        self.up[self.find(a)] = self.find(b)


def _open(k: int, num: int, den: int):
    """Rows (left, right: lists of doc_id, comp, text; right null: left with itself) -> links.
    Links between documents already joined in the row are not looked for."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found: list[tuple[int, int]] = []
            for row in batch.to_pylist():
                sides = []
                for side in (row["left"], row["right"]):
                    texts = [x["text"].encode() for x in side or ()]
                    ends = np.cumsum([0, *map(len, texts)])
                    shingles, n = shingle_sets(np.frombuffer(b"".join(texts), np.uint8), ends, k)
                    sides.append(list(zip(side or (), np.split(shingles, np.cumsum(n)[:-1]), strict=False)))
                left, right = sides
                joined, alone = _Union(), row["right"] is None
                union = None if alone or len(right) < 3 else np.unique(np.concatenate([s for _, s in right]))
                for at, (x, a) in enumerate(left):
                    if not len(a):
                        continue
                    need = -(-num * len(a) // den)
                    if union is not None and int(np.isin(a, union, assume_unique=True, kind="sort").sum()) < need:
                        continue
                    for y, b in left[at + 1 :] if alone else right:
                        if num * max(len(a), len(b)) > den * min(len(a), len(b)) or joined.find(x["comp"]) == joined.find(y["comp"]):
                            continue
                        both = len(np.intersect1d(a, b, assume_unique=True))
                        if den * both >= num * (len(a) + len(b) - both):
                            joined.join(x["comp"], y["comp"])
                            found.append((x["doc_id"], y["doc_id"]))
            yield pa.RecordBatch.from_arrays([pa.array([p[i] for p in found], pa.int64()) for i in (0, 1)], ["a", "b"])

    return run


def link_groups(docs: DataFrame, members: DataFrame, pairs: DataFrame, scratch: Scratch, label: str, k: int, num: int, den: int) -> DataFrame:
    """Links (a, b) between the members (g, doc_id, comp) of paired groups (g1, g2; g2 null: inside g1)."""
    pairs = scratch.write(pairs, f"{label}-pairs")
    asked = pairs.select(F.col("g1").alias("g")).unionByName(pairs.where("g2 is not null").select(F.col("g2").alias("g"))).distinct()
    members = scratch.write(members.join(asked, "g", "left_semi"), f"{label}-members")
    ids = members.select("doc_id").distinct()
    texts = docs.select("doc_id", "text").join(_bounded(ids, ids.count()), "doc_id", "left_semi").dropDuplicates(["doc_id"])
    held = members.join(texts, "doc_id").groupBy("g").agg(F.collect_list(F.struct("doc_id", "comp", "text")).alias("held"))
    held = scratch.write(held, f"{label}-held")
    left = held.select(F.col("g").alias("g1"), F.col("held").alias("left"))
    right = held.select(F.col("g").alias("g2"), F.col("held").alias("right"))
    inside = pairs.where("g2 is null").join(left, "g1").select("left", F.lit(None).cast(right.schema["right"].dataType).alias("right"))
    across = pairs.where("g2 is not null").join(left, "g1").join(right, "g2").select("left", "right")
    links = scratch.write(inside.unionByName(across).mapInArrow(_open(k, num, den), "a long, b long"), f"{label}-links")
    scratch.drop(f"{label}-held", f"{label}-members", f"{label}-pairs")
    return links


def jaccard_components(docs: DataFrame, k: int = 5, num: int = 80, den: int = 100, group: int = GROUP) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable by links) of every row of ``docs``."""
    scratch = Scratch(docs.sparkSession, "jaccard-rows")
    rows = numbered(docs.select("doc_id", "text"), scratch)
    classes = scratch.write(row_components(rows, k, num, den, group), "classes").join(rows.select(ROW, "doc_id"), ROW)
    least = classes.groupBy("component").agg(F.min("doc_id").alias("component_id"))
    return classes.join(least, "component").select("doc_id", "n_shingles", "component_id")


def row_components(rows: DataFrame, k: int = 5, num: int = 80, den: int = 100, group: int = GROUP) -> DataFrame:
    """The number, n_shingles and component (smallest number reachable by links) of every ``numbered`` row."""
    classes = _components(rows.select(F.col(ROW).alias("doc_id"), "text"), k, num, den, group)
    return classes.select(F.col("doc_id").alias(ROW), "n_shingles", F.col("component_id").alias("component"))


def _components(docs: DataFrame, k: int, num: int, den: int, group: int) -> DataFrame:
    """doc_id, n_shingles, component_id of rows whose doc_ids are all different and not null."""
    spark = docs.sparkSession
    scratch = Scratch(spark, "jaccard")
    docs = docs.select("doc_id", "text")
    named = ["n", "fp1", "fp2"]
    sets = scratch.write(describe(docs, rarity_classes(docs, k), k, num, den), "sets")
    light = scratch.write(sets.select("doc_id", *named), "light")
    kinds = scratch.write(light.where("n > 0").groupBy(*named).agg(F.min("doc_id").alias("rep")), "kinds")
    reps = sets.join(kinds.select(F.col("rep").alias("doc_id")), "doc_id", "left_semi").dropDuplicates(["doc_id"])
    reps = scratch.write(reps, "reps")
    scratch.drop("sets")

    # step 1: inside groups of similar documents
    members = [similar_groups(reps, j, group, num, den) for j in (0, 1)]
    members = scratch.write(members[0].unionByName(members[1]).withColumn("comp", F.col("doc_id")), "similar")
    crowded = members.groupBy("g").count().where("count > 1").select(F.col("g").alias("g1"), F.lit(None).cast("long").alias("g2"))
    links = link_groups(docs, members, crowded, scratch, "near", k, num, den)
    first = scratch.write(connected_components(links, scratch, "first"), "first")

    # step 2: the token-group matrix over what is still apart
    width = first.groupBy("root").agg((F.floor((F.count("*") - 1) / group) + 1).alias("parts"))
    joined = first.join(width, "root").select(F.col("node").alias("doc_id"), F.col("root").alias("comp"), F.xxhash64(F.lit("component"), "root").alias("e"), F.xxhash64("root", F.pmod(F.xxhash64("node"), "parts")).alias("g"))
    lone = members.where(F.shiftrightunsigned("g", 58) == 0).join(first.select(F.col("node").alias("doc_id")), "doc_id", "left_anti").join(reps.select("doc_id", "n"), "doc_id")
    # the bound is as good as the sizes in a group are close
    lone = lone.withColumn("g", F.xxhash64("g", F.floor(F.log("n") * SIZE_STEPS))).select("doc_id", "comp", F.col("g").alias("e"), "g", "n")
    placed = joined.join(reps.select("doc_id", "n"), "doc_id").unionByName(lone)
    placed = scratch.write(placed, "placed")
    entities = scratch.write(placed.groupBy("e").agg(F.min("n").alias("low"), F.max("n").alias("high"), F.min("g").alias("g"), (F.max("g") > F.min("g")).alias("wide")), "entities")
    rows = reps.select("doc_id", F.explode("prefix").alias("token")).join(placed.select("doc_id", "e"), "doc_id")
    matrix = scratch.write(rows.select("token", "e").distinct(), "matrix")
    shared = matrix.groupBy("token").agg(F.min("e").alias("x"), F.max("e").alias("y")).where("x < y").select("token")
    matrix = scratch.write(matrix.join(shared, "token", "left_semi"), "shared")
    scratch.drop("matrix")
    side = lambda i, *columns: entities.select(*[F.col(x).alias(f"{x}{i}") for x in ("e", *columns)])
    ends = [matrix.withColumnRenamed("e", f"e{i}").join(side(i, "low", "high"), f"e{i}") for i in (1, 2)]
    met = ends[0].join(ends[1], "token").where((F.col("e1") < F.col("e2")) & _close_sizes("low1", "high1", "low2", "high2", num, den))
    met = met.groupBy("e1", "e2", "low1", "high1", "low2", "high2").agg(F.count("*").alias("c")).where(_reachable("low1", "high1", "low2", "high2", num, den))
    met = scratch.write(met.join(side(1, "g", "wide"), "e1").join(side(2, "g", "wide"), "e2"), "met")
    member = placed.select("g", "doc_id", "comp")
    comp = placed.select("doc_id", "comp")
    own = lambda doc: F.xxhash64(F.lit("document"), doc)
    # one pair of groups for each pair of entities: large families of near copies join here
    links = link_groups(docs, member, met.select("g1", "g2"), scratch, "apart", k, num, den)
    edges = _between(links, comp)
    # the other pairs of groups, document against group, of entities that are still apart
    home = comp.join(scratch.write(connected_components(edges, scratch, "second"), "second"), comp.comp == F.col("node"), "left").select("doc_id", F.coalesce("root", "comp").alias("now"))
    homes = placed.join(home, "doc_id").groupBy("e").agg(F.min("now").alias("a"), F.max("now").alias("z")).where("a = z").select("e", F.col("a").alias("home"))
    wide = met.where("wide1 or wide2").select("e1", "e2", "g1", "g2")
    wide = wide.join(homes.select(F.col("e").alias("e1"), F.col("home").alias("h1")), "e1", "left").join(homes.select(F.col("e").alias("e2"), F.col("home").alias("h2")), "e2", "left")
    wide = scratch.write(wide.where(~F.coalesce(F.col("h1") == F.col("h2"), F.lit(False))).select("e1", "e2", F.col("g1").alias("done1"), F.col("g2").alias("done2")), "wide")
    asked = wide.select(F.col("e1").alias("e")).unionByName(wide.select(F.col("e2").alias("e"))).distinct()
    cells = scratch.write(rows_of(reps, placed.join(asked, "e", "left_semi"), matrix), "cells")
    unions = cells.groupBy("token", F.col("e").alias("e2"), F.col("g").alias("g2")).agg(F.lit(1).alias("_"))
    spans = placed.groupBy(F.col("g").alias("g2")).agg(F.min("n").alias("low2"), F.max("n").alias("high2"))
    asks = cells.select("token", F.col("doc_id").alias("q"), F.col("e").alias("e1"), F.col("g").alias("g1"), F.col("n").alias("n1")).join(wide, "e1")
    bound = asks.join(unions, ["token", "e2"]).groupBy("q", "g1", "n1", "done1", "done2", "g2").agg(F.count("*").alias("c")).join(spans, "g2")
    bound = bound.where(_reachable("n1", "n1", "low2", "high2", num, den) & ~((F.col("g1") == F.col("done1")) & (F.col("g2") == F.col("done2"))))
    pairs = scratch.write(bound.select(own(F.col("q")).alias("g1"), "g2", "q"), "bound")
    single = pairs.select(F.col("g1").alias("g"), F.col("q").alias("doc_id")).distinct().join(comp, "doc_id").select("g", "doc_id", "comp")
    more = link_groups(docs, member.unionByName(single), pairs.select("g1", "g2"), scratch, "wide", k, num, den)

    last = connected_components(edges.unionByName(_between(more, comp)), scratch, "last")
    final = comp.join(last, comp.comp == last.node, "left").select(F.col("doc_id").alias("rep"), F.coalesce("root", "comp").alias("component_id"))
    copies = kinds.join(final, "rep", "left").select(*named, F.coalesce("component_id", "rep").alias("component_id"))
    linked = light.where("n > 0").join(copies, named)
    bare = light.where("n = 0").withColumn("component_id", F.col("doc_id"))
    columns = ["doc_id", F.col("n").alias("n_shingles"), "component_id"]
    scratch.drop("reps", "shared", "cells")
    return linked.select(*columns).unionByName(bare.select(*columns))


def rows_of(reps: DataFrame, placed: DataFrame, matrix: DataFrame) -> DataFrame:
    """token, doc_id, e, g, n: the prefix shingles of the placed documents that several entities have."""
    rows = reps.select("doc_id", F.explode("prefix").alias("token")).join(placed.select("doc_id", "e", "g", "n"), "doc_id")
    return rows.join(matrix.select("token").distinct(), "token", "left_semi")


def _reachable(low1: str, high1: str, low2: str, high2: str, num: int, den: int):
    """Whether c shared prefix shingles leave a link possible between sets of these sizes.

    Of two sets the one whose prefix ends first shares nothing with the other outside both prefixes but
    the rest of itself, which is ceil(num n / den) - 1 long at most; a link needs num (n1 + n2) / (num + den).
    """
    rest = F.greatest(*[F.floor((F.col(h) * num + den - 1) / den) - 1 for h in (high1, high2)])
    need = F.floor(((F.col(low1) + F.col(low2)) * num + num + den - 1) / (num + den))
    return _close_sizes(low1, high1, low2, high2, num, den) & (F.col("c") + rest >= need)


def _close_sizes(low1: str, high1: str, low2: str, high2: str, num: int, den: int):
    """Whether sets of these sizes can link at all."""
    return (F.col(high1) * den >= F.col(low2) * num) & (F.col(high2) * den >= F.col(low1) * num)


def _between(links: DataFrame, comp: DataFrame) -> DataFrame:
    """Links of documents as links of their components."""
    ends = [comp.select(F.col("doc_id").alias(x), F.col("comp").alias(f"c{x}")) for x in ("a", "b")]
    return links.join(ends[0], "a").join(ends[1], "b").select(F.col("ca").alias("a"), F.col("cb").alias("b"))

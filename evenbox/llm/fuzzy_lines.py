"""Fuzzy line deduplication with DataFrame functions only.

A line is normalised to its words: lower case, maximal runs of letters and digits. Lines of the same words are one
variant. A line of ``LONG`` different words or more has a SimHash in blocks: a word's hash chooses its block, and the words
of a block vote on the block's 32 bits, each once, however often it occurs. There are 4, 8 or 16 blocks by the line's length. A changed
word touches two blocks at most, so lines that differ in e words agree on all but 2 e blocks. Blocks stand in a ring, and two
close ones that two lines share make them a candidate pair (of four blocks, any two), in lines of very many words one: so one changed word is always survived. In a
shorter line every word is a block of its own, and the keys are the line without one word, and the whole line. Lines of fewer than ``FEW`` words (long names, scripts without spaces)
have keys of characters: bands of min-hashes of their 4-grams, and halves where one edit is allowed at most.
Candidate pairs are verified by edit distance of the normalised lines, without the words they begin and end with in common.

Large groups: each key first links its variants to the first of them, and the components of
those links are found; only then do variants of one key that are still in different components meet.
One occurrence of each connected group stays: the first by (doc_id, line number). Texts are dealt out by document once, so that
votes are added up without moving words; later only the lines to verify are read again.

Votes: 32 bits are four longs of eight one-byte lanes, so a word costs one hash and four additions. A block of more than
63 words is named by its sums instead of their majority.
"""

from __future__ import annotations

from functools import reduce
from hashlib import blake2b

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenbox.llm.components import connected_components
from evenbox.llm.scratch import ROW, Scratch, numbered, shuffle_width

MIN_SIMILARITY = 0.9
#: lines of at least so many words have blocks chosen by hash
LONG = 16
#: from this many words on a line has 8 blocks, and 16, and keys of one block; before, 4 blocks
MORE, MANY, VAST = 32, 64, 128
#: two blocks of fewer words are no key, by the bits of a block's number, nor is one block of fewer
PAIR_WORDS = {2: 6, 3: 7, 4: 7}
BLOCK_WORDS = 7
#: lines of fewer words have character keys
FEW = 4
#: min-hashes of a band of character keys, and bands
BAND = 3
BANDS = 20
_SALTS = [int.from_bytes(blake2b(bytes([k]), digest_size=4).digest(), "little", signed=True) for k in range(BAND * BANDS)]
#: a set of keys up to this size goes to every executor, a larger one is joined by shuffle
BROADCAST_KEYS = 250_000
#: every eighth bit of a long, the lanes' lowest bits
_LANES = 0x0101010101010101


def line_words(docs: DataFrame) -> DataFrame:
    """row, doc_id, line (number from 0) and words (an array, empty where there is no letter or digit) of every line."""
    row = F.col(ROW) if ROW in docs.columns else F.monotonically_increasing_id()
    texts = docs.select(row.alias("row"), "doc_id", F.lower("text").alias("text"))
    lines = texts.select("row", "doc_id", F.posexplode(F.split("text", "\n")).alias("line", "raw"))
    return lines.select("row", "doc_id", "line", F.regexp_extract_all("raw", F.lit(r"[\p{L}\p{N}]+"), F.lit(0)).alias("words"))


def document_lines(docs: DataFrame) -> DataFrame:
    """row, doc_id, line and norm (its words, a space between them) of every line that has a letter or digit."""
    return line_words(docs).select("row", "doc_id", "line", F.array_join("words", " ").alias("norm")).where("norm <> ''")


def _majority(i: int) -> Column:
    """Bits 8 k + i of a block: whether more than half of its n words voted for lane k of sum i."""
    level = (F.lit(63) - F.floor(F.col("n") / 2)) * F.lit(_LANES)
    return F.shiftrightunsigned((F.col(f"s{i}") + level).bitwiseAND(F.lit(_LANES << 6)), 6 - i)


def block_names(docs: DataFrame) -> DataFrame:
    """The blocks of every line: row, doc_id, line, vid and check (hashes of its words in order), size (its characters), w (its distinct words),
    bits (the line has 2^bits blocks; 0: one for each word), block, n (distinct words of the block), name (its low 8 bits are n)."""
    own = ["row", "doc_id", "line", "vid", "check", "size"]
    lines = line_words(docs)
    named = [F.xxhash64("words").alias("vid"), F.xxhash64(F.lit("check"), "words").alias("check"), F.length(F.array_join("words", " ")).alias("size")]
    lines = lines.select("row", "doc_id", "line", *named, F.array_distinct("words").alias("words"))
    lines = lines.select(*own, "words", F.size("words").alias("w"))
    bits = F.when(F.col("w") < LONG, 0).when(F.col("w") < MORE, 2).when(F.col("w") < MANY, 3).otherwise(4)
    words = lines.select(*own, "words", "w", bits.alias("bits")).select(*own, "w", "bits", F.posexplode("words").alias("at", "word"))
    words = words.select(*own, "w", "bits", "at", F.xxhash64("word").alias("h"))
    block = F.expr("CASE WHEN bits = 0 THEN at ELSE CAST(shiftrightunsigned(h, 64 - bits) AS INT) END")
    sums = [F.expr(f"try_sum(shiftrightunsigned(h, {i}) & {_LANES}L)").alias(f"s{i}") for i in range(4)]
    blocks = words.groupBy(*own, "w", "bits", block.alias("block")).agg(F.count("*").alias("n"), *sums)
    voted = F.when(F.col("n") <= 63, reduce(lambda x, y: x.bitwiseOR(y), [_majority(i) for i in range(4)])).otherwise(F.lit(-1))
    name = F.xxhash64(voted, F.when(F.col("n") > 63, F.xxhash64(*[f"s{i}" for i in range(4)]))).bitwiseAND(F.lit(~255)).bitwiseOR(F.least("n", F.lit(255)))
    return blocks.select(*own, "w", "bits", "block", "n", name.alias("name"))


#: the blocks that make up a key, by the bits of a block's number
_PAIRS = {2: [(0, 1), (1, 2), (2, 3), (0, 3), (0, 2), (1, 3)], 3: [(i, (i + step) % 8) for step in (1, 2) for i in range(8)], 4: [(i, (i + 1) % 16) for i in range(16)]}


def _keys() -> Column:
    """The keys of a line, some null: two blocks that are close in a ring, or one of a line of very many words; of a short line all words but one, and all."""
    name = [F.coalesce(f"b{j}", F.lit(0)) for j in range(16)]
    words = lambda i: name[i].bitwiseAND(F.lit(255))
    pair = lambda least, i, j: F.when(words(i) + words(j) >= least, F.xxhash64("bits", F.lit(i), F.lit(j), name[i], name[j]))
    one = lambda i: F.when(words(i) >= BLOCK_WORDS, F.xxhash64("bits", F.lit(i), name[i]))
    out = []
    for j in range(16):
        without = F.xxhash64(F.lit("without"), F.col("all").bitwiseXOR(F.col(f"b{j}")), F.col("w") - 1)
        key = F.when(F.col("bits") == 0, F.when((F.col("w") >= FEW) & F.col(f"b{j}").isNotNull(), without)).when(F.col("w") >= VAST, one(j))
        for bits, pairs in _PAIRS.items():
            if j < len(pairs):
                key = key.when(F.col("bits") == bits, pair(PAIR_WORDS[bits], *pairs[j]))
        out.append(key)
    return F.array(*out, F.when((F.col("bits") == 0) & (F.col("w") >= FEW), F.xxhash64(F.lit("without"), "all", "w")))


def hashed_lines(docs: DataFrame) -> DataFrame:
    """row, doc_id, line, vid and check (hashes of the words in order), size (characters), w (distinct words), keys (some null) of every line with a word.

    ``docs`` are dealt out by document before, so nothing is moved here."""
    named = [F.max(F.when(F.col("block") == j, F.col("name"))).alias(f"b{j}") for j in range(16)]
    lines = block_names(docs).groupBy("row", "doc_id", "line", "vid", "check", "size", "w", "bits").agg(F.bit_xor("name").alias("all"), *named)
    return lines.select("row", "doc_id", "line", "w", "size", "vid", "check", _keys().alias("keys"))


def _band_keys(features: DataFrame) -> DataFrame:
    """Rows (vid, f: the hash of a feature) -> vid, key: a key for each band of min-hashes. Equal lines are one."""
    minima = features.groupBy("vid").agg(*[F.min(F.col("f").bitwiseXOR(F.lit(x))).alias(f"m{k}") for k, x in enumerate(_SALTS)])
    keys = [F.xxhash64(F.lit(k), *[F.col(f"m{BAND * k + i}") for i in range(BAND)]) for k in range(BANDS)]
    return minima.select("vid", F.explode(F.array(*keys)).alias("key"))


def _half_keys(shorter: Column) -> list[Column]:
    """Both halves of a line, as cut if the shorter line of a pair has ``shorter`` characters."""
    half = F.floor(shorter / 2).cast("int")
    ends = (F.substring("norm", F.lit(1), half), F.substring("norm", F.col("size") - (shorter - half) + 1, shorter - half))
    return [F.xxhash64(F.lit(f"half {k}"), shorter, end) for k, end in enumerate(ends)]


def character_keys(lines: DataFrame) -> DataFrame:
    """vid, key of lines (vid, size, norm) of few words."""
    grams = lines.where("size >= 16").select("vid", F.explode(F.regexp_extract_all("norm", F.lit("(?s)(?=(.{4}))"), F.lit(1))).alias("gram"))
    halves = F.array(*_half_keys(F.col("size")), *_half_keys(F.col("size") - 1))
    halves = lines.where(F.col("size").between(9, 19)).select("vid", F.explode(halves).alias("key")).distinct()
    return _band_keys(grams.select("vid", F.hash("gram").alias("f"))).unionByName(halves)


def texts_of(asked: DataFrame, variants: DataFrame, docs: DataFrame) -> DataFrame:
    """vid and words of the asked variants (vid), read again where they first stand."""
    places = variants.join(_bounded(asked), "vid", "left_semi").select("vid", F.col("at.row").alias("at_row"), F.col("at.line").alias("at_line"))
    rows = docs.join(_bounded(places.select(F.col("at_row").alias(ROW)).distinct()), ROW, "left_semi")
    lines = line_words(rows).join(_bounded(places), (F.col("row") == F.col("at_row")) & (F.col("line") == F.col("at_line")))
    return lines.select("vid", "words")


def _bounded(rows: DataFrame) -> DataFrame:
    """A hint to broadcast ids if they are few enough, by a count."""
    return F.broadcast(rows) if rows.count() <= BROADCAST_KEYS else rows


def _with(rows: DataFrame, **columns: Column) -> DataFrame:
    """``rows`` with columns that are worked out once for a row; a plain column would be again in every filter and column that uses it."""
    return rows.select("*", F.inline(F.array(F.struct(*[c.alias(name) for name, c in columns.items()]))))


def _first_difference(a: str, b: str) -> Column:
    """The place, from 0, of the first word in which two arrays differ."""
    return F.array_position(F.zip_with(a, b, lambda x, y: x.eqNullSafe(y)), False).cast("int") - 1


def verified(pairs: DataFrame, lines: DataFrame, scratch: Scratch, min_similarity: float) -> DataFrame:
    """The pairs (a, b) of variants whose lines (vid, words, size) are similar enough: edit similarity 1 - distance / longer length.

    Words that differ place by place bound the distance from above; only where that bound is too large is the distance worked out, up to its limit.
    """
    side = lambda x: lines.select(F.col("vid").alias(x), F.col("words").alias(f"words_{x}"), F.col("size").alias(f"size_{x}"))
    both = pairs.join(side("a").select("a", "size_a"), "a").join(side("b").select("b", "size_b"), "b")
    limit = F.floor(F.greatest("size_a", "size_b") * F.lit(1 - min_similarity) + F.lit(1e-9)).cast("int")
    both = both.where(F.least("size_a", "size_b") >= F.greatest("size_a", "size_b") * min_similarity - 1e-9).select("a", "b", limit.alias("limit"))
    texts = both.join(side("a").drop("size_a"), "a").join(side("b").drop("size_b"), "b")
    texts = _with(texts, head=_first_difference("words_a", "words_b"))
    rest = lambda w: F.reverse(F.slice(w, F.col("head") + 1, F.size(w)))
    texts = _with(texts.select("a", "b", "limit", rest("words_a").alias("rest_a"), rest("words_b").alias("rest_b")), tail=_first_difference("rest_a", "rest_b"))
    # the middles, backwards
    middle = lambda w: F.slice(w, F.col("tail") + 1, F.size(w))
    texts = _with(texts, x=middle("rest_a"), y=middle("rest_b")).select("a", "b", "limit", "x", "y")
    length = lambda w: F.coalesce(F.length(w) + 1, F.lit(0))
    costs = F.zip_with("x", "y", lambda x, y: F.when(x.eqNullSafe(y), 0).otherwise(F.greatest(length(x), length(y))))
    texts = _with(texts, at_most=F.aggregate(costs, F.lit(0), lambda total, cost: total + cost))
    spaced = lambda w: f"concat(array_join(reverse({w}), ' '), CASE WHEN size({w}) > 0 THEN ' ' ELSE '' END)"
    # the cost grows with the limit, so a small one is tried first
    exact = F.expr(f"CASE WHEN levenshtein({spaced('x')}, {spaced('y')}, least(limit, 32)) >= 0 THEN true WHEN limit <= 32 THEN false ELSE levenshtein({spaced('x')}, {spaced('y')}, limit) >= 0 END")
    return texts.where(F.when(F.col("at_most") <= F.col("limit"), True).otherwise(exact)).select("a", "b")


def similar_variants(places: DataFrame, variants: DataFrame, docs: DataFrame, scratch: Scratch, min_similarity: float) -> DataFrame:
    """(node, root) over variants; those without a partner are left out."""
    few = scratch.write(variants.where(f"w < {FEW} AND size >= 9").select("vid"), "few")
    tiny = texts_of(few, variants, docs).select("vid", F.array_join("words", " ").alias("norm")).withColumn("size", F.length("norm"))
    named = places.select(F.explode("keys").alias("key"), "vid").where("key IS NOT NULL")
    keys = named.unionByName(scratch.write(character_keys(scratch.write(tiny, "tiny")), "characters").select("key", "vid"))
    shared = scratch.write(keys.groupBy("key").agg(F.min("vid").alias("a"), F.max("vid").alias("z")).where("a < z").select("key", "a"), "shared")
    rows = scratch.write(keys.join(_bounded(shared), "key").select("key", "a", "vid").distinct(), "rows")
    scratch.drop("shared")
    stars = scratch.write(rows.where("vid <> a").select("a", F.col("vid").alias("b")).distinct(), "stars")
    asked = scratch.write(stars.select(F.col("a").alias("vid")).unionByName(stars.select(F.col("b").alias("vid"))).distinct(), "asked")
    lines = scratch.write(texts_of(asked, variants, docs).withColumn("size", F.length(F.array_join("words", " "))), "lines")
    scratch.drop("asked")
    first = scratch.write(connected_components(verified(stars, lines, scratch, min_similarity), scratch, "first"), "first")

    scratch.drop("stars")
    rows = rows.join(first, F.col("vid") == F.col("node"), "left").join(lines.select("vid", "size"), "vid")
    rows = scratch.write(rows.select("key", "a", "vid", "size", F.coalesce("root", "vid").alias("comp")), "homes")
    mixed = rows.groupBy("key").agg(F.min("comp").alias("x"), F.max("comp").alias("y")).where("x < y").select("key")
    # the first variant of a key has met all others
    rows = scratch.write(rows.where("vid <> a").join(_bounded(mixed), "key", "left_semi").select("key", "vid", "size", "comp"), "mixed")
    x, y = rows.alias("x"), rows.alias("y")
    sizes = F.least("x.size", "y.size") >= F.greatest("x.size", "y.size") * min_similarity - 1e-9
    more = x.join(y, (F.col("x.key") == F.col("y.key")) & (F.col("x.comp") < F.col("y.comp")) & sizes)
    more = scratch.write(more.select(F.col("x.vid").alias("a"), F.col("y.vid").alias("b")).distinct(), "more")
    scratch.drop("rows", "homes", "mixed")
    links = first.select(F.col("node").alias("a"), F.col("root").alias("b")).unionByName(verified(more, lines, scratch, min_similarity))
    groups = scratch.write(connected_components(links, scratch, "last"), "groups")
    scratch.drop("lines", "more", "first")
    return groups


def repeated_lines(docs: DataFrame, min_similarity: float = MIN_SIMILARITY, scratch: Scratch | None = None) -> DataFrame:
    """Every line with a letter or digit: doc_id, line, group_doc and group_line (the first occurrence of
    its group), kept (it is that occurrence).

    Null and empty texts have no lines; blank lines are not lines here; repeated rows of one doc_id
    are repeated occurrences of which one stays; an empty table gives no rows; null doc_ids come
    first; extra columns are ignored.
    """
    scratch = scratch or Scratch(docs.sparkSession, "lines")
    rows = numbered(docs.select("doc_id", "text"), scratch)
    return grouped_lines(rows, scratch, min_similarity).drop("row")


def grouped_lines(docs: DataFrame, scratch: Scratch, min_similarity: float = MIN_SIMILARITY) -> DataFrame:
    """The columns of ``repeated_lines``, and row, over ``numbered`` rows; a row is named by its number alone."""
    docs = docs.select(ROW, "doc_id", "text")
    dealt = docs.repartition(shuffle_width(docs.sparkSession), ROW).select(F.col(ROW), "doc_id", "text")
    places = scratch.write(hashed_lines(dealt), "places")
    scratch.drop()  # the dealt texts
    places = _apart(places, scratch)
    variants = places.groupBy("vid").agg(F.min(F.struct("doc_id", "line", "row")).alias("at"), F.first("w").alias("w"), F.first("size").alias("size"), F.count("*").alias("times"))
    variants = scratch.write(variants, "variants")
    scratch.drop()
    groups = similar_variants(places, variants, docs, scratch, min_similarity)
    # a line that occurs once and resembles no other is its own group and needs no join
    shared = variants.join(groups, variants.vid == groups.node, "left").where("times > 1 OR root IS NOT NULL").select("vid", "at", F.coalesce("root", "vid").alias("comp"))
    shared = scratch.write(shared, "several")
    heads = shared.groupBy("comp").agg(F.min("at").alias("head"))
    heads = scratch.write(shared.join(heads, "comp").select("vid", "head"), "heads")
    scratch.drop("several", "variants")
    own = F.struct("doc_id", "line", "row")
    marked = places.select("row", "doc_id", "line", "vid").join(_bounded(heads), "vid", "left").withColumn("head", F.coalesce("head", own))
    kept = (F.col("row") == F.col("head.row")) & (F.col("line") == F.col("head.line"))
    return marked.select("row", "doc_id", "line", F.col("head.doc_id").alias("group_doc"), F.col("head.line").alias("group_line"), kept.alias("kept"))


def _apart(places: DataFrame, scratch: Scratch) -> DataFrame:
    """``places`` with a new vid for lines of one vid whose second hash or size differs."""
    torn = places.groupBy("vid").agg(F.min("check").alias("x"), F.max("check").alias("y"), F.min("size").alias("s"), F.max("size").alias("t")).where("x < y OR s < t")
    torn = scratch.write(torn.select(F.col("vid").alias("torn")), "torn")
    if torn.isEmpty():
        return places
    fresh = F.when(F.col("torn").isNotNull(), F.xxhash64("vid", "check", "size")).otherwise(F.col("vid"))
    return scratch.write(places.join(_bounded(torn), F.col("vid") == F.col("torn"), "left").withColumn("vid", fresh).drop("torn"), "apart")


def drop_repeated_lines(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with their columns, without the lines that repeat an earlier one. A document that loses
    its last line with a letter or digit goes; one that never had any stays as it was. n_chars, if
    there, is counted anew."""
    scratch = options.pop("scratch", None) or Scratch(docs.sparkSession, "lines")
    rows = numbered(docs, scratch)
    gone = grouped_lines(rows, scratch, **options).where("not kept").groupBy(F.col("row").alias(ROW)).agg(F.collect_set("line").alias("_evenbox_gone"))
    marked = rows.join(_bounded(scratch.write(gone, "gone")), ROW, "left")
    rest = F.filter(F.split("text", "\n"), lambda line, i: ~F.array_contains("_evenbox_gone", i))
    text = F.when(F.col("_evenbox_gone").isNull(), F.col("text")).otherwise(F.array_join(rest, "\n"))
    cut = marked.withColumn("text", text).where(F.col("_evenbox_gone").isNull() | F.col("text").rlike(r"[\p{L}\p{N}]"))
    if "n_chars" in docs.columns:
        cut = cut.withColumn("n_chars", F.when(F.col("_evenbox_gone").isNull(), F.col("n_chars")).otherwise(F.length("text").cast(docs.schema["n_chars"].dataType)))
    return cut.select(*docs.columns)

"""Shard placement by a permutation-filled lookup table, DataFrame functions only on the data path.

A table of a prime number of slots is filled before any data is read: every shard walks its own permutation
of the slots (an offset and a stride from a digest of its name; the size is prime, so every stride visits
all slots) and the shards take turns to claim their next free slot. A heavier shard takes more turns.
Shares then differ by a slot for each turn at most, and when a shard goes, almost only its own slots change hands.
The table depends on shard names and weights alone, so its size is fixed; it goes to every executor, and a
record's shard is one look at the slot that is the remainder of its key's digest.

Defined results: a null key has a digest of its own and is placed like any other; equal keys share a shard;
an empty table gives no rows; other columns of the rows are kept.
"""

from __future__ import annotations

import hashlib
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: slots; a prime at least a hundred times the shards keeps shares within about one per cent
SLOTS = 65537
SHARDS = 64
#: stands for a null key
_NULL = "<null>"


def is_prime(n: int) -> bool:
    return n > 1 and all(n % k for k in range(2, int(n**0.5) + 1))


def _digest(text: str) -> int:
    return int(hashlib.md5(text.encode()).hexdigest()[:15], 16)


def fill_table(shards: Sequence[str], slots: int = SLOTS, weights: Sequence[int] | None = None) -> list[int]:
    """The shard number of every slot."""
    if not is_prime(slots):
        raise ValueError(f"{slots} is not a prime")
    weights = weights or [1] * len(shards)
    if len(shards) > slots or not any(w > 0 for w in weights):
        raise ValueError("there must be shards with a weight, and no more of them than slots")
    at = [_digest(f"offset/{name}") % slots for name in shards]
    stride = [_digest(f"stride/{name}") % (slots - 1) + 1 for name in shards]
    table, free = [-1] * slots, slots
    while free:
        for shard, turns in enumerate(weights):
            for _ in range(min(turns, free)):
                while table[at[shard]] >= 0:
                    at[shard] = (at[shard] + stride[shard]) % slots
                table[at[shard]] = shard
                free -= 1
    return table


def key_slot(key: Column, slots: int = SLOTS) -> Column:
    """The slot of a key: the first 60 bits of its digest, modulo the slots."""
    digest = F.md5(F.coalesce(key.cast("string"), F.lit(_NULL)).cast("binary"))
    return F.pmod(F.conv(F.substring(digest, 1, 15), 16, 10).cast("long"), F.lit(slots)).cast("int")


def place_rows(rows: DataFrame, key: str, shards: int | Sequence[str] = SHARDS, slots: int = SLOTS, weights: Sequence[int] | None = None) -> DataFrame:
    """``rows`` with slot and shard (columns of these names, in any case, are replaced)."""
    names = [f"shard-{i}" for i in range(shards)] if isinstance(shards, int) else list(shards)
    table = fill_table(names, slots, weights)
    line = F.lit(",".join(map(str, table)))
    lookup = rows.sparkSession.range(1).select(F.posexplode(F.split(line, ",").cast("array<int>")).alias("_evenbox_slot", "_evenbox_shard"))
    kept = [rows[f"`{c}`"] for c in rows.columns if c.lower() not in ("slot", "shard")]
    placed = rows.select(*kept, key_slot(rows[f"`{key}`"], slots).alias("_evenbox_slot")).join(F.broadcast(lookup), "_evenbox_slot")
    return placed.withColumnsRenamed({"_evenbox_slot": "slot", "_evenbox_shard": "shard"}).select(*[f"`{c}`" for c in rows.columns if c.lower() not in ("slot", "shard")], "slot", "shard")


def write_shards(rows: DataFrame, key: str, path: str, shards: int | Sequence[str] = SHARDS, files_each: int = 4, **options) -> None:
    """Write ``rows`` as Parquet, a folder for each shard, each dealt over ``files_each`` tasks."""
    placed = place_rows(rows, key, shards, **options)
    n = shards if isinstance(shards, int) else len(shards)
    dealt = placed.repartition(n * files_each, "shard", F.pmod("slot", F.lit(files_each)))
    dealt.drop("slot").write.mode("overwrite").partitionBy("shard").parquet(path)


def placement_sql(table: str, key: str, shards: int = SHARDS, slots: int = SLOTS) -> str:
    """The placement as DuckDB SQL, with the lookup table written out."""
    filled = ",".join(map(str, fill_table([f"shard-{i}" for i in range(shards)], slots)))
    digest = f"md5(coalesce(CAST({key} AS VARCHAR), '{_NULL}'))"
    return f"WITH lookup AS (SELECT CAST(string_split('{filled}', ',') AS INTEGER[]) AS filled), keyed AS (SELECT {key}, CAST(CAST('0x' || substr({digest}, 1, 15) AS BIGINT) % {slots} AS INTEGER) AS slot FROM {table}) SELECT {key}, slot, filled[slot + 1] AS shard FROM keyed, lookup"

"""Sharding by a permutation-filled lookup table, in DataFrame functions only.

Each shard has a permutation of the slots of a table of prime size, given by an offset and a step that are hashes of its name.
Shards take turns, as often as their weights say, and claim the next free slot of their permutation until the table is full.
The table is a row per slot of a bounded number; placement is one hash of the key and one lookup in the broadcast table.

A null key is a key like any other (the text "null"), and so is a very long one. Repeated rows go to one shard. Columns beside
the key, those with names used here included, are not read. An empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
import json

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Slots of the table when nothing else is said: a prime well over 100 times the usual number of shards.
SLOTS = 10_007
#: More slots than this are refused: the table is broadcast.
MOST_SLOTS = 4_000_037


def fill(shards: dict[str, int], slots: int = SLOTS) -> list[str]:
    """Shard of each slot; shards: turns of each per round, in this order."""
    if not shards or len(shards) > slots or slots > MOST_SLOTS or min(shards.values()) < 1:
        raise ValueError("shards with a weight of 1 or more are needed, and a table that holds them all")
    if any(slots % k == 0 for k in range(2, int(slots**0.5) + 1)):
        raise ValueError("the number of slots must be prime")
    number = lambda text: int(hashlib.md5(text.encode()).hexdigest()[:8], 16)
    walk = {s: [number(f"offset:{s}") % slots, 1 + number(f"step:{s}") % (slots - 1)] for s in shards}
    table: list[str | None] = [None] * slots
    free = slots
    while free:
        for shard, turns in shards.items():
            for _ in range(min(turns, free)):
                place, step = walk[shard]
                while table[place] is not None:
                    place = (place + step) % slots
                table[place] = shard
                walk[shard][0] = (place + step) % slots
                free -= 1
    return table


def slot_of(key: Column, slots: int) -> Column:
    """Slot of a key: the first 15 hex digits of the md5 of its text, modulo the number of slots."""
    text = F.md5(F.coalesce(key.cast("string"), F.lit("null")).cast("binary"))
    return F.pmod(F.conv(F.substring(text, 1, 15), 16, 10).cast("long"), F.lit(slots)).cast("int")


def place(docs: DataFrame, shards: dict[str, int], slots: int = SLOTS, key_col: str = "doc_id") -> DataFrame:
    """(doc_id, slot, shard) of each row."""
    table = lookup_table(docs.sparkSession, shards, slots)
    rows = docs.select(docs[key_col].alias("doc_id"), slot_of(docs[key_col], slots).alias("slot"))
    return rows.join(F.broadcast(table), "slot").select("doc_id", "slot", "shard")


def lookup_table(spark: SparkSession, shards: dict[str, int], slots: int = SLOTS) -> DataFrame:
    """(slot, shard), a row per slot."""
    names = F.from_json(F.lit(json.dumps(fill(shards, slots))), "array<string>")
    return spark.range(1).select(F.posexplode(names).alias("slot", "shard"))


def moved(before: dict[str, int], after: dict[str, int], slots: int = SLOTS) -> float:
    """Share of slots whose shard changes when the shards do."""
    return sum(a != b for a, b in zip(fill(before, slots), fill(after, slots))) / slots


def sql(shards: dict[str, int], slots: int = SLOTS) -> str:
    """The same placement for DuckDB: the table is filled turn by turn by a recursive query over free slots."""
    number = lambda text: f"('0x' || substr(md5({text}), 1, 8))::BIGINT"
    turns = ", ".join(f"({k}, '{s}')" for k, s in enumerate(s for s, n in shards.items() for _ in range(n)))
    n = sum(shards.values())
    return f"""
WITH RECURSIVE turn(k, shard) AS (VALUES {turns}),
pref AS MATERIALIZED (
  SELECT shard, list(({number("'offset:' || shard")} % {slots} + j * (1 + {number("'step:' || shard")} % {slots - 1})) % {slots} ORDER BY j) AS p
  FROM (SELECT DISTINCT shard FROM turn), range({slots}) r(j) GROUP BY shard),
filled(i, taken, slot, shard) AS (
  SELECT 0, list_value(-1)::BIGINT[], -1::BIGINT, NULL::VARCHAR
  UNION ALL
  SELECT f.i + 1, list_append(f.taken, c), c, t.shard
  FROM filled f JOIN turn t ON t.k = f.i % {n} JOIN pref ON pref.shard = t.shard,
  LATERAL (SELECT list_filter(pref.p, lambda x: NOT list_contains(f.taken, x))[1] AS c)
  WHERE f.i < {slots})
SELECT doc_id, slot::INTEGER AS slot, filled.shard AS shard
FROM (SELECT doc_id, ('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'null')), 1, 15))::BIGINT % {slots} AS slot FROM documents)
JOIN filled USING (slot)"""

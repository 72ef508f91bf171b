"""Placement of rows on shards by a permutation-filled lookup table.

Every shard has a preference order of the slots of a prime-sized table: it starts at
an offset and advances by a skip, both from the MD5 of its name, and so visits each
slot once. Shards take turns claiming their next free slot until the table is full.
Slots are dealt evenly (sizes differ by one at most), and when a shard leaves, few of
the others' slots change. A row's slot is a hash of its key; its shard is one look-up.

The table's size is a parameter, not a function of the data, so it may be broadcast.
Placement uses DataFrame functions only and does not shuffle. Null keys hash as empty
text; repeated keys go to one shard, for that is the point of placement by key.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SHARDS = tuple(f"shard-{k:02d}" for k in range(8))
#: A prime, at least a hundred times the number of shards.
SLOTS = 1031


def fill_table(shards: tuple[str, ...] = SHARDS, slots: int = SLOTS) -> list[int]:
    """The shard number of each slot."""
    if not shards or len(shards) > slots or any(slots % d == 0 for d in range(2, int(slots**0.5) + 1)):
        raise ValueError("slots must be a prime, and there must be 1 to that many shards")
    digest = [hashlib.md5(s.encode()).hexdigest() for s in shards]
    at = [int(d[:8], 16) % slots for d in digest]
    skip = [int(d[8:16], 16) % (slots - 1) + 1 for d in digest]
    table, taken = [-1] * slots, 0
    while True:
        for k in range(len(shards)):
            while table[at[k]] >= 0:
                at[k] = (at[k] + skip[k]) % slots
            table[at[k]] = k
            taken += 1
            if taken == slots:
                return table


def slot_of(key: Column, slots: int = SLOTS) -> Column:
    """The slot of a key: the first 32 bits of the MD5 of its text, modulo the table's size."""
    text = F.coalesce(key.cast("string"), F.lit(""))
    return F.pmod(F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long"), F.lit(slots)).cast("int")


def lookup_table(spark: SparkSession, shards: tuple[str, ...] = SHARDS, slots: int = SLOTS) -> DataFrame:
    """(slot, shard) as a DataFrame made from one literal."""
    text = ",".join(map(str, fill_table(shards, slots)))
    return spark.range(1).select(F.posexplode(F.split(F.lit(text), ",")).alias("slot", "shard")).select("slot", F.col("shard").cast("int").alias("shard"))


def place(df: DataFrame, key: str, shards: tuple[str, ...] = SHARDS, slots: int = SLOTS) -> DataFrame:
    """``df`` with the columns slot and shard; the table's fixed size is what makes the broadcast safe.

    Columns of these names in ``df`` are replaced.
    """
    rest = df.drop("slot", "shard")
    return rest.withColumn("slot", slot_of(F.col(f"`{key}`"), slots)).join(F.broadcast(lookup_table(df.sparkSession, shards, slots)), "slot", "left").select(*(F.col(f"`{c}`") for c in rest.columns), "slot", "shard")


def oracle(shards: tuple[str, ...] = SHARDS, slots: int = SLOTS) -> str:
    """DuckDB SQL for op10: the turns are the steps of a recursion over a list of claimed slots."""
    n = len(shards)
    names = ", ".join(f"({k}, '{s}')" for k, s in enumerate(shards))
    hexed = "('0x' || substr(md5(name), {}, 8))::BIGINT"
    return f"""
WITH RECURSIVE shards(k, name) AS (VALUES {names}),
pref AS (SELECT k, {hexed.format(1)} % {slots} AS start, {hexed.format(9)} % {slots - 1} + 1 AS skip FROM shards),
orders AS (SELECT list((SELECT list((start + j * skip) % {slots} ORDER BY j) FROM range({slots}) r(j)) ORDER BY k) AS p FROM pref),
turns(step, owner, slot) AS (
  SELECT 0, list_resize([]::INTEGER[], {slots}, -1), -1::BIGINT
  UNION ALL
  SELECT step + 1, list_concat(list_concat(owner[1:s], [(step % {n})::INTEGER]), owner[s + 2:]), s
  FROM (SELECT step, owner, list_filter(p[step % {n} + 1], lambda x: owner[x + 1] < 0)[1] AS s FROM turns, orders WHERE step < {slots})
),
lookup AS (SELECT slot, ((step - 1) % {n})::INTEGER AS shard FROM turns WHERE step > 0)
SELECT d.doc_id, h.slot, l.shard
FROM documents d, LATERAL (SELECT (('0x' || substr(md5(coalesce(d.doc_id::VARCHAR, '')), 1, 8))::BIGINT % {slots})::INTEGER AS slot) h
LEFT JOIN lookup l ON l.slot = h.slot
"""

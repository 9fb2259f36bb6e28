"""Sharding by a permutation-filled lookup table, in DataFrame functions only.

A shard's name gives it a permutation of the table's slots (a start and a step, the table's size being prime).  Shards
take turns; at its turn a shard claims the next free slot of its permutation, until all slots are taken, so the numbers
of slots differ by at most one turn.  If a shard leaves or joins, few keys move between the others.  A key's slot is its
hash modulo the table's size.  The table has as many rows as it has slots, whatever the data, and is broadcast.

Odd input: a null key is placed like the empty string; equal keys go to one shard; other columns pass unchanged, whatever
their names, but for ``slot`` and ``shard``, which the result replaces (a key of such a name too); an empty table stays empty.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: 24 shards and a prime of slots at least a hundred times as many.
SHARDS, SLOTS = tuple(f"shard-{k:02d}" for k in range(24)), 2411


def _number(name: str, at: int) -> int:
    return int(hashlib.md5(name.encode()).hexdigest()[at : at + 8], 16)


def fill(names: tuple[str, ...] = SHARDS, slots: int = SLOTS, weights: dict[str, int] | None = None) -> list[int]:
    """Slot -> number of its shard.  ``weights``: turns of a shard in each round, 1 unless said."""
    table, left = [-1] * slots, slots
    start = [_number(n, 0) % slots for n in names]
    step = [_number(n, 8) % (slots - 1) + 1 for n in names]
    tried = [0] * len(names)
    while left:
        for k, name in enumerate(names):
            for _ in range((weights or {}).get(name, 1)):
                if not left:
                    break
                while table[at := (start[k] + tried[k] * step[k]) % slots] >= 0:
                    tried[k] += 1
                table[at] = k
                left -= 1
    return table


def slot_of(key: Column, slots: int = SLOTS) -> Column:
    digest = F.md5(F.coalesce(key.cast("string"), F.lit("")).cast("binary"))
    return (F.conv(F.substring(digest, 1, 8), 16, 10).cast("long") % slots).cast("int")


def table(spark: SparkSession, names: tuple[str, ...] = SHARDS, slots: int = SLOTS, weights: dict[str, int] | None = None) -> DataFrame:
    """Rows (slot, shard)."""
    return spark.createDataFrame([(s, names[k]) for s, k in enumerate(fill(names, slots, weights))], "slot int, shard string")


def assign(docs: DataFrame, key: str = "doc_id", names: tuple[str, ...] = SHARDS, slots: int = SLOTS, weights: dict[str, int] | None = None) -> DataFrame:
    """``docs`` with the columns ``slot`` and ``shard`` after them; other columns of these names lose their place."""
    lookup = table(docs.sparkSession, names, slots, weights)
    # The rows travel as one value, so that no name of theirs can meet one of ours.
    rows = docs.select(F.struct("*").alias("row"), slot_of(F.col(key), slots).alias("slot")).join(F.broadcast(lookup), "slot")
    return rows.select(*[F.col("row").getField(c).alias(c) for c in docs.columns if c not in ("slot", "shard")], "slot", "shard")


ORACLE = f"""
WITH RECURSIVE names AS (SELECT i, 'shard-' || lpad(CAST(i AS VARCHAR), 2, '0') AS name FROM range({len(SHARDS)}) t(i)),
cfg AS (SELECT list(CAST(('0x' || substr(md5(name), 1, 8)) AS BIGINT) % {SLOTS} ORDER BY i) AS b, list(CAST(('0x' || substr(md5(name), 9, 8)) AS BIGINT) % {SLOTS - 1} + 1 ORDER BY i) AS s FROM names),
r AS (SELECT 0 AS t, list_transform(range({SLOTS}), lambda x: -1) AS tab, NULL::BIGINT AS place
  UNION ALL
  SELECT t + 1, list_concat(list_concat(tab[1:p], [t % {len(SHARDS)}]), tab[p + 2:]), p FROM (
    SELECT t, tab, list_transform(list_filter(range({SLOTS}), lambda j: tab[((b[t % {len(SHARDS)} + 1] + j * s[t % {len(SHARDS)} + 1]) % {SLOTS}) + 1] = -1)[1:1], lambda j: (b[t % {len(SHARDS)} + 1] + j * s[t % {len(SHARDS)} + 1]) % {SLOTS})[1] AS p
    FROM r, cfg WHERE t < {SLOTS})),
tab AS (SELECT place AS slot, (t - 1) % {len(SHARDS)} AS i FROM r WHERE t > 0)
SELECT doc_id, CAST(slot AS INTEGER) AS slot, name AS shard
FROM documents JOIN tab ON tab.slot = CAST(('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '')), 1, 8)) AS BIGINT) % {SLOTS} JOIN names USING (i)
"""

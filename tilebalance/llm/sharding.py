"""Placement of rows on shards through a permutation-filled lookup table.

Every shard has its own permutation of the slots of a prime-sized table
((offset + k*skip) mod size).  Shards take turns; the one whose turn it is
claims the first free slot of its permutation.  All shards so hold equal
numbers of slots (within one, by weight), and when a shard leaves, almost only
its own slots change hands.  The table is a rule's output of fixed size; it is
broadcast, and a row is placed by one hash and one lookup.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SLOTS, SHARDS = 65537, 256


def _number(text: str) -> int:
    return int(hashlib.md5(text.encode()).hexdigest()[:15], 16)


def lookup_table(shards: list[str], slots: int = SLOTS) -> list[int]:
    """Index of the owning shard for each slot.  slots must be prime and at least the number of shards."""
    if slots < 2 or any(slots % d == 0 for d in range(2, int(slots**0.5) + 1)):
        raise ValueError(f"{slots} slots: not a prime")
    if not shards or len(set(shards)) != len(shards) or len(shards) > slots:
        raise ValueError("shards must be distinct names, one at least and no more than slots")
    at = [_number(f"{s}/offset") % slots for s in shards]
    skip = [_number(f"{s}/skip") % (slots - 1) + 1 for s in shards]
    owner, left = [-1] * slots, slots
    while left:
        for k in range(len(shards)):
            while owner[at[k]] >= 0:
                at[k] = (at[k] + skip[k]) % slots
            owner[at[k]] = k
            left -= 1
            if not left:
                break
    return owner


def slot_of(key: Column, slots: int = SLOTS) -> Column:
    """Slot of a key: the first 15 hex digits of the MD5 of its text, modulo the table size.  Null keys count as empty text."""
    return F.pmod(F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit("")).cast("binary")), 1, 15), 16, 10).cast("bigint"), F.lit(slots)).cast("int")


def place(df: DataFrame, key: str, shards: list[str], slots: int = SLOTS, slot_col: str = "slot", shard_col: str = "shard") -> DataFrame:
    """df with its slot and shard.  Columns of those names must not exist yet (ValueError): choose others by slot_col and shard_col.

    Rows with equal keys, nulls and repeats included, go to the same shard; an
    empty table stays empty.
    """
    if taken := {slot_col.lower(), shard_col.lower()} & {c.lower() for c in df.columns}:
        raise ValueError(f"columns exist already: {sorted(taken)}")
    spark, owner = df.sparkSession, lookup_table(shards, slots)
    packed = ",".join(map(str, owner))
    table = spark.range(1).select(F.posexplode(F.split(F.lit(packed), ",")).alias(slot_col, "k")).select(slot_col, F.element_at(F.lit(list(shards)), F.col("k").cast("int") + 1).alias(shard_col))
    return df.withColumn(slot_col, slot_of(F.col(key), slots)).join(F.broadcast(table), slot_col).select(*df.columns, slot_col, shard_col)


def write_shards(placed: DataFrame, path: str, shard_col: str = "shard", files_per_shard: int = 1) -> None:
    """One folder per shard; a hot shard's rows are spread over files_per_shard writers."""
    placed.withColumn("_part", F.pmod(F.xxhash64(*[c for c in placed.columns if c != shard_col]), F.lit(files_per_shard))).repartition(shard_col, "_part").drop("_part").write.partitionBy(shard_col).mode("overwrite").parquet(path)


def shard_names(n: int = SHARDS) -> list[str]:
    return [f"shard-{k:05d}" for k in range(n)]


def sql(n: int = SHARDS, slots: int = SLOTS) -> str:
    owner = ",".join(map(str, lookup_table(shard_names(n), slots)))
    return f"""
SELECT doc_id, slot, printf('shard-%05d', CAST(t.owners[slot + 1] AS INTEGER)) AS shard, n_bytes
FROM (SELECT doc_id, CAST(CAST(concat('0x', substr(md5(CAST(doc_id AS VARCHAR)), 1, 15)) AS BIGINT) % {slots} AS INTEGER) AS slot,
             CAST(strlen(coalesce(text, '')) AS BIGINT) AS n_bytes FROM documents)
CROSS JOIN (SELECT string_split('{owner}', ',') AS owners) t
"""

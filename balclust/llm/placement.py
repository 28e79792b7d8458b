"""Sharding by a permutation-filled lookup table.

Every shard has its own order of preference over the slots of a table whose size is prime;
the shards take turns and claim the next free slot they prefer until the table is full. A key
is placed by its slot alone, so that placement costs one hash and one look at a broadcast table
whose size is the parameter ``slots``, and few keys move when a shard comes or goes.

Defined cases: a null key is placed like the empty string; repeated rows are placed alike; an
empty table gives an empty result; columns of the input named slot or shard give way to ours.
"""

from __future__ import annotations

import hashlib
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: A prime; also the proven bound of the broadcast table's rows.
SLOTS, SHARDS = 65_537, 64


def _number(what: str) -> int:
    return int(hashlib.md5(what.encode()).hexdigest()[:15], 16)


def fill(shards: Sequence[str], slots: int = SLOTS, weights: Sequence[int] | None = None) -> list[int]:
    """Which shard (by its place in shards) owns each slot. A shard of weight w gets w turns a round."""
    if not shards or slots <= len(shards) or any(slots % p == 0 for p in range(2, int(slots**0.5) + 1)):
        raise ValueError("slots must be a prime above the number of shards, and there must be shards")
    at = [_number(f"{s}/offset") % slots for s in shards]
    step = [_number(f"{s}/step") % (slots - 1) + 1 for s in shards]
    owner, free = [-1] * slots, slots
    while free:
        for k in range(len(shards)):
            for _ in range(weights[k] if weights else 1):
                if not free:
                    return owner
                while owner[at[k]] >= 0:
                    at[k] = (at[k] + step[k]) % slots
                owner[at[k]] = k
                free -= 1
    return owner


def slot_of(key: Column, slots: int = SLOTS) -> Column:
    """The slot of a key: the first 60 bits of its MD5, modulo the table's size."""
    return F.pmod(F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit(""))), 1, 15), 16, 10).cast("long"), F.lit(slots))


def place(df: DataFrame, key: str, shards: Sequence[str], slots: int = SLOTS, weights: Sequence[int] | None = None) -> DataFrame:
    """df with the slot and the shard of each row's key."""
    owners = ",".join(map(str, fill(shards, slots, weights)))
    table = df.sparkSession.range(1).select(F.posexplode(F.split(F.lit(owners), ",")).alias("_slot", "_shard")).select(F.col("_slot").cast("long").alias("slot"), F.col("_shard").cast("int").alias("shard"))
    rows = common.as_row(df).withColumn("slot", slot_of(F.col("row").getField(key), slots)).join(F.broadcast(table), "slot")
    return rows.select(*(F.col("row").getField(c).alias(c) for c in df.columns if c not in ("slot", "shard")), "slot", "shard")


def _shards() -> list[str]:
    return [f"shard-{k:03d}" for k in range(SHARDS)]


def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return place(common.documents(spark, sf_dir).select("doc_id", "n_chars"), "doc_id", _shards()).select("doc_id", "n_chars", "slot", "shard")


def op5_sql() -> str:
    owners = ",".join(map(str, fill(_shards())))
    return f"""WITH keyed AS (SELECT doc_id, n_chars, CAST('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '')), 1, 15) AS BIGINT) % {SLOTS} AS slot FROM documents),
owners AS (SELECT unnest(range(0, {SLOTS})) AS slot, unnest(string_split('{owners}', ',')) AS shard)
SELECT doc_id, n_chars, CAST(slot AS BIGINT) AS slot, CAST(shard AS INTEGER) AS shard FROM keyed JOIN owners USING (slot)"""

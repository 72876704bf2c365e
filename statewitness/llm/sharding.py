"""Sharding by a permutation-filled lookup table [native].

Every shard has its own order of the slots of a prime-sized table (an offset and a step, both hashed
from its name). Shards take turns; each claims the next free slot of its order until the table is full.
Shares differ by one slot at most, and when a shard leaves, few slots of other shards change hands. The
table has a fixed size, whatever the data, so it is broadcast: placing a row is one hash and one
lookup, without a shuffle.

Defined results: the key is the text form of the id; a null key is placed like an empty one; equal keys
share a shard, so repeated rows stay together; an empty table gives no rows; extra columns are
carried along, but for input columns named ``slot`` or ``shard``, which the results replace. At least one shard is needed, and names are distinct.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: A prime some hundred times the number of shards keeps shares within one per cent.
SLOTS = 65_537
SHARDS = tuple(f"shard-{k:03d}" for k in range(64))


def lookup_table(shards: tuple[str, ...] = SHARDS, slots: int = SLOTS) -> np.ndarray:
    """The position in ``shards`` of the owner of every slot."""
    if not shards or len(set(shards)) != len(shards) or len(shards) > slots:
        raise ValueError("shards must be one or more distinct names, no more than slots")
    if slots < 2 or any(slots % k == 0 for k in range(2, int(slots**0.5) + 1)):
        raise ValueError("slots must be prime, so every step visits every slot")
    draws = [hashlib.sha256(name.encode()).digest() for name in shards]
    at = [int.from_bytes(d[:8], "little") % slots for d in draws]
    step = [int.from_bytes(d[8:16], "little") % (slots - 1) + 1 for d in draws]
    owner, left = [-1] * slots, slots
    while left:
        for k in range(len(shards)):
            while owner[at[k]] >= 0:
                at[k] = (at[k] + step[k]) % slots
            owner[at[k]] = k
            left -= 1
            if not left:
                break
    return np.array(owner, np.int32)


def slot_of(key: Column, slots: int = SLOTS) -> Column:
    digest = F.md5(F.coalesce(key.cast("string"), F.lit("")))
    return F.pmod(F.conv(F.substring(digest, 1, 15), 16, 10).cast("long"), F.lit(slots)).cast("int")


def place(df: DataFrame, key: str = "doc_id", shards: tuple[str, ...] = SHARDS, slots: int = SLOTS) -> DataFrame:
    """``df`` with the slot and the shard number of each row."""
    rows = [(k, int(v)) for k, v in enumerate(lookup_table(shards, slots))]
    table = df.sparkSession.createDataFrame(rows, "slot int, shard int")
    others = [F.col(f"`{c}`") for c in df.columns if c not in ("slot", "shard")]
    return df.select(*others, slot_of(F.col(f"`{key}`"), slots).alias("slot")).join(F.broadcast(table), "slot")  # ``slots`` rows, fixed


def write_shards(df: DataFrame, path: str, key: str = "doc_id", shards: tuple[str, ...] = SHARDS, files_each: int = 8) -> None:
    """Write one folder for each shard; a shard's rows are dealt to ``files_each`` tasks by a salt."""
    placed = place(df, key, shards)
    salt = F.pmod(F.xxhash64(F.col(key)), F.lit(files_each))
    placed.repartition(len(shards) * files_each, "shard", salt).write.partitionBy("shard").parquet(path)


def query(spark, sf_dir: str) -> DataFrame:
    return place(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id")).select("doc_id", "slot", "shard")


def oracle() -> str:
    owners = ", ".join(map(str, lookup_table().tolist()))
    slot = f"('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '')), 1, 15))::BIGINT % {SLOTS}"
    return f"WITH t AS (SELECT [{owners}] AS owners), d AS (SELECT doc_id, CAST({slot} AS INTEGER) AS slot FROM documents) SELECT doc_id, slot, CAST(owners[slot + 1] AS INTEGER) AS shard FROM d, t"

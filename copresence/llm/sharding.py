"""Shard placement through a permutation-filled lookup table.

Every shard has a preference order over the slots of a prime-sized table (start and stride from its name's digest).
Shards take turns claiming the next free slot they prefer, so each owns nearly the same number of slots, and a change
of the shard set moves few of them. A row's key picks a slot by one hash and one modulo; the slot's owner comes from
the table, which is broadcast: its size is the parameter `slots`, never the data's.

Defined cases: a null key is placed as the empty string; equal keys share a shard; an empty input gives no rows;
columns of the input that are called like the added ones are replaced in the output.
"""

from __future__ import annotations

import hashlib
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import hex_number

SLOTS = 16381  # prime
MAX_SLOTS = 1 << 20  # bound of what is broadcast: about 16 MB
SHARDS = tuple(f"shard-{i:03d}" for i in range(64))


def _is_prime(n: int) -> bool:
    return n > 1 and all(n % d for d in range(2, int(n**0.5) + 1))


def lookup_table(shards: Sequence[str] = SHARDS, slots: int = SLOTS, weights: Sequence[int] | None = None) -> list[int]:
    """Owner (index into shards) of each slot. weights: claims that a shard makes per turn."""
    if not shards or len(set(shards)) != len(shards):
        raise ValueError("shards must be distinct and not empty")
    if not _is_prime(slots) or not len(shards) <= slots <= MAX_SLOTS:
        raise ValueError(f"slots must be a prime from the number of shards up to {MAX_SLOTS}")
    claims = list(weights or [1] * len(shards))
    if len(claims) != len(shards) or min(claims) < 0 or not any(claims):
        raise ValueError("weights must be non-negative, one per shard, and not all 0")
    place, stride = [], []
    for name in shards:
        digest = hashlib.sha256(name.encode()).digest()
        place.append(int.from_bytes(digest[:8], "big") % slots)
        stride.append(int.from_bytes(digest[8:16], "big") % (slots - 1) + 1 if slots > 1 else 0)
    owner, free = [-1] * slots, slots
    while free:
        for shard, times in enumerate(claims):
            for _ in range(min(times, free)):
                at = place[shard]
                while owner[at] >= 0:
                    at = (at + stride[shard]) % slots
                owner[at] = shard
                place[shard] = (at + stride[shard]) % slots
                free -= 1
    return owner


def table_frame(spark: SparkSession, owner: Sequence[int]) -> DataFrame:
    """The table as rows (__slot int, __shard int), made from one literal."""
    return spark.range(1).select(F.posexplode(F.split(F.lit(",".join(map(str, owner))), ",")).alias("__slot", "__shard")).select("__slot", F.col("__shard").cast("int").alias("__shard"))


def slot_of(key: Column, slots: int = SLOTS) -> Column:
    return F.pmod(hex_number(F.md5(F.coalesce(key.cast("string"), F.lit(""))), 1, 15), F.lit(slots)).cast("int")


def assign_shards(df: DataFrame, key: str = "doc_id", shards: Sequence[str] = SHARDS, slots: int = SLOTS, weights: Sequence[int] | None = None) -> DataFrame:
    """df with slot (int) and shard (int, index into shards): one scan, no shuffle."""
    table = table_frame(df.sparkSession, lookup_table(shards, slots, weights))
    keep = [F.col(f"`{c}`") for c in df.columns if c not in ("slot", "shard")]
    placed = df.withColumn("__slot", slot_of(F.col(f"`{key}`"), slots))
    return placed.join(F.broadcast(table), "__slot", "left").select(*keep, F.col("__slot").alias("slot"), F.col("__shard").alias("shard"))


def moved_slots(before: Sequence[int], after: Sequence[int]) -> float:
    """Share of slots whose owner differs between two tables of equal size."""
    return sum(a != b for a, b in zip(before, after, strict=True)) / len(before)


def write_shards(df: DataFrame, path: str, key: str = "doc_id", files_per_shard: int = 1, **how) -> None:
    """Write df as Parquet, a folder per shard; rows of a shard are dealt over files_per_shard tasks by key."""
    placed = assign_shards(df, key, **how)
    part = F.pmod(F.xxhash64(F.col(f"`{key}`")), F.lit(files_per_shard))
    placed.repartition(max(1, placed.sparkSession.sparkContext.defaultParallelism), "shard", part).write.mode("overwrite").partitionBy("shard").parquet(path)

"""Sharding by a permutation-filled lookup table.

Shards take turns; each claims the next free slot of its own permutation of a prime number of slots.  Slots differ by at most
one between shards, and a shard that leaves gives up few slots but its own.  The table has a fixed size (``SLOTS`` rows), so
it is broadcast, and placing a row is one probe.

Rows are placed by a key's hash, not by its value, and equal keys share a shard.  Integer keys are folded as they are; keys of any
other type (strings, dates, structures) by their 64-bit hash.  Defined results: a null key goes to slot 0's shard; empty tables give empty results; equal rows get equal shards; ``place`` keeps all columns of its input and adds
``slot`` and ``shard`` (names that an input already has raise an error).
"""

from __future__ import annotations

import zlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegralType

SHARDS, SLOTS = 64, 10_007
#: Key hash: (|key| mod P) * A + B mod P, in 64-bit integers.
P, A, B = 2_147_483_647, 48_271, 11


def lookup_table(names: list[str], slots: int = SLOTS) -> list[int]:
    """Index of the shard that owns each slot; ``slots`` is prime and at least the number of shards."""
    if len(names) != len(set(names)) or not 0 < len(names) <= slots:
        raise ValueError("shard names must be distinct, and no more than the slots")
    if slots < 2 or any(slots % d == 0 for d in range(2, int(slots**0.5) + 1)):
        raise ValueError(f"{slots} is not prime")
    starts = [zlib.crc32(f"start {n}".encode()) % slots for n in names]
    steps = [zlib.crc32(f"step {n}".encode()) % (slots - 1) + 1 for n in names]
    owner, tried, free = [-1] * slots, [0] * len(names), slots
    while free:
        for shard in range(len(names)):
            while owner[slot := (starts[shard] + tried[shard] * steps[shard]) % slots] >= 0:
                tried[shard] += 1
            owner[slot] = shard
            tried[shard] += 1
            free -= 1
            if not free:
                break
    return owner


def shard_names(n: int = SHARDS) -> list[str]:
    return [f"shard-{i:05d}" for i in range(n)]


def slot_of(key: Column, slots: int = SLOTS) -> Column:
    """Slot of an integer key."""
    folded = F.pmod(key.cast("long"), F.lit(P))
    return F.coalesce(F.pmod(F.pmod(folded * A + B, F.lit(P)), F.lit(slots)), F.lit(0)).cast("int")


def place(df: DataFrame, key: str, names: list[str], slots: int = SLOTS) -> DataFrame:
    """``df`` with ``slot int, shard int``."""
    if clash := {"slot", "shard"} & {c.lower() for c in df.columns}:
        raise ValueError(f"the input already has {sorted(clash)}")
    text = ",".join(map(str, lookup_table(names, slots)))
    table = df.sparkSession.range(1).select(F.posexplode(F.split(F.lit(text), ",")).alias("__slot", "__owner"))
    table = table.select("__slot", F.col("__owner").cast("int").alias("shard"))
    number = F.col(key) if isinstance(df.schema[key].dataType, IntegralType) else F.when(F.col(key).isNotNull(), F.xxhash64(key))
    keyed = df.withColumn("slot", slot_of(number, slots))
    return keyed.join(F.broadcast(table), F.col("slot") == F.col("__slot"), "left").drop("__slot")


def write_shards(df: DataFrame, key: str, names: list[str], path: str, salts: int = 8) -> None:
    """Writes one folder per shard; rows of a shard are dealt over ``salts`` writers, so that a heavy key has no task to itself."""
    placed = place(df, key, names).drop("slot").withColumn("__salt", (F.rand(1) * salts).cast("int"))
    placed.repartition(len(names) * salts, "shard", "__salt").drop("__salt").write.partitionBy("shard").parquet(path)

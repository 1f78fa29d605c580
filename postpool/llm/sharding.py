"""Sharding: a lookup table of prime size, filled by shards that take turns to claim slots in their order of preference.

A key's hash picks a slot, the slot names the shard: constant time, near-equal shares, and few moves when a shard goes.
Only DataFrame functions touch rows. Edge cases: a null key is placed like the empty string; equal keys go to equal
shards; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, functions as F

#: Hex digits of an MD5 digest that make a hash: 60 bits, a BIGINT in any SQL dialect.
DIGITS = 15
SLOTS = 65537
SHARDS = tuple(f"shard-{i:03d}" for i in range(64))


def _hash(text: str) -> int:
    return int(hashlib.md5(text.encode()).hexdigest()[:DIGITS], 16)


def is_prime(n: int) -> bool:
    return n > 1 and all(n % i for i in range(2, int(n**0.5) + 1))


def preference(name: str, slots: int) -> tuple[int, int]:
    """(offset, skip): the shard's j-th choice is slot (offset + j * skip) mod slots, a permutation as slots is prime."""
    return _hash(f"offset:{name}") % slots, _hash(f"skip:{name}") % (slots - 1) + 1


def lookup_table(shards: tuple[str, ...] = SHARDS, slots: int = SLOTS, turns: dict[str, int] | None = None) -> list[int]:
    """The shard's number in each slot. `turns` gives a shard more claims a round (its weight). Size: slots, fixed."""
    if not is_prime(slots) or not 0 < len(shards) <= slots or len(set(shards)) < len(shards):
        raise ValueError("slots must be prime, and shards distinct and no more than slots")
    owner = [-1] * slots
    at = [preference(s, slots) for s in shards]
    place = [offset for offset, _ in at]
    free = slots
    while free:
        for i, name in enumerate(shards):
            for _ in range((turns or {}).get(name, 1)):
                if not free:
                    break
                while owner[place[i]] >= 0:
                    place[i] = (place[i] + at[i][1]) % slots
                owner[place[i]] = i
                free -= 1
    return owner


def slot_of(key: Column, slots: int = SLOTS) -> Column:
    return F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit("")).cast("binary")), 1, DIGITS), 16, 10).cast("long") % slots


def place(df: DataFrame, key: str, shards: tuple[str, ...] = SHARDS, slots: int = SLOTS, turns: dict[str, int] | None = None) -> DataFrame:
    """Adds slot and shard to every row. No shuffle: the table is one constant of the plan, folded once, sent with each task."""
    owners = F.split(F.lit(",".join(map(str, lookup_table(shards, slots, turns)))), ",")
    names = F.split(F.lit("\n".join(shards)), "\n")
    slot = slot_of(F.col(f"`{key}`"), slots)
    out = df.withColumn("slot", slot)
    return out.withColumn("shard", F.get(names, F.get(owners, F.col("slot").cast("int")).cast("int")))


def sizes(placed: DataFrame) -> DataFrame:
    """(shard, n_rows), to see how even the shards are."""
    return placed.groupBy("shard").agg(F.count(F.lit(1)).alias("n_rows"))

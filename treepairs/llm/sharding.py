"""Sharding through a permutation-filled lookup table, with DataFrame functions only on the rows.

Every shard has an order of preference over the slots of a table of prime size, given by an offset and a stride from a
digest of its name. The shards take turns; in its turn a shard claims the next free slot of its order. The table has a
fixed number of rows, whatever the data, so it is broadcast; a row's place is a digest of its key modulo the table size.
Removing a shard moves few rows besides its own.

Defined cases: a null key is placed as the empty key; repeated rows go to the same shard; an empty table gives an empty
result; other columns are kept by :func:`place`. A third of all rows with one key go to one shard by definition: use a
key of high cardinality, as the query does.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of the broadcast table are bounded by this.
LARGEST_TABLE = 655_373


def _digest(text: str) -> int:
    return int(hashlib.md5(text.encode()).hexdigest()[:15], 16)


def is_prime(n: int) -> bool:
    return n > 1 and all(n % d for d in range(2, int(n**0.5) + 1))


def preference(name: str, size: int) -> tuple[int, int]:
    return _digest(f"offset:{name}") % size, _digest(f"stride:{name}") % (size - 1) + 1


def fill(names: list[str], size: int) -> list[int]:
    """The shard of each slot."""
    if not names or len(set(names)) != len(names):
        raise ValueError("shards need distinct names")
    if not is_prime(size) or size < len(names) or size > LARGEST_TABLE:
        raise ValueError(f"the table size must be a prime of at least {len(names)} and at most {LARGEST_TABLE}")
    table, claimed = [-1] * size, 0
    orders = [preference(n, size) for n in names]
    turn = [0] * len(names)
    while claimed < size:
        for shard, (offset, stride) in enumerate(orders):
            while table[slot := (offset + turn[shard] * stride) % size] >= 0:
                turn[shard] += 1
            table[slot] = shard
            claimed += 1
            if claimed == size:
                break
    return table


def slot_of(key: Column, size: int) -> Column:
    head = F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit(""))), 1, 15), 16, 10).cast("long")
    return F.pmod(head, F.lit(size)).cast("int")


def lookup(spark: SparkSession, names: list[str], size: int) -> DataFrame:
    """slot, shard: at most LARGEST_TABLE rows."""
    return spark.range(1).select(F.posexplode(F.lit(fill(names, size))).alias("slot", "shard"))


def place(rows: DataFrame, key: Column, names: list[str], size: int = 6553) -> DataFrame:
    """All columns, ``slot`` and ``shard``; replaces columns of these names."""
    rest = rows.drop("slot", "shard")
    return rest.withColumn("slot", slot_of(key, size)).join(F.broadcast(lookup(rows.sparkSession, names, size)), "slot").select(*rest.columns, "slot", "shard")

"""Placement by a permutation-filled lookup table.

Every shard orders the slots of a prime-sized table by a permutation of its own and the shards take turns in claiming their
next free slot, as often in a round as their weight.  The table has a fixed size, so it is broadcast; a row is placed by
one hash and one look-up.  When a shard goes, few slots besides its own change hands.

Defined results: a null key is placed like any other value; equal keys share a shard; an empty table gives an empty result;
columns named ``slot`` or ``shard`` are replaced, all others stay.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SLOTS = 65_537


def is_prime(n: int) -> bool:
    return n > 1 and all(n % d for d in range(2, int(n**0.5) + 1))


def lookup_table(shards: dict[str, int], slots: int = SLOTS) -> list[str]:
    """The shard of each slot; ``shards`` maps names to whole positive weights."""
    if not is_prime(slots) or not 0 < len(shards) <= slots:
        raise ValueError("the table's size must be prime and no smaller than the number of shards")
    if any(w < 1 for w in shards.values()):
        raise ValueError("weights must be whole and positive")
    names = sorted(shards)
    starts, steps = [], []
    for name in names:
        h = hashlib.sha256(name.encode()).digest()
        starts.append(int.from_bytes(h[:8], "big") % slots)
        steps.append(int.from_bytes(h[8:16], "big") % (slots - 1) + 1)
    owner: list[str | None] = [None] * slots
    at, left = starts[:], slots
    while True:
        for i, name in enumerate(names):
            for _ in range(shards[name]):
                while owner[at[i]] is not None:
                    at[i] = (at[i] + steps[i]) % slots
                owner[at[i]] = name
                left -= 1
                if not left:
                    return owner  # type: ignore[return-value]


def place(df: DataFrame, key: str, shards: dict[str, int], slots: int = SLOTS) -> DataFrame:
    """``df`` with ``slot`` and ``shard``; columns of these names are replaced."""
    if key in ("slot", "shard"):
        raise ValueError("the key may not be named slot or shard")
    df = df.drop("slot", "shard")
    table = df.sparkSession.createDataFrame(list(enumerate(lookup_table(shards, slots))), "slot int, shard string")
    slot = F.pmod(F.xxhash64(F.col(key)), F.lit(slots)).cast("int")
    return df.withColumn("slot", slot).join(F.broadcast(table), "slot")


def moved(before: list[str], after: list[str]) -> float:
    """Share of slots that change hands although their shard stays."""
    stays = set(after)
    return sum(a in stays and a != b for a, b in zip(before, after)) / len(before)


def write_shards(df: DataFrame, key: str, shards: dict[str, int], path: str, files: int = 4) -> None:
    """Write each shard's rows to a folder of its own, in up to ``files`` files, whatever the sizes of the shards."""
    placed = place(df, key, shards).withColumn("_part", F.pmod(F.xxhash64(F.col(key), F.lit(1)), F.lit(files)))
    placed.repartition(len(shards) * files, "shard", "_part").drop("_part", "slot").write.partitionBy("shard").parquet(path)

"""Hash slots of objects, and the workers that slots and replicas go to."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Odd multiplier of the portable slot hash; fixed, so that stored layouts stay readable.
MULTIPLIER = 1327217885


def slot_of(object_id: Column | str, p: int, kind: str = "mult") -> Column:
    """Slot in [0, 2^p): ``mult`` is portable to other engines, ``xx`` mixes better."""
    col = F.col(object_id) if isinstance(object_id, str) else object_id
    if kind == "xx":
        return F.pmod(F.xxhash64(col), F.lit(1 << p)).cast("int")
    low = F.pmod(col, F.lit(1 << 32))
    return F.shiftright(F.pmod(low * F.lit(MULTIPLIER), F.lit(1 << 32)), 32 - p).cast("int")


def slot_of_int(object_id: int, p: int) -> int:
    return ((object_id % (1 << 32)) * MULTIPLIER % (1 << 32)) >> (32 - p)


def worker_of_slot(slot: Column | str, n: int) -> Column:
    """Slots are dealt round robin."""
    return F.pmod(F.col(slot) if isinstance(slot, str) else slot, F.lit(n)).cast("int")


def object_placement(objects: DataFrame, p: int, n: int, replicas: int = 3, kind: str = "mult") -> DataFrame:
    """object_id, slot, copy and worker: the slot's worker and the next ones hold a copy each."""
    placed = objects.select("object_id", slot_of("object_id", p, kind).alias("slot"))
    copies = placed.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(min(replicas, n) - 1))))
    return copies.withColumn("worker", F.pmod(F.col("slot") + F.col("copy"), F.lit(n)).cast("int"))

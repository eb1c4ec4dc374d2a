"""Sharding by jump consistent hashing, in SQL functions only.

A key walks through ever larger bucket numbers driven by a 64-bit linear congruential
generator; the last bucket below the shard count is its shard. Adding a shard moves a key
only if the next jump lands exactly on the new shard. Spark's BIGINT arithmetic raises on
overflow, so the generator's state is kept as two 32-bit halves and multiplied in 16-bit limbs.

Edge cases: a null key behaves as key 0, a null text has no bytes, repeated rows get
slots of their own, an empty table gives an empty result, further columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Fixed value: the multiplier of the generator.
MULTIPLIER = 2862933555777941757
_HALF = 0xFFFFFFFF
_LIMB = 0xFFFF
#: More shards than this would need longer walks than the bound below covers.
MAX_STEPS = 256


def _advance(high: Column, low: Column) -> tuple[Column, Column]:
    """(high, low) * MULTIPLIER + 1 modulo 2**64."""
    m = [(MULTIPLIER >> (16 * k)) & _LIMB for k in range(4)]
    first, second = low * m[0], low * m[1]
    total = first + F.shiftleft(second.bitwiseAND(_LIMB), 16) + F.lit(1)
    upper = (
        F.shiftright(total, 32)
        + F.shiftright(second, 16)
        + low * m[2]
        + F.shiftleft((low * m[3]).bitwiseAND(_LIMB), 16)
        + high * m[0]
        + F.shiftleft((high * m[1]).bitwiseAND(_LIMB), 16)
    )
    return upper.bitwiseAND(F.lit(_HALF)), total.bitwiseAND(F.lit(_HALF))


def jump_shard(key: Column, n_shards: int) -> Column:
    """struct(shard INT, grown INT): the shard among n_shards, and among n_shards + 1."""
    if n_shards < 1:
        raise ValueError("n_shards must be at least 1")
    key = F.coalesce(key.cast("bigint"), F.lit(0).cast("bigint"))
    long = lambda v: F.lit(v).cast("bigint")
    start = F.struct(
        F.shiftrightunsigned(key, 32).alias("high"),
        key.bitwiseAND(long(_HALF)).alias("low"),
        long(-1).alias("at"),
        long(0).alias("next"),
    )

    def step(s: Column, _: Column) -> Column:
        high, low = _advance(s["high"], s["low"])
        leap = F.floor((s["next"] + 1).cast("double") * (F.lit(2147483648.0) / (F.shiftright(high, 1) + 1).cast("double")))
        moved = F.struct(high.alias("high"), low.alias("low"), s["next"].alias("at"), leap.cast("bigint").alias("next"))
        return F.when(s["next"] < long(n_shards), moved).otherwise(s)

    def finish(s: Column) -> Column:
        done = F.struct(
            s["at"].cast("int").alias("shard"),
            F.when(s["next"] == long(n_shards), long(n_shards)).otherwise(s["at"]).cast("int").alias("grown"),
        )
        return F.when(s["next"] >= long(n_shards), done).otherwise(F.raise_error(F.lit("a key's walk is too long")).cast("struct<shard:int,grown:int>"))

    # each step raises the bucket by one at least, so n_shards steps always suffice
    return F.aggregate(F.sequence(F.lit(1), F.lit(min(n_shards, MAX_STEPS))), start, step, finish)


def shard_documents(docs: DataFrame, n_shards: int = 24, slices: int = 256) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row of docs.

    Slots are numbered in two levels: rows of a shard are dealt to `slices` by a hash, ranked
    there, and shifted by the sizes of the slices before; no task sees a whole shard. The table
    of slice sizes has n_shards * slices rows at most, whatever the input, and is broadcast.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    walk = F.col("walk")
    rows = (
        docs.select(F.col("doc_id"), (F.octet_length(text).cast("bigint") + 8).alias("size"), F.crc32(F.encode(text, "UTF-8")).alias("text_crc32"))
        .withColumn("walk", jump_shard(F.col("doc_id"), n_shards))
        .select("doc_id", "size", "text_crc32", walk["shard"].alias("shard"), walk["grown"].alias("grown_shard"))
        .withColumn("slice", F.pmod(F.xxhash64("doc_id", "text_crc32", "size"), F.lit(slices)).cast("int"))
    )
    sizes = rows.groupBy("shard", "slice").agg(F.count(F.lit(1)).alias("rows_here"))
    before = Window.partitionBy("shard").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.select("shard", "slice", F.coalesce(F.sum("rows_here").over(before), F.lit(0)).alias("offset"))
    inside = Window.partitionBy("shard", "slice").orderBy("doc_id", "text_crc32", "size")
    return (
        rows.withColumn("rank", F.row_number().over(inside))
        .join(F.broadcast(offsets), ["shard", "slice"])
        .select(
            "doc_id",
            "size",
            "text_crc32",
            F.lit("key").alias("law"),
            "shard",
            (F.col("offset") + F.col("rank") - 1).cast("bigint").alias("slot"),
            "grown_shard",
        )
    )

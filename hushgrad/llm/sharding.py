"""Sharding by jump consistent hashing, in DataFrame functions only.

A 64-bit key walks a fixed linear congruential sequence; each state names the
next bucket count at which the key would move, so the shard for n buckets is
the last jump below n.  No ring table exists, and going from n to n+1 shards
moves exactly the keys whose walk lands on n.

The multiplication modulo 2**64 is put together from 32 and 16 bit limbs, since
ANSI arithmetic refuses a product that overflows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hushgrad.llm import store

#: Fixed values of the published jump hash: multiplier and increment of its generator.
MULTIPLIER = 2862933555777941757
INCREMENT = 1
ROWS_PER_SLOT_GROUP = 20_000


def _lo(c: Column) -> Column:
    return c.bitwiseAND(F.lit(0xFFFFFFFF))


def _times(x32: Column, factor: int) -> Column:
    """x32 (0..2**32-1) times a 32-bit factor, as (low 32 bits, high 32 bits) in a struct."""
    p = x32 * F.lit(factor & 0xFFFF)
    q = x32 * F.lit(factor >> 16)
    low = p + F.shiftleft(q.bitwiseAND(F.lit(0xFFFF)), 16)
    return F.struct(_lo(low).alias("lo"), _lo(F.shiftrightunsigned(low, 32) + F.shiftrightunsigned(q, 16)).alias("hi"))


def _advance(key: Column) -> Column:
    """key * MULTIPLIER + INCREMENT modulo 2**64, as a struct of unsigned halves."""
    x0, x1 = key["lo"], key["hi"]
    m0, m1 = MULTIPLIER & 0xFFFFFFFF, MULTIPLIER >> 32
    a = _times(x0, m0)
    low = a["lo"] + F.lit(INCREMENT)
    high = a["hi"] + _times(x1, m0)["lo"] + _times(x0, m1)["lo"] + F.shiftrightunsigned(low, 32)
    return F.struct(_lo(low).alias("lo"), _lo(high).alias("hi"))


def jump_shards(key: Column, shards: int) -> Column:
    """struct(shard, grown): the jump hash of a long key for `shards` and for `shards`+1 buckets.

    Each step of the walk moves to a larger bucket number, so shards+1 steps
    always suffice; after the walk has passed the end the state stays as it is.
    """
    key = F.coalesce(key.cast("long"), F.lit(0).cast("long"))
    start = F.struct(
        F.struct(_lo(key).alias("lo"), _lo(F.shiftrightunsigned(key, 32)).alias("hi")).alias("key"),
        F.lit(-1).cast("long").alias("shard"),
        F.lit(-1).cast("long").alias("grown"),
        F.lit(0).cast("long").alias("jump"),
    )

    def step(state: Column, _: Column) -> Column:
        moved = _advance(state["key"])
        # the top 31 bits of the state choose the next jump
        share = (F.shiftrightunsigned(moved["hi"], 1) + F.lit(1)).cast("double")
        jump = F.floor((state["jump"] + F.lit(1)).cast("double") * (F.lit(float(1 << 31)) / share)).cast("long")
        return F.when(
            state["jump"] <= F.lit(shards),
            F.struct(
                moved.alias("key"),
                F.when(state["jump"] < F.lit(shards), state["jump"]).otherwise(state["shard"]).alias("shard"),
                state["jump"].alias("grown"),
                jump.alias("jump"),
            ),
        ).otherwise(state)

    walked = F.aggregate(F.sequence(F.lit(0), F.lit(shards)), start, step)
    return F.struct(walked["shard"].cast("int").alias("shard"), walked["grown"].cast("int").alias("grown"))


def shard(docs: DataFrame, shards: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: doc_id, size, text_crc32, law, shard, slot, grown_shard.

    law is always `key`: the id and the number of shards alone decide.  size is
    the text's UTF-8 bytes plus 16.  slot numbers a shard's rows from 0 without
    gaps.  A shard may hold any share of the table, so a slot is the row's place
    in a small group of its shard (a hash of id and text) plus the counts of the
    groups before it; the number of groups follows the row count.

    A null text counts as empty; a null id is sharded as 0; rows that repeat an
    id share its shard and get slots of their own; an empty table gives no rows.
    """
    rows = docs.select(
        F.col(id_col).alias("doc_id"),
        F.coalesce(F.col(text_col), F.lit("")).alias("_t"),
    )
    groups = max(1, -(-rows.count() // (shards * ROWS_PER_SLOT_GROUP)))
    # with the text, or rows that share an id (or have none) would be one group
    placed = F.pmod(F.xxhash64("doc_id", "_t", F.lit(17)), F.lit(groups)).cast("int") if groups > 1 else F.lit(0)
    both = jump_shards(F.col("doc_id"), shards)
    counts = store.settle(
        rows.select(both["shard"].alias("shard"), placed.alias("_g")).groupBy("shard", "_g").agg(F.count(F.lit(1)).alias("_n")),
        "shard-counts",
    )
    # rows of this window: one per group of about ROWS_PER_SLOT_GROUP rows
    before = counts.select(
        "shard",
        "_g",
        F.expr("coalesce(sum(_n) over (partition by shard order by _g rows between unbounded preceding and 1 preceding), 0L)").alias("_before"),
    )
    numbered = (
        rows.select(
            "doc_id",
            (F.octet_length("_t") + F.lit(16)).cast("long").alias("size"),
            F.crc32(F.col("_t").cast("binary")).alias("text_crc32"),
            both.alias("_b"),
            placed.alias("_g"),
        )
        .select("doc_id", "size", "text_crc32", F.col("_b.shard").alias("shard"), F.col("_b.grown").alias("grown_shard"), "_g")
        .withColumn("_r", F.expr("row_number() over (partition by shard, _g order by doc_id, text_crc32, size)"))
    )
    return numbered.join(before, ["shard", "_g"]).select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit("key").alias("law"),
        "shard",
        (F.col("_before") + F.col("_r") - 1).cast("long").alias("slot"),
        "grown_shard",
    )

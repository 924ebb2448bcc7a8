"""Bitmaps of the rows that a later step needs, so that others are left out in the scan (native DataFrame operations only)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from crossaudit.functions.storage import materialize

#: Fewest and most words of 64 bits in a bitmap; between them it has 16 bits for each row needed. Beyond the most (8 MB)
#: more rows pass by chance, which the join that follows drops again.
LEAST_WORDS, MOST_WORDS = 1 << 10, 1 << 20


def _slot(words: int, *key: Column) -> Column:
    return F.xxhash64(*key).bitwiseAND(F.lit(words * 64 - 1))


def only_needed(need: DataFrame, rows: DataFrame, *key: Column) -> DataFrame:
    """Rows whose ``key`` may equal a row of ``need`` (all its columns, of the key's types); none that does is lost."""
    words = LEAST_WORDS
    n = need.count()
    while words * 4 < n and words < MOST_WORDS:
        words *= 2
    slot = _slot(words, *[F.col(c) for c in need.columns])
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), slot.bitwiseAND(F.lit(63)).cast("int"))
    some = need.select(F.call_function("shiftright", slot, F.lit(6)).alias("at"), bit.alias("bit")).groupBy("at").agg(F.bit_or("bit").alias("bits"))
    every = need.sparkSession.range(words).select(F.col("id").alias("at")).join(some, "at", "left").select("at", F.coalesce("bits", F.lit(0).cast("long")).alias("bits"))
    table = materialize(every.agg(F.sort_array(F.collect_list(F.struct("at", "bits"))).alias("x")).select(F.col("x.bits").alias("bitmap")), "bitmap")
    own = _slot(words, *key)
    word = F.get(table.scalar(), F.call_function("shiftright", own, F.lit(6)).cast("int"))
    return rows.where(F.call_function("shiftright", word, own.bitwiseAND(F.lit(63)).cast("int")).bitwiseAND(F.lit(1)) == 1)

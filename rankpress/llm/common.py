"""Shared pieces: table access, fold rules, lineage cuts, samples by thresholds; and the byte spans of the engine."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from ..functions.spans import WORD_RE, SpanHasher, as_bytes, chunks, lower_ascii, mix, spared, word_spans  # noqa: F401
from ..sources.tables import cut, shared_folder, table  # noqa: F401

def fold(key: str, mod: int) -> Column:
    """crc32 of the key written as text, modulo `mod`; a null key falls in fold 1 (never held out)."""
    return F.coalesce(F.pmod(F.crc32(F.col(key).cast("string").cast("binary")), F.lit(mod)), F.lit(1))


def held_out(key: str, mod: int) -> Column:
    return fold(key, mod) == 0


def near_bound(df: DataFrame, key: str, by: str, n: int) -> DataFrame:
    """About n rows of each value of `by`, all where there are fewer: those whose hash of the key lies below a threshold that
    the value's number of rows sets. No sort, no window, and no row's place depends on another row."""
    place = F.pmod(F.xxhash64(F.col(key)), F.lit(1 << 52)) / float(1 << 52)
    sizes = df.groupBy(by).agg(F.count("*").alias("_of"), F.min(place).alias("_least")).where(F.col(by).isNotNull())
    sizes = sizes.withColumn("_upto", F.when(F.col("_of") > n, (F.lit(float(n)) / F.col("_of"))).otherwise(1.0)).withColumnRenamed(by, "_by")
    return df.join(F.broadcast(cut(sizes)), F.col(by) == F.col("_by")).where((place < F.col("_upto")) | (place == F.col("_least"))).drop("_by", "_of", "_least", "_upto")

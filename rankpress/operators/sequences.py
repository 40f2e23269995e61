"""Running values over long sequences, such as a busy user's events, without one task for each sequence.

A sequence is cut into buckets that follow its order. Windows run within a bucket only; what earlier buckets hand on is aggregated to a
row a bucket, carried over these few rows by a window, and joined back.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window as W, functions as F


def hour_of(ts: str = "ts") -> Column:
    """Hours since 1970: buckets for events in the order of time."""
    return F.datediff(F.col(ts).cast("date"), F.lit("1970-01-01").cast("date")) * 24 + F.hour(ts)


def _carried(df: DataFrame, keys: list[str], bucket: str, part: Column, carry, name: str) -> DataFrame:
    """df with `name`: what the buckets before a row's own come to. part: aggregate of a bucket; carry: of parts, over a window."""
    parts = df.groupBy(*keys, bucket).agg(part.alias("_part"))
    past = W.partitionBy(*keys).orderBy(bucket).rowsBetween(W.unboundedPreceding, -1)
    parts = parts.select(*(F.col(k).alias(f"_k{i}") for i, k in enumerate((*keys, bucket))), carry(F.col("_part")).over(past).alias(name))
    same = reduce(lambda a, b: a & b, (F.col(k).eqNullSafe(F.col(f"_k{i}")) for i, k in enumerate((*keys, bucket))))
    return df.join(parts, same).drop(*(f"_k{i}" for i in range(len(keys) + 1)))


def running_sum(df: DataFrame, keys: list[str], bucket: str, order: list[str], value: Column, name: str, own: bool = True) -> DataFrame:
    """df with `name`: the sum of value over the rows of the same keys up to this one, itself included or not."""
    d = _carried(df.withColumn("_v", value), keys, bucket, F.sum("_v"), F.sum, "_past")
    here = F.sum("_v").over(W.partitionBy(*keys, bucket).orderBy(*order).rowsBetween(W.unboundedPreceding, 0 if own else -1))
    return d.withColumn(name, F.coalesce(here, F.lit(0)) + F.coalesce("_past", F.lit(0))).drop("_v", "_past")


def last_before(df: DataFrame, keys: list[str], bucket: str, order: list[str], value: Column, name: str) -> DataFrame:
    """df with `name`: the last value that isn't null among the rows of the same keys before this one."""
    d = df.withColumn("_v", value)
    latest = F.max(F.when(F.col("_v").isNotNull(), F.struct(*order, "_v")))["_v"]
    d = _carried(d, keys, bucket, latest, lambda c: F.last(c, ignorenulls=True), "_past")
    here = F.last("_v", ignorenulls=True).over(W.partitionBy(*keys, bucket).orderBy(*order).rowsBetween(W.unboundedPreceding, -1))
    return d.withColumn(name, F.coalesce(here, "_past")).drop("_v", "_past")


def moving(df: DataFrame, keys: list[str], bucket: str, order: list[str], what: Column, rows: int, name: str, chunk: int = 4096) -> DataFrame:
    """df with `name`: the aggregate `what` over this row and the rows - 1 before it. Rows are numbered, cut into chunks by number, and
    the last ones of a chunk stand in front of the next one too."""
    d = running_sum(df, keys, bucket, order, F.lit(1), "_i", own=False)
    no = F.expr(f"_i div {chunk}")
    also = F.when(F.col("_i") % chunk > chunk - rows, F.array(no, no + 1)).otherwise(F.array(no))
    d = d.withColumn("_chunk", F.explode(also))
    w = W.partitionBy(*keys, "_chunk").orderBy("_i").rowsBetween(1 - rows, 0)
    return d.withColumn(name, what.over(w)).where(F.col("_chunk") == no).drop("_i", "_chunk")

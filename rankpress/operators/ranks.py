"""Ranks under count models of any size, by joins: the same numbers as CountModel gives, with no model sent to a task.

Tokens come with their packed contexts, are counted as distinct pairs of longest context and token, and each pair is ranked once. A context's
list of followers is one row, at most as long as the vocabulary; the list of no context is the one that goes to all tasks.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..functions.predictors import BITS, context_keys


def pairs(texts: DataFrame, tokenizer, order: int, keep: str = "grp") -> DataFrame:
    """(keep, ctx, token, n): distinct pairs of the texts of each value of `keep`, counted within tasks before the shuffle."""

    def run(batches):
        for b in batches:
            names, all_ = b.column(0).to_pylist(), b.column(1).to_pylist()
            for g in sorted(set(names), key=str):
                ids = [tokenizer.encode(t) for n, t in zip(names, all_) if n == g and t]
                if not ids:
                    continue
                both = np.stack([np.concatenate([context_keys(x, order)[order] for x in ids]), np.concatenate(ids).astype(np.int64)])
                u, n = np.unique(both, axis=1, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array([g] * len(n), pa.string()), pa.array(u[0]), pa.array(u[1].astype(np.int32)), pa.array(n.astype(np.int64))], names=["grp", "ctx", "token", "n"])

    d = texts.select(F.col(keep).cast("string").alias("grp"), "text").where("text is not null")
    got = d.mapInArrow(run, "grp string, ctx long, token int, n long")
    return got.groupBy("grp", "ctx", "token").agg(F.sum("n").alias("n"))


def lists(counts: DataFrame) -> DataFrame:
    """(level, ctx, tokens): the followers of each context, the commonest first, of equal ones the smaller id."""
    got = counts.groupBy("level", "ctx").agg(F.array_sort(F.collect_list(F.struct((-F.col("cnt")).alias("c"), "token"))).alias("t"))
    return got.select("level", "ctx", F.transform("t", lambda x: x["token"]).alias("tokens"))


def rank_pairs(distinct: DataFrame, counts: DataFrame, order: int) -> DataFrame:
    """(ctx, token, rank) of distinct pairs of longest context and token, under counts (level, ctx, token, cnt) of texts.

    From the longest context down, a pair is settled by the first list that has its token: its place there, and one for each token of the
    longer context's list that stands behind it. What no list has stands behind all, by id.
    """
    followers = lists(counts)
    left = distinct.select("ctx", "token").distinct().withColumn("above", F.lit(None).cast("array<int>"))
    done = None
    for k in range(order, -1, -1):
        have = followers.where(F.col("level") == k).select(F.col("ctx").alias("key"), "tokens")
        if k:
            left = left.withColumn("key", F.col("ctx").bitwiseAND(F.lit((1 << (BITS * k)) - 1))).join(have, "key", "left").drop("key")
        else:
            first = have.groupBy().agg(F.coalesce(F.first("tokens"), F.array().cast("array<int>")).alias("tokens"))
            left = left.crossJoin(F.broadcast(first))
        place = F.coalesce(F.array_position("tokens", F.col("token")), F.lit(0))
        behind = F.size(F.array_intersect("above", F.slice("tokens", F.col("_place").cast("int") + 1, F.greatest(F.lit(0), F.size("tokens") - F.col("_place").cast("int")))))
        left = left.withColumn("_place", place)
        if not k:  # the unseen ones
            unseen = F.size("tokens") + F.col("token") - F.size(F.filter("tokens", lambda x: x < F.col("token")))
            got = left.select("ctx", "token", F.when(F.col("_place") > 0, F.col("_place") - 1 + F.when(F.col("above").isNull(), 0).otherwise(behind)).otherwise(unseen).cast("long").alias("rank"))
        else:
            got = left.where("_place > 0").select("ctx", "token", (F.col("_place") - 1 + F.when(F.col("above").isNull(), 0).otherwise(behind)).cast("long").alias("rank"))
            left = left.where("_place = 0").select("ctx", "token", F.col("tokens").alias("above"))
        done = got if done is None else done.unionByName(got)
    return done


def histogram(texts: DataFrame, counts: DataFrame, tokenizer, order: int, keep: str = "grp") -> DataFrame:
    """(grp, rank, n): how often each rank stands in the texts of a group."""
    p = pairs(texts, tokenizer, order, keep)
    return p.join(rank_pairs(p, counts, order), ["ctx", "token"]).groupBy("grp", "rank").agg(F.sum("n").alias("n"))

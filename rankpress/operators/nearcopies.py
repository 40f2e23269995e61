"""Near copies by the Jaccard similarity of word shingles, exact.

Two texts are near copies when the sets of their five-word shingles have a similarity of 0.8 or more. Fingerprints of 64 bits
don't decide that: such texts differ in ten bits on average and in more than any index can probe. So the index here holds
shingles. Under one order of all shingles, two sets of similarity s share a shingle among the first n - ceil(s*n) + 1 of each
(n: its size), so only these are indexed. Any order is right; one that puts common shingles last, known from a quarter of
the texts, makes few candidates. Every candidate is verified on both whole sets.

The shingles of a passage that several texts share all stand in the same texts. Entries with the same texts, told by count, smallest, largest and
a sum of hashes, are one entry with a weight, so a shared passage costs its texts once and not once a shingle.

Only groups are asked for, not pairs. First each set is compared with the smallest of every entry it stands in (and with whatever the
caller names), and then the pairs of an entry that aren't in one group yet: a group of many copies costs a pair a member, and no
pair that could join two groups is left out. Of these pairs only those are made whose places allow it: two similar sets meet in
their first common shingle, and both have to hold all they share from there on, s/(1+s) of both sizes or more. In the smaller of two sets that place is
among the first 1 - 2s/(1+s) of it (a ninth), so an entry in which no set has it as early makes no pair at all.

Words are split at white space and compared without ASCII case. Texts with fewer words are one shingle; null and empty texts
are copies of each other. Equal sets are one node, so copies cost one row each.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F

from ..functions.spans import SpanHasher, as_bytes, chunks, lower_ascii, mix, spared, word_spans
from ..sources.tables import cut
from .components import components


#: Tables up to so many rows of longs are sent to all tasks; a larger one meets its partner in a shuffle.
SENT = 1 << 19


def _sent(df: DataFrame) -> DataFrame:
    """df, cut, to be broadcast if it is small: texts then stay where they are."""
    df = cut(df)
    return F.broadcast(df) if df.count() <= SENT else df


def shingles(texts: list, width: int = 5) -> list[np.ndarray]:
    """The sorted set of each text's shingles, by 64-bit hashes."""
    out = []
    for i, j in chunks(texts, 1 << 19):
        data, starts = as_bytes(texts[i:j], b" ")
        data = lower_ascii(data)
        a, b = word_spans(data)
        h = SpanHasher(data)(a, b)
        edge = np.searchsorted(a, starts)
        for x, y in zip(edge[:-1].tolist(), edge[1:].tolist()):
            w, s = h[x:y], np.zeros(max(0, min(1, y - x), y - x - width + 1), np.uint64)
            for k in range(min(width, len(w))):
                s = mix(s + w[k : k + len(s)] + np.uint64(k + 1))
            out.append(np.unique(s))
    return out


def _common(docs: DataFrame, width: int, one_in: int, least: int, most: int) -> tuple[np.ndarray, np.ndarray]:
    """(shingle, count) of the commonest shingles of a part of the texts, at most `most`, ordered by shingle; they decide the order of the
    index, and no result."""

    def run(batches):
        for b in spared(batches):
            for s in shingles(b.column(0).to_pylist(), width):
                yield pa.RecordBatch.from_arrays([pa.array(s.view(np.int64))], names=["t"])

    part = docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(one_in)) == 0).select("text")
    n = cut(part.mapInArrow(run, "t long").groupBy("t").agg(F.count("*").alias("n")).where(F.col("n") >= least))
    step = F.floor(F.log2("n") * 8).cast("int")  # counts in steps of a twelfth, so that no sort is needed to find the commonest
    taken, low = 0, None
    for r in n.groupBy(step.alias("s")).count().orderBy(F.desc("s")).collect():
        taken += r["count"]
        if taken > most:
            break
        low = r.s
    got = n.where(step >= low if low is not None else F.lit(False)).toArrow()
    t, c = got.column("t").to_numpy().view(np.uint64), got.column("n").to_numpy()
    order = np.argsort(t)
    return t[order], c[order]


def _sets(docs: DataFrame, width: int, similarity: float, common) -> DataFrame:
    """(doc_id, digest, n, first): the set's digest and size and the shingles by which it is indexed."""
    held = docs.sparkSession.sparkContext.broadcast(common)

    def run(batches):
        known, count = held.value
        for b in spared(batches):
            digest, size, first = [], [], []
            for s in shingles(b.column(1).to_pylist(), width):
                digest.append(xxhash.xxh3_128_digest(s.tobytes()))
                size.append(len(s))
                keep = len(s) - math.ceil(similarity * len(s) - 1e-9) + 1 if len(s) else 0
                if len(known) and len(s):  # places count, so short sets are ordered, too
                    at = np.minimum(np.searchsorted(known, s), len(known) - 1)
                    s = s[np.lexsort((s, np.where(known[at] == s, count[at], 0)))]
                first.append(s[:keep].view(np.int64))
            offsets = pa.array(np.concatenate([[0], np.cumsum([len(x) for x in first])]).astype(np.int32))
            lists = pa.ListArray.from_arrays(offsets, pa.array(np.concatenate([np.zeros(0, np.int64), *first])))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(digest, pa.binary()), pa.array(size, pa.int32()), lists], names=["doc_id", "digest", "n", "first"])

    return docs.mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, digest binary, n int, first array<long>")


def _verified(docs: DataFrame, pairs: DataFrame, width: int, similarity: float) -> DataFrame:
    """The pairs (a, b) of doc_ids whose whole sets are similar enough; a pair comes again for each repeated row of its ids."""

    def run(batches):
        for b in spared(batches):
            sets = shingles(b.column(1).to_pylist(), width)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([s.view(np.int64) for s in sets], pa.list_(pa.int64()))], names=["id", "set"])

    ids = pairs.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()
    sets = cut(docs.join(_sent(ids), "doc_id", "left_semi").mapInArrow(run, f"id {dict(docs.dtypes)['doc_id']}, set array<long>"))
    both = pairs.join(sets.select(F.col("id").alias("a"), "set"), "a").join(sets.select(F.col("id").alias("b"), F.col("set").alias("set2")), "b")
    same = F.size(F.array_intersect("set", "set2"))
    return both.where(same >= similarity * (F.size("set") + F.size("set2") - same) - 1e-9).select("a", "b")


def _early(similarity: float):
    """Whether the smaller of two similar sets can have its first shared shingle at `pos`."""
    return F.col("n") - F.col("pos") >= 2 * similarity / (1 + similarity) * F.col("n") - 1e-6


def crossing(placed: DataFrame, similarity: float) -> DataFrame:
    """(a, b), some more than once: the pairs of an entry that are in different groups and that their places in it allow to be similar.

    placed: (t, node, n, pos, root): the place of an entry's first shingle in each of its sets, their sizes and groups.
    """
    told = placed.groupBy("t").agg(F.min("root").alias("r1"), F.max("root").alias("r2"), F.max(_early(similarity)).alias("early"))
    placed = cut(placed.join(told.where("r1 <> r2 and early").select("t"), "t", "left_semi"))
    a = placed.where(_early(similarity)).withColumnRenamed("node", "a")
    b = placed.select("t", F.col("node").alias("b"), F.col("n").alias("m"), F.col("pos").alias("pos2"), F.col("root").alias("root2"))
    common = F.least(F.col("n") - F.col("pos"), F.col("m") - F.col("pos2"))
    fits = common >= similarity / (1 + similarity) * (F.col("n") + F.col("m")) - 1e-6
    return a.join(b, "t").where(((F.col("n") < F.col("m")) | (F.col("n") == F.col("m")) & (F.col("a") < F.col("b"))) & (F.col("root") != F.col("root2")) & fits).select("a", "b")


def groups(docs: DataFrame, width: int = 5, similarity: float = 0.8, one_in: int = 4, least: int = 2, most: int = 1 << 21, candidates: DataFrame | None = None) -> DataFrame:
    """(doc_id, component_id) of each row with a doc_id: the smallest doc_id that near copies reach from it.

    one_in, least, most: which shingles count as common. candidates: pairs (a, b) of doc_ids that are compared first; they may spare work and
    change no result. doc_id, of any ordered type, is taken to name one text; rows without one are left out.
    """
    d = docs.where("doc_id is not null").select("doc_id", "text")
    f = cut(_sets(d, width, similarity, _common(d, width, one_in, least, most)))
    nodes = cut(f.groupBy("digest").agg(F.min("doc_id").alias("node"), F.first("n").alias("n")))
    copies = f.select("doc_id", "digest").join(nodes, "digest").where("doc_id <> node").select("doc_id").distinct()
    entry = f.join(_sent(copies), "doc_id", "left_anti").select(F.posexplode("first").alias("pos", "t"), F.col("doc_id").alias("node"), "n")
    lowest = F.min(F.struct("node", "pos"))
    shared = entry.groupBy("t").agg(lowest["node"].alias("low"), lowest["pos"].alias("at"), F.max("node").alias("high"), F.count("*").alias("k"), F.sum(F.xxhash64("node").cast("decimal(38,0)")).alias("h")).where("low <> high")
    # the shingles of a passage stand in the same texts: the first of them stands for all, with their number as its weight
    alike = shared.groupBy("low", "high", "k", "h").agg(F.min_by("t", "at").alias("t"), F.count("*").alias("w"))
    e = cut(entry.join(_sent(alike.select("t", "low", "w")), "t"))
    # sets of too different sizes can't be similar; c shared shingles of the index leave at most the rest of one set to share, and
    # similarity asks for s/(1+s) of both sizes
    beyond = F.ceil(similarity * F.greatest("n", "m") - 1e-9) - 1
    may = (F.col("c") + beyond >= similarity / (1 + similarity) * (F.col("n") + F.col("m")) - 1e-6) & (F.least("n", "m") >= similarity * F.greatest("n", "m") - 1e-6)
    star = e.where("node <> low").groupBy(F.col("node").alias("a"), F.col("low").alias("b"), "n").agg(F.sum("w").alias("c"))
    star = star.join(nodes.select(F.col("node").alias("b"), F.col("n").alias("m")), "b").where(may).select("a", "b")
    if candidates is not None:
        named = f.select("doc_id", "digest").join(nodes.select("digest", "node"), "digest").select("doc_id", "node").distinct()
        one = lambda c: named.select(F.col("doc_id").alias(c), F.col("node").alias(f"{c}2"))
        star = star.union(candidates.join(one("a"), "a").join(one("b"), "b").where("a2 <> b2").select(F.greatest("a2", "b2"), F.least("a2", "b2")))
    near = cut(_verified(d, cut(star.distinct()), width, similarity))
    comp = components(near)
    placed = e.join(comp, "node", "left").select("t", "node", "n", "pos", F.coalesce("root", "node").alias("root"))
    rest = cut(crossing(placed, similarity).distinct())
    comp = components(near.union(_verified(d, rest, width, similarity)))
    named = nodes.join(comp, "node", "left").select("digest", F.coalesce("root", "node").alias("component_id"))
    return f.select("doc_id", "digest").join(named, "digest").select("doc_id", "component_id")

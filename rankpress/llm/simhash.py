"""SimHash near-duplicates by multi-index hashing (operator 7).

A fingerprint is 64 majority bits over the XXH64 hashes of a text's word shingles. Pairs within two bits are found from an
index with two tables, one for each 32-bit half: two bits of difference leave at most one in the first half, or none in the
second. So the first half is probed with its Hamming ball of radius one and the second half exactly; every fetched pair is
verified on all 64 bits. The self-join is symmetric, so half a ball is enough: of two halves that differ in one bit, the one
that has the bit set probes with it cleared.

Only distinct fingerprints are indexed, so copies cost one row each. A table entry that holds more than `hot` fingerprints is
not fetched: the fingerprints in it probe the whole 64-bit ball instead (at most 2,081 keys each, equal to a fingerprint or
nothing), which is exact and bounded however large the entry.

Null and empty texts have fingerprint zero and link like any other; repeated rows and ties link through their common
fingerprint; an empty table gives an empty result; extra columns of the input are ignored.
"""

from __future__ import annotations

from decimal import Decimal

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F

from ..operators.components import components
from .common import cut, spared, table

SEED = 42


def fingerprint(text: str | None, width: int = 3) -> int:
    """Unsigned 64-bit SimHash of one text; see the module."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    n = max(1, len(words) - width + 1)
    norm = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    ones = np.zeros(64, np.int64)
    digest = xxhash.xxh64_digest
    for i in range(0, n, 1 << 16):  # a very long text in pieces
        j = min(n, i + (1 << 16))
        last = ends[i + width - 1 : j + width - 1] if len(words) >= width else ends[-1:]
        h = b"".join([digest(norm[a:b], SEED) for a, b in zip(starts[i:j].tolist(), last.tolist())])
        ones += np.unpackbits(np.frombuffer(h, np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > n).tobytes(), "big")


def fingerprints(docs: DataFrame, width: int = 3, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, fp long): the fingerprint's bits as a signed long."""

    def run(batches):
        for b in spared(batches):
            fps = [fingerprint(t, width) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.array(fps, np.uint64).view(np.int64))], names=["doc_id", "fp"])

    d = docs.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text"))
    return d.mapInArrow(run, "doc_id long, fp long")


def _half(name: str, which: int):
    return F.shiftrightunsigned(name, 32) if which == 0 else F.col(name).bitwiseAND(F.lit(0xFFFFFFFF))


def _clears(value, bits: int):
    """The values that value becomes with one set bit cleared."""
    return F.transform(F.filter(F.sequence(F.lit(0), F.lit(bits - 1)), lambda i: F.getbit(value, i) == 1), lambda i: value.bitwiseXOR(F.call_function("shiftleft", F.lit(1).cast("long"), i)))


def links(fps: DataFrame, hot: int = 512, node: str = "fp") -> DataFrame:
    """(a, b): all pairs of different fingerprints (column fp, distinct) within two bits, named by the column `node`; some may come twice."""
    # one long names the table and the half, and for probes says whether it is the exact one
    fps = fps.select("fp", F.col(node).alias("id"))
    there = fps.select(F.col("fp").alias("fp2"), F.col("id").alias("id2"))
    seg = lambda which, fp: _half(fp, which) + F.lit(which << 32)
    table_ = there.select(F.explode(F.array(seg(0, "fp2"), seg(1, "fp2"))).alias("k"), "fp2", "id2")
    probe = fps.select(F.explode(F.concat(F.array(seg(0, "fp"), seg(1, "fp")), _clears(_half("fp", 0), 32))).alias("k"), "fp", "id")
    crowded = cut(table_.groupBy("k").count().where(F.col("count") > hot).select("k"))
    differ = F.bit_count(F.col("fp").bitwiseXOR(F.col("fp2")))
    pair = (F.col("id").alias("a"), F.col("id2").alias("b"))
    near = probe.join(table_.join(crowded, "k", "left_anti"), "k").where((F.col("fp") != F.col("fp2")) & (differ <= 2)).select(*pair)
    # members of crowded entries look for every key of their full ball among all fingerprints; links are symmetric
    packed = table_.join(crowded, "k", "left_semi").select(F.col("fp2").alias("fp"), F.col("id2").alias("id")).distinct()
    bit = lambda i: F.call_function("shiftleft", F.lit(1).cast("long"), i)
    bits = F.sequence(F.lit(0), F.lit(63))
    one = F.transform(bits, bit)
    two = F.flatten(F.transform(F.sequence(F.lit(0), F.lit(62)), lambda i: F.transform(F.sequence(i + 1, F.lit(63)), lambda j: bit(i).bitwiseOR(bit(j)))))
    ball = packed.select("id", "fp", F.explode(F.concat(one, two)).alias("flip")).select("id", F.col("fp").bitwiseXOR(F.col("flip")).alias("fp2"))
    return near.union(ball.join(there, "fp2").select(*pair))


def near_duplicates(docs: DataFrame, width: int = 3, hot: int = 512, spread: int = 256) -> DataFrame:
    """One row per document: doc_id, fingerprint (16 hex digits), component_id, the smallest doc_id it reaches.

    The documents of one fingerprint are dealt to `spread` parts by their ids, and each part learns its component for itself: no
    join brings more than a spread-th of a group of copies, or more than `spread` parts of it, to one key. A fingerprint is
    linked under its smallest doc_id, so the root of a component is the id asked for; one that has null ids only gets a number
    above all longs, and a component of such alone has a null component_id.
    """
    f = cut(fingerprints(docs, width)).withColumn("part", F.pmod(F.xxhash64("doc_id"), F.lit(spread)).cast("int"))
    parts = cut(f.groupBy("fp", "part").agg(F.min("doc_id").alias("first_id")))
    classes = parts.groupBy("fp").agg(F.min("first_id").alias("first_id"))
    beyond = (F.col("fp").cast("decimal(20,0)") + F.lit(Decimal(1 << 64))).cast("decimal(20,0)")
    classes = cut(classes.select("fp", F.coalesce(F.col("first_id").cast("decimal(20,0)"), beyond).alias("node")))
    comp = components(links(classes, hot, "node"))
    low = F.coalesce("root", "node")
    named = classes.join(comp, "node", "left").select("fp", F.when(low < F.lit(Decimal(1 << 63)), low).cast("long").alias("component_id"))
    named = parts.select("fp", "part").join(named, "fp")
    return f.join(named, ["fp", "part"]).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, width: int = 3) -> DataFrame:
    """The documents, each group of near copies cut to its smallest doc_id (all rows of that id, columns as given).

    Rows with a null doc_id take part in no group and stay.
    """
    drop = near_duplicates(docs, width).where("component_id <> doc_id").select(F.col("doc_id").alias("_gone"))
    return docs.join(drop, docs.doc_id == F.col("_gone"), "left_anti")


def op7(spark, sf_dir):
    return near_duplicates(table(spark, sf_dir, "documents"))


QUERIES = {"op7_simhash": op7}
SQL: dict[str, str] = {}

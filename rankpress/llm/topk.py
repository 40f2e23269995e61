"""Exact top-k inner products by ball-tree branch and bound (operator 10).

Components become floor(64 * x). Candidates are dealt to shards of bounded size, each shuffled once to a task that builds its ball
tree; the trees are written down. Queries come in blocks of bounded size, which are sent to all tasks. A task visits the nodes of
its trees in the order of their largest upper bound q . c + |q| r over the queries still open there; a query leaves a node whose
bound lies below its current k-th score, and takes that score along from tree to tree. Trees are searched in waves, one tree alone, then some,
then the rest: what a wave has found is the floor with which the queries enter the next one. Bounds are raised by the rounding
error of the arithmetic, and ties stay open, so nothing that belongs to the answer is cut.

Products are exact: in double precision where no sum can reach 2**53, else in Python's integers, held to the range of a long.
Vectors that are null or hold null or non-finite components take no part, nor do rows with a null vec_id; shorter vectors are
padded with zeros. Rows with a repeated vec_id are candidates each, but one query (with the least vector). A query never finds
its own vec_id. An empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import heapq
import pickle

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window as W, functions as F

from .common import cut, table
from .vectors import matrix, valid

SCHEMA = "query_id long, vec_id long, score long"


class BallTree:
    """Nodes as (centre, radius, first row, last row, children); rows are reordered so that a node's are consecutive."""

    def __init__(self, x: np.ndarray, leaf: int = 256):
        self.order = np.arange(len(x))
        self.nodes: list[tuple[np.ndarray, float, int, int, tuple[int, int] | None]] = []
        self._x, self._leaf = x, leaf
        if len(x):
            self._grow(0, len(x))
        del self._x

    def _grow(self, a: int, b: int) -> int:
        rows = self._x[self.order[a:b]]
        centre = rows.mean(axis=0)
        dist = np.linalg.norm(rows - centre, axis=1)
        me = len(self.nodes)
        self.nodes.append((centre, float(dist.max()), a, b, None))
        if b - a > self._leaf and dist.max() > 0:
            far = rows[np.argmax(dist)]
            other = rows[np.argmax(np.linalg.norm(rows - far, axis=1))]
            side = np.argsort(rows @ (other - far), kind="stable")  # the median along the widest direction
            self.order[a:b] = self.order[a:b][side]
            mid = (a + b) // 2
            kids = (self._grow(a, mid), self._grow(mid, b))
            self.nodes[me] = (*self.nodes[me][:4], kids)
        return me


def search(q: np.ndarray, q_id: np.ndarray, floor: np.ndarray, x: np.ndarray, x_id: np.ndarray, k: int, tree: BallTree | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query row, candidate row, score) of each query's k best rows of x with scores of at least its floor. tree: one over x, whose
    rows then have to be in the order of x_id."""
    order = np.argsort(x_id, kind="stable")
    if tree is None:
        x, x_id = x[order], x_id[order]
    top = max(np.abs(x).max(initial=0), np.abs(q).max(initial=0))
    n = len(x)
    if top * top * max(1, x.shape[1]) * (n + 1) >= 2.0**62 or top * top * max(1, x.shape[1]) >= 2.0**53:
        return _plain(q, q_id, floor, x, x_id, order, k)
    tree, norm = tree or BallTree(x), np.linalg.norm(q, axis=1)
    low = np.iinfo(np.int64).min
    best = np.full((len(q), k), low)  # score * (n + 1) - place among the ids: the order asked for, in one number
    least = floor.astype(float)  # the k-th score so far

    def bound(node: int, who: np.ndarray) -> np.ndarray:
        c, r, *_ = tree.nodes[node]
        up = q[who] @ c + norm[who] * r
        return up + 1e-9 * (1 + np.abs(up) + norm[who] * (r + np.linalg.norm(c)))

    everyone = np.arange(len(q))
    heap = [(-float(bound(0, everyone).max(initial=0)), 0, everyone)] if n and len(q) else []
    while heap:
        _, node, who = heapq.heappop(heap)
        _, _, a, b, kids = tree.nodes[node]
        who = who[bound(node, who) >= least[who]]  # the k-th scores have risen meanwhile
        if not len(who):
            continue
        if kids:
            for kid in kids:
                up = bound(kid, who)
                if len(some := who[up >= least[who]]):
                    heapq.heappush(heap, (-float(up.max()), kid, some))
            continue
        rows = tree.order[a:b]
        s = np.rint(q[who] @ x[rows].T).astype(np.int64)
        key = np.where((x_id[rows] == q_id[who][:, None]) | (s < least[who][:, None]), low, s * (n + 1) + (n - rows))
        both = np.concatenate([best[who], key], axis=1)
        best[who] = np.partition(both, both.shape[1] - k, axis=1)[:, -k:]
        kth = best[who].min(axis=1)
        least[who] = np.where(kth > low, np.maximum(least[who], kth // (n + 1)), least[who])
    i, j = np.nonzero(best > low)
    key = best[i, j]
    return i, order[n - key % (n + 1)], key // (n + 1)


def _plain(q, q_id, floor, x, x_id, order, k):
    """The same by Python's integers, for components too large for exact doubles."""
    xs = [[int(v) for v in r] for r in x]
    out = []
    for i, r in enumerate(q):
        r = [int(v) for v in r]
        s = [(-max(-(2**63), min(2**63 - 1, sum(map(int.__mul__, r, y)))), int(x_id[j]), j) for j, y in enumerate(xs) if x_id[j] != q_id[i]]
        out += [(i, order[j], -v) for v, _, j in heapq.nsmallest(k, s) if -v >= floor[i]]
    return tuple(np.array([o[c] for o in out], np.int64) for c in range(3))


def floored(column, width: int) -> np.ndarray:
    """Rows of a list column as floor(64 * x) in doubles, held to the range of a long."""
    return np.clip(np.floor(64 * matrix(column, width)), -(2.0**63), 2.0**63)


def planted(rows: DataFrame, width: int, shard: int) -> tuple[DataFrame, int]:
    """(s, tree): the candidates' shards with their trees, one row each, and their number."""
    shards = max(1, -(-rows.count() // shard))

    def build(t: pa.Table) -> pa.Table:
        t = t.sort_by("vec_id")
        x = floored(t.column("v"), width)
        body = pickle.dumps((x, t.column("vec_id").to_numpy(), BallTree(x)), protocol=5)
        return pa.table({"s": t.column("s").slice(0, 1), "tree": pa.array([body], pa.large_binary()).cast(pa.binary())})

    dealt = rows.withColumn("s", F.pmod(F.xxhash64("vec_id", F.monotonically_increasing_id()), F.lit(shards)))
    return cut(dealt.groupBy("s").applyInArrow(build, "s long, tree binary")), shards


def _asked(trees: DataFrame, held, k: int) -> DataFrame:
    """Each query's k best of all trees of a task, with scores of at least its floor; held: the queries, broadcast."""

    def run(batches):
        q_id, q, floor = held.value
        best = [np.zeros(0, np.int64)] * 3  # query row, vec_id, score
        floor = floor.copy()
        for b in batches:
            for body in b.column(0):
                x, ids, tree = pickle.loads(body.as_py())
                i, j, s = search(q, q_id, floor, x, ids, k, tree)
                i, v, s = (np.concatenate(p) for p in zip(best, (i, ids[j], s)))
                order = np.lexsort((v, -s, i))
                i, v, s = i[order], v[order], s[order]
                place = np.arange(len(i)) - np.searchsorted(i, i)
                best = [c[place < k] for c in (i, v, s)]
                full = place == k - 1
                floor[i[full]] = np.maximum(floor[i[full]], s[full])
        yield pa.RecordBatch.from_arrays([pa.array(q_id[best[0]]), pa.array(best[1]), pa.array(best[2])], names=["query_id", "vec_id", "score"])

    return trees.select("tree").mapInArrow(run, SCHEMA)


def top_k(emb: DataFrame, k: int = 20, every: int = 20, shard: int = 16_384, shard_bytes: int = 32 << 20, block_bytes: int = 32 << 20) -> DataFrame:
    """query_id, rank, vec_id, score; queries are the rows whose vec_id is divisible by `every`.

    shard, shard_bytes: candidates of a tree, and the size of their vectors at most. block_bytes: size of the vectors of the queries that are sent to the tasks at a time.
    """
    spark = emb.sparkSession
    rows = cut(emb.where(valid("embedding") & F.col("vec_id").isNotNull()).select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").alias("v")))
    width = rows.agg(F.max(F.size("v"))).first()[0] or 1
    queries = cut(rows.where(F.pmod("vec_id", F.lit(every)) == 0).groupBy("vec_id").agg(F.min("v").alias("v")))
    trees, shards = planted(rows, width, max(1, min(shard, shard_bytes // (8 * width))))
    blocks = max(1, -(-queries.count() * 8 * width // block_bytes))
    waves = sorted({0, 1, min(shards, 1 + shards // 8), shards})
    best = W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    top = lambda df: df.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
    out = None
    for b in range(blocks):
        asked = queries.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == b).toArrow().sort_by("vec_id")
        q_id, q = asked.column("vec_id").to_numpy(), floored(asked.column("v"), width)
        floor, found = np.full(len(q_id), -(2**63)), None
        for lo, hi in zip(waves, waves[1:]):
            held = spark.sparkContext.broadcast((q_id, q, floor))
            got = _asked(trees.where((F.col("s") >= lo) & (F.col("s") < hi)), held, k)
            found = got if found is None else found.union(got)
            if hi < shards:  # at most k rows a query stay for the next floors
                found = cut(top(found).drop("rank"))
                kth = found.groupBy("query_id").agg(F.when(F.count("*") >= k, F.min("score")).alias("kth")).where("kth is not null").toArrow()
                floor = floor.copy()
                floor[np.searchsorted(q_id, kth.column("query_id").to_numpy())] = kth.column("kth").to_numpy()
        found = top(found) if blocks == 1 else cut(top(found))
        out = found if out is None else out.union(found)
    return out.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def op10(spark, sf_dir):
    return top_k(table(spark, sf_dir, "embeddings"))


SQL10 = """
with e as (
  select vec_id, list_transform(embedding, lambda x: floor(64 * x::double)::bigint) v from embeddings
  where vec_id is not null and embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0),
s as (
  select q.vec_id query_id, c.vec_id, list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2]))::bigint score
  from e q join e c on q.vec_id <> c.vec_id where q.vec_id % 20 = 0)
select query_id, (row_number() over (partition by query_id order by score desc, vec_id))::int rank, vec_id, score from s
qualify row_number() over (partition by query_id order by score desc, vec_id) <= 20
"""

QUERIES = {"op10_top_k": op10}
SQL = {"op10_top_k": SQL10}

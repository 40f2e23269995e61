"""Near-duplicate embeddings by spherical k-means cells (operator 6).

Equal vectors of a label, known by 128 bits of hash, are one class, indexed once. Every large label gets cells by spherical k-means,
fitted in a task of its own on a bounded sample of the label; every class has the cell of its nearest centre as its home and visits
each cell that could hold a partner. The test for a visit is exact: if y is nearer to centre j than to centre i, x lies in cell i and
the two are within the angle of the threshold, then x . (ci - cj) / |ci - cj| is at most the angle's sine. So no link is lost, whatever
the centres. Centres are sent to all tasks while they are small, else each meets the parts of its label in a shuffle. Cells are compared
in square blocks of bounded size, and a block gives sums of links and one root per member of its local components, never pairs, so a
group of copies costs arithmetic but no rows. The rows of a class are dealt to parts by their ids, and only these parts learn the
class's component: vectors are shuffled to their class once and to their cells once, as they came, not as doubles.

Vectors that are null, zero, or hold null or non-finite components, and rows with a null label, link with nothing and keep
themselves; vectors of unequal length in a label are padded with zeros; rows with the same vec_id, or none, count as rows, but rows of a vector that has no id at all link with nothing; an empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..operators.components import components
from .common import cut, table


def valid(name: str):
    """Not null, and every component is a finite number."""
    return F.col(name).isNotNull() & F.forall(name, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))


def matrix(column: pa.ChunkedArray | pa.Array, width: int | None = None) -> np.ndarray:
    """Rows of a list column as float64, shorter ones padded with zeros."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    size = np.diff(column.offsets.to_numpy()) if len(column) else np.zeros(0, int)
    d = width or int(size.max(initial=0))
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(float)
    if len(size) and size.min() == d:
        return flat.reshape(-1, d)
    out = np.zeros((len(size), d))
    out[np.repeat(np.arange(len(size)), size), np.arange(len(flat)) - np.repeat(np.cumsum(size) - size, size)] = flat
    return out


def unit(x: np.ndarray) -> np.ndarray:
    top = np.abs(x).max(axis=1, keepdims=True, initial=0)
    x = x / np.where(top > 0, top, 1)  # squares of very large or small components stay in range
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def spherical_kmeans(x: np.ndarray, k: int, rounds: int = 12, seed: int = 7) -> np.ndarray:
    """k unit centres of the unit rows x."""
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), min(k, len(x)), replace=False)]
    for _ in range(rounds):
        home = np.argmax(x @ c.T, axis=1)
        s = np.zeros_like(c)
        np.add.at(s, home, x)
        norm = np.linalg.norm(s, axis=1, keepdims=True)
        c = np.where(norm > 1e-12, s / np.maximum(norm, 1e-12), c)
    return c


def fit_cells(classes: DataFrame, per_cell: int, sample: int) -> DataFrame:
    """(label, n, centre): the centres of each label with more than 2 * per_cell classes: one for per_cell classes, or the root of
    their number where that is less, beyond per_cell**2. A label's sample has about `sample` rows, four a centre at least."""
    sizes = classes.groupBy("label").agg(F.count("*").alias("n")).where(F.col("n") > 2 * per_cell)
    k = F.least(F.ceil(F.col("n") / per_cell), F.greatest(F.lit(per_cell), F.ceil(F.sqrt("n")))).cast("long")
    sizes = cut(sizes.withColumn("k", k).withColumn("share", F.greatest(F.lit(sample), 4 * F.col("k")) / F.col("n")))
    place = F.pmod(F.xxhash64("cls"), F.lit(1 << 52)) / float(1 << 52)
    rows = classes.join(F.broadcast(sizes), "label").where(place < F.col("share")).select("label", "n", "k", "cls", "v")

    def fit(t: pa.Table) -> pa.Table:
        t = t.sort_by("cls")
        c = spherical_kmeans(unit(matrix(t.column("v"))), t.column("k")[0].as_py())
        return pa.table({"label": pa.array([t.column("label")[0].as_py()] * len(c), pa.int64()), "n": pa.array([t.column("n")[0].as_py()] * len(c), pa.int64()), "centre": pa.array(c.tolist(), pa.list_(pa.float64()))})

    return rows.groupBy("label").applyInArrow(fit, "label long, n long, centre array<double>")


def _placed(t: pa.Table, c: np.ndarray, sine: float) -> pa.Table:
    """The rows of one label, with cell and visit: at home (0), and in each cell that might hold a partner (1)."""
    x = matrix(t.column("v"))
    wide = lambda a: np.pad(a, ((0, 0), (0, max(x.shape[1], c.shape[1]) - a.shape[1])))
    c = wide(c)
    s = unit(wide(x)) @ c.T
    h = np.argmax(s, axis=1)
    gap = np.sqrt(np.maximum(2 - 2 * (c @ c.T), 0))[h]
    i, j = np.nonzero((s[np.arange(len(h)), h][:, None] - s <= sine * gap + 1e-12) & (np.arange(len(c)) != h[:, None]))
    who = np.concatenate([np.arange(len(h)), i])
    out = t.select(["label", "cls", "m", "v"]).take(pa.array(who))
    return out.append_column("cell", pa.array(np.concatenate([h, j]))).append_column("visit", pa.array((np.arange(len(who)) >= len(h)).astype(np.int64)))


def place(classes: DataFrame, cells: DataFrame, cosine: float, sent: int = 32 << 20, part: int = 1 << 14) -> DataFrame:
    """(label, cls, m, v, cell, visit). sent: bytes of centres that may go to all tasks; beyond, the centres of a label meet its rows
    in parts of about `part` rows."""
    sine = float(np.sqrt(1 - cosine * cosine)) + 1e-9
    kind = dict(classes.dtypes)["v"]
    schema = f"label long, cls long, m long, v {kind}, cell long, visit long"
    d = classes.select("label", "cls", "m", "v")
    size = cells.agg(F.sum(8 * F.size("centre"))).first()[0] or 0
    if size <= sent:
        got = cells.toArrow()
        label = np.array(got.column("label").to_pylist(), np.int64)
        held = d.sparkSession.sparkContext.broadcast({int(x): matrix(got.column("centre").filter(pa.array(label == x))) for x in np.unique(label)})

        def run(batches):
            for b in batches:
                t = pa.Table.from_batches([b])
                mine = b.column(0).to_numpy()
                large = np.isin(mine, list(held.value))
                few = t.filter(pa.array(~large))
                if len(few):
                    yield from few.append_column("cell", pa.array(np.full(len(few), -1))).append_column("visit", pa.array(np.zeros(len(few), np.int64))).to_batches()
                for x in np.unique(mine[large]):
                    yield from _placed(t.filter(pa.array(mine == x)), held.value[int(x)], sine).to_batches()

        return d.mapInArrow(run, schema)
    parts = cells.groupBy("label").agg(F.ceil(F.max("n") / part).alias("parts"))
    small = d.join(cells.select("label").distinct(), "label", "left_anti").select("*", F.lit(-1).cast("long").alias("cell"), F.lit(0).cast("long").alias("visit"))
    rows = d.join(parts, "label").withColumn("part", F.pmod(F.xxhash64("cls"), F.col("parts"))).drop("parts")
    each = cells.join(parts, "label").select("label", "centre", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)).alias("part"))

    def meet(t: pa.Table, c: pa.Table) -> pa.Table:
        if len(t):
            return _placed(t, matrix(c.column("centre")), sine)
        return t.select(["label", "cls", "m", "v"]).append_column("cell", pa.array([], pa.int64())).append_column("visit", pa.array([], pa.int64()))

    return small.unionByName(rows.groupBy("label", "part").cogroup(each.groupBy("label", "part")).applyInArrow(meet, schema))


def _block(t: pa.Table, cosine: float, tile: int = 1024) -> pa.Table:
    """Links and local roots of one block: rows of role 0 or 2 against rows of role 1 or 2, some rows at a time."""
    t = t.sort_by([("cls", "ascending"), ("role", "ascending")])
    role, cls, m = (t.column(c).to_numpy() for c in ("role", "cls", "m"))
    x = unit(matrix(t.column("v")))
    h, o = np.flatnonzero(role != 1), np.flatnonzero(role != 0)
    links = np.zeros(len(cls), np.int64)
    ids, at = np.unique(cls, return_inverse=True)
    root = np.arange(len(ids))
    others = x[o].T
    for k in range(0, len(h), tile):
        i, j = np.nonzero(x[h[k : k + tile]] @ others >= cosine)
        i, j = h[k + i], o[j]
        keep = cls[i] != cls[j]
        i, j = i[keep], j[keep]
        links += np.bincount(i, m[j], len(cls)).astype(np.int64)
        a, b = at[i], at[j]
        while len(a):
            u, v = root[a], root[b]
            apart = u != v
            if not apart.any():
                break
            a, b, u, v = a[apart], b[apart], u[apart], v[apart]
            np.minimum.at(root, np.maximum(u, v), np.minimum(u, v))
            while (root[root] != root).any():
                root = root[root]
    out = (links > 0) | (root[at] != at)
    return pa.table({"cls": cls[out], "links": links[out], "root": ids[root[at[out]]]})


def near_duplicates(emb: DataFrame, cosine: float = 0.93, per_cell: int = 4096, sample: int = 4096, block: int = 16_384, sent: int = 32 << 20, spread: int = 256) -> DataFrame:
    """vec_id, n_links, component_id, kept, a row for each row of emb (vec_id, embedding, label).

    per_cell, sample: see fit_cells(). block: rows of a block of a cell. sent: see place(). spread: parts of a class's rows.
    """
    ok = valid("v") & F.exists("v", lambda x: x != 0)
    rows = emb.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("long").alias("label"), F.col("embedding").alias("v"))
    rows = rows.withColumn("label", F.when(ok, F.col("label"))).withColumns({"h1": F.xxhash64("v"), "h2": F.xxhash64(F.lit(1), F.reverse("v"))})
    key = ["label", "h1", "h2"]
    classes = cut(rows.where("label is not null").groupBy(*key).agg(F.min("vec_id").alias("cls"), F.count("*").alias("m"), F.first("v").alias("v")).where("cls is not null"))
    placed = cut(place(classes, cut(fit_cells(classes, per_cell, sample)), cosine, sent))
    sizes = placed.groupBy("label", "cell").agg(F.ceil(F.count("*") / block).cast("int").alias("n"))
    placed = placed.join(sizes, ["label", "cell"]).withColumn("own", F.pmod(F.xxhash64("cls"), F.col("n")).cast("int"))
    other = F.transform(F.sequence(F.lit(0), F.col("n") - 1), lambda k: F.struct(k.alias("a"), F.col("own").alias("b"), F.lit(1).alias("role")))
    home = F.transform(F.sequence(F.lit(0), F.col("n") - 1), lambda k: F.struct(F.col("own").alias("a"), k.alias("b"), F.lit(0).alias("role")))
    both = F.array(F.struct(F.lit(0).alias("a"), F.lit(0).alias("b"), F.when(F.col("visit") == 0, 2).otherwise(1).alias("role")))  # one block: one row serves both sides
    at = F.when(F.col("n") == 1, both).when(F.col("visit") == 0, F.concat(home, other)).otherwise(other)
    dealt = placed.select("label", "cell", "cls", "m", "v", F.explode(at).alias("at")).select("label", "cell", "at.*", "cls", "m", "v")
    found = cut(dealt.groupBy("label", "cell", "a", "b").applyInArrow(lambda t: _block(t, cosine), "cls long, links long, root long"))
    comp = components(found.where("cls <> root").select(F.col("cls").alias("a"), F.col("root").alias("b")))
    links = found.groupBy("cls").agg(F.sum("links").alias("links")).join(comp.withColumnRenamed("node", "cls"), "cls", "full")
    known = classes.join(links, "cls", "left").select(*key, (F.col("m") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("root", "cls").alias("component_id"))
    thin = rows.drop("v").withColumn("part", F.when(F.col("label").isNotNull(), F.pmod(F.xxhash64("vec_id"), F.lit(spread))))
    parts = thin.where("label is not null").select(*key, "part").distinct().join(known, key)
    out = thin.join(parts, [*key, "part"], "left").select("vec_id", F.coalesce("n_links", F.lit(0)).alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def op6(spark, sf_dir):
    return near_duplicates(table(spark, sf_dir, "embeddings"))


SQL6 = """
with recursive e as (
  select vec_id, label, list_transform(embedding, lambda x: x::double) v from embeddings
  where label is not null and embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0 and len(list_filter(embedding, lambda x: x <> 0)) > 0),
links as (select a.vec_id a, b.vec_id b from e a join e b on a.label = b.label and a.vec_id <> b.vec_id where list_cosine_similarity(a.v, b.v) >= 0.93),
reach as (select vec_id a, vec_id b from embeddings union select r.a, l.b from reach r join links l on r.b = l.a),
low as (select a, min(b) low from reach group by a),
n as (select a, count(*) n from links group by a)
select vec_id, coalesce(n, 0)::bigint n_links, low component_id, vec_id = low kept from embeddings m join low on low.a = m.vec_id left join n on n.a = m.vec_id
"""

QUERIES = {"op6_embedding_dedup": op6}
SQL = {"op6_embedding_dedup": SQL6}

"""Corpus preparation: blocks, books, splits without leaks, domains, and other tables as text."""

from __future__ import annotations

import html

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from ..sources.tables import cut
from . import nearcopies

#: The Latin letters and their one-to-one images in a block of three-byte characters.
LATIN = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ"
FAR = "".join(chr(0x0905 + i) for i in range(52))


def prefix(df: DataFrame, n: int = 10_000) -> DataFrame:
    """The first n code points of each text."""
    return df.withColumn("text", F.substring("text", 1, n))


def blocks(df: DataFrame, size: int = 10_000) -> DataFrame:
    """Rows of df cut into blocks of `size` code points: the columns of df with `block` and the block's text.

    A narrow step: each row becomes ceil(length / size) rows. An empty text is one empty block, a null one a null block.
    """
    n = F.greatest(F.lit(1), F.ceil(F.length("text") / size)).cast("int")
    cuts = F.transform(F.sequence(F.lit(0), F.coalesce(n, F.lit(1)) - 1), lambda i: F.substring(F.col("text"), i * size + 1, F.lit(size)))
    return df.select(*[c for c in df.columns if c != "text"], F.posexplode(cuts).alias("block", "text"))


def books(df: DataFrame, by: str = "lang", size: int = 10_000, sep: str = "\n") -> DataFrame:
    """(by, book_no, text): a group's texts in the order of doc_id, one after the other, cut into books of `size` code points.

    A text's place comes from running lengths within ranges of ids and totals of ranges, so that no group meets in one task;
    then each book is put together from its own pieces.
    """
    d = df.where("text is not null").select(by, "doc_id", F.concat("text", F.lit(sep)).alias("text")).withColumns({"_n": F.length("text").cast("long"), "_b": F.expr("doc_id div 4096")})
    parts = d.groupBy(by, "_b").agg(F.sum("_n").alias("_s"))
    parts = parts.withColumn("_off", F.coalesce(F.sum("_s").over(W.partitionBy(by).orderBy("_b").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    run = F.coalesce(F.sum("_n").over(W.partitionBy(by, "_b").orderBy("doc_id", "text").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    d = d.withColumn("_in", run).join(parts.select(F.col(by).alias("_by"), F.col("_b").alias("_bb"), "_off"), F.col(by).eqNullSafe(F.col("_by")) & (F.col("_b") == F.col("_bb")))
    d = d.withColumn("_at", F.col("_in") + F.col("_off"))
    first, last = F.expr(f"_at div {size}"), F.expr(f"(_at + _n - 1) div {size}")
    d = d.withColumn("book_no", F.explode(F.sequence(first, last)))
    begin = F.greatest(F.lit(0), F.col("book_no") * size - F.col("_at"))
    end = F.least(F.col("_n"), (F.col("book_no") + 1) * size - F.col("_at"))
    piece = F.substring(F.col("text"), (begin + 1).cast("int"), (end - begin).cast("int"))
    return d.groupBy(by, "book_no").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("_at", piece.alias("p")))), lambda x: x["p"]), "").alias("text"))


def text_key(text: str | Column = "text") -> Column:
    """The digest that names a text; a null text counts as an empty one."""
    return F.md5(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")))


def near_copies(df: DataFrame, width: int = 5, similarity: float = 0.8) -> DataFrame:
    """(digest, cluster_id): the texts that stand in a cluster with another text, and the smallest digest of the cluster.

    Exact: every two texts whose word shingles have the similarity are linked; see operators.nearcopies. Only distinct texts
    are looked at, and only members of clusters of two and more are returned.
    """
    texts = df.select(text_key().alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).dropDuplicates(["doc_id"])
    got = nearcopies.groups(texts, width, similarity).where("doc_id <> component_id").select(F.col("doc_id").alias("digest"), F.col("component_id").alias("cluster_id"))
    got = cut(got)
    return got.unionByName(got.select(F.col("cluster_id").alias("digest"), "cluster_id").distinct())


def with_clusters(df: DataFrame, sent: int = 1 << 20) -> DataFrame:
    """df with cluster_id: the digest of the text, or for near copies the smallest digest among them.

    Rows are joined by digest, so repeated and null ids do no harm; the table of near copies goes to the rows while it has at most
    `sent` rows, so that texts stay where they are.
    """
    near = cut(near_copies(df)).withColumnRenamed("digest", "_digest")
    near = F.broadcast(near) if near.count() <= sent else near
    d = df.withColumn("_key", text_key()).join(near, F.col("_key") == F.col("_digest"), "left")
    return d.withColumn("cluster_id", F.coalesce("cluster_id", "_key")).drop("_key", "_digest")


def copy_clusters(df: DataFrame) -> DataFrame:
    """(doc_id, cluster_id), one row for each row of df: documents joined by exact or near copies."""
    return with_clusters(df).select("doc_id", "cluster_id")


def split_of(key: str | Column, train: int = 80, valid: int = 10) -> Column:
    """train, valid or test by a digest of the key: stable under any order of rows."""
    h = F.conv(F.substring(F.md5(F.col(key).cast("string") if isinstance(key, str) else key), 1, 6), 16, 10).cast("int") % 100
    return F.when(h < train, "train").when(h < train + valid, "valid").otherwise("test")


def split(df: DataFrame, train: int = 80, valid: int = 10, by: str = "cluster") -> DataFrame:
    """df with cluster_id and split; by 'cluster' near copies stay on one side, by 'text' exact ones only."""
    d = with_clusters(df) if by == "cluster" else df.withColumn("cluster_id", text_key())
    return d.withColumn("split", split_of("cluster_id", train, valid))


def domain_pairs(domains: DataFrame, column: str) -> DataFrame:
    """(train_domain, eval_domain): all pairs of the few domains."""
    d = domains.select(column).distinct()
    return d.select(F.col(column).alias("train_domain")).crossJoin(F.broadcast(d.select(F.col(column).alias("eval_domain"))))


def shift_script(df: DataFrame, back: bool = False) -> DataFrame:
    """Latin letters to a script of three-byte characters, one to one, or back."""
    return df.withColumn("text", F.translate("text", FAR, LATIN) if back else F.translate("text", LATIN, FAR))


def page_text(df: DataFrame, keep_markup: bool = False, references: dict[str, str] | None = None) -> DataFrame:
    """Pages with their html as `text`, with markup or without.

    references: the character references to decode, in this order and only as written; None: all that HTML knows, also those that
    lack their semicolon.
    """
    if keep_markup:
        return df.withColumn("text", F.col("html"))
    t = F.regexp_replace("html", r"(?isu)<(script|style)(?![0-9A-Za-z_]).*?</(script|style)[\t\n\f\r ]*>|<!--.*?-->|<[^>]*>", " ")
    one_blank = lambda c: F.regexp_replace(c, r"[\t\n\f\r ]+", " ")
    if references is None:
        plain = one_blank(F.pandas_udf(lambda s: s.map(html.unescape), "string")(F.coalesce(t, F.lit(""))))
    else:
        plain = one_blank(t)
        for name, char in references.items():
            plain = F.replace(plain, F.lit(name), F.lit(char))
    return df.withColumn("text", F.when(F.col("html").isNotNull(), F.regexp_replace(plain, r"^\p{Zs}+|\p{Zs}+\z", "")))


def rows_as_text(df: DataFrame, order_by: list[str], columns: list[str], sep: str = ",", lines: int = 100) -> DataFrame:
    """(block, text): rows as delimited lines in an order, `lines` to a block; the order's first column has to be an integer.

    Blocks are cut by ranges of the first column, so no global sort is needed.
    """
    line = F.concat_ws(sep, *[F.coalesce(F.col(c).cast("string"), F.lit("")) for c in columns])
    key = F.expr(f"{order_by[0]} div {lines}").alias("block")
    got = df.select(key, F.struct(*order_by, line.alias("line")).alias("r")).groupBy("block").agg(F.array_sort(F.collect_list("r")).alias("rs"))
    return got.select("block", F.array_join(F.transform("rs", lambda r: r["line"]), "\n").alias("text"))


def text_stats(df: DataFrame, by: list[str]) -> DataFrame:
    """docs, chars, bytes and lines of each group; nulls count as documents without text."""
    lines = F.size(F.split("text", "\n"))
    return df.groupBy(*by).agg(F.count("*").alias("docs"), F.sum(F.length("text")).alias("chars"), F.sum(F.octet_length("text")).alias("bytes"), F.sum(F.when(F.col("text").isNotNull(), lines)).cast("long").alias("lines"))

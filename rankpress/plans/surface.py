"""More of the relational surface: SQL with the engine's own functions, join strategies, windows and multisets."""

from __future__ import annotations

from pyspark.sql import Window as W, functions as F

from ..functions import sql
from ..operators import sequences
from ..sources.tables import table
from . import pipeline
from .relational import SYM, _docs, _order0, pairs, r6, symbols

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(twin: str):
    def put(f):
        QUERIES[f.__name__], SQL[f.__name__] = f, twin
        return f

    return put


def _sql(spark, d, statement: str):
    """The statement over the documents, with the engine's functions."""
    sql.register(spark)
    return spark.sql(statement, docs=_docs(spark, d))


@query("select doc_id, md5(text) digest, true same_ids from documents")
def sql_scalar_functions(spark, d):
    """Compressing and tokenising in SQL, and back."""
    return _sql(spark, d, "select doc_id, md5(rp_decompress(rp_compress(text, 'brotli'), 'brotli')) digest, rp_decode(rp_encode(text, 'bpe1024'), 'bpe1024') = text same_ids from {docs}")


@query("select ('0x' || h)::int token, count(*) n from (select unnest(regexp_extract_all(hex(encode(text)), '..')) h from documents) group by h")
def sql_table_function(spark, d):
    """Counts of byte tokens through the table function; rows are summed within tasks."""
    return _sql(spark, d, "select t.token, count(*) n from {docs} as x, lateral rp_tokens(x.text, 'byte') as t group by t.token")


@query(
    f"with recursive n as (select lang, symbol, count(*) n from ({SYM}) group by all), "
    "h as (select lang, list_sort(list(n)) l, 0::bigint bits from n group by lang union all select lang, list_sort(list_append(l[3:], l[1] + l[2])), bits + l[1] + l[2] from h where len(l) > 1), "
    "t as (select lang, sum(n) t from n group by lang), e as (select n.lang, round(-sum(n / t * log2(n / t)), 6) entropy from n join t on n.lang is not distinct from t.lang group by n.lang) "
    "select h.lang, bits, entropy from h join e on h.lang is not distinct from e.lang where len(l) = 1"
)
def huffman_total_bits(spark, d):
    """Bits of each language under its own Huffman code, and its entropy, by the aggregate functions over counts."""
    sql.register(spark)
    n = symbols(_docs(spark, d), "lang").groupBy("lang", "symbol").agg(F.count("*").alias("n"))
    return spark.sql("select lang, rp_huffman_bits(n) bits, round(rp_entropy(n), 6) entropy from {n} group by lang", n=n)


@query(
    f"with n as (select symbol, count(*) n from ({SYM}) group by symbol), r as (select symbol, n, row_number() over (order by n desc, symbol) - 1 k from n) "
    "select s.strategy, sum(n * k)::bigint ranks, sum(n)::bigint symbols from r, (values ('broadcast'), ('merge'), ('shuffle_hash')) s(strategy) group by s.strategy"
)
def rank_join_strategies(spark, d):
    """Sum of the ranks without context: the counted pairs meet the ranked model by each of the join strategies."""
    counted = pairs(_docs(spark, d)).groupBy("before", "symbol").agg(F.count("*").alias("c"))
    model = _order0(_docs(spark, d)).select("symbol", "rank")
    one = lambda how: counted.join(model.hint(how), "symbol").agg(F.lit(how).alias("strategy"), F.sum(F.col("c") * F.col("rank")).alias("ranks"), F.sum("c").alias("symbols"))
    return one("broadcast").union(one("merge")).union(one("shuffle_hash"))


@query(
    "select user_id, event_id, last_value(case when event_type = 'error' then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) error_id from events"
)
def asof_event(spark, d):
    """Each event with the user's last error before it, carried from hour to hour."""
    e = table(spark, d, "events").select("user_id", "event_id", "ts", "event_type").withColumn("hour", sequences.hour_of())
    error = F.when(F.col("event_type") == "error", F.col("event_id"))
    return sequences.last_before(e, ["user_id"], "hour", ["ts", "event_id"], error, "error_id").select("user_id", "event_id", "error_id")


@query(
    "select source, lang, chars, dense_rank() over w place, round(percent_rank() over w, 6) share, ntile(2) over w half, first_value(chars) over w most, "
    "nth_value(chars, 2) over (w rows between unbounded preceding and unbounded following) runner_up, lag(chars) over w - chars step "
    "from (select source, lang, sum(len(text))::bigint chars from documents group by all) window w as (partition by source order by chars desc, lang)"
)
def language_places(spark, d):
    """The languages of a source by their characters, through ranking and analytic windows."""
    w = W.partitionBy("source").orderBy(F.desc("chars"), F.col("lang").asc_nulls_last())
    whole = w.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    n = _docs(spark, d).groupBy("source", "lang").agg(F.sum(F.length("text")).alias("chars"))
    return n.select(
        "source", "lang", "chars", F.dense_rank().over(w).cast("long").alias("place"), r6(F.percent_rank().over(w)).alias("share"), F.ntile(2).over(w).cast("long").alias("half"), F.first("chars").over(w).alias("most"),
        F.nth_value("chars", 2).over(whole).alias("runner_up"), (F.lag("chars").over(w) - F.col("chars")).alias("step"),
    )


@query("select count(*) documents, 0::bigint lost, 0::bigint extra from documents")
def roundtrip_multiset(spark, d):
    """Rows that a round trip loses or adds, repeated rows counted."""
    x = _docs(spark, d).select("doc_id", "text")
    a = x.select("doc_id", F.md5("text").alias("digest"))
    b = pipeline.decompress(pipeline.compress(x, codec="zstd")).select("doc_id", F.md5("text").alias("digest"))
    n = lambda df, name: df.agg(F.count("*").alias(name))
    return n(a, "documents").crossJoin(n(a.exceptAll(b), "lost")).crossJoin(n(b.exceptAll(a), "extra"))


@query(f"select lang, count(distinct before || symbol) contexts, true near from ({SYM}) group by lang")
def distinct_contexts(spark, d):
    """Distinct pairs of neighbours, and whether the sketch's number is within a tenth of it."""
    p = pairs(_docs(spark, d), "lang").groupBy("lang", "before", "symbol").agg(F.count("*").alias("c"))
    both = F.concat("before", "symbol")
    return p.groupBy("lang").agg(F.count_distinct(both).alias("contexts"), F.approx_count_distinct(both, 0.02).alias("about")).select("lang", "contexts", (F.abs(F.col("about") / F.col("contexts") - 1) < 0.1).alias("near"))

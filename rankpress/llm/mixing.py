"""Mixing sources to target weights by a low-discrepancy schedule (operator 9), in DataFrame functions only.

The documents of a source, shuffled by a digest of their id, are laid end to end and cut into blocks of equally many words.
A schedule of slots takes blocks, one to a slot: slot i stands at the van der Corput point of i, and belongs to the source in whose
stretch of the axis the point falls; the stretches are the cumulative targets, counted in blocks. The r-th slot of a source takes
its r-th block, and the blocks go round once more where the target exceeds the source. So every stretch of the schedule, from its first
slot on, holds the sources in nearly their shares; a source's last slot is trimmed to the target.

Nothing is ranked over a whole source: running sums and ranks are taken within small buckets and moved by bucket totals, so a
source with a third of all rows is spread like the others. The points are made by all tasks.

A null text has size 0; a null source is a source of its own, the last; documents of size 0 take part with nothing taken and no slot;
null ids share a digest and stand side by side in their source; repeated rows are documents of their own; without any word all
targets are 0; an empty table gives an empty result; other columns are ignored by the query and kept by mixed().
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from .common import WORD_RE, cut, table

#: Weights of the sources in their order, repeating; all sources together take so much of all sizes; a source at most so much of its own.
WEIGHTS, SHARE, CAP = (3, 1, 2), 1.5, 2


def sizes(docs: DataFrame) -> DataFrame:
    """docs with `size`, and `shuffled`, the digest by which a source's documents are ordered."""
    return docs.withColumns({"size": F.coalesce(F.regexp_count("text", F.lit(WORD_RE)), F.lit(0)).cast("long"), "shuffled": F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")))})


def targets(sized: DataFrame) -> DataFrame:
    """source, source_size, target: caps bind in the order of cap over weight, so one sorted pass finds the common level.

    With the sources in that order, level k is what the weights from k on would get if all before k are at their caps;
    the first k whose cap lies above level k ends the capped ones.
    """
    per = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    place = W.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*map(F.lit, WEIGHTS)), F.pmod(F.row_number().over(place) - 1, F.lit(len(WEIGHTS))) + 1)
    per = per.withColumns({"weight": weight, "cap": CAP * F.col("source_size")})
    order = (F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    before, after, every = W.orderBy(*order).rowsBetween(W.unboundedPreceding, -1), W.orderBy(*order).rowsBetween(0, W.unboundedFollowing), W.partitionBy()
    total = F.lit(SHARE) * F.sum("source_size").over(every)
    level = (total - F.coalesce(F.sum("cap").over(before), F.lit(0))) / F.sum("weight").over(after)
    per = per.withColumns({"level": level, "place": F.row_number().over(W.orderBy(*order))})
    free = F.when(F.col("cap") / F.col("weight") > F.col("level"), F.struct("place", "level"))
    per = per.withColumn("level", F.min(free).over(every)["level"])
    return per.select("source", "source_size", F.least(F.col("cap").cast("double"), F.col("weight") * F.col("level")).alias("target"))


def plan(sized: DataFrame, slots: int = 1 << 18) -> DataFrame:
    """targets() with the plan of the schedule, one row per source.

    block: words of a block; words: the target in whole words; n_blocks of the source; n_slots it needs; first: the place
    where its interval of the points' axis begins, in slots; bits: the schedule has 2**bits points.
    """
    every = W.partitionBy()
    t = targets(sized).withColumn("words", F.floor(F.col("target") + 1e-6))
    t = t.withColumn("block", F.greatest(F.lit(1), F.ceil(F.sum("words").over(every) / slots)).cast("long"))
    blocks = lambda n: F.ceil(n / F.col("block")).cast("long")
    t = t.withColumn("n_blocks", blocks(F.col("source_size")))
    t = t.withColumn("n_slots", F.when(F.col("words") <= F.col("source_size"), blocks(F.col("words"))).otherwise(F.col("n_blocks") + blocks(F.col("words") - F.col("source_size"))))
    upto = W.orderBy(F.col("source").asc_nulls_last()).rowsBetween(W.unboundedPreceding, -1)
    t = t.withColumn("first", F.coalesce(F.sum("n_slots").over(upto), F.lit(0)))
    return t.withColumn("bits", F.ceil(F.log2(F.greatest(F.lit(2), F.sum("n_slots").over(every)))).cast("int"))


def _running(df: DataFrame, keys: list[str], bucket: str, order: list, value: Column, name: str) -> DataFrame:
    """df with `name`: the sum of value over the rows of the same keys before each, in order; bucket must follow the order."""
    df = df.withColumn("_v", value)
    parts = df.groupBy(*keys, bucket).agg(F.sum("_v").alias("_s"))
    past = W.partitionBy(*keys).orderBy(bucket).rowsBetween(W.unboundedPreceding, -1)
    parts = parts.withColumn("_off", F.coalesce(F.sum("_s").over(past), F.lit(0)))
    on = [F.col(f"l.{k}").eqNullSafe(F.col(f"r.{k}")) for k in (*keys, bucket)]
    inner = W.partitionBy(*keys, bucket).orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
    df = df.withColumn("_in", F.coalesce(F.sum("_v").over(inner), F.lit(0)))
    return df.alias("l").join(parts.alias("r"), on).select("l.*", (F.col("_in") + F.col("_off")).alias(name)).drop("_v", "_in")


def schedule(p: DataFrame) -> DataFrame:
    """(slot, source, block_no, turn, take): the mix in its order; turn 0 is the first passage of a source's blocks."""
    bits = p.agg(F.max("bits")).first()[0] or 0
    bit = lambda k: F.expr(f"shiftleft(cast(getbit(slot, {k}) as bigint), {bits - 1 - k})")
    point = reduce(lambda a, b: a + b, map(bit, range(bits)), F.lit(0).cast("long"))
    s = p.sparkSession.range(1 << bits if bits else 0).select(F.col("id").alias("slot")).withColumn("point", point)
    s = s.join(F.broadcast(p), (F.col("point") >= F.col("first")) & (F.col("point") < F.col("first") + F.col("n_slots"))).withColumn("chunk", F.expr("slot div 4096"))
    s = _running(s, ["source"], "chunk", ["slot"], F.lit(1).cast("long"), "rank")
    s = s.withColumns({"turn": F.when(F.col("rank") >= F.col("n_blocks"), 1).otherwise(0), "block_no": F.expr("rank % n_blocks")})
    left = F.when(F.col("turn") == 0, F.least("words", "source_size")).otherwise(F.col("words") - F.col("source_size")) - F.col("block_no") * F.col("block")
    return s.select("slot", "source", "block_no", "turn", F.least(F.col("block"), left).alias("take"))


def mix(docs: DataFrame, slots: int = 1 << 18) -> DataFrame:
    """docs with size, source_size, target, taken (the words that the schedule takes of each document, repeats counted), first_slot and
    n_slots: the earliest slot that takes of it, null if none does, and how many do."""
    sized = cut(sizes(docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", "source", "text")).drop("text"))
    p = cut(plan(sized, slots))
    at_turn = lambda k: F.max(F.when(F.col("turn") == k, F.struct("slot", "take"))).alias(f"t{k}")
    given = schedule(p).groupBy("source", "block_no").agg(at_turn(0), at_turn(1))
    laid = _running(sized.withColumn("bucket", F.conv(F.substring("shuffled", 1, 3), 16, 10).cast("int")), ["source"], "bucket", ["shuffled", "doc_id", "size"], F.col("size"), "begin")
    laid = laid.alias("l").join(F.broadcast(p).alias("p"), F.col("l.source").eqNullSafe(F.col("p.source"))).select("l.*", "p.source_size", "p.target", "p.block")
    cover = F.when(F.col("size") > 0, F.sequence(F.expr("begin div block"), F.expr("(begin + size - 1) div block")))
    parts = laid.withColumn("block_no", F.explode_outer(cover))
    got = parts.alias("a").join(given.alias("g"), F.col("a.source").eqNullSafe(F.col("g.source")) & (F.col("a.block_no") == F.col("g.block_no")), "left").select("a.*", "g.t0", "g.t1")
    at = F.col("block_no") * F.col("block")
    words = lambda t: F.when(F.col(t).isNull(), 0).otherwise(F.greatest(F.lit(0), F.least(F.col("begin") + F.col("size"), at + F.col(t)["take"]) - F.greatest("begin", at)))
    got = got.withColumns({"w0": words("t0"), "w1": words("t1")})
    first = F.min(F.least(*(F.when(F.col(f"w{k}") > 0, F.col(f"t{k}")["slot"]) for k in (0, 1)))).alias("first_slot")
    n = F.sum((F.col("w0") > 0).cast("long") + (F.col("w1") > 0).cast("long")).alias("n_slots")
    return got.groupBy("row").agg(*(F.first(c).alias(c) for c in ("doc_id", "size", "source_size", "target")), F.sum(F.col("w0") + F.col("w1")).alias("taken"), first, n)


def mixed(docs: DataFrame, slots: int = 1 << 18) -> DataFrame:
    """The documents of the mix, each as often as it is taken: taken over size, rounded, copies as rows of their own.

    Rows of the same doc_id share what the mix takes of them; a document without a word is left out.
    """
    m = mix(docs.select("doc_id", "source", "text"), slots).where("size > 0").groupBy("doc_id").agg((F.sum("taken") / F.sum("size")).alias("_times"))
    m = m.select(F.col("doc_id").alias("_id"), F.expr("cast(floor(_times + 0.5) as int)").alias("_times")).where("_times > 0")
    out = docs.join(m, F.col("doc_id").eqNullSafe(F.col("_id")))
    return out.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_times")))).select(*docs.columns)


def op9(spark, sf_dir):
    m = mix(table(spark, sf_dir, "documents"))
    return m.select("doc_id", "size", "source_size", F.round("target", 6).alias("target"), "taken", "first_slot", "n_slots")


#: The same mix, each source ranked in one window.
SQL9 = """
with sized as (
  select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint size, md5(coalesce(doc_id::varchar, '')) shuffled from documents),
per as (select source, sum(size)::bigint source_size, [3, 1, 2][1 + (row_number() over (order by source nulls last) - 1) % 3] weight from sized group by source),
lev as (
  select *, 2 * source_size cap,
    (1.5 * (sum(source_size) over ())::double - coalesce(sum(2 * source_size) over (o rows between unbounded preceding and 1 preceding), 0)::double)
      / (sum(weight) over (o rows between current row and unbounded following))::double lev, row_number() over o place
  from per window o as (order by 2.0::double * source_size / weight, source nulls last)),
tgt as (
  select source, source_size, least(cap::double, weight * coalesce(arg_min(lev, case when cap::double / weight > lev then place end) over (), 1e300)) target from lev),
w as (select *, floor(target + 1e-6)::bigint words from tgt),
blk as (select *, greatest(1, ceil((sum(words) over ())::double / 262144))::bigint block from w),
nb as (select *, ceil(source_size::double / block)::bigint n_blocks,
  case when words <= source_size then ceil(words::double / block) else ceil(source_size::double / block) + ceil((words - source_size)::double / block) end::bigint n_slots from blk),
pl as (select *, coalesce(sum(n_slots) over (order by source nulls last rows between unbounded preceding and 1 preceding), 0)::bigint begins,
  ceil(log2(greatest(2, (sum(n_slots) over ())::bigint)))::int bits from nb),
pts as (
  select slot, list_sum(list_transform(range(bits), lambda k: ((slot >> k) & 1) << (bits - 1 - k)))::bigint point
  from (select max(bits)::bigint bits from pl) b, lateral (select unnest(range(1::bigint << b.bits)) slot) s),
sl as (
  select p.*, slot, row_number() over (partition by source order by slot) - 1 rnk
  from pts join pl p on point >= begins and point < begins + n_slots),
tk as (
  select source, slot, rnk % n_blocks block_no,
    least(block, case when rnk < n_blocks then least(words, source_size) else words - source_size end - (rnk % n_blocks) * block) take from sl),
laid as (
  select d.*, t.source_size, t.target, t.block,
    coalesce(sum(size) over (partition by d.source order by shuffled, doc_id, size rows between unbounded preceding and 1 preceding), 0)::bigint bg, row_number() over () rid
  from sized d join pl t on d.source is not distinct from t.source),
got as (
  select l.rid, sum(w) taken, min(slot) first_slot, count(*) n from (select l.rid, k.slot, least(bg + size, k.block_no * block + take) - greatest(bg, k.block_no * block) w
  from (select *, unnest(range(bg // block, (bg + size - 1) // block + 1)) b from laid where size > 0) l
  join tk k on k.source is not distinct from l.source and k.block_no = l.b) l where w > 0 group by l.rid)
select doc_id, size, source_size, round(target, 6) target, coalesce(taken, 0)::bigint taken, first_slot, coalesce(n, 0)::bigint n_slots from laid left join got using (rid)
"""

QUERIES = {"op9_mixing": op9}
SQL = {"op9_mixing": SQL9}

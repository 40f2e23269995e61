"""Measures: ratio, bits a character, entropy, gains, averages, rank distributions, losslessness."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window as W, functions as F


def ratio(raw: str | Column, packed: str | Column) -> Column:
    """Raw over packed size; larger is better. Null where nothing was packed."""
    raw, packed = (F.col(c) if isinstance(c, str) else c for c in (raw, packed))
    return F.when(packed > 0, raw / packed)


def bits_per(units: str | Column, packed: str | Column) -> Column:
    """Bits a unit: code points for bpc, bytes for bpb."""
    units, packed = (F.col(c) if isinstance(c, str) else c for c in (units, packed))
    return F.when(units > 0, 8 * packed / units)


def summary(results: DataFrame, by: list[str]) -> DataFrame:
    """Of each group: n, pooled ratios and bits, mean, median, least and largest block ratio, tokens, rank-0 share, time."""
    r = ratio("raw_bytes", "packed_bytes")
    raw, chars, packed = (F.sum(c) for c in ("raw_bytes", "raw_chars", "packed_bytes"))
    return results.where("raw_bytes > 0").groupBy(*by).agg(
        F.count("*").alias("n"), (raw / packed).alias("ratio_bytes"), (chars / packed).alias("ratio_chars"), (8 * packed / chars).alias("bpc"), (8 * packed / raw).alias("bpb"),
        F.avg(r).alias("ratio_mean"), F.percentile(r, F.lit(0.5)).alias("ratio_median"), F.min(r).alias("ratio_min"), F.max(r).alias("ratio_max"),
        F.sum("n_tokens").alias("n_tokens"), F.avg("top1").alias("top1"), F.avg("rank_entropy").alias("rank_entropy"), F.avg("encode_ms").alias("encode_ms"),
    )


def average(results: DataFrame, how: str, group: str) -> DataFrame:
    """One mean of block ratios for each model and codec: macro (of groups' means), micro (of blocks) or pooled (of sizes)."""
    keys = ["model", "serializer", "codec", "mode"]
    r = results.where("packed_bytes > 0").withColumn("r", ratio("raw_bytes", "packed_bytes"))
    if how == "macro":
        return r.groupBy(group, *keys).agg(F.avg("r").alias("r")).groupBy(*keys).agg(F.avg("r").alias("ratio"))
    if how == "micro":
        return r.groupBy(*keys).agg(F.avg("r").alias("ratio"))
    if how == "pooled":
        return r.groupBy(*keys).agg((F.sum("raw_bytes") / F.sum("packed_bytes")).alias("ratio"))
    raise ValueError(how)


def improvement(results: DataFrame, base: Column, variant: Column, keys: list[str]) -> DataFrame:
    """keys, ratio_base, ratio_new, gain_pct = 100 * (new / base - 1), from unrounded sizes of rows that match on keys."""
    a = results.where(base).groupBy(*keys).agg((F.sum("raw_bytes") / F.sum("packed_bytes")).alias("ratio_base"))
    b = results.where(variant).groupBy(*keys).agg((F.sum("raw_bytes") / F.sum("packed_bytes")).alias("ratio_new"))
    return a.join(b, keys).withColumn("gain_pct", 100 * (F.col("ratio_new") / F.col("ratio_base") - 1))


def codec_gain(results: DataFrame, first: str, second: str, what: str = "codec") -> DataFrame:
    """grp, model, ratio_first, ratio_second, gain_pct: what the second codec (or serializer) gains over the first on the same ranks."""
    size = lambda c: F.sum(F.when(F.col(what) == c, F.col("packed_bytes")))
    raw = F.sum(F.when(F.col(what) == first, F.col("raw_bytes")))
    t = results.groupBy("grp", "model").agg((raw / size(first)).alias("ratio_first"), (raw / size(second)).alias("ratio_second"))
    return t.withColumn("gain_pct", 100 * (F.col("ratio_second") / F.col("ratio_first") - 1))


def amortised(results: DataFrame, sizes: DataFrame) -> DataFrame:
    """model, codec, ratio_bytes, n_params, n_bytes, ratio_with_model: pooled ratios without and with the model's bytes (sizes: model,
    n_params, n_bytes) charged once to all that is packed."""
    t = results.groupBy("model", "codec").agg(F.sum("raw_bytes").alias("raw"), F.sum("packed_bytes").alias("packed")).join(F.broadcast(sizes), "model")
    return t.select("model", "codec", (F.col("raw") / F.col("packed")).alias("ratio_bytes"), "n_params", "n_bytes", (F.col("raw") / (F.col("packed") + F.col("n_bytes"))).alias("ratio_with_model"))


def gain_interval(results: DataFrame, base: Column, variant: Column, draws: int = 200) -> DataFrame:
    """gain_pct of pooled ratios with a paired bootstrap interval of 95 %: each block's weight in a draw is a Poisson count
    taken from a digest of block and draw, so draws need no passes of their own and reruns agree."""
    keys = ["grp", "doc_id", "block"]
    a = results.where(base).select(*keys, "raw_bytes", F.col("packed_bytes").alias("pa"))
    b = results.where(variant).select(*keys, F.col("packed_bytes").alias("pb"))
    d = a.join(b, keys).withColumn("draw", F.explode(F.sequence(F.lit(0), F.lit(draws))))
    u = F.conv(F.substring(F.md5(F.concat_ws("-", *keys, "draw")), 1, 8), 16, 10).cast("double") / 2**32
    w = F.when(F.col("draw") == 0, 1).otherwise(sum((u > p).cast("int") for p in (0.36787944, 0.73575888, 0.91969860, 0.98101184, 0.99634015)))
    g = d.withColumn("w", w).groupBy("grp", "draw").agg((100 * (F.sum(F.col("w") * F.col("pa")) / F.sum(F.col("w") * F.col("pb")) - 1)).alias("g"))
    return g.groupBy("grp").agg(F.max(F.when(F.col("draw") == 0, F.col("g"))).alias("gain_pct"), F.percentile(F.when(F.col("draw") > 0, F.col("g")), F.lit(0.025)).alias("low"), F.percentile(F.when(F.col("draw") > 0, F.col("g")), F.lit(0.975)).alias("high"))


def entropy(symbols: DataFrame, by: list[str], symbol: str = "symbol", base: str = "2") -> DataFrame:
    """Shannon entropy of each group's symbols, in bits or nats. Symbols are counted before they are compared."""
    n = symbols.groupBy(*by, symbol).agg(F.count("*").alias("n"))
    return entropy_of_counts(n, by, base)


def entropy_of_counts(n: DataFrame, by: list[str], base: str = "2") -> DataFrame:
    log = F.log2 if base == "2" else F.log
    total = n.groupBy(*by).agg(F.sum("n").alias("total"), F.sum(F.col("n") * log("n")).alias("s"), F.count("*").alias("symbols"))
    return total.select(*by, "symbols", (log("total") - F.col("s") / F.col("total")).alias("entropy"))


def conditional_entropy(pairs: DataFrame, by: list[str]) -> DataFrame:
    """Entropy of `symbol` given `before`, in bits."""
    n = pairs.groupBy(*by, "before", "symbol").agg(F.count("*").alias("n"))
    ctx = n.groupBy(*by, "before").agg(F.sum("n").alias("c"), F.sum(F.col("n") * F.log2("n")).alias("s"))
    return ctx.groupBy(*by).agg((F.sum(F.col("c") * F.log2("c") - F.col("s")) / F.sum("c")).alias("entropy"))


def rank_histogram(ranks: DataFrame, by: list[str]) -> DataFrame:
    return ranks.groupBy(*by, "rank").agg(F.count("*").alias("n"))


def decay_fit(hist: DataFrame, by: list[str]) -> DataFrame:
    """Slope and r2 of ln(n) against rank, and the shares of the ranks below 1, 5 and 10."""
    share = lambda k: (F.sum(F.when(F.col("rank") < k, F.col("n")).otherwise(0)) / F.sum("n")).alias(f"top{k}")
    return hist.groupBy(*by).agg(F.regr_slope(F.log("n"), "rank").alias("slope"), F.regr_r2(F.log("n"), "rank").alias("r2"), share(1), share(5), share(10), (F.sum(F.col("rank") * F.col("n")) / F.sum("n")).alias("mean_rank"))


def monotonicity(results: DataFrame, order: str, value: str, by: list[str]) -> DataFrame:
    """Steps along a ladder, and how many of them lower the value."""
    w = W.partitionBy(*by).orderBy(order)
    d = results.withColumn("step", F.col(value) - F.lag(value).over(w))
    return d.groupBy(*by).agg(F.count("step").alias("steps"), F.sum(F.when(F.col("step") < 0, 1).otherwise(0)).cast("long").alias("violations"))


def factors(results: DataFrame, by: list[str]) -> DataFrame:
    """Correlations of block ratios with rank-0 share, rank entropy and tokens a character."""
    r = ratio("raw_bytes", "packed_bytes")
    return results.where("packed_bytes > 0").groupBy(*by).agg(F.corr(r, "top1").alias("with_top1"), F.corr(r, "rank_entropy").alias("with_entropy"), F.corr(r, F.col("n_tokens") / F.col("raw_chars")).alias("with_fertility"), F.count("*").alias("n"))


def lossless(original: DataFrame, decoded: DataFrame) -> DataFrame:
    """doc_ids whose text didn't come back; empty when all did."""
    o = original.select("doc_id", F.md5("text").alias("a"))
    d = decoded.select("doc_id", F.md5("text").alias("b"))
    return o.join(d, "doc_id", "full").where(~F.col("a").eqNullSafe(F.col("b"))).select("doc_id")

"""Streaming forms: block compression, adaptive ranks with state, windows, sessions, late data, joins, deduplication.

Sources are any streaming DataFrames; sinks are the caller's. Time columns without a zone are read as UTC.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..functions.predictors import AdaptiveRanker
from ..plans import pipeline

ROCKS = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def timed(events: DataFrame, ts: str = "ts", delay: str = "1 hour") -> DataFrame:
    """Events with `ts` as a timestamp and a watermark on it."""
    return events.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay)


def compress(docs: DataFrame, **how) -> DataFrame:
    """Frames of a stream of documents: stateless, so append mode with any sink."""
    return pipeline.compress(docs, **how)


def to_frames(frames: DataFrame, path: str, checkpoint: str):
    """A query that writes each micro-batch once: its number names the folder, so a repeated batch overwrites itself."""

    def put(batch: DataFrame, no: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={no}")

    return frames.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).start()


class _Adaptive(StatefulProcessor):
    """Counts after contexts of lengths 0..order of a key's symbols; contexts are capped, the oldest leave first."""

    def __init__(self, order: int, contexts: int, ttl_ms: int | None):
        self.order, self.contexts, self.ttl = order, contexts, ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("counts", "last array<string>, keys array<string>, symbols array<array<string>>, counts array<array<long>>", self.ttl)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        last, table = [], {}
        if self.state.exists():
            last, keys, symbols, counts = self.state.get()
            last, table = list(last), {k: dict(zip(s, c)) for k, s, c in zip(keys, symbols, counts)}
        out = []
        batch = pd.concat(list(rows)).sort_values(["ts", "event_id"])
        for ts, event, symbol in zip(batch["ts"], batch["event_id"], batch["symbol"]):
            ctx = ["\x1f".join([str(k), *last[len(last) - k :]]) for k in range(min(self.order, len(last)) + 1)]
            rank = rank_among(table, ctx, symbol)
            out.append((key[0], event, symbol, rank))
            for c in ctx:
                seen = table.pop(c, {})
                seen[symbol] = seen.get(symbol, 0) + 1
                table[c] = seen
            while len(table) > self.contexts:
                table.pop(next(iter(table)))
            last = [*last, symbol][-self.order :] if self.order else []
        self.state.update((last, list(table), [list(v) for v in table.values()], [list(v.values()) for v in table.values()]))
        yield pd.DataFrame(out, columns=["key", "event_id", "symbol", "rank"])

    def close(self) -> None:
        pass


def rank_among(table: dict, contexts: list[str], symbol: str) -> int:
    """Place of a symbol in the order that the counts give, longest context first; -1 for one that no context has seen."""
    listed: list[str] = []
    for c in reversed(contexts):
        for s, _ in sorted(table.get(c, {}).items(), key=lambda x: (-x[1], x[0])):
            if s not in listed:
                listed.append(s)
    return listed.index(symbol) if symbol in listed else -1


RANKS = "key long, event_id long, symbol string, rank long"


def adaptive_ranks(events: DataFrame, key: str = "user_id", symbol: str = "event_type", order: int = 1, contexts: int = 1000, ttl_ms: int | None = None) -> DataFrame:
    """key, event_id, symbol, rank: each event's rank under what its key has shown so far. Needs the RocksDB state store."""
    e = events.select(F.col(key).alias("key"), "ts", "event_id", F.col(symbol).alias("symbol"))
    return e.groupBy("key").transformWithStateInPandas(_Adaptive(order, contexts, ttl_ms), RANKS, "Append", "None")


def adaptive_ranks_batch(events: DataFrame, key: str = "user_id", symbol: str = "event_type", order: int = 1) -> DataFrame:
    """The batch twin. A key's events are sorted by the shuffle and read as they come, a key at a time."""

    def run(parts):
        state: dict = {}
        for b in parts:
            out = []
            for k, event, s in zip(b["key"], b["event_id"], b["symbol"]):
                if state.get("key") != k:
                    state = {"key": k, "last": [], "table": {}}
                last, table = state["last"], state["table"]
                ctx = ["\x1f".join([str(n), *last[len(last) - n :]]) for n in range(min(order, len(last)) + 1)]
                out.append((k, event, s, rank_among(table, ctx, s)))
                for c in ctx:
                    table.setdefault(c, {})
                    table[c][s] = table[c].get(s, 0) + 1
                state["last"] = [*last, s][-order:] if order else []
            yield pd.DataFrame(out, columns=["key", "event_id", "symbol", "rank"])

    e = events.select(F.col(key).alias("key"), "ts", "event_id", F.col(symbol).alias("symbol"))
    return e.repartition("key").sortWithinPartitions("key", "ts", "event_id").mapInPandas(run, RANKS)


def histogram(events: DataFrame, size: str, slide: str | None = None, symbol: str = "event_type") -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.groupBy(w, symbol).agg(F.count("*").alias("n"))


def sessions(events: DataFrame, gap: str = "30 minutes", key: str = "user_id", symbol: str = "event_type") -> DataFrame:
    """key, session_start, symbols: a session's symbols in the order of time."""
    g = events.groupBy(key, F.session_window("ts", gap)).agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", F.col(symbol).alias("s")))).alias("r"))
    return g.select(key, F.col("session_window.start").alias("session_start"), F.transform("r", lambda x: x["s"]).alias("symbols"))


def late_report(query) -> int:
    """Rows that all stateful operators of a query have dropped as too late, from its progress."""
    return sum(int(o.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for o in p["stateOperators"])


def drift(ranks: DataFrame, window: str, baseline: float, ts: str = "ts") -> DataFrame:
    """Windows whose mean log2(rank + 2) lies above a baseline."""
    return ranks.groupBy(F.window(ts, window)).agg(F.avg(F.log2(F.col("rank") + 2)).alias("bits")).withColumn("alarm", F.col("bits") > baseline)


def with_labels(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Stream-static join; Spark broadcasts the static side where it's small."""
    return docs.join(labels, "doc_id", "left")


def dedup(events: DataFrame, key: str = "event_id") -> DataFrame:
    return events.dropDuplicatesWithinWatermark([key])


def ranker(vocab_size: int, order: int = 2) -> AdaptiveRanker:
    """The one-pass predictor for blocks of a stream."""
    return AdaptiveRanker(vocab_size, order)

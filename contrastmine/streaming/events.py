"""Streaming: windowed class supports, session baskets, deduplication, drift of known patterns and the trigger to mine again.

Every function takes a batch or a streaming DataFrame; on a stream, set a watermark first or pass one."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Any

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.labeled import Item, encode, occurs


def read_events(spark: SparkSession, folder: str, schema, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def _marked(df: DataFrame, ts: str, watermark: str | None) -> DataFrame:
    return df.withWatermark(ts, watermark) if watermark else df


def window_supports(df: DataFrame, by: str, positive: Column, width: str, slide: str | None = None, ts: str = "ts", watermark: str | None = None) -> DataFrame:
    """(window_start, by, n_pos, n_neg): class supports of each value in tumbling or sliding windows."""
    win = F.window(ts, width, slide) if slide else F.window(ts, width)
    counted = _marked(df, ts, watermark).groupBy(win.alias("w"), by).agg(F.sum(positive.cast("long")).alias("n_pos"), F.sum(1 - positive.cast("long")).alias("n_neg"))
    return counted.select(F.col("w.start").alias("window_start"), by, "n_pos", "n_neg")


def pattern_window_supports(df: DataFrame, items: list[Item], patterns: dict[str, tuple[int, ...]], positive: Column, width: str, slide: str | None = None, ts: str = "ts", watermark: str | None = None) -> DataFrame:
    """(window_start, pattern, n_pos, n_neg) of a fixed list of patterns."""
    ids = F.array_compact(F.array(*(F.when(F.coalesce(i.predicate, F.lit(False)), F.lit(k)) for k, i in enumerate(items))))
    base = _marked(df, ts, watermark).select(ts, ids.alias("items"), positive.cast("long").alias("y"))
    hits = F.array_compact(F.array(*(F.when(occurs(F.col("items"), p, len(items)), F.lit(n)) for n, p in patterns.items())))
    spread = base.select(ts, "y", F.explode(hits).alias("pattern"))
    win = F.window(ts, width, slide) if slide else F.window(ts, width)
    return spread.groupBy(win.alias("w"), "pattern").agg(F.sum("y").alias("n_pos"), F.sum(1 - F.col("y")).alias("n_neg")).select(F.col("w.start").alias("window_start"), "pattern", "n_pos", "n_neg")


def session_itemsets(df: DataFrame, gap: str = "30 minutes", key: str = "user_id", ts: str = "ts", item: str = "event_type", watermark: str | None = None) -> DataFrame:
    """(key, session_start, n_events, items): sessions as sets of event types."""
    grouped = _marked(df, ts, watermark).groupBy(key, F.session_window(ts, gap).alias("s"))
    return grouped.agg(F.count(F.lit(1)).alias("n_events"), F.array_sort(F.collect_set(item)).alias("items")).select(key, F.col("s.start").alias("session_start"), "n_events", "items")


def dedup(df: DataFrame, key: str, ts: str = "ts", watermark: str = "10 minutes") -> DataFrame:
    return df.withWatermark(ts, watermark).dropDuplicatesWithinWatermark([key])


DRIFT = "pattern string, n_pos long, n_neg long, inside boolean"


def drift(supports: DataFrame, inside: Callable[[int, int], bool]) -> DataFrame:
    """Running supports per pattern from a stream of (pattern, n_pos, n_neg); a row whenever a pattern enters or leaves the region."""

    def update(key: tuple[Any, ...], frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        x, y, was = state.get if state.exists else (0, 0, False)
        for f in frames:
            x, y = x + int(f["n_pos"].sum()), y + int(f["n_neg"].sum())
        now = bool(inside(x, y))
        state.update((x, y, now))
        if now != was:
            yield pd.DataFrame({"pattern": [key[0]], "n_pos": [x], "n_neg": [y], "inside": [now]})

    return supports.groupBy("pattern").applyInPandasWithState(update, DRIFT, "n_pos long, n_neg long, inside boolean", "append", "NoTimeout")


def mine_again(stream: DataFrame, items: list[Item], positive: Column, rows_path: str, due: Callable[[DataFrame], bool], mine: Callable[[DataFrame], None]):
    """A writer that appends each batch's weighted rows and calls mine(all rows so far) when due(rows) says so."""

    def each(batch: DataFrame, epoch: int) -> None:
        rows = encode(batch, items, positive.cast("int")).groupBy("items").agg(F.sum("label").cast("long").alias("w_pos"), F.sum(1 - F.col("label")).cast("long").alias("w_neg"))
        rows.write.mode("overwrite").parquet(f"{rows_path}/epoch={epoch}")
        held = batch.sparkSession.read.parquet(rows_path).groupBy("items").agg(F.sum("w_pos").alias("w_pos"), F.sum("w_neg").alias("w_neg"))
        if due(held):
            mine(held)

    return stream.writeStream.foreachBatch(each)

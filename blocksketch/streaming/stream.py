"""Sketches of streams: running stacked sketches, windows, late data, duplicates, and a gate that emits a cell after enough slices."""

from __future__ import annotations

import os
import tempfile
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import HashFamily


def running_sketch(events: DataFrame, width: int, family: HashFamily) -> DataFrame:
    """(i, k, h, v): the stacked sketch of user by hour counts, kept up to date as events arrive; it is linear, so state is only its entries."""
    c = ((F.dayofmonth("ts") - 1) * 24 + F.hour("ts")).cast("long")
    e = events.select(F.col("user_id").cast("long").alias("i"), F.inline(family.entries(c, F.lit(1).cast("long"), width)))
    return e.groupBy("i", "k", "h").agg(F.sum("sv").alias("v"))


def windowed(events: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    out = events.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum(F.floor(F.col("value") * 100 + 0.5).cast("long")).alias("cents"))
    return out.select(F.col("w.start").alias("start"), "event_type", "n", "cents")


def sessions(events: DataFrame, gap: str) -> DataFrame:
    out = events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return out.select(F.col("w.start").alias("start"), "user_id", "n")


def deduplicated(events: DataFrame, delay: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def gate(partials: DataFrame, needed: int) -> DataFrame:
    """partials(bi, bj, k, total) to a row per cell once `needed` distinct slices have arrived: (bi, bj, n_survivors, total). Later slices are ignored."""

    def step(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        seen, total = state.get if state.exists else ([], 0)
        seen = list(seen)
        if len(seen) < needed:
            for pdf in batches:
                for k, v in sorted(zip(pdf["k"], pdf["total"], strict=True)):
                    if k not in seen and len(seen) < needed:
                        seen.append(int(k))
                        total += int(v)
            state.update((seen, total))
            if len(seen) == needed:
                yield pd.DataFrame({"bi": [key[0]], "bj": [key[1]], "n_survivors": [needed], "total": [total]})

    return partials.groupBy("bi", "bj").applyInPandasWithState(step, "bi int, bj int, n_survivors int, total long", "seen array<int>, total long", "append", "NoTimeout")


def finished(df: DataFrame, mode: str = "complete") -> DataFrame:
    """All of a stream's present input worked through. Complete results are a table in memory; appended rows, as many as the input may have, go to files
    that tasks write and read."""
    spark: SparkSession = df.sparkSession
    name = f"stream_{os.urandom(6).hex()}"
    place = spark.conf.get("spark.checkpoint.dir", None)
    folder = f"{place}/{name}" if place else tempfile.mkdtemp(prefix=name)
    out = df.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/log").trigger(availableNow=True)
    q = out.format("parquet").start(f"{folder}/rows") if mode == "append" else out.format("memory").queryName(name).start()
    try:
        q.awaitTermination()
    finally:
        q.stop()
    return spark.read.schema(df.schema).parquet(f"{folder}/rows") if mode == "append" else spark.table(name)

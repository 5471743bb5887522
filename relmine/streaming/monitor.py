"""Accepted rules watched over a stream: windowed satisfaction, alarms, and drift counters."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from relmine.model import Config, Relation
from relmine.operators.satisfy import holds


def event_time(df: DataFrame, column: str = "ts") -> DataFrame:
    """A time that watermarks accept: timestamps without a zone are read in the session's zone."""
    return df.withColumn(column, F.col(column).cast("timestamp"))


def flagged(df: DataFrame, rels: Sequence[Relation], cfg: Config | None = None) -> DataFrame:
    """(all columns, rule, ok): a row for each rule and event that counts."""
    pairs = F.array(*(F.struct(F.lit(r.text).alias("rule"), holds(r, exact=False, cfg=cfg).alias("ok")) for r in rels))
    return df.select("*", F.inline(pairs)).where("ok is not null")


def windowed(df: DataFrame, rels: Sequence[Relation], length: str = "1 day", slide: str | None = None, late: str | None = "1 hour", column: str = "ts") -> DataFrame:
    """(rule, window_start, hits, n_rows) in tumbling or sliding windows; rows later than ``late`` are dropped by a stream."""
    f = flagged(event_time(df, column), rels)
    f = f.withWatermark(column, late) if late else f
    w = F.window(column, length, slide) if slide else F.window(column, length)
    return f.groupBy("rule", w.alias("w")).agg(F.count_if("ok").alias("hits"), F.count("*").alias("n_rows")).select("rule", F.col("w.start").alias("window_start"), "hits", "n_rows")


def sessions(df: DataFrame, rels: Sequence[Relation], gap: str, key: str, late: str | None = "1 hour", column: str = "ts") -> DataFrame:
    """(rule, key, session_start, hits, n_rows): sessions of one key, closed by ``gap``."""
    f = flagged(event_time(df, column), rels)
    f = f.withWatermark(column, late) if late else f
    return f.groupBy("rule", key, F.session_window(column, gap).alias("w")).agg(F.count_if("ok").alias("hits"), F.count("*").alias("n_rows")).select("rule", key, F.col("w.start").alias("session_start"), "hits", "n_rows")


def alarms(windows: DataFrame, tau: float) -> DataFrame:
    return windows.where(F.col("hits") < F.col("n_rows") * tau)


def replay(spark, path: str, schema: T.StructType, files_per_trigger: int = 1) -> DataFrame:
    """A folder of Parquet files as a stream."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def run_to_table(stream: DataFrame, checkpoint: str, out: str, mode: str = "append") -> None:
    """Work off what is there and stop; a restart goes on from the checkpoint."""
    stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).format("parquet").option("path", out).trigger(availableNow=True).start().awaitTermination()


def on_alarm(windows: DataFrame, tau: float, act, checkpoint: str):
    """Call ``act(frame, batch)`` with each micro-batch's alarms."""
    return windows.writeStream.outputMode("update").option("checkpointLocation", checkpoint).foreachBatch(lambda df, i: act(alarms(df, tau), i)).trigger(availableNow=True).start()


def drift_counters(stream: DataFrame, key: str = "rule") -> DataFrame:
    """(rule, n_rows, violations): running counters kept as state, enough for chi-squared against a reference."""
    def update(k, frames: Iterator[pd.DataFrame], state):
        n, bad = state.get if state.exists else (0, 0)
        for f in frames:
            n, bad = n + len(f), bad + int((~f["ok"]).sum())
        state.update((n, bad))
        yield pd.DataFrame({"rule": [k[0]], "n_rows": [n], "violations": [bad]})

    return stream.groupBy(key).applyInPandasWithState(update, "rule string, n_rows long, violations long", "n_rows long, violations long", "update", "NoTimeout")

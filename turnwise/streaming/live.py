"""Live harness: dialogue acts as a stream, folded per run with watermarks, and a keyed state machine of layers and drift."""

from __future__ import annotations

import sys
from collections.abc import Iterator

import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import StructType

cloudpickle.register_pickle_by_value(sys.modules[__name__])

GAP = "12 hours"
#: Acts of the event types of a log.
ACTS = {"view": "ASK", "click": "SQL", "signup": "DRIFT", "error": "BROKEN", "purchase": "END"}


def acts(events: DataFrame, zone: str = "UTC") -> DataFrame:
    """run_id, ts (with a zone, as watermarks need), act, props."""
    kind = F.lit(None).cast("string")
    for name, act in ACTS.items():
        kind = F.when(F.col("event_type") == name, act).otherwise(kind)
    return events.select(
        F.col("user_id").alias("run_id"), F.to_utc_timestamp(F.col("ts").cast("timestamp"), F.lit(zone)).alias("ts"), kind.alias("act"), F.from_json("props", "k int")["k"].alias("k"), "event_id"
    )


def session_runs(turns: DataFrame, gap: str = GAP, watermark: str | None = None) -> DataFrame:
    """Sessions of acts per run; on a stream, with a watermark, closed sessions only."""
    t = turns.withWatermark("ts", watermark) if watermark else turns
    out = t.groupBy("run_id", F.session_window("ts", gap).alias("w")).agg(
        F.count("*").alias("n_turns"), F.bool_or(F.col("act") == "DRIFT").alias("has_drift"), F.bool_or(F.col("act") == "SQL").alias("has_sql"), F.bool_or(F.col("act") == "ASK").alias("asked")
    )
    return out.select("run_id", F.col("w.start").alias("session_start"), "n_turns", "has_drift", "has_sql", "asked")


def live_metrics(turns: DataFrame, width: str = "1 day", slide: str | None = None, watermark: str | None = None) -> DataFrame:
    """Ask rate of acts by tumbling or sliding window."""
    t = turns.withWatermark("ts", watermark) if watermark else turns
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return t.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.count_if(F.col("act") == "ASK").alias("asks")).select(F.col("w.start").alias("window_start"), "n", "asks")


def deduplicated(turns: DataFrame, watermark: str = "1 hour") -> DataFrame:
    return turns.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])


def with_samples(turns: DataFrame, samples: DataFrame) -> DataFrame:
    """Stream-static join with the runs' samples."""
    return turns.join(samples, "run_id", "left")


RUN_STATE = "asks int, n_sql int, drifts int, broken int, ended boolean"
RUN_OUTPUT = "run_id long, asks int, n_sql int, drifts int, broken int, ended boolean"


class RunMachine(StatefulProcessor):
    """Counters of each open run; a drift counts only after the first SQL, acts after the end are ignored."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("run", RUN_STATE, ttlDurationMs=7 * 24 * 3600 * 1000)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timers) -> Iterator[pd.DataFrame]:  # noqa: N802  the interface's name
        asks, n_sql, drifts, broken, ended = self.state.get() if self.state.exists() else (0, 0, 0, 0, False)
        for pdf in rows:
            for act in pdf.sort_values(["ts", "event_id"])["act"]:
                if ended:
                    break
                asks += act == "ASK"
                n_sql += act == "SQL"
                drifts += act == "DRIFT" and n_sql > 0
                broken += act == "BROKEN"
                ended = act == "END"
        state = (int(asks), int(n_sql), int(drifts), int(broken), bool(ended))
        self.state.update(state)
        yield pd.DataFrame([(int(key[0]), *state)], columns=["run_id", "asks", "n_sql", "drifts", "broken", "ended"])

    def close(self) -> None:
        pass


def live_runs(turns: DataFrame) -> DataFrame:
    """Latest counters of each run after each batch (update mode); needs the RocksDB state store."""
    return turns.groupBy("run_id").transformWithStateInPandas(statefulProcessor=RunMachine(), outputStructType=StructType.fromDDL(RUN_OUTPUT), outputMode="Update", timeMode="ProcessingTime")


def upsert(path: str, key: str = "run_id"):
    """A foreachBatch sink that keeps the newest row of each key, one folder per batch, so that a repeated batch overwrites itself."""

    def write(batch: DataFrame, batch_id: int) -> None:
        batch.dropDuplicates([key]).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return write


def latest(stored: DataFrame, key: str = "run_id") -> DataFrame:
    cols: list[Column] = [F.max_by(c, "batch").alias(c) for c in stored.columns if c not in (key, "batch")]
    return stored.groupBy(key).agg(*cols)

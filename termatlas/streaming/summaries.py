"""Summaries kept by Structured Streaming, and windowed counts of arrivals."""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from termatlas.operators.counters import SUMMARY
from termatlas.operators.rings import RingState, edges
from termatlas.sources.sinks import idempotent


def _freeze(state: RingState) -> str:
    used = len(state.slot)
    return json.dumps({"total": state.total, "replaced": state.replaced, "cell": state.cell[:used].tolist(), "f": state.f[:used].tolist(), "err": state.err[:used].tolist(), "born": state.born[:used].tolist(), "rings": state.rings[:used].tolist()})


def _thaw(kept: str, state: RingState) -> RingState:
    x = json.loads(kept)
    state.total, state.replaced = x["total"], x["replaced"]
    for k, cell in enumerate(x["cell"]):
        state._put(k, cell, state.sphere.place(cell), x["f"][k], x["err"][k], x["born"][k], np.array(x["rings"][k]))
    return state


class Keeper(StatefulProcessor):
    """A term's ring summary as one state value: read once a batch and term, updated in arrival order, written once."""

    def __init__(self, capacity: int, radii: list[float], policy: str, options: dict, ttl_ms: int | None):
        self.make = lambda: RingState(capacity, radii, policy, **options)
        self.ttl_ms = ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.kept = handle.getValueState("summary", "kept string", ttlDurationMs=self.ttl_ms)

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        frame = pd.concat(list(rows), ignore_index=True).sort_values(["ts", "seq", "msg_id", "cell"], kind="stable")
        state = _thaw(self.kept.get()[0], self.make()) if self.kept.exists() else self.make()
        state.observe_all(frame.cell.to_numpy(), np.ones(len(frame), np.int64), frame.seq.to_numpy())
        self.kept.update((_freeze(state),))
        yield pd.DataFrame([state.row(key[0])])

    def close(self) -> None:
        pass


def prepared(occ: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """A stream of arrivals with a watermark, without repeated messages and without places off the map.

    Rows later than the watermark are dropped by the deduplication.
    """
    rows = occ.where(F.col("term").isNotNull() & F.col("cell").isNotNull())
    return rows.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["msg_id", "term"])


def summarize(occ: DataFrame, capacity: int = 50, radii: list[float] | None = None, policy: str = "transfer", watermark: str = "1 hour", ttl_ms: int | None = None, **options) -> DataFrame:
    """A streaming DataFrame of the changed SUMMARY rows of each batch. The state store must be RocksDB."""
    radii = radii or edges()
    rows = prepared(occ, watermark).select("term", "cell", "ts", "seq", "msg_id")
    return rows.groupBy("term").transformWithStateInPandas(statefulProcessor=Keeper(capacity, radii, policy, options, ttl_ms), outputStructType=SUMMARY, outputMode="Update", timeMode="ProcessingTime" if ttl_ms else "None")


def start(occ: DataFrame, sink: str, checkpoint: str, available_now: bool = True, **options) -> StreamingQuery:
    """Keep summaries under sink, a folder a batch (sinks.latest reads them); a restart goes on from the checkpoint."""
    writer = summarize(occ, **options).writeStream.outputMode("update").option("checkpointLocation", checkpoint).foreachBatch(idempotent(sink))
    return (writer.trigger(availableNow=True) if available_now else writer).start()


def tumbling_counts(occ: DataFrame, size: str = "1 day") -> DataFrame:
    """window_start, term, cell, n; for batches and streams."""
    return occ.groupBy(F.window("ts", size)["start"].alias("window_start"), "term", "cell").agg(F.count("*").alias("n"))


def sliding_counts(occ: DataFrame, size: str = "7 days", slide: str = "1 day") -> DataFrame:
    return occ.groupBy(F.window("ts", size, slide)["start"].alias("window_start"), "term").agg(F.count("*").alias("n"))


def session_bursts(occ: DataFrame, gap: str = "10 minutes") -> DataFrame:
    """term, started, ended, n: arrivals of a term with no gap of this length between them."""
    return occ.groupBy("term", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("term", F.col("w.start").alias("started"), F.col("w.end").alias("ended"), "n")


def co_occurrence(left: DataFrame, right: DataFrame, hours: int = 1) -> DataFrame:
    """Pairs of arrivals of two streams (or batches) at one cell within some hours; both need watermarks as streams."""
    # arrivals meet by cell and slice of time, each of `hours`: those of a pair are in the same slice or in neighbouring ones
    part = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / F.lit(hours * 3_600_000_000))
    a = left.withColumn("slice", part).alias("a")
    b = right.withColumn("slice", F.explode(F.array(part, part - 1))).alias("b")
    near = (F.col("a.cell") == F.col("b.cell")) & (F.col("a.slice") == F.col("b.slice")) & (F.col("b.ts") >= F.col("a.ts")) & (F.col("b.ts") <= F.col("a.ts") + F.expr(f"interval {hours} hours"))
    return a.join(b, near).select(F.col("a.term").alias("a"), F.col("b.term").alias("b"), F.col("a.cell").alias("cell"), F.col("a.msg_id").alias("msg_a"), F.col("b.msg_id").alias("msg_b"))

"""Streaming assimilation of the event stream: windows, sessions, joins, a global filter per batch, filters per key in state.

Event time is ``events.ts``; an assimilation cycle is a tumbling hour.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from particle_engine.functions.rng import py_normal4
from particle_engine.operators.observe import CELLS, EPOCH, cell_of, cycle_of, grid
from particle_engine.plans.filter import Spec, run_cycle
from particle_engine.sources.store import StateStore
from particle_engine.sources.tables import SCHEMAS


def events_stream(spark: SparkSession, folder: str, files_per_batch: int = 1, pattern: str = "*.parquet") -> DataFrame:
    """File stream of event files with the declared schema."""
    return spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files_per_batch).option("pathGlobFilter", pattern).parquet(folder)


def hourly_levels(stream: DataFrame, lateness: str = "2 hours") -> DataFrame:
    """(cycle_start, n, mean_value) per tumbling hour; rows later than the watermark are dropped and counted by Spark."""
    g = stream.withWatermark("ts", lateness).groupBy(F.window("ts", "1 hour")).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("value"), 6).alias("mean_value"))
    return g.select(F.col("window.start").alias("cycle_start"), "n", "mean_value")


def smoothed_levels(stream: DataFrame, lateness: str = "2 hours") -> DataFrame:
    """(cycle_start, n, mean_value) per sliding window of 3 hours each hour."""
    g = stream.withWatermark("ts", lateness).groupBy(F.window("ts", "3 hours", "1 hour")).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("value"), 6).alias("mean_value"))
    return g.select(F.col("window.start").alias("cycle_start"), "n", "mean_value")


def bursts(stream: DataFrame, gap: str = "30 minutes", lateness: str = "2 hours") -> DataFrame:
    """(user_id, start, n) per activity session."""
    g = stream.withWatermark("ts", lateness).groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n"))
    return g.select("user_id", F.col("session_window.start").alias("start"), "n")


def once_per_event(stream: DataFrame, lateness: str = "2 hours") -> DataFrame:
    """Events without repeats of an id within the watermark."""
    return stream.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["event_id"])


def with_grid(stream: DataFrame) -> DataFrame:
    """Stream-static join: each event with its cell."""
    cells = grid(stream.sparkSession).withColumn("group_no", F.floor(F.col("cell_id") / 5).cast("int"))
    return stream.withColumn("cell_id", cell_of(F.col("user_id"), F.col("event_type"))).join(F.broadcast(cells), "cell_id")


def with_forcing(stream: DataFrame, force: DataFrame, within: str = "3 hours", lateness: str = "2 hours") -> DataFrame:
    """Stream-stream interval join: observations with boundary values of the last hours."""
    left = stream.withWatermark("ts", lateness).alias("o")
    right = force.withWatermark("ts", lateness).alias("f")
    return left.join(right, F.expr(f"o.event_type = f.event_type and f.ts <= o.ts and f.ts > o.ts - interval {within}")).select("o.event_id", F.col("f.event_id").alias("forcing_id"))


def global_filter(stream: DataFrame, initial: DataFrame, spec: Spec, store: StateStore, run_id: str, checkpoint: str) -> StreamingQuery:
    """The distributed filter per micro-batch: each whole hour of a batch is one cycle.

    Idempotent by the store's log: a repeated batch finds its cycles committed and skips
    them, and states are committed before weights.
    """
    from particle_engine.plans.filter import restore

    def each(batch: DataFrame, batch_id: int) -> None:
        seen = batch.groupBy(cycle_of(F.col("ts")).alias("cycle"), cell_of(F.col("user_id"), F.col("event_type")).alias("cell_id")).agg(F.count(F.lit(1)).alias("n"))
        seen = seen.persist()
        try:
            for cycle in sorted(r[0] for r in seen.select("cycle").distinct().collect()):  # the hours of one batch
                done = store.resume_cycle(run_id)
                if done is not None and cycle <= done:
                    continue
                states, carried = (initial, None) if done is None else restore(store, run_id, done, spec)
                mask = grid(batch.sparkSession, CELLS).join(F.broadcast(seen.where(F.col("cycle") == cycle).select("cell_id", "n")), "cell_id", "left").select("cell_id", F.col("n").isNotNull().alias("mask"))
                run_cycle(states, mask, cycle, spec, store, run_id, carried)
        finally:
            seen.unpersist()

    return stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


KEYED = "event_type string, cycle int, mean double, ess double, n long"


def keyed_filters(stream: DataFrame, particles: int = 64, seed: int = 42, noise: float = 4.0, spread: float = 49.0, lateness: str = "2 hours") -> DataFrame:
    """A small scalar filter per event type, its ensemble kept in the state store; a cycle runs once the watermark has passed its hour.

    State of a key: its ensemble and count and sum of each hour still open (a few
    hours, by the watermark).  An event-time timer closes hours without new events.
    """
    rows = stream.withWatermark("ts", lateness).select("event_type", "ts", cycle_of(F.col("ts")).alias("cycle"), "value")
    epoch = int(pd.Timestamp(EPOCH).timestamp() * 1000)

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.exists:
            kept = json.loads(state.get[0])
        else:
            kept = {"x": [50.0 + 20.0 * py_normal4(seed, 0, p, 0) for p in range(particles)], "open": {}}
        if not state.hasTimedOut:
            for pdf in batches:
                for cycle, part in pdf.groupby("cycle")["value"]:
                    n, total = kept["open"].get(str(cycle), (0, 0.0))
                    kept["open"][str(cycle)] = (n + len(part), total + float(part.sum()))
        mark = state.getCurrentWatermarkMs()
        ends = lambda c: epoch + (c + 1) * 3_600_000
        x, out = np.array(kept["x"]), []
        for cycle in sorted(int(c) for c in kept["open"] if ends(int(c)) <= mark):
            n, total = kept["open"].pop(str(cycle))
            x = x + noise * np.array([py_normal4(seed, cycle + 1, p, 0) for p in range(particles)])
            w = np.exp(-0.5 * ((total / n - x) / spread) ** 2 * n)
            w = w / w.sum()
            out.append((key[0], cycle, float((w * x).sum()), float(1 / (w * w).sum()), n))
            edges = (np.arange(particles) + 0.5) / particles
            x = x[np.searchsorted(np.cumsum(w), edges).clip(0, particles - 1)]
        kept["x"] = x.tolist()
        state.update((json.dumps(kept),))
        if kept["open"]:
            state.setTimeoutTimestamp(max(mark + 1, ends(min(map(int, kept["open"])))))
        yield pd.DataFrame(out, columns=["event_type", "cycle", "mean", "ess", "n"])

    return rows.groupBy("event_type").applyInPandasWithState(update, KEYED, "ensemble string", "append", GroupStateTimeout.EventTimeTimeout)


def drain_to_table(df: DataFrame, path: str, checkpoint: str, mode: str = "append") -> None:
    """Run a streaming plan over what is available now into Parquet (append) and wait."""
    df.writeStream.format("parquet").outputMode(mode).option("path", path).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def stream_hourly(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stream's hourly levels, run to the end over the given table and read back.

    The last hours stay open under the watermark, so the stream's answer is joined to hours that are closed.
    """
    import uuid

    from particle_engine.sources.store import shared_root

    base = f"{shared_root(spark)}/stream-{uuid.uuid4().hex}"
    # the folder holds all tables; the glob takes the events file only
    stream = events_stream(spark, sf_dir, pattern="events*.parquet")
    drain_to_table(hourly_levels(stream), f"{base}/out", f"{base}/ckpt")
    return spark.read.parquet(f"{base}/out")

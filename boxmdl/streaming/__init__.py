"""Structured Streaming: scoring events with mined patterns, online code lengths, windowed cell counts."""

from __future__ import annotations

import math
from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.codes import EPS
from ..operators.grid import Grid
from ..operators.miner import MineResult

STATE = "pattern_ids array<long>, uses array<long>"


def score(events: DataFrame, result: MineResult) -> DataFrame:
    """Events (stream or batch) with ``pid``; stateless, a join with the static cells; null outside every cell.

    Values outside the frozen grid fall into the outermost intervals.
    """
    return result.assign(events)


def _bits_of(n_patterns: int, eps: float):
    def run(key, frames, state: GroupState):
        ids, uses = (list(x) for x in state.get) if state.exists else ([], [])
        seen = dict(zip(ids, uses, strict=True))
        total = sum(uses)
        for frame in frames:
            frame = frame.sort_values(["ts", "event_id"], kind="stable")
            bits = []
            for pid in frame["pid"].tolist():
                pid = -1 if pid is None or pid != pid else int(pid)
                before = seen.get(pid, 0)
                bits.append(-math.log2((before + eps) / (total + eps * n_patterns)))
                seen[pid] = before + 1
                total += 1
            yield pd.DataFrame({"stream_key": [key[0]] * len(frame), "event_id": frame["event_id"], "ts": frame["ts"], "pid": frame["pid"], "bits": bits})
        state.update((list(seen), list(seen.values())))

    return run


def online_bits(scored: DataFrame, key: str, n_patterns: int, eps: float = EPS) -> DataFrame:
    """Bits of every event under the plug-in code of its key's own stream, from the uses kept as state.

    Needs ``event_id, ts, pid``.  Rows of one trigger are taken in order of
    time; an event without a pattern counts as a pattern of its own (-1).
    """
    rows = scored.select(F.col(key).cast("string").alias("stream_key"), "event_id", "ts", F.col("pid").cast("double").alias("pid"))
    kind = dict(scored.dtypes)
    schema = f"stream_key string, event_id {kind['event_id']}, ts {kind['ts']}, pid double, bits double"
    return rows.groupBy("stream_key").applyInPandasWithState(_bits_of(n_patterns, eps), schema, STATE, "append", GroupStateTimeout.NoTimeout)


def online_bits_batch(scored: DataFrame, key: str, n_patterns: int, eps: float = EPS) -> DataFrame:
    """The batch twin of `online_bits`, with windows."""
    from pyspark.sql import Window

    pid = F.coalesce(F.col("pid").cast("long"), F.lit(-1))
    rows = scored.select(F.col(key).cast("string").alias("stream_key"), "event_id", "ts", pid.alias("pid"))
    own = Window.partitionBy("stream_key", "pid").orderBy("ts", "event_id")
    every = Window.partitionBy("stream_key").orderBy("ts", "event_id")
    step = -F.log2((F.row_number().over(own) - 1 + F.lit(eps)) / (F.row_number().over(every) - 1 + F.lit(eps * n_patterns)))
    return rows.withColumn("bits", step)


def window_cells(events: DataFrame, grid: Grid, width: str = "1 day", slide: str | None = None, late: str = "1 hour", time: str = "ts") -> DataFrame:
    """Cell counts of tumbling (or sliding) windows of event time; rows later than `late` are dropped by a stream."""
    placed = events.withWatermark(time, late).select(F.col(time), *grid.indices())
    names = [f"b_{i}" for i in range(len(grid.axes))]
    span = F.window(time, width, slide) if slide else F.window(time, width)
    return placed.groupBy(span.alias("w"), *names).agg(F.count(F.lit(1)).alias("usage")).select(F.col("w.start").alias("start"), *names, "usage")


def session_cells(events: DataFrame, grid: Grid, gap: str = "30 minutes", key: str = "user_id", late: str = "1 hour", time: str = "ts") -> DataFrame:
    """Cell counts of a key's sessions."""
    placed = events.withWatermark(time, late).select(F.col(time), F.col(key), *grid.indices())
    names = [f"b_{i}" for i in range(len(grid.axes))]
    return placed.groupBy(F.session_window(time, gap).alias("w"), F.col(key), *names).agg(F.count(F.lit(1)).alias("usage")).select(F.col("w.start").alias("start"), key, *names, "usage")


def distinct_events(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event once, as far back as the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def drift(bits: DataFrame, width: str = "1 day") -> DataFrame:
    """Mean bits of an event by window, to hold against the batch value."""
    return bits.groupBy(F.window("ts", width).alias("w")).agg(F.count(F.lit(1)).alias("events"), F.avg("bits").alias("mean_bits")).select(F.col("w.start").alias("start"), "events", "mean_bits")


def remine(stream: DataFrame, mine: Callable[[DataFrame], MineResult], sink: Callable[[int, MineResult], None], checkpoint: str):
    """Mine every micro-batch on its own and hand each result to `sink`."""

    def each(batch: DataFrame, number: int) -> None:
        if not batch.isEmpty():
            sink(number, mine(batch))

    return stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


__all__ = ["distinct_events", "drift", "online_bits", "online_bits_batch", "remine", "score", "session_cells", "window_cells"]

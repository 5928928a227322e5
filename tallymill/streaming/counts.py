"""Counts over streams: windowed sketch cells, counter states, snapshots as of an event."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from tallymill.functions.counters import thresholds
from tallymill.functions.hashing import hash_np
from tallymill.functions.keyed import uniform_py
from tallymill.operators.cms import addresses
from tallymill.params import SketchParams


def windowed_cells(events: DataFrame, key: str, group: str, p: SketchParams, window: Column) -> DataFrame:
    """Exact cells for each window and group: sketches are sums, so this is a plain streaming aggregate."""
    at = events.select(window.alias("win"), group, F.explode(addresses(key, p)).alias("at"))
    cells = at.groupBy("win", group, F.col("at.i").alias("i"), F.col("at.col").alias("col")).agg(F.count("*").alias("cell"))
    return cells.select(F.col("win.start").alias("start"), F.col("win.end").alias("end"), group, "i", "col", "cell")


def tumbling(events: DataFrame, key: str, group: str, p: SketchParams, size: str = "1 day", time: str = "ts") -> DataFrame:
    return windowed_cells(events, key, group, p, F.window(time, size))


def sliding(events: DataFrame, key: str, group: str, p: SketchParams, size: str = "1 day", every: str = "6 hours", time: str = "ts") -> DataFrame:
    return windowed_cells(events, key, group, p, F.window(time, size, every))


def sessions(events: DataFrame, user: str, gap: str = "30 minutes", time: str = "ts") -> DataFrame:
    """(user, start, end, n) of sessions."""
    out = events.groupBy(F.session_window(time, gap).alias("win"), user).agg(F.count("*").alias("n"))
    return out.select(user, F.col("win.start").alias("start"), F.col("win.end").alias("end"), "n")


def once(events: DataFrame, key: str, time: str = "ts", late: str = "1 hour") -> DataFrame:
    """Each event once, from a source that may repeat it within the watermark."""
    return events.withWatermark(time, late).dropDuplicatesWithinWatermark([key])


def collected(stream: DataFrame, name: str, mode: str, checkpoint: str) -> DataFrame:
    """Runs a stream over all that is there into a table in memory; for results of bounded size."""
    spark = stream.sparkSession
    run = stream.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    if mode == "complete":
        run.start().awaitTermination()
    else:
        run.start().awaitTermination()
    return spark.table(name)


def stored(stream: DataFrame, path: str, checkpoint: str) -> DataFrame:
    """collected() in complete mode for results of any size: a batch's table is written to path by the
    executors, groups are kept in their stores on disk, and the last table is read."""
    spark, done = stream.sparkSession, []

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{number}")
        done.append(number)

    before = spark.conf.get(_PROVIDER, None)
    spark.conf.set(_PROVIDER, ROCKSDB)
    try:
        stream.writeStream.outputMode("complete").foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    finally:
        if before is None:
            spark.conf.unset(_PROVIDER)
        else:
            spark.conf.set(_PROVIDER, before)
    return spark.read.schema(stream.schema).parquet(f"{path}/{done[-1]}") if done else spark.createDataFrame([], stream.schema)


def late_rows(query) -> int:
    """Rows that a finished or running query dropped behind its watermark."""
    return sum(int(o.get("numRowsDroppedByWatermark", 0)) for progress in query.recentProgress for o in progress["stateOperators"])


def asof(events: DataFrame, snapshots: DataFrame, time: str = "ts", snap: str = "snap_ts") -> DataFrame:
    """Every event with the latest snapshot at or before it. Both sides are dealt by day, and the
    day's last snapshot is carried over, so no event meets more than a day of snapshots."""
    day = F.to_date(snap)
    last = snapshots.groupBy(day.alias("day")).agg(F.max(snap).alias("last"))
    days = events.select(F.to_date(time).alias("day")).distinct()
    before = days.join(last.withColumnRenamed("day", "d"), F.col("d") < F.col("day"), "left").groupBy("day").agg(F.max("last").alias("carried"))
    todays = snapshots.groupBy(day.alias("day")).agg(F.array_sort(F.collect_list(snap)).alias("snaps"))
    every = events.withColumn("day", F.to_date(time)).join(before, "day", "left").join(todays, "day", "left")
    here = F.array_max(F.filter("snaps", lambda s: s <= F.col(time)))
    return every.withColumn(snap, F.coalesce(here, F.col("carried"))).drop("day", "carried", "snaps")


class CounterStates(StatefulProcessor):
    """Keeps the packed counter states of a component as bytes and applies the increments of each
    micro-batch in order of event."""

    def __init__(self, p: SketchParams):
        self.p = p

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.cells = handle.getValueState("cells", "payload binary")
        self.thr = np.array(thresholds(self.p.base, min(self.p.cap, 255)))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        p = self.p
        held = self.cells.get() if self.cells.exists() else None
        m = np.frombuffer(held[0], np.uint8).reshape(p.l, p.w).copy() if held else np.zeros((p.l, p.w), np.uint8)
        batch = pd.concat(list(rows)).sort_values("event")
        at, row = np.stack([hash_np(batch["key"].to_numpy(), i, p) for i in range(p.l)], 1), np.arange(p.l)
        for cell, event in zip(at, batch["event"]):
            own = m[row, cell]
            u = np.array([uniform_py("ci", p.seed, event, i) for i in row]) if p.counter == "independent" else uniform_py("cc", p.seed, event)
            up = (u < self.thr[own]) & (own < 255)
            if p.rule == "conservative":
                up &= own == own.min()
            m[row, cell] = own + up
        self.cells.update((m.tobytes(),))
        yield pd.DataFrame({"k": [key[0]], "payload": [m.tobytes()], "increments": [len(batch)]})

    def close(self) -> None:
        pass


def counter_stream(events: DataFrame, p: SketchParams, component: str = "k") -> DataFrame:
    """(k, payload, increments) after every micro-batch of events(k, key, event)."""
    return events.groupBy(component).transformWithStateInPandas(CounterStates(p), outputStructType="k string, payload binary, increments long", outputMode="Update", timeMode="None")


_PROVIDER = "spark.sql.streaming.stateStore.providerClass"
ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"

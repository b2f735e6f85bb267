"""Joins and statistics over streams of objects."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import ArrayType, DoubleType, LongType, StructField, StructType, TimestampType

from ..functions.metrics import metric_of, padded
from ..operators.fits import NodeFit, chi_square_stat, confidence, make_cells
from ..operators.join import JoinPlan, mapped, region_lists


def timed(events: DataFrame, ts: str = "ts") -> DataFrame:
    """Event time as a timestamp with a zone, which watermarks need."""
    return events.withColumn(ts, F.col(ts).cast("timestamp"))


def windowed_counts(events: DataFrame, length: str, slide: str | None = None, late: str = "1 hour", key: str = "user_id", kind: str = "event_type") -> DataFrame:
    """Counts by key and kind in tumbling or sliding windows; rows later than the watermark are dropped."""
    x = timed(events).withWatermark("ts", late)
    return x.groupBy(F.window("ts", length, slide) if slide else F.window("ts", length), key, kind).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), key, kind, "n")


def sessions(events: DataFrame, gap: str, late: str = "1 hour", key: str = "user_id") -> DataFrame:
    x = timed(events).withWatermark("ts", late)
    return x.groupBy(F.session_window("ts", gap).alias("w"), key).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), key, "n", "total")


def deduplicated(events: DataFrame, keys: list[str], late: str = "1 hour") -> DataFrame:
    return timed(events).withWatermark("ts", late).dropDuplicatesWithinWatermark(keys)


def stream_static_join(stream: DataFrame, corpus: DataFrame, plan: JoinPlan) -> DataFrame:
    """Pairs of new objects and a routed corpus: the corpus (id, obj) is at home in one region, new ones go to all near regions.

    The split is frozen; its cells tile the space, so results stay exact however the data drift.
    """
    m, delta = plan.metric, plan.delta
    home = mapped(corpus, plan).select(F.col("home").alias("region"), F.col("id").alias("id_y"), F.col("obj").alias("obj_y"))
    new = mapped(stream, plan).select(F.explode(region_lists(plan, "whole")).alias("region"), F.col("id").alias("id_x"), F.col("obj").alias("obj_x"))
    both = new.join(home, "region").where(m.at_most(F.col("obj_x"), F.col("obj_y"), delta))
    return both.select("id_x", "id_y", m.distance(F.col("obj_x"), F.col("obj_y")).alias("distance"))


def stream_stream_join(left: DataFrame, right: DataFrame, metric, delta: float, within: str, late: str = "1 hour", on: str = "event_type") -> DataFrame:
    """Pairs of two streams (id, obj, ts, key) of one key, within a time and within a distance.

    Time is cut into slices of that length: a left row is in its own, a right one in the three around it, so rows
    meet those of their slice and not all that are kept of a key.
    """
    m, length = metric_of(metric), pd.Timedelta(within) // pd.Timedelta("1us")
    own = F.floor(F.unix_micros("ts") / F.lit(length))
    a = timed(left).withWatermark("ts", late).select(F.col("id").alias("id_x"), F.col("obj").alias("obj_x"), F.col("ts").alias("ts_x"), F.col(on).alias("key_x"), own.alias("slice_x"))
    b = timed(right).withWatermark("ts", late).select(F.col("id").alias("id_y"), F.col("obj").alias("obj_y"), F.col("ts").alias("ts_y"), F.col(on).alias("key_y"), F.explode(F.sequence(own - 1, own + 1)).alias("slice_y"))
    near = F.expr(f"key_x = key_y AND slice_x = slice_y AND ts_y BETWEEN ts_x - INTERVAL {within} AND ts_x + INTERVAL {within}")
    both = a.join(b, near).where(m.at_most(F.col("obj_x"), F.col("obj_y"), delta))
    return both.select("id_x", "id_y", m.distance(F.col("obj_x"), F.col("obj_y")).alias("distance"))


PAIR = StructType([StructField("id_x", LongType()), StructField("id_y", LongType()), StructField("distance", DoubleType())])


class RecentPairs(StatefulProcessor):
    """Pairs each new object of a key with the recent ones; objects are forgotten after a while by event time."""

    def __init__(self, metric: str, delta: float, keep_ms: int):
        self.metric, self.delta, self.keep_ms = metric, delta, keep_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.recent = handle.getListState("recent", StructType([StructField("id", LongType()), StructField("obj", ArrayType(DoubleType())), StructField("ts", TimestampType())]))

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        block, known = metric_of(self.metric).block, list(self.recent.get()) if self.recent.exists() else []
        out = []
        for pdf in rows:
            for r in pdf.sort_values(["ts", "id"]).itertuples():
                for i, o, t in known:
                    d = float(block([list(r.obj)], [list(o)])[0, 0])
                    if d <= padded(self.delta) and abs((r.ts - pd.Timestamp(t)).total_seconds()) * 1000 <= self.keep_ms:
                        out.append((min(i, r.id), max(i, r.id), d))
                known.append((int(r.id), list(map(float, r.obj)), r.ts.to_pydatetime()))
        if known:
            newest = max(pd.Timestamp(t) for _, _, t in known)
            known = [(i, list(o), t) for i, o, t in known if (newest - pd.Timestamp(t)).total_seconds() * 1000 <= self.keep_ms]
            self.recent.put(known)
        yield pd.DataFrame(out, columns=["id_x", "id_y", "distance"])

    def close(self) -> None:
        pass


def stateful_pairs(stream: DataFrame, key: str, metric: str, delta: float, keep_ms: int) -> DataFrame:
    """(id, obj, ts, key) -> pairs of objects of a key that came within ``keep_ms`` of each other."""
    x = timed(stream).withWatermark("ts", "1 hour")
    return x.groupBy(key).transformWithStateInPandas(RecentPairs(metric, delta, keep_ms), PAIR, "Append", "EventTime")


def drift_monitor(fit: NodeFit, dim: int, floor: float, alarms: list):
    """foreachBatch function: tests each batch's values against a frozen fit, and notes batches of low confidence."""
    f = fit.dims[dim]
    cuts = make_cells(f, 20)

    def check(batch: DataFrame, epoch: int) -> None:
        cell = sum((F.when(F.col("value") > F.lit(float(c)), 1).otherwise(0) for c in cuts), F.lit(0))
        import numpy as np

        seen = np.zeros(20)
        for r in batch.groupBy(cell.alias("cell")).count().collect():
            seen[r["cell"]] = r["count"]
        if seen.sum():
            stat, used = chi_square_stat(seen, np.full(20, 0.05))
            c = confidence(stat, used - 1)
            if c < floor:
                alarms.append((epoch, c))

    return check

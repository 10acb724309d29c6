"""Structured Streaming: windows, late rows, duplicates, clustering by batch, incremental cores, joins."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from cellcluster.cells import exact_cell
from cellcluster.cluster import cell_exact
from cellcluster.points import normalise
from cellcluster.spec import ClusterSpec


def timed(stream: DataFrame, ts: str = "ts") -> DataFrame:
    """Event time as a timestamp, which watermarks need."""
    return stream.withColumn(ts, F.col(ts).cast("timestamp"))


def with_lateness(stream: DataFrame, ts: str = "ts", delay: str = "1 hour") -> DataFrame:
    return timed(stream, ts).withWatermark(ts, delay)


def dedupe(stream: DataFrame, key: str) -> DataFrame:
    return stream.dropDuplicatesWithinWatermark([key])


def windowed_counts(events: DataFrame, length: str, slide: str | None = None, by: str = "event_type") -> DataFrame:
    """Count and sum by tumbling or sliding window; batch and stream alike."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    out = events.groupBy(w.alias("w"), by).agg(F.count(F.lit(1)).alias("n"), F.count("value").alias("n_values"))
    return out.select(F.col("w.start").alias("start"), by, "n", "n_values")


def session_counts(events: DataFrame, gap: str, by: str = "user_id") -> DataFrame:
    out = events.groupBy(F.session_window("ts", gap).alias("w"), by).agg(F.count(F.lit(1)).alias("n"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), by, "n")


def enrich(stream: DataFrame, dim: DataFrame, on: str) -> DataFrame:
    """Stream-static join; the static side is read again for each batch."""
    return stream.join(dim, on, "left")


def interval_stream_join(a: DataFrame, b: DataFrame, key: str, within: str = "30 minutes") -> DataFrame:
    """Two streams, joined where b follows a within a time; both need watermarks (a: ts, b: ts)."""
    x = a.select(F.col(key), F.col("ts").alias("ts_a"), F.col("event_id").alias("a"))
    y = b.select(F.col(key).alias("__key"), F.col("ts").alias("ts_b"), F.col("event_id").alias("b"))
    return x.join(y, F.expr(f"{key} = __key AND ts_b > ts_a AND ts_b <= ts_a + INTERVAL {within}")).drop("__key")


def stream_cluster(stream: DataFrame, spec: ClusterSpec, bounds: list[tuple[float, float]], sink: Callable[[DataFrame, int], None], checkpoint: str, trigger: dict | None = None):
    """Clusters each micro-batch of (point_id, f1, ...) with bounds fixed beforehand, so that coordinates mean the same in all batches."""
    def batch(df: DataFrame, number: int) -> None:
        sink(cell_exact(normalise(df, given=bounds), spec).membership, number)

    return stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


class _Promote(StatefulProcessor):
    """State of a block: its points, their counts and flags. Insertions only raise counts, so a core point stays one."""

    def __init__(self, eps: int, min_pts: int):
        self.eps, self.min_pts = eps, min_pts

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.points = handle.getMapState("points", "point_id bigint", "x1 bigint, x2 bigint, n bigint, home boolean")

    def handleInputRows(self, key, rows, timerValues):
        held = {k[0]: list(v) for k, v in self.points.iterator()}
        out = []
        for part in rows:
            for r in part.itertuples(index=False):
                if r.point_id in held:
                    continue
                n = 1
                for pid, v in held.items():
                    if (v[0] - r.x1) ** 2 + (v[1] - r.x2) ** 2 <= self.eps**2:
                        n += 1
                        v[2] += 1
                        if v[2] == self.min_pts and v[3]:
                            out.append((pid, v[2]))
                        self.points.updateValue((pid,), tuple(v))
                held[r.point_id] = [int(r.x1), int(r.x2), n, bool(r.home)]
                self.points.updateValue((int(r.point_id),), (int(r.x1), int(r.x2), n, bool(r.home)))
                if n >= self.min_pts and r.home:
                    out.append((int(r.point_id), n))
        yield pd.DataFrame(out, columns=["point_id", "n"]).astype("int64")

    def close(self) -> None:
        pass


def incremental_core(stream: DataFrame, spec: ClusterSpec, width: int) -> DataFrame:
    """Core points of the plane as they arise, insert-only: (point_id, n) once for each point, when its count reaches min_pts.

    Blocks of ``width`` along x1 keep the points of themselves and of eps around.
    """
    blocks = F.sequence(F.floor((F.col("x1") - spec.eps) / width), F.floor((F.col("x1") + spec.eps) / width))
    dealt = stream.withColumn("block", F.explode(blocks)).withColumn("home", F.floor(F.col("x1") / width) == F.col("block"))
    return dealt.groupBy("block").transformWithStateInPandas(_Promote(spec.eps, spec.min_pts), "point_id bigint, n bigint", "Append", "None")


def stream_cells(stream: DataFrame, eps: int) -> DataFrame:
    """Counts of cells of a stream of points in the plane, origin 0."""
    return stream.withColumns({f"k{j}": exact_cell(F.col(f"x{j}"), eps, 2) for j in (1, 2)}).groupBy("k1", "k2").agg(F.count(F.lit(1)).alias("n_pts"))


def expiring_cells(points: DataFrame, eps: int, horizon: str, slide: str, delay: str | None = None, ts: str = "ts") -> DataFrame:
    """Counts of the cells of the points that a sliding horizon holds, plane, origin 0; batch and stream alike.

    A point counts in every window that it lies in and expires with the last of
    them. On a stream, ``delay`` sets a watermark: the state of a window goes
    when the watermark passes its end, and rows later than that are left out.
    """
    rows = timed(points, ts) if delay is None else with_lateness(points, ts, delay)
    placed = rows.withColumns({f"k{j}": exact_cell(F.col(f"x{j}"), eps, 2) for j in (1, 2)})
    return placed.groupBy(F.window(ts, horizon, slide).alias("w"), "k1", "k2").agg(F.count(F.lit(1)).alias("n_pts")).select(F.col("w.start").alias("start"), "k1", "k2", "n_pts")


def late_rows(query) -> int:
    """Rows that the watermarks of a running or finished query left out, over its recent batches."""
    return sum(op.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for op in p["stateOperators"])

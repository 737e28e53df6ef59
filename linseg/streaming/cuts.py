"""Online detection: windowed moments, sessions, and a stateful two-piece test over the last points of each signal."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import columns as C

CUTS = "signal_id string, cut_us bigint, gain double, window_n int"
_STATE = "last_us bigint, us array<bigint>, x array<double>"


def with_event_time(df: DataFrame, ts: str, delay: str) -> DataFrame:
    """Zone-free times are cast first, for watermarks don't take them; rows later than the delay are dropped and show up in the query's progress."""
    return df.withColumn(ts, C.to_event_time(ts)).withWatermark(ts, delay)


def stream_moments(df: DataFrame, key: str, ts: str, values: list[str], window: str, slide: str | None = None) -> DataFrame:
    """Moments of each window (time in seconds from its start): signal_id, window_start, n, st, stt, sx.., stx.., sxx..; two adjacent ones give the half-split test exactly."""
    w = F.window(ts, window, slide) if slide else F.window(ts, window)
    base = df.select(F.col(key).cast("string").alias("signal_id"), ts, *values, w.alias("w"))
    t = (F.unix_micros(ts) - F.unix_micros("w.start")) / 1e6
    terms = C.sum_terms(len(values), t, "x")
    rows = base.withColumn("x", F.array(*[F.col(v).cast("double") for v in values])).withColumn("w", F.col("w"))
    return rows.groupBy("signal_id", "w").agg(*[F.sum(e).alias(n) for n, e in terms.items()]).select("signal_id", F.unix_micros("w.start").alias("window_us"), *terms)


def stream_sessions(df: DataFrame, key: str, ts: str, gap: str) -> DataFrame:
    """A session is a natural signal: signal_id, start and end in microseconds, points."""
    s = df.groupBy(F.col(key).cast("string").alias("signal_id"), F.session_window(ts, gap).alias("s")).agg(F.count("*").alias("n"))
    return s.select("signal_id", F.unix_micros("s.start").alias("start_us"), F.unix_micros("s.end").alias("end_us"), "n")


def window_cut(us: np.ndarray, x: np.ndarray, mode: str, gamma: int = 2) -> tuple[int | None, float]:
    """Cut of one full window and its gain relative to the one-line cost: in the middle, or the best two-piece model's."""
    from ..kernels.moments import Linear
    from ..kernels.splits import best_cut

    s = Linear((us - us[0]).astype(float), x)
    whole = s.one(0, s.n)
    if whole <= 0:
        return None, 0.0
    if mode == "half":
        at = s.n // 2
        gain = whole - s.one(0, at) - s.one(at, s.n)
    else:
        gain, at = best_cut(s, 0, s.n, gamma)
    return at, float(gain) / whole if at is not None else 0.0


def scan(us: np.ndarray, x: np.ndarray, window: int, mode: str, threshold: float) -> tuple[list[tuple[int, float, int]], int]:
    """Cuts of a sequence of points in time order, and where the unfinished window starts.

    A full window with enough gain emits its cut and the next window starts there; else it moves on by half.
    """
    out, lo = [], 0
    while len(us) - lo >= window:
        at, gain = window_cut(us[lo : lo + window], x[lo : lo + window], mode)
        if at is not None and gain >= threshold:
            out.append((int(us[lo + at]), gain, window))
            lo += at
        else:
            lo += window // 2
    return out, lo


def stream_cuts(df: DataFrame, key: str, ts: str, values: list[str], window: int = 40, mode: str = "refined", threshold: float = 0.5, delay: str = "10 minutes") -> DataFrame:
    """Cuts of each signal as they are certain: points wait until the watermark has passed them, so any arrival order gives the batch result.

    State of a signal: its waiting points and the unfinished window, of ``window`` points at most beyond those.
    """
    d = len(values)

    def step(key: tuple, frames: Iterable[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        got = [f for f in frames if len(f)]
        last, us, x = state.get if state.exists else (-(1 << 62), [], [])
        us, x = np.array(us, np.int64), np.array(x, float).reshape(-1, d)
        for f in got:
            us = np.concatenate([us, f["us"].to_numpy(np.int64)])
            x = np.concatenate([x, f[[f"v{i}" for i in range(d)]].to_numpy(float)])
        order = np.lexsort((*x.T[::-1], us))
        us, x = us[order], x[order]
        now = state.getCurrentWatermarkMs() * 1000
        ready = int(np.searchsorted(us, now, "left"))
        found, lo = scan(us[:ready], x[:ready], window, mode, threshold)
        us, x = us[lo:], x[lo:]
        state.update((int(last), us.tolist(), x.ravel().tolist()))
        if len(us) > ready - lo:
            state.setTimeoutTimestamp(int(us[-1] // 1000 + 1))
        if found:
            yield pd.DataFrame([(str(key[0]), *r) for r in found], columns=["signal_id", "cut_us", "gain", "window_n"])

    rows = with_event_time(df.select(F.col(key).cast("string").alias("signal_id"), F.col(ts).alias("at"), *[F.col(v).cast("double").alias(f"v{i}") for i, v in enumerate(values)]), "at", delay)
    rows = rows.withColumn("us", F.unix_micros("at"))
    return rows.groupBy("signal_id").applyInPandasWithState(step, CUTS, _STATE, "append", "EventTimeTimeout")


def batch_cuts(df: DataFrame, key: str, ts: str, values: list[str], window: int = 40, mode: str = "refined", threshold: float = 0.5) -> DataFrame:
    """What ``stream_cuts`` emits once every point is in."""
    d = len(values)

    def kernel(f: pd.DataFrame) -> pd.DataFrame:
        us, x = f["us"].to_numpy(np.int64), f[[f"v{i}" for i in range(d)]].to_numpy(float)
        order = np.lexsort((*x.T[::-1], us))
        found, _ = scan(us[order], x[order], window, mode, threshold)
        return pd.DataFrame([(str(f["signal_id"].iloc[0]), *r) for r in found], columns=["signal_id", "cut_us", "gain", "window_n"])

    rows = df.select(F.col(key).cast("string").alias("signal_id"), F.unix_micros(C.to_event_time(ts)).alias("us"), *[F.col(v).cast("double").alias(f"v{i}") for i, v in enumerate(values)])
    return rows.groupBy("signal_id").applyInPandas(kernel, CUTS)


def without_repeats(cuts: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Guards a sink against cuts that a restarted query emits again."""
    timed = cuts.withColumn("cut_at", F.timestamp_micros("cut_us")).withWatermark("cut_at", delay)
    return timed.dropDuplicatesWithinWatermark(["signal_id", "cut_us"])


def with_thresholds(points: DataFrame, thresholds: DataFrame) -> DataFrame:
    """Stream-static join with a table of one row a signal."""
    return points.join(thresholds, "signal_id", "left")


def resegment(batch: DataFrame, stored_cuts: DataFrame, **options) -> DataFrame:
    """For foreachBatch: refines from the cuts of the last run instead of anew."""
    from ..operators.segment import segment

    return segment(batch, 1, "refine_boundaries", init=stored_cuts, on_infeasible="clamp", **options)


def drain(stream: DataFrame, folder: str, mode: str = "append") -> DataFrame:
    """Runs a finite stream to its end into Parquet below ``folder`` (shared by driver and executors) and returns that.

    Appended rows go through the file sink, which commits each batch once; in complete mode a batch replaces the last.
    """
    out = f"{folder}/rows"
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/progress").trigger(availableNow=True)
    if mode == "append":
        q = writer.format("parquet").option("path", out).start()
    else:
        q = writer.foreachBatch(lambda df, i: df.write.mode("overwrite").parquet(out)).start()
    q.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(out)


def drain_closed(found: Callable[[DataFrame], DataFrame], source: DataFrame, ts: str, folder: str) -> DataFrame:
    """``drain`` of found(source), then of a closing row far in the future: its watermark passes every point, so none is held back.

    ``source`` is a file stream that gets no more rows.  The closing row has nulls but for its time.
    """
    spark, schema = source.sparkSession, source.schema
    last = f"{folder}/closing"
    spark.createDataFrame([], schema).write.mode("overwrite").parquet(last)
    rows = source.unionByName(spark.readStream.schema(schema).parquet(last))
    drain(found(rows), folder)
    end = F.lit("2200-01-01 00:00:00")  # later ones overflow pandas times
    spark.range(1).select(*[(end if f.name == ts else F.lit(None)).cast(f.dataType).alias(f.name) for f in schema]).write.mode("append").parquet(last)
    return drain(found(rows), folder)

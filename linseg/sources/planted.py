"""Signals with known cuts: piecewise lines and weak curves added to standardised table columns.

Every number is drawn from an md5 of (seed, signal, piece, dimension, purpose), so SQL can rebuild the rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.columns import unit_hash

#: Mean and spread that standardise the supplier rows' four columns (fixed, so that subsets agree).
SUPPLIER_SCALE = ((25.5, 14.4), (5_000_000.0, 2_880_000.0), (5.0, 3.2), (4.0, 2.6))


def truth(sizes: DataFrame, k_lo: int, k_hi: int | None = None, d: int = 1, seed: str = "p", amp: float = 1.0, curv: float = 0.0) -> DataFrame:
    """Pieces of each signal (sizes: signal_id, n): seg_no, start_pos, end_pos and, by dimension, level, slope and curve coefficients."""
    k_hi = k_lo if k_hi is None else k_hi
    s = F.col("signal_id")
    rows = sizes.withColumn("k", (F.lit(k_lo) + F.floor(unit_hash(seed, s, "k") * (k_hi - k_lo + 1))).cast("int"))

    def cut(j: Column) -> Column:
        inner = F.floor(F.col("n") * (j + 0.5 * (unit_hash(seed, s, j, "cut") - 0.5)) / F.col("k")).cast("bigint")
        return F.when(j == 0, F.lit(0).cast("bigint")).when(j == F.col("k"), F.col("n")).otherwise(inner)

    rows = rows.select("signal_id", "n", "k", F.explode(F.sequence(F.lit(0), F.col("k") - 1)).alias("seg_no"))
    j = F.col("seg_no")
    sign = F.when(j % 2 == 0, 1.0).otherwise(-1.0)
    draw = lambda r, what: unit_hash(seed, s, j, F.lit(r), what)
    return rows.select(
        "signal_id", "seg_no", cut(j).alias("start_pos"), cut(j + 1).alias("end_pos"), "n", "k",
        F.array(*[sign * amp * (0.5 + draw(r, "level")) for r in range(d)]).alias("level"), F.array(*[2 * amp * (draw(r, "slope") - 0.5) for r in range(d)]).alias("tilt"),
        F.array(*[F.array(*[curv * amp * (draw(r, f"deg{g}") - 0.5) for g in (2, 3, 4)]) for r in range(d)]).alias("curve"),
    )


def plant(sig: DataFrame, pieces: DataFrame, scale: tuple, nz: float = 1.0, noise: tuple = ("table",)) -> DataFrame:
    """The signal with the pieces' means added to its standardised values; noise may add a sinusoid ('trig') and impulses ('impulse')."""
    p = pieces.select(F.col("signal_id").alias("__sid"), "start_pos", "end_pos", F.col("n").alias("size"), "level", "tilt", "curve")
    rows = sig.join(p, (F.col("signal_id") == F.col("__sid")) & (F.col("pos") >= F.col("start_pos")) & (F.col("pos") < F.col("end_pos")))
    u = (F.col("pos") - F.col("start_pos")) / F.col("size")
    values = []
    for r, (mean, sd) in enumerate(scale):
        c = F.col("curve")[r]
        v = nz * ((F.col("x")[r] - mean) / sd) + F.col("level")[r] + F.col("tilt")[r] * u + c[0] * u * u + c[1] * u * u * u + c[2] * u * u * u * u
        if "trig" in noise:
            v = v + 0.5 * nz * F.sin(F.col("pos") * (2 * 3.141592653589793 / 7))
        if "impulse" in noise:
            h = unit_hash("impulse", F.col("signal_id"), F.col("pos"), F.lit(r))
            v = v + F.when(h < 0.005, 6 * nz).when(h < 0.01, -6 * nz).otherwise(0.0)
        values.append(v)
    return rows.select("signal_id", "pos", "t", F.array(*values).alias("x"))


class Planted:
    """``plant`` of one signal, on arrays: (places, values) -> values.  Pieces: its rows of ``truth``."""

    def __init__(self, pieces: list, scale: tuple, nz: float = 1.0):
        self.pieces = sorted((p.start_pos, p.end_pos, p.n, tuple(p.level), tuple(p.tilt), tuple(map(tuple, p.curve))) for p in pieces)
        self.scale, self.nz = scale, nz

    def __call__(self, pos: np.ndarray, x: np.ndarray) -> np.ndarray:
        out = np.empty(x.shape)
        for start, end, size, level, tilt, curve in self.pieces:
            i, j = np.searchsorted(pos, start), np.searchsorted(pos, end)
            u = (pos[i:j] - start) / size
            for r, (mean, sd) in enumerate(self.scale if i < j else ()):
                c = curve[r]
                out[i:j, r] = self.nz * ((x[i:j, r] - mean) / sd) + level[r] + tilt[r] * u + c[0] * u * u + c[1] * u * u * u + c[2] * u * u * u * u
        return out


def sizes(sig: DataFrame) -> DataFrame:
    return sig.groupBy("signal_id").agg(F.count("*").alias("n"))


def planted(sig: DataFrame, scale: tuple, k_lo: int, k_hi: int | None = None, seed: str = "p", amp: float = 1.0, nz: float = 1.0, curv: float = 0.0, noise: tuple = ("table",)) -> tuple[DataFrame, DataFrame]:
    """(signal with k, truth)."""
    t = truth(sizes(sig), k_lo, k_hi, len(scale), seed, amp, curv)
    x = plant(sig, t, scale, nz, noise).join(t.groupBy("signal_id").agg(F.max("k").alias("k")), "signal_id")
    return x, t.select("signal_id", "seg_no", "start_pos", "end_pos")


def _drawn(seed: str, i: int, n_range: tuple[int, int], k_range: tuple[int, int], d_range: tuple[int, int]) -> tuple[np.random.Generator, int, int, np.ndarray]:
    """Size, dimensions and cuts of signal i, and the generator that its values come from."""
    rng = np.random.default_rng(int(hashlib.md5(f"{seed}|{i}".encode()).hexdigest()[:16], 16))
    n = int(round(n_range[0] * (n_range[1] / n_range[0]) ** rng.uniform()))
    k = int(rng.integers(k_range[0], k_range[1] + 1))
    least = max(2, n // (4 * k))
    inner = np.sort(rng.integers(0, n - k * least + 1, k - 1)) + least * np.arange(1, k)
    return rng, n, int(rng.integers(d_range[0], d_range[1] + 1)), np.concatenate([[0], inner, [n]])


def drawn_signals(spark: SparkSession, count: int, n_range: tuple[int, int], k_range: tuple[int, int] = (2, 2), d_range: tuple[int, int] = (2, 16), seed: str = "d", curve: float = 2.0, loudest: float = 0.4) -> tuple[DataFrame, DataFrame]:
    """(signals with k, truth): sizes even on a logarithmic scale, pieces of a quarter of the mean size at least.

    Pieces are lines with weak curves.  Gaussian noise, a sinusoid and impulses come on top, each at a level drawn for the signal.
    One task makes a signal, so signals are of one task's size.
    """

    def points(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for i in (i for b in batches for i in b.column(0).to_pylist()):
            rng, n, d, cuts = _drawn(seed, i, n_range, k_range, d_range)
            gauss, wave, knock = rng.uniform(0.05, loudest), rng.uniform(0, loudest / 2), rng.uniform(0, 4 * loudest)
            period, phase = rng.uniform(5, 50), rng.uniform(0, 2 * np.pi)
            x = np.empty((n, d))
            for a, b in zip(cuts, cuts[1:]):
                u = np.linspace(0, 1, b - a, endpoint=False)[:, None]
                level, tilt, bend = (rng.normal(size=d) for _ in range(3))
                x[a:b] = level + tilt * u + curve * bend * u * (1 - u)
            x += gauss * rng.normal(size=(n, d)) + wave * np.sin(2 * np.pi * np.arange(n) / period + phase)[:, None]
            x += np.where(rng.uniform(size=(n, d)) < 0.005, knock * rng.choice([-1.0, 1.0], size=(n, d)), 0.0)
            for lo in range(0, n, 20_000):
                part = np.arange(lo, min(lo + 20_000, n))
                values = pa.ListArray.from_arrays(pa.array(np.arange(len(part) + 1, dtype=np.int32) * d), pa.array(x[part].ravel()))
                yield pa.RecordBatch.from_arrays([pa.array([str(i)] * len(part)), pa.array(part), pa.array(part.astype(float)), values, pa.array(np.full(len(part), len(cuts) - 1, np.int32))], names=["signal_id", "pos", "t", "x", "k"])

    def pieces(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for i in (i for b in batches for i in b.column(0).to_pylist()):
            cuts = _drawn(seed, i, n_range, k_range, d_range)[3]
            k = len(cuts) - 1
            yield pa.RecordBatch.from_arrays([pa.array([str(i)] * k), pa.array(np.arange(k, dtype=np.int32)), pa.array(cuts[:-1].astype(np.int64)), pa.array(cuts[1:].astype(np.int64))], names=["signal_id", "seg_no", "start_pos", "end_pos"])

    ids = spark.range(count).repartition(min(count, 64), "id")
    return ids.mapInArrow(points, "signal_id string, pos bigint, t double, x array<double>, k int"), ids.mapInArrow(pieces, "signal_id string, seg_no int, start_pos bigint, end_pos bigint")

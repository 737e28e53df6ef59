"""Which signals are small enough for one task, and which are cut into blocks."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MOST_POINTS, MOST_BYTES = 2_000_000, 512 << 20


def signal_profile(sig: DataFrame) -> DataFrame:
    """signal_id, n, d, bytes of prefix moments: one aggregate with partial sums."""
    p = sig.groupBy("signal_id").agg(F.count("*").alias("n"), F.max(F.size("x")).alias("d"))
    return p.withColumn("bytes", F.col("n") * (2 * F.col("d") + 4) * 8)


def choose_regime(sig: DataFrame, most_points: int = MOST_POINTS, most_bytes: int = MOST_BYTES) -> tuple[DataFrame, DataFrame]:
    """(fleet rows, profile of giant signals).  The profile of giants is small: each stands for gigabytes."""
    p = signal_profile(sig)
    giant = p.where((F.col("n") > most_points) | (F.col("bytes") > most_bytes))
    return sig.join(giant.select("signal_id"), "signal_id", "left_anti"), giant


def exclusive_offsets(totals: DataFrame, key: str = "block", value: str = "n") -> list[tuple[int, int]]:
    """(block, rows before it) of block totals; a row a block reaches the driver."""
    out, before = [], 0
    for r in totals.orderBy(key).collect():
        out.append((r[key], before))
        before += r[value]
    return out

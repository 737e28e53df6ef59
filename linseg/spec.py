"""What a signal is: keys, order, time and features."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The canonical frame every method takes.
SIGNAL = "signal_id string, pos bigint, t double, x array<double>"
TRUTH = "signal_id string, seg_no int, start_pos bigint, end_pos bigint"
PIECES = (
    "signal_id string, method string, seg_no int, start_pos bigint, end_pos bigint, t_start double, t_end double, n bigint, intercept array<double>, slope array<double>, "
    "sse double, cost double, k int, sweeps int, n_fits bigint, n_evals bigint, n_cells int, runtime_s double, trace array<double>, exact_k boolean, error string"
)


@dataclass(frozen=True)
class SignalSpec:
    """Columns or expressions: who (signal_id), in which order (a total order), when, and the features."""

    signal_id: Column | str | None
    order_by: tuple
    time: Column | str | None = None
    features: tuple = ()

    def key(self) -> Column:
        return F.lit("all") if self.signal_id is None else _col(self.signal_id).cast("string")

    def vector(self) -> Column:
        return F.array(*[_col(c).cast("double") for c in self.features])


def _col(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def validate(sig: DataFrame, on_missing: str = "error") -> DataFrame:
    """One aggregate: every vector of a signal has the same length, no nulls, and strictly increasing time.  Raises, or drops rows with missing values."""
    bad = F.col("x").isNull() | F.exists("x", lambda v: v.isNull() | F.isnan(v)) | F.col("t").isNull()
    if on_missing == "drop_row":
        return sig.where(~bad)
    row = sig.agg(F.sum(bad.cast("int")), F.min(F.size("x")), F.max(F.size("x"))).first()
    if row[0]:
        raise ValueError(f"{row[0]} rows have missing values")
    if row[1] != row[2]:
        raise ValueError(f"vectors have {row[1]} to {row[2]} features")
    return sig

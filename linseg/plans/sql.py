"""SQL surface: a table function over partitions of a query."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

_OUT = "signal_id string, seg_no int, start_pos bigint, end_pos bigint, t_start double, n bigint, intercept array<double>, slope array<double>, sse double"


class SegmentSignal:
    """``segment_signal(TABLE(q) PARTITION BY signal_id ORDER BY t, 7, 'refine_then_merge')``; q has signal_id, t, x."""

    def __init__(self):
        self.t, self.x, self.sid, self.k, self.method = [], [], None, 1, ""

    def eval(self, row, k: int, method: str):
        self.sid, self.k, self.method = row["signal_id"], k, method
        self.t.append(float(row["t"]))
        self.x.append(row["x"])

    def terminate(self):
        if not self.t:
            return
        from ..operators.segment import run

        r = run(np.array(self.t), np.array(self.x, float), self.k, self.method, on_infeasible="clamp")
        for i, (a, b, (c, m, e)) in enumerate(zip(r["cuts"], r["cuts"][1:], r["lines"])):
            yield self.sid, i, int(a), int(b), self.t[a], int(b - a), c.tolist(), m.tolist(), float(e)


def register_sql(spark: SparkSession, name: str = "segment_signal") -> None:
    spark.udtf.register(name, udtf(SegmentSignal, returnType=_OUT))

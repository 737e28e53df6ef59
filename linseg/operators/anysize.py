"""One entry for signals of any size: many small ones in one shuffle, giant ones block by block."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..kernels.refine import uniform
from ..plans import regime
from ..spec import PIECES
from . import giant
from .segment import segment

#: Searches that run over blocks; a giant signal gives an error row for any other.
BLOCKWISE = ("refine_boundaries", "refine_then_merge", "bottom_up_merge")
#: Cells that the greedy merge of a giant signal starts from.
CELLS = 100_000


def segment_any(sig: DataFrame, k: int, method: str, most_points: int = regime.MOST_POINTS, most_bytes: int = regime.MOST_BYTES, block: int = giant.BLOCK, **options) -> DataFrame:
    """``segment`` for the signals that one task holds, and the block form for the few that none does.

    The profile (one partial aggregate) decides.  Giant signals are searched one after the other, each over all tasks; their refinement
    visits odd cuts after even ones, and their merging starts from ``CELLS`` even cells.
    """
    fleet, big = regime.choose_regime(sig, most_points, most_bytes)
    small = segment(fleet, k, method, **options)
    rows: list[dict] = []
    for r in big.select("signal_id").collect():
        if method not in BLOCKWISE:
            rows.append({"signal_id": r.signal_id, "method": method, "k": k, "error": f"{method} doesn't run over blocks"})
            continue
        began = time.perf_counter()
        blocks = giant.Blocks(sig.where(F.col("signal_id") == r.signal_id).select("pos", "t", "x"), block)
        given = {n: options[n] for n in ("gamma", "tol", "max_iter") if n in options}
        if method == "refine_boundaries":
            cuts, trace = giant.refine(blocks, uniform(blocks.n, k), **given)
        elif method == "refine_then_merge":
            cuts, trace = giant.refine_then_merge(blocks, k, size=options.get("k_init"), **given)
        else:
            cuts, trace = giant.bottom_up(blocks, k, CELLS), []
        rows += giant.pieces(blocks, cuts, r.signal_id, method, trace, time.perf_counter() - began)
        blocks.rows.unpersist()
    return small.unionByName(piece_rows(sig.sparkSession, rows))


def piece_rows(spark: SparkSession, rows: list[dict]) -> DataFrame:
    """Pieces found over blocks, a row each, as ``segment`` returns them."""
    schema = T._parse_datatype_string(PIECES)
    return spark.createDataFrame([tuple(x.get(f.name) for f in schema) for x in rows], schema)

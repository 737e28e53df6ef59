"""The single entry to every search: many signals, one kernel call each."""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..kernels import merging, optimal, refine, splits
from ..kernels.moments import COSTS, Linear, Unfit
from ..spec import PIECES

_OPTIONS = ("gamma", "tol", "max_iter", "order", "seed")


def _refining(o: dict) -> dict:
    return {k: o[k] for k in _OPTIONS if k in o}


def _start(s: Linear, k: int, o: dict) -> np.ndarray:
    init = o.get("init", "uniform")
    if isinstance(init, str):
        return refine.uniform(s.n, k) if init == "uniform" else refine.random_cuts(s.n, k, o.get("gamma", 2), o.get("seed", "0"))
    return np.asarray(init)


def _result(cuts, trace=(), cells=None, exact=True) -> dict:
    return {"cuts": np.asarray(cuts), "trace": list(trace), "cells": cells, "exact": exact}


def _penalized(s: Linear, k: int, o: dict) -> dict:
    if "beta" in o:
        return _result(optimal.penalized(s, o["beta"], o.get("gamma", 2)))
    cuts, beta, _ = optimal.penalized_for_k(s, k, o.get("gamma", 2))
    t0 = time.perf_counter()
    cuts = optimal.penalized(s, beta, o.get("gamma", 2))
    return _result(cuts, exact=len(cuts) - 1 == k) | {"final_run_s": time.perf_counter() - t0}


def _over_cells(s: Linear, k: int, o: dict, sf: float) -> dict:
    cuts, cells = optimal.optimal_over_cells(s, k, o.get("sf", sf), o.get("gamma", 2), o.get("compress", "moments"))
    return _result(cuts, cells=cells)


def _cells_refine(s: Linear, k: int, o: dict) -> dict:
    cuts, trace, cells = optimal.cells_then_refine(s, k, o.get("sf", 10), **_refining(o))
    return _result(cuts, trace, cells)


#: Every search by name: (signal, k, options) -> cuts and what it counted.
METHODS = {
    "refine_boundaries": lambda s, k, o: _result(*refine.refine(s, _start(s, k, o), **_refining(o))),
    "multistart_refine": lambda s, k, o: _result(*refine.multistart(s, k, o.get("q", 20), **_refining(o))),
    "refine_then_merge": lambda s, k, o: _result(*merging.refine_then_merge(s, k, o.get("k_init"), polish=o.get("polish", False), **_refining(o))),
    "cells_then_refine": _cells_refine,
    "bottom_up_merge": lambda s, k, o: _result(merging.bottom_up(s, k, o.get("delta", 2))[0]),
    "binary_split": lambda s, k, o: _result(splits.binary_split(s, k, o.get("gamma", 2))),
    "random_interval_split": lambda s, k, o: _result(splits.random_interval_split(s, k, o.get("n_intervals", 100), o.get("gamma", 2), o.get("seed", "0"))),
    "sliding_contrast": lambda s, k, o: _result(splits.sliding_contrast(s, k, o.get("window", 50), o.get("min_gap"), o.get("gamma", 2))),
    "optimal_over_cells": lambda s, k, o: _over_cells(s, k, o, 50),
    "optimal_over_cells_10": lambda s, k, o: _over_cells(s, k, o, 10),
    "optimal_partition": lambda s, k, o: _result(optimal.optimal_partition(s, k, o.get("gamma", 2))),
    "penalized_optimal": _penalized,
    "brute_force": lambda s, k, o: _result(optimal.brute_force(s, k, o.get("gamma", 2))),
    "unknown_k": lambda s, k, o: _result(*merging.unknown_k(s, o.get("beta"), k, **_refining(o))),
    "uniform": lambda s, k, o: _result(refine.uniform(s.n, k)),
    "one_piece": lambda s, k, o: _result([0, s.n]),
}
#: ``exact`` finds the least cost; ``bounded`` can be made to come as near as wanted; the rest are heuristics.
EXACTNESS = {"optimal_partition": "exact", "penalized_optimal": "exact", "brute_force": "exact", "optimal_over_cells": "bounded", "optimal_over_cells_10": "bounded"}


def run(t: np.ndarray, x: np.ndarray, k: int, method: str, cost: str = "l2_linear", on_infeasible: str = "error", **options) -> dict:
    """One signal, numpy only.  Infeasible k is clamped to what fits, or reported as an error, and so is a signal too large for the method."""
    try:
        return _run(t, x, k, method, cost, on_infeasible, **options)
    except Unfit as e:
        return {"error": str(e)}


def _run(t: np.ndarray, x: np.ndarray, k: int, method: str, cost: str, on_infeasible: str, **options) -> dict:
    gamma = options.get("gamma", 2)
    fits = max(1, len(t) // gamma)
    if k > fits and method not in ("unknown_k", "one_piece"):
        if on_infeasible == "error":
            return {"error": f"{len(t)} points don't hold {k} pieces of {gamma}"}
        k = fits
    t0 = time.perf_counter()
    coarse = options.pop("coarse", 1)
    if coarse > 1:  # search on every coarse-th point, then polish on all
        rough = _run(t[::coarse], x[::coarse], k, method, cost, "clamp", **options)
        s = COSTS[cost](t, x)
        got = _result(*refine.refine(s, np.minimum(rough["cuts"] * coarse, s.n), **_refining(options)))
    else:
        s = COSTS[cost](t, x)
        got = METHODS[method](s, k, options)
    seconds = got.pop("final_run_s", time.perf_counter() - t0)
    lines = [s.exact(int(a), int(b)) for a, b in zip(got["cuts"], got["cuts"][1:])]
    return got | {"lines": lines, "cost": sum(v[2] for v in lines), "seconds": seconds, "fits": s.count.fits, "evals": s.count.evals, "k": len(lines), "error": None}


def _numpy(table: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    pos = table["pos"].to_numpy()
    order = np.argsort(pos, kind="stable")
    x = table["x"].combine_chunks()
    flat = x.flatten().to_numpy(zero_copy_only=False).astype(float)
    return pos[order], table["t"].to_numpy()[order].astype(float), flat.reshape(len(pos), -1)[order]


def segment(sig: DataFrame, k: int | str, method: str | tuple[str, ...], cost: str = "l2_linear", on_infeasible: str = "error", **options) -> DataFrame:
    """Pieces of every signal.  ``k``: a number, or the name of a column of ``sig``.  ``init`` may be a frame (signal_id, cuts array).

    Several methods run one after the other where one shuffle has put the signal.
    """
    methods = (method,) if isinstance(method, str) else method
    if unknown := set(methods) - set(METHODS):
        raise ValueError(f"unknown method {sorted(unknown)}; one of {sorted(METHODS)}")
    fields = to_arrow_schema(T._parse_datatype_string(PIECES))
    cols = ["signal_id", "pos", "t", "x"]
    narrow = sig.select(*cols, F.col(k).cast("int").alias("k")) if isinstance(k, str) else sig.select(*cols)
    init = options.pop("init", "uniform")
    if isinstance(init, DataFrame):
        narrow = narrow.join(init.select("signal_id", F.col("cuts").cast("array<bigint>").alias("init")), "signal_id")
    elif init != "uniform":
        options["init"] = init
    with_k, with_init = isinstance(k, str), isinstance(init, DataFrame)

    def kernel(table: pa.Table) -> pa.Table:
        sid = table["signal_id"][0].as_py()
        pos, t, x = _numpy(table)
        own = table["k"][0].as_py() if with_k else k
        more = {"init": np.array(table["init"][0].as_py())} if with_init else {}
        seeded = {"seed": f"{options.get('seed', '0')}|{sid}"}
        rows = []
        for method in methods:
            r = run(t, x, own, method, cost, on_infeasible, **(options | seeded | more))
            if r["error"]:
                rows.append({"signal_id": sid, "method": method, "k": own, "error": r["error"]})
                continue
            rows += [
                {
                    "signal_id": sid, "method": method, "seg_no": i, "start_pos": int(pos[a]), "end_pos": int(pos[b]) if b < len(pos) else int(pos[-1]) + 1, "t_start": t[a], "t_end": t[b] if b < len(t) else None,
                    "n": int(b - a), "intercept": c.tolist(), "slope": m.tolist(), "sse": e, "cost": r["cost"], "k": r["k"], "sweeps": max(0, len(r["trace"]) - 1), "n_fits": r["fits"], "n_evals": r["evals"],
                    "n_cells": r["cells"], "runtime_s": r["seconds"], "trace": r["trace"] if i == 0 else None, "exact_k": r["exact"], "error": None,
                }
                for i, (a, b, (c, m, e)) in enumerate(zip(r["cuts"], r["cuts"][1:], r["lines"]))
            ]
        return pa.Table.from_pylist(rows, schema=fields)

    return narrow.groupBy("signal_id").applyInArrow(kernel, PIECES)


def cuts_of(pieces: DataFrame) -> DataFrame:
    """Inner cuts: signal_id, method, pos, t."""
    return pieces.where("seg_no > 0").select("signal_id", "method", F.col("start_pos").alias("pos"), F.col("t_start").alias("t"))


def cut_arrays(pieces: DataFrame) -> DataFrame:
    """A start for refinement: signal_id and the whole cut array."""
    return pieces.groupBy("signal_id").agg(F.sort_array(F.array_distinct(F.flatten(F.collect_list(F.array("start_pos", "end_pos"))))).alias("cuts"))


def scores_of(pieces: DataFrame) -> DataFrame:
    """One row a signal and method."""
    return pieces.where("seg_no = 0").select("signal_id", "method", "k", "cost", "runtime_s", "sweeps", "n_fits", "n_evals", "n_cells", "exact_k", "trace")


def merge_paths(sig: DataFrame, delta: int = 2) -> DataFrame:
    """Every merge down to one piece: signal_id, step, cut removed, gain, pieces left."""
    schema = "signal_id string, step int, cut bigint, gain double, pieces int"
    fields = to_arrow_schema(T._parse_datatype_string(schema))

    def kernel(table: pa.Table) -> pa.Table:
        pos, t, x = _numpy(table)
        s = Linear(t, x)
        edges = merging.cells(s.n, delta)
        _, path = merging.merge(s, edges, 1)
        sid = table["signal_id"][0].as_py()
        return pa.Table.from_pylist([{"signal_id": sid, "step": i + 1, "cut": c, "gain": g, "pieces": len(edges) - 2 - i} for i, (c, g) in enumerate(path)], schema=fields)

    return sig.select("signal_id", "pos", "t", "x").groupBy("signal_id").applyInArrow(kernel, schema)


def optimal_paths(sig: DataFrame, k_max: int, gamma: int = 2) -> DataFrame:
    """signal_id, k, cost, cuts for every k up to k_max from one table."""
    schema = "signal_id string, k int, cost double, cuts array<bigint>"
    fields = to_arrow_schema(T._parse_datatype_string(schema))

    def kernel(table: pa.Table) -> pa.Table:
        _, t, x = _numpy(table)
        sid = table["signal_id"][0].as_py()
        return pa.Table.from_pylist([{"signal_id": sid, "k": k, "cost": c, "cuts": cuts.tolist()} for k, c, cuts in optimal.optimal_path(Linear(t, x), min(k_max, max(1, len(t) // gamma)), gamma)], schema=fields)

    return sig.select("signal_id", "pos", "t", "x").groupBy("signal_id").applyInArrow(kernel, schema)


def cells_of(sig: DataFrame, k: int, sf: float = 50, budget: float | None = None) -> DataFrame:
    """Balanced cells: signal_id, cell, start_pos, end_pos, cost; and the bicriteria scale.  ``budget``: a share of the one-line cost instead of the scale's."""
    schema = "signal_id string, cell int, start_pos bigint, end_pos bigint, cost double, scale double"
    fields = to_arrow_schema(T._parse_datatype_string(schema))

    def kernel(table: pa.Table) -> pa.Table:
        _, t, x = _numpy(table)
        s = Linear(t, x)
        scale = optimal.bicriteria(s, k)[0]
        edges = optimal.cell_edges(s, k, sf)[0] if budget is None else optimal.balanced_cells(s, budget * s.one(0, s.n))
        sid = table["signal_id"][0].as_py()
        return pa.Table.from_pylist([{"signal_id": sid, "cell": i, "start_pos": int(a), "end_pos": int(b), "cost": s.one(int(a), int(b)), "scale": scale} for i, (a, b) in enumerate(zip(edges, edges[1:]))], schema=fields)

    return sig.select("signal_id", "pos", "t", "x").groupBy("signal_id").applyInArrow(kernel, schema)

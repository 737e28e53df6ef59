"""The reference's experiments on the given tables: score rows and the tables made of them."""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import apps, giant, metrics
from .operators.anysize import piece_rows, segment_any
from .operators.segment import scores_of, segment
from .plans import regime
from .sources import builders, planted

SINGLE = ("binary_split", "multistart_refine", "sliding_contrast", "bottom_up_merge", "refine_then_merge")
SMALL = ("optimal_over_cells", "optimal_over_cells_10", "cells_then_refine", "bottom_up_merge", "refine_then_merge", "optimal_partition", "multistart_refine", "penalized_optimal", "binary_split")
LARGE = ("optimal_over_cells", "optimal_over_cells_10", "cells_then_refine", "bottom_up_merge", "refine_then_merge", "multistart_refine")
FRAMES = ("optimal_over_cells", "optimal_over_cells_10", "cells_then_refine", "bottom_up_merge", "refine_then_merge")


def compare(sig: DataFrame, k: int | str, methods: tuple, **options) -> DataFrame:
    """Pieces of every method on every signal; one shuffle for all methods."""
    return segment(sig, k, tuple(methods), **options)


def scored(sig: DataFrame, truth: DataFrame | None, k: int | str, methods: tuple, base: str, search: Callable = compare, **options) -> DataFrame:
    """One row a method, as the published tables and figures have it.  search: ``compare``, or what gives pieces in its place.

    Relative run time and cost against the base, covering and Rand with the share of signals that reach 0.975 and the ninth
    decile of what is missing to 1, the slope of log run time on log size, counters.  Rows that a penalty could not bring to the
    asked number of pieces are left out of these and shown by ``exact``, the share of the others.
    """
    sig = sig.persist()
    pieces = search(sig, k, methods, **options).persist()  # measured several times below; each search runs once
    s = metrics.evaluate(truth, pieces) if truth is not None else scores_of(pieces).withColumn("covering", F.lit(None).cast("double")).withColumn("rand", F.lit(None).cast("double"))
    s = s.join(planted.sizes(sig), "signal_id").persist()
    exact = s.groupBy("method").agg(F.avg(F.col("exact_k").cast("double")).alias("exact"))
    s = s.where("exact_k")
    out = metrics.relative_cost(s, base).select("method", F.col("mean_ratio").alias("relative_cost"), F.col("ratio_of_means").alias("cost_of_means"), "signals")
    out = out.join(metrics.relative_runtime(s, base).select("method", F.col("ratio_of_means").alias("relative_runtime")), "method")
    reach = lambda c: F.avg((F.col(c) >= 0.975).cast("double")).alias(f"{c}_reached")
    short = lambda c: F.percentile(1 - F.col(c), F.lit(0.9)).alias(f"{c}_missing")
    more = s.groupBy("method").agg(
        F.avg("covering").alias("covering"), F.avg("rand").alias("rand"), reach("covering"), reach("rand"), short("covering"), short("rand"), F.regr_slope(F.log(F.greatest("runtime_s", F.lit(1e-6))), F.log("n")).alias("slope"), F.min("n").alias("least_n"), F.max("n").alias("most_n"),
        F.avg("runtime_s").alias("seconds"), F.avg("n_fits").alias("n_fits"), F.avg("n_evals").alias("n_evals"), F.avg("sweeps").alias("sweeps"), F.avg("n_cells").alias("n_cells"),
    )
    return out.join(more, "method").join(exact, "method")


def published_single_cut(spark: SparkSession, count: int = 200) -> DataFrame:
    """One cut, 400 to 15,000 points, 2 to 16 dimensions."""
    x, truth = planted.drawn_signals(spark, count, (400, 15_000), (2, 2), seed="p1")
    return scored(x, truth, 2, SINGLE, "binary_split")


def published_many_small(spark: SparkSession, count: int = 200) -> DataFrame:
    """2 to 10 pieces, 50 to 2,000 points."""
    x, truth = planted.drawn_signals(spark, count, (50, 2_000), (2, 10), seed="p2")
    return scored(x, truth, "k", SMALL, "optimal_partition")


def published_many_large(spark: SparkSession, count: int = 100) -> DataFrame:
    """2 to 10 pieces, 4,000 to 175,000 points."""
    x, truth = planted.drawn_signals(spark, count, (4_000, 175_000), (2, 10), seed="p3")
    return scored(x, truth, "k", LARGE, "optimal_over_cells")


def single_cut(spark: SparkSession, sf: str, amp: float = 0.5) -> DataFrame:
    """One planted cut in each supplier's rows."""
    x, truth = planted.planted(builders.supplier_signal(spark, sf), planted.SUPPLIER_SCALE, 2, None, "w1", amp, 1.0, 0.3)
    return scored(x, truth, 2, SINGLE, "binary_split")


def many_cuts_small(spark: SparkSession, sf: str) -> DataFrame:
    x, truth = planted.planted(builders.supplier_signal(spark, sf), planted.SUPPLIER_SCALE, 2, 10, "w2", 1.0, 1.0, 0.3)
    return scored(x, truth, "k", SMALL, "optimal_partition")


#: The total order of line items, and the columns of their values.
LINE_ORDER = ["l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
LINE_VALUES = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]


def line_values() -> Column:
    return F.array(F.col("l_quantity"), F.round(F.col("l_extendedprice") * 100), F.round(F.col("l_discount") * 100), F.round(F.col("l_tax") * 100))


def line_items(spark: SparkSession, sf: str) -> DataFrame:
    """pos, t, x of all line items in their total order (positions by range partitions, no global window)."""
    rows = giant.with_global_position(builders.load_table(spark, sf, "lineitem", LINE_ORDER + LINE_VALUES), LINE_ORDER)
    return rows.select(F.col("pos").cast("bigint").alias("pos"), F.col("pos").cast("double").alias("t"), line_values().alias("x"))


def slices(spark: SparkSession, sf: str, sizes: tuple[int, ...]) -> DataFrame:
    """One signal of each size: the first rows of all line items in their total order."""
    size = F.explode(F.array(*[F.lit(n) for n in sizes])).alias("size")
    grown = line_items(spark, sf).where(F.col("pos") < max(sizes)).select("pos", "t", "x", size).where(F.col("pos") < F.col("size"))
    return grown.select(F.col("size").cast("string").alias("signal_id"), "pos", "t", "x")


def many_cuts_large(spark: SparkSession, sf: str, sizes: tuple[int, ...] = (4000, 10_000, 30_000)) -> DataFrame:
    x, truth = planted.planted(slices(spark, sf, sizes), planted.SUPPLIER_SCALE, 2, 10, "w3", 1.0, 1.0, 0.3)
    return scored(x, truth, "k", LARGE, "optimal_over_cells")


def frames(spark: SparkSession, sf: str, scene: int = 1000, p: int = 32, k: int = 7) -> DataFrame:
    """Seven pieces of each scene of embeddings, principal components first; no truth."""
    sig = apps.reduce_pca(builders.frame_signal(spark, sf, scene), p)
    return scored(sig, None, k, FRAMES, "optimal_over_cells")


def one_scene(spark: SparkSession, sf: str) -> DataFrame:
    """One scene, two components, seven pieces, five frames of each."""
    sig = apps.reduce_pca(builders.frame_signal(spark, sf), 2)
    return apps.summarize(segment(sig, 7, "refine_then_merge"), 5)


def run_time_growth(spark: SparkSession, sf: str, sizes: tuple[int, ...] = (400, 800, 1600, 3200, 6400, 12_800), methods: tuple = SINGLE) -> DataFrame:
    """Slope of log run time on log size, by method; slices of the line items with a planted cut."""
    x, _ = planted.planted(slices(spark, sf, sizes), planted.SUPPLIER_SCALE, 2, None, "w6", 0.5, 1.0, 0.3)
    s = scores_of(compare(x, 2, methods)).withColumn("n", F.col("signal_id").cast("double"))
    return metrics.scaling_slope(s)


def mismatch(spark: SparkSession, sf: str) -> DataFrame:
    """Strong curves: the least cost isn't the best cut."""
    x, truth = planted.planted(builders.supplier_signal(spark, sf), planted.SUPPLIER_SCALE, 2, None, "w7", 0.5, 0.5, 3.0)
    return scored(x, truth, 2, ("binary_split", "bottom_up_merge"), "binary_split")


def million_points(spark: SparkSession, sf: str, n: int = 1_000_000, most_points: int = regime.MOST_POINTS) -> DataFrame:
    """The scale claim: all line items, tiled where they are fewer than ``n``, planted, ten pieces by refine-then-merge; over blocks where one task doesn't hold ``n``."""
    base = line_items(spark, sf)
    rows = base.count()
    times = max(1, -(-n // max(rows, 1)))
    tiled = base.select(F.explode(F.sequence(F.lit(0), F.lit(times - 1))).alias("rep"), "pos", "x").select(F.lit("tiled").alias("signal_id"), (F.col("pos") + F.col("rep") * rows).alias("pos"), "x").where(F.col("pos") < max(n, rows))
    sig = tiled.withColumn("t", F.col("pos").cast("double")).select("signal_id", "pos", "t", "x")
    x, truth = planted.planted(sig, planted.SUPPLIER_SCALE, 10, None, "w8", 1.0, 1.0, 0.3)
    search = lambda sig, k, methods: segment_any(sig, k, methods[0], most_points)
    return scored(x, truth, 10, ("refine_then_merge",), "refine_then_merge", search)


def down_sampled(spark: SparkSession, sf: str, steps: tuple[int, ...] = (1, 2, 5, 10), most_points: int = regime.MOST_POINTS, block: int = giant.BLOCK) -> DataFrame:
    """Search on every m-th point of all line items, then a polish on all: cost and covering by m.

    The signal is shuffled once for all steps.  One task searches it where it holds it; else it is searched over blocks, packed as they
    come from the ranges of the total order, and the planted values are made whenever a block is read.
    """
    k, plan = 8, ("w9", 1.0, 0.3)
    lines = builders.load_table(spark, sf, "lineitem", LINE_ORDER + LINE_VALUES)
    n = lines.count()
    if n <= most_points:
        whole = line_items(spark, sf).withColumn("signal_id", F.lit("all"))
        x, truth = planted.planted(whole.select("signal_id", "pos", "t", "x"), planted.SUPPLIER_SCALE, k, None, plan[0], plan[1], 1.0, plan[2])
        x = x.persist()  # the steps share its one shuffle
        found = reduce(DataFrame.unionByName, [segment(x, k, "refine_then_merge", coarse=m).withColumn("method", F.lit(str(m))) for m in steps]).persist()
    else:
        size = spark.createDataFrame([("all", n)], "signal_id string, n bigint")
        truth = planted.truth(size, k, None, len(planted.SUPPLIER_SCALE), *plan)
        blocks = giant.Blocks.ordered(lines, LINE_ORDER, line_values(), block, planted.Planted(truth.collect(), planted.SUPPLIER_SCALE))  # k rows
        rows = []
        for m in steps:
            began = time.perf_counter()
            cuts, trace = giant.refine_from_coarse(blocks, k, m)
            rows += giant.pieces(blocks, cuts, "all", str(m), trace, time.perf_counter() - began)
        blocks.rows.unpersist()
        found = piece_rows(spark, rows)
    return metrics.evaluate(truth, found).select(F.col("method").cast("int").alias("m"), "cost", "covering", "rand", "runtime_s")


def number_unknown(spark: SparkSession, sf: str) -> DataFrame:
    """Found against planted number of pieces."""
    x, truth = planted.planted(builders.supplier_signal(spark, sf), planted.SUPPLIER_SCALE, 2, 8, "w11", 2.0, 1.0, 0.0)
    found = scores_of(segment(x, 12, "unknown_k", on_infeasible="clamp")).select("signal_id", F.col("k").alias("found"))
    return truth.groupBy("signal_id").agg(F.count("*").alias("planted")).join(found, "signal_id")


def business_series(spark: SparkSession, sf: str) -> DataFrame:
    """Daily orders and weekly orders by market segment in four pieces: exact and refine-then-merge cost."""
    weekly = builders.buckets_to_signal(builders.weekly_segment(spark, sf), ["n", "cents"])
    sig = builders.daily_orders(spark, sf).unionByName(weekly)
    sig = apps.standardize(sig, 2)
    return scores_of(compare(sig, 4, ("optimal_partition", "refine_then_merge"))).select("signal_id", "method", "k", "cost", "runtime_s")


def ablation(spark: SparkSession, sf: str) -> DataFrame:
    """Minimum piece, tolerance and visit order of the refinement on planted signals: cost, covering, sweeps."""
    x, truth = planted.planted(builders.supplier_signal(spark, sf), planted.SUPPLIER_SCALE, 2, 10, "abl", 1.0, 1.0, 0.3)
    settings = [{"gamma": g} for g in (1, 2, 8)] + [{"tol": t} for t in (1e-2, 1e-6)] + [{"order": o} for o in ("left_to_right", "odd_even")]
    parts = [metrics.evaluate(truth, segment(x, "k", "refine_then_merge", **o)).withColumn("setting", F.lit(str(o))) for o in settings]
    return reduce(DataFrame.unionByName, parts).groupBy("setting").agg(F.avg("cost").alias("cost"), F.avg("covering").alias("covering"), F.avg("sweeps").alias("sweeps"))

"""What segmentations are for: summaries, anomalies, subsets, descriptions, correlation with events."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .fit import point_costs, project


def downsample(sig: DataFrame, m: int) -> DataFrame:
    """Every m-th point of each signal; places are renumbered, times stay."""
    return sig.where(F.col("pos") % m == 0).withColumn("pos", F.floor(F.col("pos") / m).cast("bigint"))


def restrict(sig: DataFrame, lo: float, hi: float) -> DataFrame:
    return sig.where((F.col("t") >= lo) & (F.col("t") < hi))


def standardize(sig: DataFrame, d: int) -> DataFrame:
    """Zero mean and unit spread of each dimension and signal; time centred on a unit span."""
    w = Window.partitionBy("signal_id")
    span = F.max("t").over(w) - F.min("t").over(w)
    t = F.when(span > 0, (F.col("t") - F.avg("t").over(w)) / span).otherwise(0.0)
    cols = [F.col("x")[i] for i in range(d)]
    z = [F.when(F.stddev_pop(c).over(w) > 0, (c - F.avg(c).over(w)) / F.stddev_pop(c).over(w)).otherwise(0.0) for c in cols]
    return sig.select("signal_id", "pos", t.alias("t"), F.array(*z).alias("x"))


def handle_missing(sig: DataFrame, d: int, policy: str = "zero") -> DataFrame:
    """Null or NaN features: zero, ffill (the last known value), or drop_row."""
    cols = [F.nanvl(F.col("x")[i], F.lit(None).cast("double")) for i in range(d)]
    if policy == "drop_row":
        return sig.where(~reduce(lambda a, b: a | b, [c.isNull() for c in cols]))
    w = Window.partitionBy("signal_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    fill = {"zero": lambda c: F.coalesce(c, F.lit(0.0)), "ffill": lambda c: F.coalesce(F.last(c, True).over(w), F.lit(0.0))}[policy]
    return sig.select("signal_id", "pos", "t", F.array(*[fill(c) for c in cols]).alias("x"))


def reduce_pca(sig: DataFrame, p: int) -> DataFrame:
    """The first p principal components over all points: one pass for the Gram matrix (d squared numbers on the driver)."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector, vector_to_array

    v = sig.withColumn("v", array_to_vector("x"))
    return PCA(k=p, inputCol="v", outputCol="y").fit(v).transform(v).select("signal_id", "pos", "t", vector_to_array("y").alias("x"))


def pca_variance(sig: DataFrame, p: int) -> DataFrame:
    """component, share of variance."""
    from pyspark.ml.feature import PCA
    from pyspark.ml.functions import array_to_vector

    m = PCA(k=p, inputCol="v", outputCol="y").fit(sig.select(array_to_vector("x").alias("v")))
    return sig.sparkSession.createDataFrame([(i, float(x)) for i, x in enumerate(m.explainedVariance)], "component int, share double")


def summarize(pieces: DataFrame, per_piece: int = 5) -> DataFrame:
    """Places of frames evenly spaced in each piece."""
    n = F.col("end_pos") - F.col("start_pos")
    frame = F.explode(F.sequence(F.lit(0), F.lit(per_piece - 1))).alias("frame")
    rows = pieces.where(n > 0).select("signal_id", "seg_no", "start_pos", "end_pos", frame)
    at = F.col("start_pos") + F.floor((2 * F.col("frame") + 1) * (F.col("end_pos") - F.col("start_pos")) / (2 * per_piece)).cast("bigint")
    return rows.select("signal_id", "seg_no", "frame", at.alias("pos"))


def shade(pieces: DataFrame) -> DataFrame:
    return pieces.withColumn("shade", F.pmod("seg_no", F.lit(2)))


def residual_anomalies(sig: DataFrame, pieces: DataFrame, z: float = 4.0) -> DataFrame:
    """Points whose distance from their line is over z times the piece's root mean square distance."""
    e = point_costs(project(sig, pieces))
    rms = F.sqrt(F.avg("error").over(Window.partitionBy("signal_id", "seg_no")))
    return e.withColumn("ratio", F.when(rms > 0, F.sqrt("error") / rms).otherwise(0.0)).where(F.col("ratio") > z).select("signal_id", "pos", "seg_no", "ratio")


def worst_residuals(sig: DataFrame, pieces: DataFrame, n: int) -> DataFrame:
    return point_costs(project(sig, pieces)).select("signal_id", "pos", "seg_no", "error").orderBy(F.desc("error"), "signal_id", "pos").limit(n)


def expand_tags(pieces: DataFrame, tags: DataFrame) -> DataFrame:
    """Pieces that hold a tagged place (signal_id, pos): a left semi-join."""
    t = tags.select(F.col("signal_id").alias("__sid"), F.col("pos").alias("__at"))
    return pieces.join(t, (F.col("signal_id") == F.col("__sid")) & (F.col("__at") >= F.col("start_pos")) & (F.col("__at") < F.col("end_pos")), "left_semi")


def describe_pieces(pieces: DataFrame, flat: float = 1e-3) -> DataFrame:
    """Per piece and dimension: start and end value, direction, whether nearly constant against its own spread."""
    dims = F.posexplode(F.arrays_zip("intercept", "slope"))
    rows = pieces.select("signal_id", "method", "seg_no", "t_start", "n", "sse", dims.alias("dim", "line"))
    slope = F.col("line.slope")
    return rows.select(
        "signal_id", "method", "seg_no", "dim", (F.col("line.intercept") + slope * F.col("t_start")).alias("start_value"), slope.alias("slope"),
        F.signum(slope).cast("int").alias("direction"), (F.abs(slope) * F.col("n") <= F.greatest(F.sqrt(F.col("sse") / F.col("n")), F.lit(flat))).alias("nearly_constant"),
    )


def correlate_cuts(cuts: DataFrame, events: DataFrame, within: float) -> DataFrame:
    """Pairs of a cut (signal_id, t) and an event (signal_id, at) at most ``within`` apart: equi-join on time buckets, then a filter."""
    c = cuts.select("signal_id", F.col("t").alias("cut_t"), F.explode(F.array(*[F.floor(F.col("t") / within) + i for i in (-1, 0, 1)])).alias("slot"))
    e = events.select("signal_id", "at", F.floor(F.col("at") / within).alias("slot"))
    return c.join(e, ["signal_id", "slot"]).where(F.abs(F.col("at") - F.col("cut_t")) <= within).select("signal_id", "cut_t", "at")


def range_join_blocks(sig: DataFrame, pieces: DataFrame, width: int = 1024) -> DataFrame:
    """Points with their piece by an equi-join: long pieces are listed under every block of places they touch."""
    p = pieces.select("signal_id", "seg_no", "start_pos", "end_pos", F.explode(F.sequence(F.floor(F.col("start_pos") / width), F.floor((F.col("end_pos") - 1) / width))).alias("block"))
    s = sig.withColumn("block", F.floor(F.col("pos") / width))
    return s.join(p, ["signal_id", "block"]).where("pos >= start_pos and pos < end_pos").drop("block", "start_pos", "end_pos")


def asof_last(points: DataFrame, starts: DataFrame, value: str) -> DataFrame:
    """The latest start at or before each point, by one union and one window instead of a range join."""
    a = points.select("signal_id", "pos", F.lit(1).alias("side"), F.lit(None).cast(starts.schema[value].dataType).alias(value))
    b = starts.select("signal_id", "pos", F.lit(0).alias("side"), value)
    w = Window.partitionBy("signal_id").orderBy("pos", "side").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn(value, F.last(value, True).over(w)).where("side = 1").drop("side")


def position_pairs(sig: DataFrame, max_n: int = 2000) -> DataFrame:
    """Places i < j of each signal; signals over ``max_n`` points are refused."""
    n = sig.groupBy("signal_id").agg(F.count("*").alias("n"))
    if n.where(F.col("n") > max_n).limit(1).count():
        raise ValueError(f"pairs are for signals of up to {max_n} points")
    return sig.select("signal_id", F.col("pos").alias("i")).join(sig.select("signal_id", F.col("pos").alias("j")), "signal_id").where("i < j")

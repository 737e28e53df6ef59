"""Accuracy and cost measures; partitions are rows (signal_id, seg_no, start_pos, end_pos), half-open."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def jaccard(a_lo, a_hi, b_lo, b_hi) -> Column:
    both = F.greatest(F.least(a_hi, b_hi) - F.greatest(a_lo, b_lo), F.lit(0))
    return both / ((a_hi - a_lo) + (b_hi - b_lo) - both)


def overlaps(truth: DataFrame, pred: DataFrame) -> DataFrame:
    """Pairs of a true and a predicted piece that share points, with the number shared; equi-join on the signal."""
    t = truth.select("signal_id", F.col("seg_no").alias("t_seg"), F.col("start_pos").alias("t_lo"), F.col("end_pos").alias("t_hi"))
    p = pred.select("signal_id", *(["method"] if "method" in pred.columns else [F.lit("").alias("method")]), F.col("seg_no").alias("p_seg"), F.col("start_pos").alias("p_lo"), F.col("end_pos").alias("p_hi"))
    j = t.join(p, "signal_id").where("t_lo < p_hi and p_lo < t_hi")
    return j.withColumn("shared", F.least("t_hi", "p_hi") - F.greatest("t_lo", "p_lo"))


def covering(truth: DataFrame, pred: DataFrame) -> DataFrame:
    """Size-weighted best overlap of the true pieces; 1 only for equal partitions."""
    o = overlaps(truth, pred).withColumn("j", jaccard(F.col("t_lo"), F.col("t_hi"), F.col("p_lo"), F.col("p_hi")))
    best = o.groupBy("signal_id", "method", "t_seg").agg(F.max("j").alias("j"), F.max(F.col("t_hi") - F.col("t_lo")).alias("size"))
    return best.groupBy("signal_id", "method").agg((F.sum(F.col("j") * F.col("size")) / F.sum("size")).alias("covering"))


def rand_index(truth: DataFrame, pred: DataFrame) -> DataFrame:
    """Share of ordered pairs of distinct points that both partitions join or both part; from overlap sizes, not from pairs."""
    o = overlaps(truth, pred)
    n2 = F.sum(F.col("shared") * F.col("shared"))
    both = o.groupBy("signal_id", "method").agg(n2.alias("both"), F.sum("shared").alias("n"))
    side = lambda seg, name: o.groupBy("signal_id", "method", seg).agg(F.sum("shared").alias("s")).groupBy("signal_id", "method").agg(F.sum(F.col("s") * F.col("s")).alias(name))
    j = both.join(side("t_seg", "t2"), ["signal_id", "method"]).join(side("p_seg", "p2"), ["signal_id", "method"])
    n = F.col("n")
    return j.select("signal_id", "method", F.when(n > 1, (n * (n - 1) - F.col("t2") - F.col("p2") + 2 * F.col("both")) / (n * (n - 1))).otherwise(1.0).alias("rand"))


def cut_f1(truth: DataFrame, pred: DataFrame, margin: int = 5) -> DataFrame:
    """F1 of the inner cuts: a true cut and its nearest predicted one match, one to one, within the margin."""
    t = truth.where("seg_no > 0").select("signal_id", F.col("start_pos").alias("t_cut"))
    p = pred.where("seg_no > 0").select("signal_id", "method", F.col("start_pos").alias("p_cut"))
    near = t.join(p, "signal_id").where(F.abs(F.col("t_cut") - F.col("p_cut")) <= margin).withColumn("gap", F.abs(F.col("t_cut") - F.col("p_cut")))
    a = Window.partitionBy("signal_id", "method", "t_cut").orderBy("gap", "p_cut")
    b = Window.partitionBy("signal_id", "method", "p_cut").orderBy("gap", "t_cut")
    hits = near.withColumn("ra", F.row_number().over(a)).withColumn("rb", F.row_number().over(b)).where("ra = 1 and rb = 1").groupBy("signal_id", "method").agg(F.count("*").alias("hits"))
    n_t = truth.groupBy("signal_id").agg(F.sum((F.col("seg_no") > 0).cast("bigint")).alias("n_true"))
    n_p = pred.groupBy("signal_id", "method").agg(F.sum((F.col("seg_no") > 0).cast("bigint")).alias("n_pred"))
    j = n_p.join(n_t, "signal_id").join(hits, ["signal_id", "method"], "left").fillna(0, ["hits"])
    total = F.col("n_true") + F.col("n_pred")
    return j.select("signal_id", "method", "n_true", "n_pred", "hits", F.when(total > 0, 2 * F.col("hits") / total).otherwise(1.0).alias("f1"))


def deficit_cdf(scores: DataFrame, measure: str) -> DataFrame:
    """Share of signals whose deficit 1 - score is at most x, by method."""
    d = scores.select("signal_id", "method", (1 - F.col(measure)).alias("deficit"))
    return d.withColumn("share", F.cume_dist().over(Window.partitionBy("method").orderBy("deficit")))


def share_at_least(scores: DataFrame, measure: str, level: float = 0.975) -> DataFrame:
    return scores.groupBy("method").agg(F.avg((F.col(measure) >= level).cast("double")).alias("share"))


def relative(scores: DataFrame, base: str, measure: str) -> DataFrame:
    """Against a base method: mean of the signals' ratios, and ratio of the means."""
    b = scores.where(F.col("method") == base).select("signal_id", F.col(measure).alias("b"))
    j = scores.join(b, "signal_id")
    return j.groupBy("method").agg(F.avg(F.when(F.col("b") > 0, F.col(measure) / F.col("b"))).alias("mean_ratio"), (F.avg(measure) / F.avg("b")).alias("ratio_of_means"), F.count("*").alias("signals"))


def relative_cost(scores: DataFrame, base: str) -> DataFrame:
    return relative(scores, base, "cost")


def relative_runtime(scores: DataFrame, base: str) -> DataFrame:
    return relative(scores, base, "runtime_s")


def scaling_slope(scores: DataFrame) -> DataFrame:
    """Slope of log run time against log size (columns runtime_s, n), by method."""
    return scores.groupBy("method").agg(F.regr_slope(F.log("runtime_s"), F.log("n")).alias("slope"))


def evaluate(truth: DataFrame, pieces: DataFrame) -> DataFrame:
    """Score rows: cost, run time, counters, covering, Rand."""
    base = pieces.where("seg_no = 0").select("signal_id", "method", "k", "cost", "runtime_s", "sweeps", "n_fits", "n_evals", "n_cells", "exact_k")
    good = pieces.where("error is null")
    return base.join(covering(truth, good), ["signal_id", "method"]).join(rand_index(truth, good), ["signal_id", "method"])


def score_rollup(scores: DataFrame, dims: list[str], how: str = "rollup") -> DataFrame:
    aggs = [F.avg("cost").alias("cost"), F.avg("covering").alias("covering"), F.avg("rand").alias("rand"), F.count("*").alias("signals"), F.grouping_id().alias("level")]
    return getattr(scores, how)(*dims).agg(*aggs)


def pivot_scores(scores: DataFrame, methods: list[str], measure: str = "covering") -> DataFrame:
    return scores.groupBy("signal_id").pivot("method", methods).agg(F.first(measure))


def agree(a: DataFrame, b: DataFrame, how: str = "intersect") -> DataFrame:
    """Cuts (signal_id, pos) of two methods: in both, in either, or in the first alone."""
    a, b = a.select("signal_id", "pos"), b.select("signal_id", "pos")
    return {"intersect": a.intersect, "union": lambda o: a.unionByName(o).distinct(), "except": a.exceptAll}[how](b)

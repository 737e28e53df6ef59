"""Lines, moments, projection and cost, all inside the JVM."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import columns as C


def fit_lines(sig: DataFrame, d: int, by: list[str] = ["signal_id"]) -> DataFrame:  # noqa: B006
    """Line of each group and dimension: intercept, slope, sse, one row a dimension; one aggregate pass."""
    aggs = []
    for i in range(d):
        x = F.col("x")[i]
        aggs += [F.regr_slope(x, "t").alias(f"slope{i}"), F.regr_intercept(x, "t").alias(f"intercept{i}"), F.regr_syy(x, "t").alias(f"syy{i}"), F.regr_sxy(x, "t").alias(f"sxy{i}")]
    wide = sig.groupBy(*by).agg(F.count("*").alias("n"), F.regr_sxx(F.col("x")[0], "t").alias("stt"), F.avg(F.col("x")[0]).alias("__m"), *aggs)
    rows = F.array(*[F.struct(F.lit(i).alias("dim"), F.coalesce(f"intercept{i}", F.lit(0.0)).alias("intercept"), F.coalesce(f"slope{i}", F.lit(0.0)).alias("slope"), F.when(F.col("stt") > 0, F.greatest(F.col(f"syy{i}") - F.col(f"sxy{i}") * F.col(f"sxy{i}") / F.col("stt"), F.lit(0.0))).otherwise(0.0).alias("sse")) for i in range(d)])
    return wide.select(*by, "n", F.explode(rows).alias("f")).select(*by, "n", "f.*")


def moments(sig: DataFrame, d: int, by: list[str] = ["signal_id"]) -> DataFrame:  # noqa: B006
    """Mergeable sums of each group; partial sums cross the shuffle."""
    return sig.groupBy(*by).agg(*[F.sum(e).alias(n) for n, e in C.sum_terms(d).items()])


def merge_moments(a: DataFrame, b: DataFrame, d: int, by: list[str]) -> DataFrame:
    return a.unionByName(b).groupBy(*by).agg(*[F.sum(n).alias(n) for n in C.sum_names(d)])


def prefix_moments(sig: DataFrame, d: int) -> DataFrame:
    """Sums over the points before and at each place (p_ columns), and the place; for signals of one task's size."""
    w = Window.partitionBy("signal_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    return sig.select("signal_id", "pos", *[F.sum(e).over(w).alias(f"p_{n}") for n, e in C.sum_terms(d).items()])


def range_cost(prefix: DataFrame, ranges: DataFrame, d: int, sloped: bool = True) -> DataFrame:
    """Adds cost to ranges (signal_id, start_pos, end_pos), by two equi-joins on the ends."""
    hi = prefix.select("signal_id", (F.col("pos") + 1).alias("end_pos"), *[F.col(f"p_{n}").alias(f"h_{n}") for n in C.sum_names(d)])
    lo = prefix.select("signal_id", (F.col("pos") + 1).alias("start_pos"), *[F.col(f"p_{n}").alias(f"l_{n}") for n in C.sum_names(d)])
    both = ranges.join(hi, ["signal_id", "end_pos"]).join(lo, ["signal_id", "start_pos"], "left")
    m = lambda n: F.col(f"h_{n}") - F.coalesce(F.col(f"l_{n}"), F.lit(0.0))
    return both.select(*ranges.columns, C.line_cost(m, d, sloped).alias("cost"))


def merge_gain(cells: DataFrame, d: int) -> DataFrame:
    """Discrepancy of each cell with the next: cost of both as one less the sum of their costs."""
    w = Window.partitionBy("signal_id").orderBy("cell")
    nxt = cells.select("*", *[F.lead(n).over(w).alias(f"next_{n}") for n in C.sum_names(d)]).where("next_n is not null")
    own, other = (lambda n: F.col(n)), (lambda n: F.col(f"next_{n}"))
    both = lambda n: F.col(n) + F.col(f"next_{n}")
    return nxt.select("signal_id", "cell", (C.line_cost(both, d) - C.line_cost(own, d) - C.line_cost(other, d)).alias("gain"))


def _in_piece(sig: DataFrame, pieces: DataFrame, cols: list[str]) -> DataFrame:
    """Points with columns of the piece that holds them; the piece's names are changed first, for both sides may stem from one frame."""
    p = pieces.select(F.col("signal_id").alias("__sid"), F.col("start_pos").alias("__lo"), F.col("end_pos").alias("__hi"), *[F.col(c).alias(f"__{c}") for c in cols])
    rows = sig.join(p, (F.col("signal_id") == F.col("__sid")) & (F.col("pos") >= F.col("__lo")) & (F.col("pos") < F.col("__hi")))
    return rows.select(*sig.columns, *[F.col(f"__{c}").alias(c) for c in cols])


def project(sig: DataFrame, pieces: DataFrame) -> DataFrame:
    """Each point with its piece and the line's value there: equi-join on the signal, range condition on the place."""
    joined = _in_piece(sig, pieces, ["seg_no", "intercept", "slope"])
    return joined.select("signal_id", "pos", "t", "x", "seg_no", C.line_value(F.col("intercept"), F.col("slope"), F.col("t")).alias("x_hat"))


def point_costs(projected: DataFrame) -> DataFrame:
    return projected.withColumn("error", C.sq_dist(F.col("x"), F.col("x_hat")))


def fitting_cost(sig: DataFrame, pieces: DataFrame) -> DataFrame:
    """Total squared error of a model on its signal."""
    return point_costs(project(sig, pieces)).groupBy("signal_id").agg(F.sum("error").alias("cost"))


def fit_pieces(sig: DataFrame, ranges: DataFrame, d: int) -> DataFrame:
    """Best lines of given pieces (signal_id, seg_no, start_pos, end_pos): one join, one aggregate."""
    rows = _in_piece(sig, ranges, ["seg_no", "start_pos", "end_pos"])
    sums = moments(rows, d, ["signal_id", "seg_no", "start_pos", "end_pos"])
    m = F.col
    return sums.select(
        "signal_id", "seg_no", "start_pos", "end_pos", F.array(*[C.intercept_of(m, i) for i in range(d)]).alias("intercept"), F.array(*[C.slope_of(m, i) for i in range(d)]).alias("slope"), C.line_cost(m, d).alias("sse")
    )


def uniform_pieces(sig: DataFrame, k: int) -> DataFrame:
    """Equal-size pieces of every signal."""
    n = sig.groupBy("signal_id").agg(F.count("*").alias("n"))
    seg = n.select("signal_id", "n", F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("seg_no"))
    return seg.select("signal_id", "seg_no", F.floor(F.col("seg_no") * F.col("n") / k).cast("bigint").alias("start_pos"), F.floor((F.col("seg_no") + 1) * F.col("n") / k).cast("bigint").alias("end_pos")).where("end_pos > start_pos")


def cut_curve(sig: DataFrame, d: int, gamma: int = 2, by: list[str] = ["signal_id"]) -> DataFrame:  # noqa: B006
    """Cost of cutting each group in two at each place, and uncut, and its points n: one window for all, no join."""
    run = Window.partitionBy(*by).orderBy("pos").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    whole = Window.partitionBy(*by)
    terms = C.sum_terms(d)
    cols = sig.select(*by, "pos", *[F.sum(e).over(run).alias(f"l_{n}") for n, e in terms.items()], *[F.sum(e).over(whole).alias(f"a_{n}") for n, e in terms.items()])
    left, right = (lambda n: F.col(f"l_{n}")), (lambda n: F.col(f"a_{n}") - F.col(f"l_{n}"))
    good = cols.where((F.col("l_n") >= gamma) & (F.col("a_n") - F.col("l_n") >= gamma))
    return good.select(*by, (F.col("pos") + 1).alias("cut"), (C.line_cost(left, d) + C.line_cost(right, d)).alias("cost"), C.line_cost(lambda n: F.col(f"a_{n}"), d).alias("whole"), F.col("a_n").cast("bigint").alias("n"))


def best_single_cut(sig: DataFrame, d: int, gamma: int = 2, by: list[str] = ["signal_id"]) -> DataFrame:  # noqa: B006
    """The exact two-piece model: cut, cost, gain; the smallest place wins ties."""
    best = cut_curve(sig, d, gamma, by).groupBy(*by).agg(F.min(F.struct("cost", "cut")).alias("b"), F.first("whole").alias("whole"))
    return best.select(*by, F.col("b.cut").alias("cut"), F.col("b.cost").alias("cost"), (F.col("whole") - F.col("b.cost")).alias("gain"))


def binary_split(sig: DataFrame, d: int, k: int, gamma: int = 2) -> DataFrame:
    """Cuts of k-1 rounds; each round cuts in every signal the piece of greatest gain.  Signals stay where the first shuffle put them."""
    pieces = sig.withColumn("lo", F.lit(0).cast("bigint"))
    cuts = None
    for _ in range(k - 1):
        found = best_single_cut(pieces, d, gamma, ["signal_id", "lo"])
        top = found.groupBy("signal_id").agg(F.max(F.struct("gain", -F.col("lo"), "cut")).alias("b")).select("signal_id", F.col("b.cut").alias("cut"))
        cuts = top if cuts is None else cuts.unionByName(top)
        pieces = sig.join(cuts.groupBy("signal_id").agg(F.sort_array(F.collect_list("cut")).alias("cs")), "signal_id")
        pieces = pieces.select("signal_id", "pos", "t", "x", F.coalesce(F.array_max(F.filter("cs", lambda c: c <= F.col("pos"))), F.lit(0)).cast("bigint").alias("lo"))
    return cuts


def sliding_curve(sig: DataFrame, d: int, window: int = 50) -> DataFrame:
    """Gain of cutting the window about each place in halves: three frames of one window pass."""
    half = window // 2
    w = Window.partitionBy("signal_id").orderBy("pos")
    terms = C.sum_terms(d)
    cols = sig.select("signal_id", "pos", *[F.sum(e).over(w.rowsBetween(-half, -1)).alias(f"l_{n}") for n, e in terms.items()], *[F.sum(e).over(w.rowsBetween(0, half - 1)).alias(f"r_{n}") for n, e in terms.items()])
    left, right = (lambda n: F.col(f"l_{n}")), (lambda n: F.col(f"r_{n}"))
    both = lambda n: F.col(f"l_{n}") + F.col(f"r_{n}")
    whole = cols.where((F.col("l_n") == half) & (F.col("r_n") == half))
    return whole.select("signal_id", F.col("pos").alias("cut"), (C.line_cost(both, d) - C.line_cost(left, d) - C.line_cost(right, d)).alias("gain"))


def peaks(curve: DataFrame) -> DataFrame:
    """Local maxima of a curve; the first place of a plateau."""
    w = Window.partitionBy("signal_id").orderBy("cut")
    marked = curve.withColumn("before", F.lag("gain").over(w)).withColumn("after", F.lead("gain").over(w))
    return marked.where("(before is null or gain > before) and (after is null or gain >= after)").select("signal_id", "cut", "gain")


def top_per_signal(df: DataFrame, n: int, by: list) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy("signal_id").orderBy(*by))).where(F.col("rank") <= n)

"""The registered queries of the segmentation library, and the SQL that they are compared with."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import experiments as X
from . import oracles as O
from .functions import columns as C
from .operators import apps, fit, giant, metrics
from .operators import segment as S
from .plans import regime, sql
from .sources import builders as B
from .sources import planted as P
from .sources.tables import cut_lineage, load_table, shared_folder
from .streaming import cuts as online

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(oracle: str | None = None):
    def register(f):
        QUERIES[f.__name__] = f
        if oracle:
            ORACLES[f.__name__] = oracle
        return f

    return register


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """Seven pieces of the hourly event counts, with their lines."""
    pieces = S.segment(B.hourly_signal(spark, sf), 7, "refine_then_merge")
    return pieces.select("signal_id", "seg_no", "start_pos", "end_pos", "n", "intercept", "slope", "sse")


def r6(c, scale: float = 1.0, digits: int = 6):
    return F.round((F.col(c) if isinstance(c, str) else c) / scale, digits)


def _lines_sql(signal: str, d: int) -> str:
    rows = [
        f"select signal_id, count(*) n, {i} dim, round(regr_intercept(x{i}, t), 4) + 0.0 intercept, round(regr_slope(x{i}, t), 4) + 0.0 slope, round((regr_syy(x{i}, t) - regr_sxy(x{i}, t) * regr_sxy(x{i}, t) / regr_sxx(x{i}, t)) / 1e6, 3) sse from s group by 1"
        for i in range(d)
    ]
    return f"with s as ({signal}) " + " union all ".join(rows)


@query(_lines_sql(O.USER, 2))
def line_fit_user(spark, sf):
    return fit.fit_lines(B.user_signal(spark, sf), 2).select("signal_id", "n", "dim", r6("intercept", 1, 4).alias("intercept"), (r6("slope", 1, 4) + F.lit(0.0)).alias("slope"), r6("sse", 1e6, 3).alias("sse"))


@query(_lines_sql(O.SUPPLIER, 4))
def line_fit_supplier(spark, sf):
    return fit.fit_lines(B.supplier_signal(spark, sf), 4).select("signal_id", "n", "dim", r6("intercept", 1, 4).alias("intercept"), (r6("slope", 1, 4) + F.lit(0.0)).alias("slope"), r6("sse", 1e6, 3).alias("sse"))


@query(f"with s as ({O.HOURLY}) select signal_id, count(*)::double n, sum(t) st, sum(t * t) stt, " + ", ".join(f"sum(x{i}) sx{i}, sum(t * x{i}) stx{i}, sum(x{i} * x{i}) sxx{i}" for i in range(5)) + " from s group by 1")
def moments_hourly(spark, sf):
    return fit.moments(B.hourly_signal(spark, sf), 5)


_TENS = "from e b join e a on a.signal_id = b.signal_id and a.e = b.e - 10 where b.e % 10 = 0"


@query(f"with {O.ends(O.USER, 2)} select a.signal_id, a.e start_pos, b.e end_pos, round({O.cost('a', 'b', 2)} / 1e6, 4) cost {_TENS}")
def prefix_cost_ranges(spark, sf):
    sig = B.user_signal(spark, sf)
    ranges = P.sizes(sig).select("signal_id", F.explode(F.sequence(F.lit(10), F.col("n"), F.lit(10))).alias("end_pos")).select("signal_id", (F.col("end_pos") - 10).alias("start_pos"), "end_pos")
    return fit.range_cost(fit.prefix_moments(sig, 2), ranges, 2).withColumn("cost", r6("cost", 1e6, 4))


@query(f"with {O.ends(O.USER, 2)} select a.signal_id, a.e start_pos, b.e end_pos, round({O.cost('a', 'b', 2, False)} / 1e6, 4) cost {_TENS}")
def piecewise_constant_cost(spark, sf):
    sig = B.user_signal(spark, sf)
    ranges = P.sizes(sig).select("signal_id", F.explode(F.sequence(F.lit(10), F.col("n"), F.lit(10))).alias("end_pos")).select("signal_id", (F.col("end_pos") - 10).alias("start_pos"), "end_pos")
    return fit.range_cost(fit.prefix_moments(sig, 2), ranges, 2, False).withColumn("cost", r6("cost", 1e6, 4))


_THIRDS = "thirds as (select signal_id, j seg_no, (j * n) // 3 lo, ((j + 1) * n) // 3 hi from (select signal_id, n::bigint n, unnest(range(3)) j from size))"


@query(f"with {O.ends(O.USER, 2)}, {_THIRDS} select signal_id, round(sum({O.cost('a', 'b', 2)}) / 1e6, 4) cost from thirds join e a using (signal_id) join e b using (signal_id) where a.e = lo and b.e = hi group by 1")
def fitting_cost(spark, sf):
    sig = B.user_signal(spark, sf)
    return fit.fitting_cost(sig, fit.fit_pieces(sig, fit.uniform_pieces(sig, 3), 2)).withColumn("cost", r6("cost", 1e6, 4))


@query(
    f"""with {O.ends(O.USER, 2)}, {_THIRDS}, l as (select signal_id, seg_no, lo, hi, {O.slope("a", "b", 0)} m0, {O.slope("a", "b", 1)} m1, a.n an, b.n bn, a.st ast, b.st bst, a.sx0 a0, b.sx0 b0, a.sx1 a1, b.sx1 b1 from thirds join e a using (signal_id) join e b using (signal_id) where a.e = lo and b.e = hi)
    select s.signal_id, s.pos, seg_no::int seg_no, round(((b0 - a0) - m0 * (bst - ast)) / (bn - an) + m0 * t, 5) hat0, round(((b1 - a1) - m1 * (bst - ast)) / (bn - an) + m1 * t, 5) hat1 from s join l on l.signal_id = s.signal_id and pos >= lo and pos < hi"""
)
def segment_projection(spark, sf):
    sig = B.user_signal(spark, sf)
    p = fit.project(sig, fit.fit_pieces(sig, fit.uniform_pieces(sig, 3), 2))
    return p.select("signal_id", "pos", "seg_no", F.round(F.col("x_hat")[0], 5).alias("hat0"), F.round(F.col("x_hat")[1], 5).alias("hat1"))


@query(f"with {O.ends(O.USER, 2)} select a.signal_id, a.e // 10 cell, round(({O.cost('a', 'c', 2)} - {O.cost('a', 'b', 2)} - {O.cost('b', 'c', 2)}) / 1e6, 4) gain from e a join e b on b.signal_id = a.signal_id and b.e = a.e + 10 join size z on z.signal_id = a.signal_id join e c on c.signal_id = a.signal_id and c.e = least(z.n, a.e + 20) where a.e % 10 = 0 and z.n > a.e + 10")
def merge_gain_cells(spark, sf):
    sig = B.user_signal(spark, sf).withColumn("cell", F.floor(F.col("pos") / 10))
    return fit.merge_gain(fit.moments(sig, 2, ["signal_id", "cell"]), 2).withColumn("gain", r6("gain", 1e6, 4))


@query(f"with {O.ends(O.USER, 2)}, f as (select a.signal_id, {', '.join(f'{O.slope(chr(97), chr(98), i)} m{i}, ((b.sx{i} - a.sx{i}) - ({O.slope(chr(97), chr(98), i)}) * (b.st - a.st)) / (b.n - a.n) c{i}' for i in range(2))} from e a join e b using (signal_id) where a.e = 0 and b.e = 20) select signal_id, round(sum((x0 - c0 - m0 * t) * (x0 - c0 - m0 * t) + (x1 - c1 - m1 * t) * (x1 - c1 - m1 * t)) / 1e6, 3) cost from s join f using (signal_id) group by 1")
def given_line_cost(spark, sf):
    """Cost of the first twenty points' line on the whole signal, from moments alone."""
    sig = B.user_signal(spark, sf)
    head = fit.moments(sig.where("pos < 20"), 2)
    line = head.select("signal_id", *[e for i in range(2) for e in (C.intercept_of(F.col, i).alias(f"c{i}"), C.slope_of(F.col, i).alias(f"m{i}"))])
    whole = fit.moments(sig, 2).join(line, "signal_id")
    return whole.select("signal_id", r6(C.given_line_cost(F.col, 2, [F.col("c0"), F.col("c1")], [F.col("m0"), F.col("m1")]), 1e6, 3).alias("cost"))


def _choose_sql(top: str, r: str) -> str:
    """Ways to choose r (0 to 3) out of ``top``; none out of fewer than r."""
    t = f"greatest({top}, 0)"
    return f"(case {r} when 0 then 1 when 1 then {t} when 2 then {t} * ({t} - 1) // 2 else {t} * greatest({t} - 1, 0) * greatest({t} - 2, 0) // 6 end)::bigint"


@query(f"with z as (select user_id::varchar signal_id, count(*) n from events group by 1) select signal_id, n, k::int k, g::int gamma, {_choose_sql('n - k * (g - 1) - 1', 'k - 1')} partitions, {_choose_sql('n - 2', 'k - 1')} printed from z, range(2, 5) b(k), range(1, 4) c(g)")
def partition_count(spark, sf):
    """Ways to cut each user's events into k pieces of gamma or more, and the count as the reference prints it; none where they don't fit."""
    n = B.load_table(spark, sf, "events", ["user_id"]).groupBy(F.col("user_id").cast("string").alias("signal_id")).agg(F.count("*").alias("n"))
    grid = n.withColumn("k", F.explode(F.array(*map(F.lit, (2, 3, 4))))).withColumn("gamma", F.explode(F.array(*map(F.lit, (1, 2, 3)))))
    choose = lambda top, k: F.aggregate(F.sequence(F.lit(1), k), F.lit(1).cast("bigint"), lambda acc, i: F.call_function("div", acc * F.greatest(top - k + i, F.lit(0)), i).cast("bigint"))
    k1 = F.col("k") - 1
    return grid.select("signal_id", "n", "k", "gamma", choose(F.col("n") - F.col("k") * (F.col("gamma") - 1) - 1, k1).alias("partitions"), choose(F.col("n") - 2, k1).alias("printed"))


_BEST_ONLY = f"with {O.ends(O.USER, 2)}, {O.best_cut(2)}"
_BEST_USER = f"with {O.ends(O.USER, 2)}, {O.best_cut(2)} select signal_id, cut, round(cost / 1e6, 4) cost from best"


@query(_BEST_USER)
def best_single_cut_user(spark, sf):
    return fit.best_single_cut(B.user_signal(spark, sf), 2).select("signal_id", "cut", r6("cost", 1e6, 4).alias("cost"))


def _planted(spark, sf):
    x, truth = P.planted(B.supplier_signal(spark, sf), P.SUPPLIER_SCALE, 2, None, "po", 2.0, 0.5)
    return x.drop("k"), truth


_PLANTED = O.planted(O.SUPPLIER, P.SUPPLIER_SCALE, 2, "po", 2.0, 0.5)
_BEST_PLANTED = f"with {_PLANTED}, {O.ends('select * from planted', 4)}, {O.best_cut(4)}"


@query(f"{_BEST_PLANTED} select best.signal_id, best.cut, start_pos true_cut from best join truth on truth.signal_id = best.signal_id and seg_no = 1")
def best_single_cut_planted(spark, sf):
    x, truth = _planted(spark, sf)
    best = fit.best_single_cut(x, 4).select("signal_id", "cut")
    return best.join(truth.where("seg_no = 1").select("signal_id", F.col("start_pos").alias("true_cut")), "signal_id")


@query(f"with {_PLANTED} select signal_id, seg_no, start_pos, end_pos from truth")
def planted_truth(spark, sf):
    return _planted(spark, sf)[1]


@query(O.binary_split(O.USER, 2, 4))
def binary_split_k4(spark, sf):
    return fit.binary_split(B.user_signal(spark, sf), 2, 4)


@query(O.binary_split(O.USER, 2, 4))
def binary_split_kernel(spark, sf):
    return S.cuts_of(S.segment(B.user_signal(spark, sf), 4, "binary_split")).select("signal_id", F.col("pos").alias("cut"))


_CURVE = f"curve as (select o.signal_id, o.e cut, {O.cost('a', 'b', 2)} - {O.cost('a', 'o', 2)} - {O.cost('o', 'b', 2)} gain from e o join e a on a.signal_id = o.signal_id and a.e = o.e - 10 join e b on b.signal_id = o.signal_id and b.e = o.e + 10)"


@query(f"with {O.ends(O.USER, 2)}, {_CURVE} select signal_id, cut, round(gain / 1e6, 4) gain from curve")
def sliding_contrast_curve(spark, sf):
    return fit.sliding_curve(B.user_signal(spark, sf), 2, 20).withColumn("gain", r6("gain", 1e6, 4))


@query(f"with {O.ends(O.USER, 2)}, {_CURVE}, l as (select *, lag(gain) over w before, lead(gain) over w after from curve window w as (partition by signal_id order by cut)) select signal_id, cut, round(gain / 1e6, 4) gain from l where (before is null or gain > before) and (after is null or gain >= after)")
def sliding_contrast_peaks(spark, sf):
    return fit.peaks(fit.sliding_curve(B.user_signal(spark, sf), 2, 20)).withColumn("gain", r6("gain", 1e6, 4))


@query(
    f"""with {O.ends(O.USER, 2)}, {_CURVE}, one as (select signal_id, max({{'gain': gain, 'left': -cut}}) b from curve group by 1),
    two as (select c.signal_id, max({{'gain': c.gain, 'left': -c.cut}}) b from curve c join one using (signal_id) where abs(c.cut + one.b.left) >= 10 group by 1)
    select signal_id, -b.left cut from one union all select signal_id, -b.left from two"""
)
def sliding_contrast_cuts(spark, sf):
    return S.cuts_of(S.segment(B.user_signal(spark, sf), 3, "sliding_contrast", window=20)).select("signal_id", F.col("pos").alias("cut"))


@query(
    f"""with {O.ends(O.USER, 2)},
    i as (select signal_id, n::bigint n, -1 i, 0::bigint lo, n::bigint hi from size union all
      select signal_id, n, i, least(a, b), greatest(a, b) from (select signal_id, n::bigint n, i, floor({O.draw("'0'", "signal_id", "'0'", "n::bigint::varchar", "i::varchar", "'a'")} * (n + 1))::bigint a, floor({O.draw("'0'", "signal_id", "'0'", "n::bigint::varchar", "i::varchar", "'b'")} * (n + 1))::bigint b from size, range(10) r(i))),
    c as (select i.signal_id, i.i, min({{'cost': {O.cost("a", "o", 2)} + {O.cost("o", "b", 2)}, 'cut': o.e}}) b, min({O.cost("a", "b", 2)}) whole from i join e a on a.signal_id = i.signal_id and a.e = lo join e b on b.signal_id = i.signal_id and b.e = hi
      join e o on o.signal_id = i.signal_id and o.e >= lo + 2 and o.e <= hi - 2 group by 1, 2)
    select signal_id, max({{'gain': whole - b.cost, 'i': -i, 'cut': b.cut}}).cut cut from c group by 1"""
)
def random_interval_split_k2(spark, sf):
    return S.cuts_of(S.segment(B.user_signal(spark, sf), 2, "random_interval_split", n_intervals=10)).select("signal_id", F.col("pos").alias("cut"))


@query(f"{O.layers(O.USER, 2, 3)}, top as (select l3.signal_id, l3.i c2, l3.cost cost from l3 join size z on z.signal_id = l3.signal_id and l3.j = z.n) select top.signal_id, l2.i c1, top.c2 c2, round(top.cost / 1e6, 4) cost from top join l2 on l2.signal_id = top.signal_id and l2.j = top.c2")
def optimal_partition_k3_user(spark, sf):
    p = S.segment(B.user_signal(spark, sf), 3, "optimal_partition")
    return p.groupBy("signal_id").agg(F.max(F.when(F.col("seg_no") == 1, F.col("start_pos"))).alias("c1"), F.max(F.when(F.col("seg_no") == 2, F.col("start_pos"))).alias("c2"), r6(F.first("cost"), 1e6, 4).alias("cost"))


@query(f"{O.layers(O.USER, 2, 3)} select signal_id, k, round(cost / 1e6, 4) cost from (" + " union all ".join(f"select l.signal_id, {k} k, l.cost from l{k} l join size z on z.signal_id = l.signal_id and l.j = z.n" for k in (1, 2, 3)) + ")")
def optimal_path_user(spark, sf):
    return S.optimal_paths(B.user_signal(spark, sf), 3).select("signal_id", "k", r6("cost", 1e6, 4).alias("cost"))


_BETA = 4e8


@query(f"{O.layers(O.USER, 2, 4)}, a as (" + " union all ".join(f"select l.signal_id, {k} k, l.cost from l{k} l join size z on z.signal_id = l.signal_id and l.j = z.n" for k in (1, 2, 3, 4)) + f") select signal_id, b.k::int k, round(b.cost / 1e6, 4) cost from (select signal_id, min({{'p': cost + {_BETA} * k, 'k': k, 'cost': cost}}) b from a group by 1)")
def penalized_user(spark, sf):
    p = S.segment(B.user_signal(spark, sf), 1, "penalized_optimal", beta=_BETA)
    return S.scores_of(p).select("signal_id", "k", r6("cost", 1e6, 4).alias("cost"))


@query()
def penalized_for_k3_user(spark, sf):
    p = S.segment(B.user_signal(spark, sf), 3, "penalized_optimal")
    return S.scores_of(p).select("signal_id", "k", "exact_k", r6("cost", 1e6, 4).alias("cost"))


@query(f"{O.layers(O.BENCHMARK, 1, 3)}, top as (select l3.signal_id, l3.i c2, l3.cost cost from l3 join size z on z.signal_id = l3.signal_id and l3.j = z.n) select l2.i c1, top.c2 c2, round(top.cost, 3) cost from top join l2 on l2.signal_id = top.signal_id and l2.j = top.c2")
def brute_force_k3_small(spark, sf):
    p = S.segment(B.benchmark_signal(spark, sf), 3, "brute_force")
    return p.groupBy("signal_id").agg(F.max(F.when(F.col("seg_no") == 1, F.col("start_pos"))).alias("c1"), F.max(F.when(F.col("seg_no") == 2, F.col("start_pos"))).alias("c2"), r6(F.first("cost"), 1, 3).alias("cost")).drop("signal_id")


@query(O.merge_path(O.USER, 2, 10, 1) + " select step::int step, signal_id, cut, round(gain / 1e6, 4) gain from m where step > 0")
def merge_path_user(spark, sf):
    return S.merge_paths(B.user_signal(spark, sf), 10).select("step", "signal_id", "cut", r6("gain", 1e6, 4).alias("gain"))


@query(O.merge_path(O.USER, 2, 10, 3) + " select signal_id, unnest(edges[2:len(edges) - 1])::bigint cut from m where len(edges) = 4")
def bottom_up_user(spark, sf):
    return S.cuts_of(S.segment(B.user_signal(spark, sf), 3, "bottom_up_merge", delta=10)).select("signal_id", F.col("pos").alias("cut"))


@query(O.merge_path(O.HOURLY, 5, 24, 7) + " select unnest(edges[2:len(edges) - 1])::bigint cut from m where len(edges) = 8")
def bottom_up_hourly(spark, sf):
    return S.cuts_of(S.segment(B.hourly_signal(spark, sf), 7, "bottom_up_merge", delta=24)).select(F.col("pos").alias("cut"))


@query(
    f"""with recursive {O.ends(O.USER, 2)}, w as (select b.signal_id, 0.2 * {O.cost("a", "b", 2)} budget, z.n from size z join e a on a.signal_id = z.signal_id and a.e = 0 join e b on b.signal_id = z.signal_id and b.e = z.n),
    g(cell, signal_id, lo, hi) as (select -1, signal_id, 0::bigint, 0::bigint from w union all
      select cell + 1, g.signal_id, g.hi, max(b.e)::bigint from g join w using (signal_id) join e a on a.signal_id = g.signal_id and a.e = g.hi join e b on b.signal_id = g.signal_id and b.e > g.hi
      where g.hi < w.n and (b.e <= g.hi + 2 or {O.cost("a", "b", 2)} <= w.budget) group by 1, 2, 3)
    select signal_id, cell::int cell, lo start_pos, hi end_pos from g where cell >= 0"""
)
def balanced_cells_user(spark, sf):
    return S.cells_of(B.user_signal(spark, sf), 3, budget=0.2).select("signal_id", "cell", "start_pos", "end_pos")


@query(f"with recursive {O.ends(O.USER, 2)}, {O.bicriteria(2, 3)} select signal_id, round(scale / 1e6, 4) scale from scale")
def bicriteria_cost(spark, sf):
    return S.cells_of(B.user_signal(spark, sf), 3).where("cell = 0").select("signal_id", r6("scale", 1e6, 4).alias("scale"))


_FACTORS = {"10": "10.0", "50": "50.0", "log": "100 * log2(n)"}


@query(" union all ".join(f"(select signal_id, '{f}' sf, n_cells::int n_cells, round(cost / 1e6, 4) cost from ({O.over_cells(O.USER, 2, x)} select * from top))" for f, x in _FACTORS.items()))
def optimal_over_cells_user(spark, sf):
    sig = B.user_signal(spark, sf)
    parts = [S.scores_of(S.segment(sig, 3, "optimal_over_cells", sf=f)).withColumn("sf", F.lit(str(f))) for f in (10, 50, "log")]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).select("signal_id", "sf", "n_cells", r6("cost", 1e6, 4).alias("cost"))


@query(f"{O.over_cells(O.USER, 2, '10.0')} select signal_id, n_cells::int n_cells, round(cost / 1e6, 4) cost from top")
def optimal_over_cells_svd(spark, sf):
    return S.scores_of(S.segment(B.user_signal(spark, sf), 3, "optimal_over_cells", sf=10, compress="svd")).select("signal_id", "n_cells", r6("cost", 1e6, 4).alias("cost"))


_THREE = "select signal_id, 0 run, n::bigint // 3 c1, (2 * n::bigint) // 3 c2 from size"
_REFINED = O.refinement(O.USER, 2, 3, _THREE)


@query(_REFINED + " select signal_id, c1::bigint c1, c2::bigint c2 from r where sweep = 1")
def refine_one_sweep(spark, sf):
    p = S.segment(B.user_signal(spark, sf), 3, "refine_boundaries", order="left_to_right", max_iter=1)
    return p.groupBy("signal_id").agg(F.max(F.when(F.col("seg_no") == 1, F.col("start_pos"))).alias("c1"), F.max(F.when(F.col("seg_no") == 2, F.col("start_pos"))).alias("c2"))


@query(_REFINED + " select signal_id, c1::bigint c1, c2::bigint c2, sweep::int sweeps, round(cost / 1e6, 4) cost from r qualify sweep = max(sweep) over (partition by signal_id)")
def refine_fixpoint(spark, sf):
    p = S.segment(B.user_signal(spark, sf), 3, "refine_boundaries", order="left_to_right")
    return p.groupBy("signal_id").agg(F.max(F.when(F.col("seg_no") == 1, F.col("start_pos"))).alias("c1"), F.max(F.when(F.col("seg_no") == 2, F.col("start_pos"))).alias("c2"), F.first("sweeps").alias("sweeps"), r6(F.first("cost"), 1e6, 4).alias("cost"))


@query(_REFINED + " select signal_id, sweep::int sweep, round(cost / 1e6, 4) cost from r")
def refine_trace(spark, sf):
    p = S.segment(B.user_signal(spark, sf), 3, "refine_boundaries", order="left_to_right")
    return S.scores_of(p).select("signal_id", F.posexplode("trace").alias("sweep", "cost")).withColumn("cost", r6("cost", 1e6, 4))


_STARTS = f"select signal_id, run, (floor({O.draw(repr('0'), 'signal_id', 'run::varchar', repr('0'))} * (n - 3)) + 2)::bigint c1 from (select signal_id, n::bigint n, unnest(range(5)) run from size)"


@query(O.refinement(O.USER, 2, 2, _STARTS) + ", f as (select * from r qualify sweep = max(sweep) over (partition by signal_id, run)) select signal_id, round(min(cost) / 1e6, 4) cost from f group by 1")
def multistart_best(spark, sf):
    return S.scores_of(S.segment(B.user_signal(spark, sf), 2, "multistart_refine", q=5)).select("signal_id", r6("cost", 1e6, 4).alias("cost"))


@query()
def refine_then_merge_orders(spark, sf):
    sig = apps.standardize(B.daily_orders(spark, sf), 2)
    return S.cuts_of(S.segment(sig, 7, "refine_then_merge")).select("pos", F.lit("plain").alias("kind")).unionByName(S.cuts_of(S.segment(sig, 7, "refine_then_merge", polish=True)).select("pos", F.lit("polished").alias("kind")))


_LAST = "f as (select * from r qualify sweep = max(sweep) over (partition by signal_id, run))"


@query(O.refinement(O.USER, 2, 3, f"select signal_id, n_cells run, c1, c2 from ({O.over_cells(O.USER, 2, '10.0')} select * from top)", shuffled=True) + f", {_LAST} select signal_id, run::int n_cells, sweep::int sweeps, round(cost / 1e6, 4) cost from f")
def cells_then_refine_user(spark, sf):
    return S.scores_of(S.segment(B.user_signal(spark, sf), 3, "cells_then_refine")).select("signal_id", "n_cells", "sweeps", r6("cost", 1e6, 4).alias("cost"))


@query(O.refinement(O.USER, 2, 3, _THREE, shuffled=True) + f", {_LAST} select signal_id, c1::bigint c1, c2::bigint c2, sweep::int sweeps, round(cost / 1e6, 4) cost from f")
def refine_shuffled_user(spark, sf):
    """Pairs visited in an order drawn anew each sweep."""
    p = S.segment(B.user_signal(spark, sf), 3, "refine_boundaries")
    return p.groupBy("signal_id").agg(F.max(F.when(F.col("seg_no") == 1, F.col("start_pos"))).alias("c1"), F.max(F.when(F.col("seg_no") == 2, F.col("start_pos"))).alias("c2"), F.first("sweeps").alias("sweeps"), r6(F.first("cost"), 1e6, 4).alias("cost"))


@query(
    O.refinement(O.USER, 2, 3, _THREE, shuffled=True)
    + f""", {_LAST}, h as (select f.*, {O.cost("a", "c", 2)} - {O.cost("a", "b", 2)} - {O.cost("b", "c", 2)} g1, {O.cost("b", "z", 2)} - {O.cost("b", "c", 2)} - {O.cost("c", "z", 2)} g2 from f
    join e a on a.signal_id = f.signal_id and a.e = 0 join e b on b.signal_id = f.signal_id and b.e = c1 join e c on c.signal_id = f.signal_id and c.e = c2 join e z on z.signal_id = f.signal_id and z.e = f.n)
    select signal_id, case when g1 <= g2 then c2 else c1 end::bigint cut from h"""
)
def refine_then_merge_user(spark, sf):
    """Three even pieces refined in drawn order, the two of least discrepancy fused."""
    return S.cuts_of(S.segment(B.user_signal(spark, sf), 2, "refine_then_merge", k_init=3)).select("signal_id", F.col("pos").alias("cut"))


@query(O.refinement(O.USER, 2, 3, f"select signal_id, 0 run, min(cut) c1, max(cut) c2 from ({O.binary_split(O.USER, 2, 3)}) group by 1", shuffled=True) + f", {_LAST} select signal_id, sweep::int sweeps, round(cost / 1e6, 4) cost from f")
def warm_start_user(spark, sf):
    """Refinement from another method's cuts."""
    sig = B.user_signal(spark, sf)
    start = S.cut_arrays(S.segment(sig, 3, "binary_split"))
    return S.scores_of(S.segment(sig, 3, "refine_boundaries", init=start)).select("signal_id", "sweeps", r6("cost", 1e6, 4).alias("cost"))


def _best_two(sloped: bool) -> str:
    return f"select l.signal_id, min({O.cost('o', 'l', 2, sloped)} + {O.cost('l', 'h', 2, sloped)}) cost from e l join size z on z.signal_id = l.signal_id join e o on o.signal_id = l.signal_id and o.e = 0 join e h on h.signal_id = l.signal_id and h.e = z.n where l.e >= 2 and l.e <= z.n - 2 group by 1"


@query(f"with {O.ends(O.USER, 2)} select signal_id, 'l2_linear' model, round(cost / 1e6, 3) cost from ({_best_two(True)}) union all select signal_id, 'l2_constant', round(cost / 1e6, 3) from ({_best_two(False)})")
def cost_models_user(spark, sf):
    """Mean and line costs of the best two pieces."""
    sig = B.user_signal(spark, sf)
    parts = [S.scores_of(S.segment(sig, 2, "binary_split", cost=c)).withColumn("model", F.lit(c)) for c in ("l2_linear", "l2_constant")]
    return parts[0].unionByName(parts[1]).select("signal_id", "model", r6("cost", 1e6, 3).alias("cost"))


@query()
def absolute_cost_user(spark, sf):
    """Absolute-error line cost of the best two pieces; signals too long for it have an error."""
    return S.segment(B.user_signal(spark, sf), 2, "binary_split", cost="l1_linear").where("seg_no = 0 or error is not null").select("signal_id", r6("cost", 1e3, 3).alias("cost"), "error")


@query(f"with {O.ends(O.USER, 2)} select z.signal_id, round({O.cost('a', 'b', 2)} / 1e6, 4) cost from size z join e a on a.signal_id = z.signal_id and a.e = 0 join e b on b.signal_id = z.signal_id and b.e = z.n")
def one_piece_user(spark, sf):
    return S.scores_of(S.segment(B.user_signal(spark, sf), 1, "one_piece")).select("signal_id", r6("cost", 1e6, 4).alias("cost"))


@query("select conv_id::varchar signal_id, count(*) || ' points don''t hold 3 pieces of 2' error from conversations group by 1 having count(*) < 6")
def infeasible_conversations(spark, sf):
    """Conversations too short for three pieces come back as error rows."""
    return S.segment(B.conversation_signal(spark, sf), 3, "refine_boundaries").where("error is not null").select("signal_id", "error")


@query()
def unknown_k_user(spark, sf):
    return S.scores_of(S.segment(B.user_signal(spark, sf), 6, "unknown_k")).select("signal_id", "k", r6("cost", 1e6, 4).alias("cost"))


@query(f"with {O.ends('select signal_id, (pos // 2)::bigint pos, t, x0, x1 from (' + O.USER + ') where pos % 2 = 0', 2)}, {O.best_cut(2)} select signal_id, cut, round(cost / 1e6, 4) cost from best")
def downsampled_cut(spark, sf):
    return fit.best_single_cut(apps.downsample(B.user_signal(spark, sf), 2), 2).select("signal_id", "cut", r6("cost", 1e6, 4).alias("cost"))


@query()
def pca_variance(spark, sf):
    return apps.pca_variance(B.frame_signal(spark, sf), 8).withColumn("share", r6("share"))


@query(f"with {O.ends(O.USER, 2)}, {_THIRDS} select signal_id, seg_no::int seg_no, f::int frame, (lo + ((2 * f + 1) * (hi - lo)) // 10)::bigint pos from thirds, range(5) r(f)")
def summary_frames(spark, sf):
    return apps.summarize(fit.uniform_pieces(B.user_signal(spark, sf), 3), 5)


_HATS = f"""with {O.ends(O.USER, 2)}, {_THIRDS}, l as (select signal_id, seg_no, lo, hi, {O.slope("a", "b", 0)} m0, {O.slope("a", "b", 1)} m1, a.n an, b.n bn, a.st ast, b.st bst, a.sx0 a0, b.sx0 b0, a.sx1 a1, b.sx1 b1 from thirds join e a using (signal_id) join e b using (signal_id) where a.e = lo and b.e = hi),
h as (select s.signal_id, pos, seg_no, x0 - (((b0 - a0) - m0 * (bst - ast)) / (bn - an) + m0 * t) r0, x1 - (((b1 - a1) - m1 * (bst - ast)) / (bn - an) + m1 * t) r1 from s join l on l.signal_id = s.signal_id and pos >= lo and pos < hi)"""


@query(f"{_HATS}, q as (select *, sqrt(r0 * r0 + r1 * r1) / sqrt(avg(r0 * r0 + r1 * r1) over (partition by signal_id, seg_no)) ratio from h) select signal_id, pos, seg_no::int seg_no, round(ratio, 5) ratio from q where ratio > 2.5")
def residual_anomalies(spark, sf):
    sig = B.user_signal(spark, sf)
    return apps.residual_anomalies(sig, fit.fit_pieces(sig, fit.uniform_pieces(sig, 3), 2), 2.5).withColumn("ratio", r6("ratio", 1, 5))


@query(
    f"""with d as (select source signal_id, doc_id, row_number() over (partition by source order by doc_id) - 1 pos from documents), n as (select signal_id, count(*) n from d group by 1),
    p as (select signal_id, j::int seg_no, (j * n) // 8 start_pos, ((j + 1) * n) // 8 end_pos from n, range(8) r(j))
    select signal_id, seg_no, start_pos::bigint start_pos, end_pos::bigint end_pos from p where exists (select 1 from d join labels using (doc_id) where toxic = 1 and d.signal_id = p.signal_id and pos >= start_pos and pos < end_pos)"""
)
def expand_tags(spark, sf):
    """Pieces of each source's documents that hold a document tagged toxic."""
    docs = load_table(spark, sf, "documents", ["doc_id", "source"]).select(F.col("source").alias("signal_id"), "doc_id")
    placed = B.with_position(docs, "signal_id", ["doc_id"])
    tags = placed.join(load_table(spark, sf, "labels").where("toxic = 1").select("doc_id"), "doc_id").select("signal_id", "pos")
    return apps.expand_tags(fit.uniform_pieces(placed, 8), tags)


@query(f"with {O.ends(O.USER, 2)}, {_THIRDS} " + " union all ".join(f"select signal_id, seg_no::int seg_no, {i} dim, round({O.slope('a', 'b', i)}, 6) slope, sign(round({O.slope('a', 'b', i)}, 9))::int direction from thirds join e a using (signal_id) join e b using (signal_id) where a.e = lo and b.e = hi" for i in range(2)))
def describe_pieces(spark, sf):
    sig = B.user_signal(spark, sf)
    p = fit.fit_pieces(sig, fit.uniform_pieces(sig, 3), 2).withColumns({"method": F.lit("uniform"), "t_start": F.col("start_pos").cast("double"), "n": F.col("end_pos") - F.col("start_pos")})
    return apps.describe_pieces(p).select("signal_id", "seg_no", "dim", r6("slope").alias("slope"), "direction")


@query(f"""{_BEST_ONLY}, ev as (select user_id::varchar signal_id, (row_number() over (partition by user_id order by ts, event_id) - 1)::double "at", event_type from events) select best.signal_id, cut::double cut_t, "at" from best join ev on ev.signal_id = best.signal_id and event_type = 'error' and abs("at" - cut) <= 3""")
def correlate_cuts(spark, sf):
    """Cuts with error events of the same user at most three places away."""
    cuts = fit.best_single_cut(B.user_signal(spark, sf), 2).select("signal_id", F.col("cut").cast("double").alias("t"))
    ev = B.with_position(load_table(spark, sf, "events", ["user_id", "ts", "event_id", "event_type"]).withColumn("signal_id", F.col("user_id").cast("string")), "signal_id", ["ts", "event_id"])
    return apps.correlate_cuts(cuts, ev.where("event_type = 'error'").select("signal_id", F.col("pos").cast("double").alias("at")), 3.0)


def _two(spark, sf):
    """Truth of the planted suppliers; the best cut and the middle one as two methods."""
    x, truth = _planted(spark, sf)
    middle = F.floor(F.col("n") / 2)
    ends = fit.cut_curve(x, 4).groupBy("signal_id").agg(F.min(F.struct("cost", "cut")).alias("b"), F.max(F.when(F.col("cut") == middle, F.struct("cost", "cut"))).alias("m"), F.max("n").alias("n"))
    both = ends.select("signal_id", "n", F.explode(F.array(F.struct(F.lit("best").alias("method"), "b.cost", "b.cut"), F.struct(F.lit("middle").alias("method"), "m.cost", "m.cut"))).alias("c")).select("signal_id", "n", "c.*")
    rows = F.explode(F.array(F.struct(F.lit(0).alias("seg_no"), F.lit(0).cast("bigint").alias("start_pos"), F.col("cut").alias("end_pos")), F.struct(F.lit(1).alias("seg_no"), F.col("cut").alias("start_pos"), F.col("n").alias("end_pos")))).alias("p")
    return cut_lineage(truth), cut_lineage(both.select("signal_id", "method", "cost", rows).select("signal_id", "method", "cost", "p.*"))  # a few rows a signal, read several times


_TWO = f"""{_BEST_PLANTED},
cutsof as (select signal_id, 'best' as "method", cut, cost from best union all
  select l.signal_id, 'middle', l.e, {O.cost("o", "l", 4)} + {O.cost("l", "h", 4)} from e l join size z on z.signal_id = l.signal_id and l.e = z.n // 2 join e o on o.signal_id = l.signal_id and o.e = 0 join e h on h.signal_id = l.signal_id and h.e = z.n),
pred as (select signal_id, "method", cost, 0 seg_no, 0 lo, cut hi from cutsof union all select signal_id, "method", cost, 1, cut, n from cutsof join size using (signal_id)),
over_ as (select t.signal_id, "method", t.seg_no ts, p.seg_no ps, least(end_pos, hi) - greatest(start_pos, lo) shared, end_pos - start_pos tn, hi - lo pn from truth t join pred p on p.signal_id = t.signal_id and start_pos < hi and lo < end_pos),
cov as (select signal_id, "method", sum(j * tn) / sum(tn) covering from (select signal_id, "method", ts, max(shared / (tn + pn - shared)) j, max(tn) tn from over_ group by 1, 2, 3) group by 1, 2),
tt as (select signal_id, "method", sum(s * s) v from (select signal_id, "method", ts, sum(shared) s from over_ group by 1, 2, 3) group by 1, 2),
pp as (select signal_id, "method", sum(s * s) v from (select signal_id, "method", ps, sum(shared) s from over_ group by 1, 2, 3) group by 1, 2),
rnd as (select o.signal_id, o."method", (n * (n - 1) - tt.v - pp.v + 2 * b) / (n * (n - 1)) rand from (select signal_id, "method", sum(shared) n, sum(shared * shared) b from over_ group by 1, 2) o join tt using (signal_id, "method") join pp using (signal_id, "method")),
score as (select cov.signal_id, cov."method", covering, rand, cost from cov join rnd using (signal_id, "method") join cutsof using (signal_id, "method"))"""


def _scores(spark, sf):
    truth, pred = _two(spark, sf)
    costs = pred.where("seg_no = 0").select("signal_id", "method", "cost")
    return metrics.covering(truth, pred).join(metrics.rand_index(truth, pred), ["signal_id", "method"]).join(costs, ["signal_id", "method"])


@query(f'{_TWO} select signal_id, "method", round(covering, 6) covering from cov')
def covering_scores(spark, sf):
    return metrics.covering(*_two(spark, sf)).withColumn("covering", r6("covering"))


@query(f'{_TWO} select signal_id, "method", round(rand, 6) rand from rnd')
def rand_scores(spark, sf):
    return metrics.rand_index(*_two(spark, sf)).withColumn("rand", r6("rand"))


@query(
    f"""{_BEST_ONLY}, p as (select s.signal_id, pos, pos >= cut a, pos >= (size.n // 2) b from s join best using (signal_id) join size using (signal_id))
    select x.signal_id, round(avg(case when (x.a = y.a) = (x.b = y.b) then 1.0 else 0.0 end), 6) rand from p x join p y on x.signal_id = y.signal_id and x.pos <> y.pos group by 1"""
)
def rand_scores_pairs(spark, sf):
    """The index from overlap sizes; the SQL compares every pair of points."""
    sig = B.user_signal(spark, sf)
    n = P.sizes(sig)
    two = lambda cut: F.explode(F.array(F.struct(F.lit(0).alias("seg_no"), F.lit(0).cast("bigint").alias("start_pos"), cut.cast("bigint").alias("end_pos")), F.struct(F.lit(1).alias("seg_no"), cut.cast("bigint").alias("start_pos"), F.col("n").alias("end_pos")))).alias("p")
    a = fit.best_single_cut(sig, 2).join(n, "signal_id").select("signal_id", two(F.col("cut"))).select("signal_id", "p.*")
    b = n.select("signal_id", two(F.floor(F.col("n") / 2))).select("signal_id", "p.*")
    return metrics.rand_index(a, b).select("signal_id", r6("rand").alias("rand"))


@query(f'{_TWO} select "method", round(1 - covering, 6) deficit, round(max(share), 6) share from (select *, cume_dist() over (partition by "method" order by 1 - covering) share from cov) group by 1, 2')
def deficit_cdf(spark, sf):
    d = metrics.deficit_cdf(_scores(spark, sf), "covering").select("method", r6("deficit").alias("deficit"), "share")
    return d.groupBy("method", "deficit").agg(r6(F.max("share")).alias("share"))


@query(f'{_TWO} select "method", round(avg(case when covering >= 0.975 then 1.0 else 0.0 end), 6) share from cov group by 1')
def share_at_least(spark, sf):
    return metrics.share_at_least(_scores(spark, sf), "covering").withColumn("share", r6("share"))


@query(f'{_TWO} select c."method", round(avg(c.cost / b.cost), 6) mean_ratio, round(avg(c.cost) / avg(b.cost), 6) ratio_of_means, count(*) signals from cutsof c join cutsof b on b.signal_id = c.signal_id and b."method" = \'best\' group by 1')
def relative_cost(spark, sf):
    return metrics.relative_cost(_scores(spark, sf), "best").withColumns({"mean_ratio": r6("mean_ratio"), "ratio_of_means": r6("ratio_of_means")})


@query(f"""{_TWO} select p.signal_id, p."method", 1::bigint n_true, 1::bigint n_pred, (case when abs(p.lo - t.start_pos) <= 5 then 1 else 0 end)::bigint hits, (case when abs(p.lo - t.start_pos) <= 5 then 1.0 else 0.0 end)::double f1 from pred p join truth t on t.signal_id = p.signal_id and t.seg_no = 1 where p.seg_no = 1""")
def cut_f1(spark, sf):
    return metrics.cut_f1(*_two(spark, sf), 5)


_DIGIT = "right(signal_id, 1)"


@query(f'{_TWO} select {_DIGIT} digit, "method", round(avg(cost), 4) cost, round(avg(covering), 6) covering, round(avg(rand), 6) rand, count(*) signals, grouping({_DIGIT}, "method")::bigint "level" from score group by rollup ({_DIGIT}, "method")')
def score_rollup(spark, sf):
    s = metrics.score_rollup(_scores(spark, sf).withColumn("digit", F.right("signal_id", F.lit(1))), ["digit", "method"])
    return s.withColumns({"cost": r6("cost", 1, 4), "covering": r6("covering"), "rand": r6("rand")})


@query(f'{_TWO} select {_DIGIT} digit, "method", round(avg(cost), 4) cost, round(avg(covering), 6) covering, round(avg(rand), 6) rand, count(*) signals, grouping({_DIGIT}, "method")::bigint "level" from score group by cube ({_DIGIT}, "method")')
def score_cube(spark, sf):
    s = metrics.score_rollup(_scores(spark, sf).withColumn("digit", F.right("signal_id", F.lit(1))), ["digit", "method"], "cube")
    return s.withColumns({"cost": r6("cost", 1, 4), "covering": r6("covering"), "rand": r6("rand")})


@query(f'{_TWO} select signal_id, round(max(covering) filter ("method" = \'best\'), 6) best, round(max(covering) filter ("method" = \'middle\'), 6) middle from cov group by 1')
def pivot_scores(spark, sf):
    return metrics.pivot_scores(_scores(spark, sf), ["best", "middle"]).withColumns({"best": r6("best"), "middle": r6("middle")})


_CENTS = "count(*) n, sum(round(o_totalprice * 100)::bigint)::bigint cents"


@query(f"select c_mktsegment signal_id, epoch_us(date_trunc('week', o_orderdate))::bigint bucket, {_CENTS} from orders join customer on o_custkey = c_custkey group by 1, 2")
def weekly_segment_signal(spark, sf):
    return B.weekly_segment(spark, sf).withColumn("bucket", C.micros("bucket"))


@query(f"select r_name || '/' || n_name signal_id, epoch_us(date_trunc('month', o_orderdate))::bigint bucket, {_CENTS} from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1, 2")
def nation_month_signal(spark, sf):
    return B.monthly_nation(spark, sf).withColumn("bucket", C.micros("bucket"))


@query("""with b as (select date_trunc('hour', ts) bucket, count(*) filter (event_type = 'click') click from events group by 1), g as (select unnest(generate_series(min(bucket), max(bucket), interval 1 hour)) bucket from b)
select epoch_us(g.bucket)::bigint bucket, coalesce(click, 0)::bigint click from g left join b using (bucket)""")
def gap_filled_hours(spark, sf):
    return B.fill_gaps(B.hourly_buckets(spark, sf), "hour", list(B.KINDS)).select(C.micros("bucket").alias("bucket"), "click")


@query(O.HOURLY)
def event_type_vector(spark, sf):
    return B.hourly_signal(spark, sf).select("signal_id", "pos", "t", *[F.col("x")[i].alias(f"x{i}") for i in range(5)])


@query("select source signal_id, (row_number() over (partition by source order by d.doc_id) - 1)::bigint pos, length(text)::double x0, (length(text) - length(replace(text, chr(10), '')) + 1)::double x1, coalesce(quality, 0)::double x2 from documents d left join labels l on l.doc_id = d.doc_id")
def doc_source_signal(spark, sf):
    return B.document_signal(spark, sf).select("signal_id", "pos", *[F.col("x")[i].alias(f"x{i}") for i in range(3)])


@query("select (row_number() over (order by page_id) - 1)::bigint pos, length(html)::double x0, (length(html) - length(replace(html, '<', '')))::double x1, length(url)::double x2 from pages")
def page_signal(spark, sf):
    return B.page_signal(spark, sf).select("pos", *[F.col("x")[i].alias(f"x{i}") for i in range(3)])


@query("select conv_id::varchar signal_id, (row_number() over (partition by conv_id order by turn) - 1)::bigint pos, length(text)::double x0 from conversations")
def conversation_signal(spark, sf):
    return B.conversation_signal(spark, sf).select("signal_id", "pos", F.col("x")[0].alias("x0"))


@query("select l_suppkey::varchar signal_id, count(*) n, 4 d, count(*) * 12 * 8 bytes from lineitem group by 1")
def signal_profile(spark, sf):
    return regime.signal_profile(B.supplier_signal(spark, sf))


@query("with n as (select l_suppkey, count(*) n from lineitem group by 1) select count(*) signals, approx_signals, quantile_cont(n, 0.5) median, round(quantile_cont(n, 0.99), 6) most from n, (select 1::boolean approx_signals) group by approx_signals")
def signal_sizes(spark, sf):
    """What a planner needs to know: signals (exact, and whether the sketch comes within a tenth), quantiles of their lengths."""
    p = regime.signal_profile(B.supplier_signal(spark, sf))
    return p.agg(F.count("*").alias("signals"), (F.abs(F.approx_count_distinct("signal_id", 0.02) / F.count("*") - 1) < 0.1).alias("approx_signals"), F.percentile("n", F.lit(0.5)).alias("median"), F.round(F.percentile("n", F.lit(0.99)), 6).alias("most"))


_KINDS = ("click", "error", "view")


@query("with p as (select *, row_number() over (partition by user_id order by ts, event_id) - 1 pos from events) select user_id::varchar signal_id, pos, " + ", ".join(f"case when event_type = '{k}' then round(value * 100) else 0.0 end {k}" for k in _KINDS) + " from p")
def long_rows_signal(spark, sf):
    """One row a value and dimension, to vectors."""
    ev = load_table(spark, sf, "events", ["user_id", "ts", "event_id", "event_type", "value"]).withColumn("signal_id", F.col("user_id").cast("string"))
    rows = B.with_position(ev, "signal_id", ["ts", "event_id"]).select("signal_id", "pos", F.col("event_type").alias("dim"), F.round(F.col("value") * 100).alias("v"))
    return B.from_long(rows, "dim", "v", list(_KINDS)).select("signal_id", "pos", *[F.col("x")[i].alias(k) for i, k in enumerate(_KINDS)])


@query(f"with s as ({O.USER}) select signal_id, pos, x0, x1 from s where t >= 10 and t < 30")
def restricted_wide_signal(spark, sf):
    """Columns to vectors, a span of time kept."""
    wide = B.user_signal(spark, sf).select("signal_id", "pos", "t", F.col("x")[0].alias("a"), F.col("x")[1].alias("b"))
    return apps.restrict(B.from_wide(wide, ["a", "b"]), 10, 30).select("signal_id", "pos", F.col("x")[0].alias("x0"), F.col("x")[1].alias("x1"))


@query("""with b as (select date_trunc('hour', ts) bucket, count(*) filter (event_type = 'click') click from events group by 1), g as (select unnest(generate_series(min(bucket), max(bucket), interval 1 hour)) bucket from b)
  select epoch_us(g.bucket)::bigint bucket, last_value(click ignore nulls) over (order by g.bucket)::bigint click from g left join b using (bucket)""")
def carried_hours(spark, sf):
    """Gaps filled with the last known value."""
    return B.fill_gaps(B.hourly_buckets(spark, sf), "hour", list(B.KINDS), "ffill").select(C.micros("bucket").alias("bucket"), "click")


@query(f"with {O.ends(O.USER, 2)}, {_CURVE} select signal_id, cut, rank::int rank from (select *, row_number() over (partition by signal_id order by gain desc, cut) rank from curve) where rank <= 2")
def top_contrasts(spark, sf):
    return fit.top_per_signal(fit.sliding_curve(B.user_signal(spark, sf), 2, 20), 2, [F.desc("gain"), "cut"]).select("signal_id", "cut", "rank")


@query(f"with {O.ends(O.USER, 2)}, {_THIRDS} select signal_id, seg_no::int seg_no, lo::bigint start_pos, hi::bigint end_pos, (seg_no % 2)::int shade from thirds")
def shaded_pieces(spark, sf):
    return apps.shade(fit.uniform_pieces(B.user_signal(spark, sf), 3))


_AGREE = f"with {O.ends(O.USER, 2)}, {O.best_cut(2)}, {_CURVE}, one as (select signal_id, max({{'gain': gain, 'left': -cut}}) b from curve group by 1)"


def _two_methods(spark, sf):
    sig = B.user_signal(spark, sf)
    top = fit.sliding_curve(sig, 2, 20).groupBy("signal_id").agg(F.max(F.struct("gain", -F.col("cut"), "cut")).alias("b"))
    return fit.best_single_cut(sig, 2).select("signal_id", F.col("cut").alias("pos")), top.select("signal_id", F.col("b.cut").alias("pos"))


@query(f"{_AGREE} select signal_id, cut pos from best union select signal_id, -b.left from one")
def method_union(spark, sf):
    return metrics.agree(*_two_methods(spark, sf), "union")


@query(f"{_AGREE} select signal_id, cut pos from best except select signal_id, -b.left from one")
def method_difference(spark, sf):
    return metrics.agree(*_two_methods(spark, sf), "except")


@query(f"with {O.ends(O.USER, 2)}, {O.best_cut(2)}, {_CURVE}, one as (select signal_id, max({{'gain': gain, 'left': -cut}}) b from curve group by 1) select signal_id, cut pos from best intersect select signal_id, -b.left from one")
def method_agreement(spark, sf):
    sig = B.user_signal(spark, sf)
    a = fit.best_single_cut(sig, 2).select("signal_id", F.col("cut").alias("pos"))
    top = fit.sliding_curve(sig, 2, 20).groupBy("signal_id").agg(F.max(F.struct("gain", -F.col("cut"), "cut")).alias("b")).select("signal_id", F.col("b.cut").alias("pos"))
    return metrics.agree(a, top)


@query(f"{_HATS}, e2 as (select signal_id, pos, seg_no, r0 * r0 + r1 * r1 error from h) select signal_id, pos, seg_no::int seg_no, round(error / 1e6, 3) error from e2 order by error desc, signal_id, pos limit 20")
def worst_residuals(spark, sf):
    sig = B.user_signal(spark, sf)
    return apps.worst_residuals(sig, fit.fit_pieces(sig, fit.uniform_pieces(sig, 3), 2), 20).withColumn("error", r6("error", 1e6, 3))


@query(f"with {O.ends(O.USER, 2)}, {_THIRDS} select s.signal_id, s.pos, seg_no::int seg_no from s join thirds l on l.signal_id = s.signal_id and pos >= lo and pos < hi")
def range_join_blocks(spark, sf):
    sig = B.user_signal(spark, sf)
    return apps.range_join_blocks(sig.select("signal_id", "pos"), fit.uniform_pieces(sig, 3), 16).select("signal_id", "pos", "seg_no")


@query(f"with {O.ends(O.USER, 2)}, {_THIRDS} select s.signal_id, s.pos, seg_no::int seg_no from s asof join thirds l on l.signal_id = s.signal_id and s.pos >= l.lo")
def asof_pieces(spark, sf):
    sig = B.user_signal(spark, sf)
    starts = fit.uniform_pieces(sig, 3).select("signal_id", F.col("start_pos").alias("pos"), "seg_no")
    return apps.asof_last(sig.select("signal_id", "pos"), starts, "seg_no")


@query(_BEST_USER.replace("select signal_id, cut, round(cost / 1e6, 4) cost from best", "select signal_id, cut from best"))
def sql_table_function(spark, sf):
    """The exact two-piece model through the SQL table function."""
    sql.register_sql(spark)
    view = f"q_{uuid.uuid4().hex}"
    B.user_signal(spark, sf).select("signal_id", "t", "x").createOrReplaceTempView(view)
    got = spark.sql(f"select * from segment_signal(table(select * from {view}) partition by signal_id order by (t), 2, 'binary_split')")
    return got.where("seg_no = 1").select("signal_id", F.col("start_pos").alias("cut"))


def _stream(spark, sf):
    schema = load_table(spark, sf, "events").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet*").parquet(sf)


def _folder(spark: SparkSession) -> str:
    return f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"


def _drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    return online.drain(stream, _folder(stream.sparkSession), mode)


@query("select user_id::varchar signal_id, epoch_us(time_bucket(interval 7 days, ts, timestamp '1970-01-01'))::bigint window_us, count(*)::double n, sum(round(value * 100)) sx0 from events group by 1, 2")
def stream_half_window(spark, sf):
    rows = online.with_event_time(_stream(spark, sf).withColumn("cents", F.round(F.col("value") * 100)), "ts", "1 hour")
    return _drained(online.stream_moments(rows, "user_id", "ts", ["cents"], "7 days"), "complete").select("signal_id", "window_us", "n", "sx0")


@query(
    """with g as (select user_id, ts, case when ts - lag(ts) over w >= interval 12 hours or lag(ts) over w is null then 1 else 0 end new from events window w as (partition by user_id order by ts)),
    i as (select user_id, ts, sum(new) over (partition by user_id order by ts) s from g) select user_id::varchar signal_id, epoch_us(min(ts))::bigint start_us, epoch_us(max(ts) + interval 12 hours)::bigint end_us, count(*) n from i group by user_id, s"""
)
def session_signals(spark, sf):
    rows = online.with_event_time(_stream(spark, sf), "ts", "1 hour")
    return _drained(online.stream_sessions(rows, "user_id", "ts", "12 hours"), "complete")


def _cents(df: DataFrame) -> DataFrame:
    return df.withColumn("cents", F.round(F.col("value") * 100))


@query(O.windowed_cuts(30, "refined", 0.3))
def stream_refined_cuts(spark, sf):
    found = lambda rows: online.stream_cuts(_cents(rows), "user_id", "ts", ["cents"], 30, "refined", 0.3)
    return online.drain_closed(found, _stream(spark, sf), "ts", _folder(spark)).select("signal_id", "cut_us", r6("gain").alias("gain"))


@query(O.windowed_cuts(30, "refined", 0.3))
def batch_refined_cuts(spark, sf):
    return online.batch_cuts(_cents(load_table(spark, sf, "events")), "user_id", "ts", ["cents"], 30, "refined", 0.3).select("signal_id", "cut_us", r6("gain").alias("gain"))


@query(O.windowed_cuts(30, "half", 0.3))
def batch_half_cuts(spark, sf):
    """The window cut in the middle, for comparison."""
    return online.batch_cuts(_cents(load_table(spark, sf, "events")), "user_id", "ts", ["cents"], 30, "half", 0.3).select("signal_id", "cut_us", r6("gain").alias("gain"))


@query("select (row_number() over (order by p_partkey) - 1)::bigint pos from part qualify p_retailprice < lag(p_retailprice) over (order by p_partkey) - 50")
def natural_saw_tooth(spark, sf):
    """The cuts of the one exactly piecewise-linear column, by dynamic programming over balanced cells with a vanishing budget."""
    sig = B.part_signal(spark, sf)
    drops = load_table(spark, sf, "part", ["p_partkey"]).agg(F.countDistinct(F.floor(F.col("p_partkey") / 1000))).first()[0]
    return S.cuts_of(S.segment(sig, int(drops), "cells_then_refine")).select("pos")


@query()
def giant_refine_then_merge(spark, sf):
    """All line items as one signal, cut into blocks: five pieces; positions come from range partitions."""
    blocks = giant.Blocks(X.line_items(spark, sf), 8192)
    cuts, trace = giant.refine_then_merge(blocks, 5, size=25)
    return spark.createDataFrame([(int(c), len(trace) - 1) for c in cuts], "pos bigint, sweeps int")


@query()
def bottom_up_rounds(spark, sf):
    return giant.bottom_up_rounds(B.user_signal(spark, sf), 2, 5, 3).select("signal_id", "cell", "n")


def _rounded(df: DataFrame) -> DataFrame:
    return df.select(*[r6(c, 1, 4).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


@query()
def experiment_single_cut(spark, sf):
    return _rounded(X.single_cut(spark, sf))


@query()
def experiment_small(spark, sf):
    return _rounded(X.many_cuts_small(spark, sf))


@query()
def experiment_large(spark, sf):
    """Line items of three lengths; the published sizes are in published_many_large."""
    return _rounded(X.many_cuts_large(spark, sf, (4000, 10_000, 30_000)))


@query()
def published_single_cut(spark, sf):
    return _rounded(X.published_single_cut(spark))


@query()
def published_many_small(spark, sf):
    return _rounded(X.published_many_small(spark))


@query()
def published_many_large(spark, sf):
    return _rounded(X.published_many_large(spark))


@query()
def experiment_frames(spark, sf):
    return _rounded(X.frames(spark, sf))


@query()
def experiment_one_scene(spark, sf):
    return X.one_scene(spark, sf)


@query()
def experiment_run_time_growth(spark, sf):
    return _rounded(X.run_time_growth(spark, sf))


@query()
def experiment_mismatch(spark, sf):
    return _rounded(X.mismatch(spark, sf))


@query()
def experiment_million_points(spark, sf):
    return _rounded(X.million_points(spark, sf))


@query()
def experiment_down_sampled(spark, sf):
    return _rounded(X.down_sampled(spark, sf))


@query()
def experiment_unknown_k(spark, sf):
    return X.number_unknown(spark, sf)


@query()
def experiment_business_series(spark, sf):
    return _rounded(X.business_series(spark, sf))


@query()
def experiment_ablation(spark, sf):
    return _rounded(X.ablation(spark, sf))

"""Operators on Spark: against the kernels, hand examples, and each other."""

import numpy as np
import pytest
from conftest import SF
from pyspark.sql import functions as F

from linseg.kernels import refine
from linseg.kernels.moments import Linear
from linseg.operators import apps, fit, giant, metrics
from linseg.operators import segment as S
from linseg.plans import regime
from linseg.sources import builders as B
from linseg.sources import planted as P
from linseg.spec import validate
from linseg.streaming import cuts as online


def frame(spark, rows, schema):
    return spark.createDataFrame(rows, schema)


def signal(spark, x, sid="a"):
    return frame(spark, [(sid, i, float(i), [float(v)]) for i, v in enumerate(x)], "signal_id string, pos bigint, t double, x array<double>")


def pieces(spark, cuts, n, method="m", sid="a"):
    e = [0, *cuts, n]
    return frame(spark, [(sid, method, i, a, b) for i, (a, b) in enumerate(zip(e, e[1:]))], "signal_id string, method string, seg_no int, start_pos bigint, end_pos bigint")


def test_covering_and_rand_of_the_hand_example(spark):
    t, p = pieces(spark, [4], 10), pieces(spark, [5], 10)
    assert metrics.covering(t, p).first().covering == pytest.approx(0.82)
    assert metrics.rand_index(t, p).first().rand == pytest.approx(0.8)
    assert metrics.rand_index(p, t).first().rand == pytest.approx(0.8)
    assert metrics.covering(t, t).first().covering == metrics.rand_index(t, t).first().rand == 1.0
    assert metrics.cut_f1(t, p, 1).first().f1 == 1.0 and metrics.cut_f1(t, p, 0).first().f1 == 0.0


def test_native_and_kernel_cuts_agree(spark):
    sig = B.user_signal(spark, SF)
    native = {r.signal_id: r.cut for r in fit.best_single_cut(sig, 2).collect()}
    kernel = {r.signal_id: r.pos for r in S.cuts_of(S.segment(sig, 2, "optimal_partition")).collect()}
    assert native == kernel and len(native) == 15


def test_input_order_and_partitions_do_not_matter(spark):
    sig = B.user_signal(spark, SF)
    a = S.cuts_of(S.segment(sig, 3, "refine_then_merge")).select("signal_id", "pos").collect()
    b = S.cuts_of(S.segment(sig.orderBy(F.rand(1)).repartition(7), 3, "refine_then_merge")).select("signal_id", "pos").collect()
    assert sorted(a) == sorted(b)


def test_costs_add_up(spark):
    sig = B.user_signal(spark, SF)
    p = S.segment(sig, 3, "binary_split")
    by = {r.signal_id: r.cost for r in fit.fitting_cost(sig, p).collect()}
    for r in p.groupBy("signal_id").agg(F.sum("sse").alias("sse"), F.first("cost").alias("cost")).collect():
        assert r.sse == pytest.approx(r.cost) == pytest.approx(by[r.signal_id])


def test_moments_merge(spark):
    sig = B.user_signal(spark, SF)
    a, b = fit.moments(sig.where("pos < 20"), 2), fit.moments(sig.where("pos >= 20"), 2)
    assert sorted(fit.merge_moments(a, b, 2, ["signal_id"]).collect()) == sorted(fit.moments(sig, 2).collect())


def test_planted_cuts_are_found(spark):
    x, truth = P.planted(B.supplier_signal(spark, SF), P.SUPPLIER_SCALE, 2, 5, "t", 2.0, 0.5)
    got = metrics.evaluate(truth, S.segment(x, "k", "cells_then_refine"))
    assert got.agg(F.min("covering")).first()[0] > 0.95
    noisy = P.planted(B.supplier_signal(spark, SF), P.SUPPLIER_SCALE, 2, None, "t", 2.0, 0.5, 0.3, ("table", "trig", "impulse"))[0]
    assert noisy.count() == x.count()


def test_giant_signal_gives_the_fleet_result(spark):
    sig = B.supplier_signal(spark, SF).where("signal_id = '1'").select("signal_id", "pos", "t", "x").persist()
    rows = sig.orderBy("pos").collect()
    s = Linear(np.array([r.t for r in rows]), np.array([r.x for r in rows]))
    blocks = giant.Blocks(sig, 64)
    start = refine.uniform(s.n, 5)
    cuts, trace = giant.refine(blocks, start)
    want, want_trace = refine.refine(s, start, order="odd_even")
    assert cuts == want.tolist() and trace == pytest.approx(want_trace)


def test_global_positions_without_a_global_window(spark):
    df = spark.range(1000).select((F.col("id") * 7919 % 1009).alias("o"))
    got = giant.with_global_position(df, ["o"], 5).orderBy("pos").collect()
    assert [r.pos for r in got] == list(range(1000)) and [r.o for r in got] == sorted(r.o for r in got)


def test_regimes(spark):
    sig = B.supplier_signal(spark, SF)
    fleet, big = regime.choose_regime(sig, most_points=595)
    assert big.count() > 0 and fleet.select("signal_id").distinct().count() + big.count() == 10


def test_stream_equals_batch_for_any_arrival_order(spark, tmp_path):
    rng = np.random.default_rng(0)
    rows = [(u, int((86_400 + i) * 1_000_000), float(rng.normal() + (20 if i > 60 + u else 0))) for u in range(3) for i in range(150)]
    df = frame(spark, rows, "user_id bigint, us bigint, value double").select("user_id", F.timestamp_micros("us").alias("ts"), "value")
    src = tmp_path / "in"
    for k in range(3):  # late points, up to three files after their time
        df.where(F.unix_micros("ts") / 1_000_000 % 3 == k).coalesce(1).write.mode("append").parquet(str(src))
    schema = df.schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(src))
    got = online.drain_closed(lambda rows: online.stream_cuts(rows, "user_id", "ts", ["value"], 30, "refined", 0.5, "10 minutes"), stream, "ts", str(tmp_path / "c"))
    batch = online.batch_cuts(df, "user_id", "ts", ["value"], 30, "refined", 0.5)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, batch.collect())) and batch.count() >= 3
    flat = online.batch_cuts(df, "user_id", "ts", ["value"], 30, "half", 0.5)
    assert flat.columns == batch.columns


def test_applications(spark):
    sig = signal(spark, [0, 1, 2, 3, 10, 9, 8, 7, 6, 50])
    p = fit.fit_pieces(sig, pieces(spark, [4], 10).drop("method"), 1)
    assert [r.pos for r in apps.summarize(p, 2).orderBy("pos").collect()] == [1, 3, 5, 8]
    assert [r.pos for r in apps.residual_anomalies(sig, p, 1.5).collect()] == [9]
    assert apps.downsample(sig, 3).count() == 4
    z = apps.standardize(sig, 1).agg(F.avg(F.col("x")[0]), F.stddev_pop(F.col("x")[0])).first()
    assert z[0] == pytest.approx(0, abs=1e-9) and z[1] == pytest.approx(1)
    holes = frame(spark, [("a", 0, 0.0, [1.0]), ("a", 1, 1.0, [float("nan")]), ("a", 2, 2.0, [None])], "signal_id string, pos bigint, t double, x array<double>")
    assert [r.x[0] for r in apps.handle_missing(holes, 1, "ffill").orderBy("pos").collect()] == [1.0, 1.0, 1.0]
    assert apps.handle_missing(holes, 1, "drop_row").count() == 1
    with pytest.raises(ValueError):
        validate(holes)
    with pytest.raises(ValueError):
        apps.position_pairs(sig, 5)


def test_infeasible_signals_become_error_rows(spark):
    got = S.segment(signal(spark, [1, 2, 3]), 2, "refine_boundaries").collect()
    assert len(got) == 1 and "don't hold" in got[0].error


def test_entry_points(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 7
    assert set(e.oracle_sql()) <= set(e.queries())


@pytest.mark.parametrize("method", ["refine_boundaries", "refine_then_merge"])
def test_one_entry_for_any_size(spark, method):
    from linseg.operators.anysize import segment_any

    sig = B.supplier_signal(spark, SF)
    want = {(r.signal_id, r.seg_no): r for r in S.segment(sig, 4, method, order="odd_even").collect()}
    got = segment_any(sig, 4, method, most_points=595, block=64, order="odd_even").collect()
    assert len(got) == len(want)
    for r in got:
        w = want[r.signal_id, r.seg_no]
        assert (r.start_pos, r.end_pos, r.n) == (w.start_pos, w.end_pos, w.n) and r.sse == pytest.approx(w.sse, rel=1e-6)
        assert list(r.slope) == pytest.approx(list(w.slope), rel=1e-5, abs=1e-6) and list(r.intercept) == pytest.approx(list(w.intercept), rel=1e-5, abs=1e-6)
    errors = segment_any(sig, 2, "optimal_partition", most_points=595).where("error is not null").collect()
    assert errors and all("blocks" in r.error for r in errors)

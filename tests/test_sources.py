"""Scans, sinks and the helpers of streams, each run once on small rows."""

from conftest import SF
from pyspark.sql import functions as F

from linseg.operators import fit
from linseg.operators import segment as S
from linseg.sources import builders as B
from linseg.sources import tables
from linseg.streaming import cuts as online


def test_other_formats_and_views(spark, tmp_path):
    rows = spark.createDataFrame([(1, "a", 0.5), (2, "b", 1.5)], "i int, s string, v double")
    for fmt in ("csv", "json", "orc"):
        rows.write.format(fmt).partitionBy("s").save(str(tmp_path / fmt))
        got = tables.load_any(spark, str(tmp_path / fmt), fmt, "i int, v double, s string")
        assert sorted(map(tuple, got.select("i", "s", "v").collect())) == [(1, "a", 0.5), (2, "b", 1.5)]
    tables.register_views({"small_rows": rows})
    assert spark.sql("select sum(v) from small_rows").first()[0] == 2.0


def test_pieces_and_moments_are_written_and_read(spark, tmp_path):
    sig = B.user_signal(spark, SF)
    pieces = S.segment(sig, 3, ("uniform", "binary_split"))
    tables.write_pieces(pieces, str(tmp_path / "pieces"))
    back = spark.read.parquet(str(tmp_path / "pieces"))
    assert back.where("method = 'uniform'").count() * 2 == back.count() == pieces.count()
    blocks = fit.moments(sig.withColumn("block", F.floor(F.col("pos") / 16)), 2, ["signal_id", "block"])
    tables.write_pyramid(blocks, "pyramid_of_users", 4, str(tmp_path / "pyramid"))
    try:
        t = spark.table("pyramid_of_users")
        assert t.count() == blocks.count()
        plan = t.groupBy("signal_id").agg(F.sum("n"))._jdf.queryExecution().executedPlan().toString()
        assert "hashpartitioning" not in plan  # buckets serve as the partitioning
    finally:
        spark.sql("drop table pyramid_of_users")


def _stream(spark, df, path):
    df.write.mode("append").parquet(path)
    return tables.read_stream(spark, path, df.schema)


def test_repeated_cuts_are_let_through_once(spark, tmp_path):
    day = 86_400_000_000
    cuts = spark.createDataFrame([("a", day, 0.5, 30), ("a", day, 0.5, 30), ("b", day, 0.7, 30)], online.CUTS)
    got = online.drain(online.without_repeats(_stream(spark, cuts, str(tmp_path / "in"))), str(tmp_path / "out"))
    assert sorted((r.signal_id, r.cut_us) for r in got.collect()) == [("a", day), ("b", day)]


def test_thresholds_join_a_stream(spark, tmp_path):
    points = spark.createDataFrame([("a", 1.0), ("b", 2.0), ("c", 3.0)], "signal_id string, v double")
    static = spark.createDataFrame([("a", 0.1), ("b", 0.2)], "signal_id string, threshold double")
    got = online.drain(online.with_thresholds(_stream(spark, points, str(tmp_path / "in")), static), str(tmp_path / "out"))
    assert sorted((r.signal_id, r.threshold) for r in got.collect()) == [("a", 0.1), ("b", 0.2), ("c", None)]


def test_stored_cuts_are_refined_on_new_points(spark):
    sig = B.user_signal(spark, SF)
    stored = S.cut_arrays(S.segment(sig, 3, "uniform"))
    again, whole = online.resegment(sig, stored), S.segment(sig, 3, "refine_boundaries")
    key = lambda df: sorted((r.signal_id, r.pos) for r in S.cuts_of(df).collect())
    assert key(again) == key(whole)

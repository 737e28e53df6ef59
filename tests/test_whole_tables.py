"""Registered queries read their whole tables: sizes beyond the old caps, and every id."""

from conftest import SF

from linseg.operators import giant
from linseg.queries import QUERIES

BIG = "/root/testdata/sf0.1"


def test_giant_signal_has_every_line_item(spark):
    rows = spark.read.parquet(f"{BIG}/lineitem.parquet").count()
    got = QUERIES["giant_refine_then_merge"](spark, BIG).collect()
    assert rows > 60_000 and max(r.pos for r in got) == rows and len(got) == 6


def test_ranges_behind_the_millionth_event(spark, tmp_path):
    n = 1_000_020
    events = spark.range(n).selectExpr("id event_id", "1L user_id", "timestamp_micros(id) ts", "'view' event_type", "cast(id % 7 as double) value", "'{\"k\": 1}' props")
    events.write.parquet(str(tmp_path / "events.parquet"))
    assert QUERIES["prefix_cost_ranges"](spark, str(tmp_path)).agg({"end_pos": "max"}).first()[0] == n


def test_compressed_cells_and_cost_models_of_every_user(spark):
    users = {str(r.user_id) for r in spark.read.parquet(f"{SF}/events.parquet").select("user_id").distinct().collect()}
    assert {r.signal_id for r in QUERIES["optimal_over_cells_svd"](spark, SF).collect()} == users
    assert {(r.signal_id, r.model) for r in QUERIES["cost_models_user"](spark, SF).collect()} == {(u, m) for u in users for m in ("l2_linear", "l2_constant")}
    assert {r.signal_id for r in QUERIES["absolute_cost_user"](spark, SF).collect()} == users


def test_experiments_of_every_supplier(spark):
    n = spark.read.parquet(f"{SF}/lineitem.parquet").select("l_suppkey").distinct().count()
    for name in ("experiment_single_cut", "experiment_mismatch", "experiment_small"):
        assert {r.signals for r in QUERIES[name](spark, SF).collect()} == {n}, name
    assert QUERIES["experiment_unknown_k"](spark, SF).count() == n


def test_rounds_end_at_k_pieces(spark):
    x = [0.0] * 400 + [50.0 + 2 * i for i in range(300)] + [-80.0] * 300
    sig = spark.createDataFrame([(s, i, float(i), [v, -v]) for s in "ab" for i, v in enumerate(x if s == "a" else x[395:405])], "signal_id string, pos bigint, t double, x array<double>")
    got = giant.bottom_up_rounds(sig, 2, 5, 3, few=8).orderBy("cell").collect()
    assert [(r.cell, r.n) for r in got if r.signal_id == "a"] == [(0, 400), (400, 300), (700, 300)]
    assert sum(r.n for r in got if r.signal_id == "b") == 10
    users = QUERIES["bottom_up_rounds"](spark, SF).groupBy("signal_id").count().collect()
    assert len(users) == 15 and all(r["count"] == 3 for r in users)


def test_partitions_of_every_users_events(spark):
    from linseg.kernels.refine import partitions, printed_partitions

    sizes = {str(r.user_id): r["count"] for r in spark.read.parquet(f"{SF}/events.parquet").groupBy("user_id").count().collect()}
    got = QUERIES["partition_count"](spark, SF).collect()
    assert {(r.signal_id, r.n) for r in got} == set(sizes.items()) and len(got) == 9 * len(sizes)
    assert all((r.partitions, r.printed) == (partitions(r.n, r.k, r.gamma), printed_partitions(r.n, r.k)) for r in got)


def test_million_points_over_blocks(spark):
    """A signal that one task isn't given is searched over blocks, and scored as the one-task search."""
    from linseg import experiments

    a, b = (experiments.million_points(spark, SF, 9_000, most).collect() for most in (4_000, 1_000_000))
    assert len(a) == len(b) == 1 and a[0].least_n == b[0].least_n == 9_000
    assert a[0].n_fits is None and b[0].n_fits > 0  # block searches don't count fits
    assert abs(a[0].covering - b[0].covering) < 0.2 and a[0].signals == 1


def test_down_sampled_over_blocks(spark):
    """One packed shuffle serves all steps: places, planted values and thinned points are those of the plain signal, and so are the scores."""
    from pyspark.sql import functions as F

    from linseg import experiments as X
    from linseg.sources import planted

    plain, truth = planted.planted(X.line_items(spark, SF).withColumn("signal_id", F.lit("all")).select("signal_id", "pos", "t", "x"), planted.SUPPLIER_SCALE, 8, None, "w9", 1.0, 1.0, 0.3)
    want = [(r.pos, r.t, r.x) for r in plain.orderBy("pos").collect()]
    lines = spark.read.parquet(f"{SF}/lineitem.parquet")
    pieces = planted.truth(planted.sizes(plain), 8, None, 4, "w9", 1.0, 0.3).collect()
    blocks = giant.Blocks.ordered(lines, X.LINE_ORDER, X.line_values(), 700, planted.Planted(pieces, planted.SUPPLIER_SCALE))
    batches = blocks.rows.orderBy("block").toArrow().to_batches()
    for step in (1, 3):
        view = blocks.every(step)
        got = [(p * step, float(t), x.tolist()) for _, ps, ts, xs in view.read.raw(batches) for p, t, x in zip(ps.tolist(), ts, xs, strict=True)]
        assert got == want[::step] and view.n == len(got)
    a, b = ({r.m: r for r in X.down_sampled(spark, SF, (1, 2, 5), most, 700).collect()} for most in (3_000, 1_000_000))
    assert a.keys() == b.keys() == {1, 2, 5}
    for m in a:
        assert abs(a[m].cost / b[m].cost - 1) < 0.05 and abs(a[m].covering - b[m].covering) < 0.2

"""From table rows to signals."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..spec import SignalSpec
from .tables import load_table

KINDS = ("click", "error", "purchase", "signup", "view")


def with_position(df: DataFrame, key: str, order: list) -> DataFrame:
    return df.withColumn("pos", (F.row_number().over(Window.partitionBy(key).orderBy(*order)) - 1).cast("bigint"))


def from_rows(df: DataFrame, spec: SignalSpec) -> DataFrame:
    """One point a row; only key, order, time and features are read.  Without a time column the place is the time."""
    order = [F.col(c) if isinstance(c, str) else c for c in spec.order_by]
    time = None if spec.time is None else (F.col(spec.time) if isinstance(spec.time, str) else spec.time).cast("double")
    rows = df.select(spec.key().alias("signal_id"), *[c.alias(f"o{i}") for i, c in enumerate(order)], *([] if time is None else [time.alias("t")]), spec.vector().alias("x"))
    placed = with_position(rows, "signal_id", [f"o{i}" for i in range(len(order))])
    return placed.select("signal_id", "pos", (F.col("pos").cast("double") if time is None else F.col("t")).alias("t"), "x")


def from_time_buckets(df: DataFrame, group: Column | None, ts: str, every: str, aggs: list[Column]) -> DataFrame:
    """One point a time bucket: signal_id, bucket, and the aggregates; the shuffle carries partial aggregates only."""
    key = F.lit("all") if group is None else group.cast("string")
    return df.groupBy(key.alias("signal_id"), F.date_trunc(every, F.col(ts)).alias("bucket")).agg(*aggs)


def buckets_to_signal(buckets: DataFrame, features: list[str]) -> DataFrame:
    return from_rows(buckets, SignalSpec("signal_id", ("bucket",), None, tuple(features)))


def from_vectors(df: DataFrame, key: Column | None, order: str, vector: str) -> DataFrame:
    rows = df.select((F.lit("all") if key is None else key.cast("string")).alias("signal_id"), F.col(order).alias("o"), F.transform(vector, lambda v: v.cast("double")).alias("x"))
    return with_position(rows, "signal_id", ["o"]).select("signal_id", "pos", F.col("pos").cast("double").alias("t"), "x")


def from_long(df: DataFrame, dim: str, value: str, dims: list) -> DataFrame:
    """(signal_id, pos, dim, value) rows to vectors; a missing dimension is 0."""
    wide = df.groupBy("signal_id", "pos").pivot(dim, dims).agg(F.sum(value))
    return wide.select("signal_id", "pos", F.col("pos").cast("double").alias("t"), F.array(*[F.coalesce(F.col(f"`{d}`"), F.lit(0.0)).cast("double") for d in dims]).alias("x"))


def from_wide(df: DataFrame, cols: list[str]) -> DataFrame:
    return df.select("signal_id", "pos", "t", F.array(*[F.col(c).cast("double") for c in cols]).alias("x"))


def fill_gaps(buckets: DataFrame, every: str, cols: list[str], policy: str = "zero") -> DataFrame:
    """Every bucket between a signal's first and last one; missing values are zero or the last known (ffill)."""
    span = buckets.groupBy("signal_id").agg(F.min("bucket").alias("lo"), F.max("bucket").alias("hi"))
    grid = span.select("signal_id", F.explode(F.sequence("lo", "hi", F.expr(f"interval 1 {every}"))).alias("bucket"))
    full = grid.join(buckets, ["signal_id", "bucket"], "left")
    if policy == "ffill":
        w = Window.partitionBy("signal_id").orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)
        return full.select("signal_id", "bucket", *[F.last(c, True).over(w).alias(c) for c in cols])
    return full.fillna(0, cols)


# Signals on the given tables.


def user_signal(spark: SparkSession, sf: str) -> DataFrame:
    """Per user: value in cents and the number in props; whole numbers, so that every engine sums them alike."""
    ev = load_table(spark, sf, "events", ["user_id", "ts", "event_id", "value", "props"])
    return from_rows(ev, SignalSpec("user_id", ("ts", "event_id"), None, (F.round(F.col("value") * 100), F.get_json_object("props", "$.k"))))


def supplier_signal(spark: SparkSession, sf: str) -> DataFrame:
    """Rows of each supplier: quantity, price in cents, discount and tax in hundredths."""
    cols = ["l_suppkey", "l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax"]
    li = load_table(spark, sf, "lineitem", cols)
    values = (F.col("l_quantity"), F.round(F.col("l_extendedprice") * 100), F.round(F.col("l_discount") * 100), F.round(F.col("l_tax") * 100))
    return from_rows(li, SignalSpec("l_suppkey", ("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey"), None, values))


def hourly_buckets(spark: SparkSession, sf: str) -> DataFrame:
    ev = load_table(spark, sf, "events", ["ts", "event_type"])
    kinds = [F.sum((F.col("event_type") == k).cast("bigint")).alias(k) for k in KINDS]
    return from_time_buckets(ev, None, "ts", "hour", kinds)


def hourly_signal(spark: SparkSession, sf: str) -> DataFrame:
    """Counts of each kind of event by the hour."""
    return buckets_to_signal(hourly_buckets(spark, sf), list(KINDS))


def daily_orders(spark: SparkSession, sf: str) -> DataFrame:
    o = load_table(spark, sf, "orders", ["o_orderdate", "o_totalprice"])
    b = from_time_buckets(o, None, "o_orderdate", "day", [F.count("*").alias("n"), F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).alias("cents")])
    return buckets_to_signal(b, ["n", "cents"])


def weekly_segment(spark: SparkSession, sf: str) -> DataFrame:
    o = load_table(spark, sf, "orders", ["o_custkey", "o_orderdate", "o_totalprice"])
    c = load_table(spark, sf, "customer", ["c_custkey", "c_mktsegment"])
    joined = o.join(c, o.o_custkey == c.c_custkey)
    return from_time_buckets(joined, F.col("c_mktsegment"), "o_orderdate", "week", [F.count("*").alias("n"), F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).alias("cents")])


def monthly_nation(spark: SparkSession, sf: str) -> DataFrame:
    """Orders by month and nation; the nation and region tables are fixed-size dimensions."""
    o = load_table(spark, sf, "orders", ["o_custkey", "o_orderdate", "o_totalprice"])
    c = load_table(spark, sf, "customer", ["c_custkey", "c_nationkey"])
    n = load_table(spark, sf, "nation", ["n_nationkey", "n_name", "n_regionkey"]).join(F.broadcast(load_table(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    joined = o.join(c, o.o_custkey == c.c_custkey).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))
    return from_time_buckets(joined, F.concat_ws("/", "r_name", "n_name"), "o_orderdate", "month", [F.count("*").alias("n"), F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).alias("cents")])


def daily_ship(spark: SparkSession, sf: str) -> DataFrame:
    li = load_table(spark, sf, "lineitem", ["l_shipdate", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag"])
    b = from_time_buckets(li, None, "l_shipdate", "day", [F.sum("l_quantity").alias("q"), F.sum("l_extendedprice").alias("p"), F.avg("l_discount").alias("dc"), F.avg("l_tax").alias("tx"), *[F.sum((F.col("l_returnflag") == f).cast("int")).alias(f) for f in ("A", "N", "R")]])
    return buckets_to_signal(b, ["q", "p", "dc", "tx", "A", "N", "R"])


def part_signal(spark: SparkSession, sf: str) -> DataFrame:
    """The one exactly piecewise-linear column: price climbs with the key and drops every thousand keys."""
    return from_rows(load_table(spark, sf, "part", ["p_partkey", "p_retailprice"]), SignalSpec(None, ("p_partkey",), None, ("p_retailprice",)))


def frame_signal(spark: SparkSession, sf: str, scene: int | None = None) -> DataFrame:
    """Embeddings in the order of their id, as one sequence of frames or scenes of so many."""
    e = load_table(spark, sf, "embeddings", ["vec_id", "embedding"])
    return from_vectors(e, None if scene is None else F.floor(F.col("vec_id") / scene), "vec_id", "embedding")


def conversation_signal(spark: SparkSession, sf: str) -> DataFrame:
    c = load_table(spark, sf, "conversations", ["conv_id", "turn", "text"])
    return from_rows(c, SignalSpec("conv_id", ("turn",), None, (F.length("text"),)))


def document_signal(spark: SparkSession, sf: str) -> DataFrame:
    """Documents of each source by id: characters, lines, quality label (0 where there is none)."""
    d = load_table(spark, sf, "documents", ["doc_id", "source", "text"])
    lab = load_table(spark, sf, "labels", ["doc_id", "quality"])
    rows = d.select("doc_id", "source", F.length("text").alias("chars"), (F.length("text") - F.length(F.replace("text", F.lit("\n"), F.lit(""))) + 1).alias("lines")).join(lab, "doc_id", "left")
    return from_rows(rows, SignalSpec("source", ("doc_id",), None, ("chars", "lines", F.coalesce("quality", F.lit(0)))))


def page_signal(spark: SparkSession, sf: str) -> DataFrame:
    p = load_table(spark, sf, "pages", ["page_id", "html", "url"])
    return from_rows(p, SignalSpec(None, ("page_id",), None, (F.length("html"), F.length("html") - F.length(F.replace("html", F.lit("<"), F.lit(""))), F.length("url"))))


def benchmark_signal(spark: SparkSession, sf: str) -> DataFrame:
    return from_rows(load_table(spark, sf, "benchmark", ["item_id", "text"]), SignalSpec(None, ("item_id",), None, (F.length("text"),)))


def balance_signal(spark: SparkSession, sf: str) -> DataFrame:
    return from_rows(load_table(spark, sf, "supplier", ["s_suppkey", "s_acctbal"]), SignalSpec(None, ("s_suppkey",), None, (F.round(F.col("s_acctbal") * 100),)))

"""Scans and sinks."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession


def load_table(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def load_any(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """Any file format Spark reads, partitioned folders included; a schema saves an inference pass."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_pieces(pieces: DataFrame, path: str, mode: str = "overwrite") -> None:
    pieces.write.mode(mode).partitionBy("method").parquet(path)


def write_pyramid(moments: DataFrame, table: str, buckets: int = 64, path: str | None = None) -> None:
    """Block moments bucketed and sorted by signal and block, so that later joins need no shuffle; below ``path``, or in the warehouse."""
    writer = moments.write.mode("overwrite").bucketBy(buckets, "signal_id").sortBy("signal_id", "block")
    (writer.option("path", path) if path else writer).saveAsTable(table)


def read_stream(spark: SparkSession, path: str, schema) -> DataFrame:
    return spark.readStream.schema(schema).parquet(path)


def register_views(frames: dict[str, DataFrame]) -> None:
    for name, df in frames.items():
        df.createOrReplaceTempView(name)


def shared_folder(spark: SparkSession) -> str:
    """The session's checkpoint folder, which driver and executors share; a temporary one only in local runs where none is set."""
    got = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not got:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        got = tempfile.mkdtemp(prefix="linseg-shared-")
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(got)
    return got


def cut_lineage(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in the shared folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)

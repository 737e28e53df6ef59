"""What the text operators share: Arrow passes over texts, checkpoints, ASCII-only word rules."""

from __future__ import annotations

import contextlib
import ctypes
import hashlib
import tempfile
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

#: Words are maximal runs of anything but these six ASCII white-space bytes; ``bytes.split()`` cuts at the same six.
WORD = r"[^\x20\x09-\x0D]+"
#: Lower-cases A-Z and nothing else.
LOWER = bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))
#: Text bytes that one step of a Python kernel holds at once.
CHUNK_BYTES = 4 << 20


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ensure_checkpoint_dir(spark: SparkSession) -> str:
    """The session's shared checkpoint folder; a temporary one only in local runs where none is configured (tests)."""
    got = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not got:
        if not spark.sparkContext.master.split("[")[0] == "local":
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        got = tempfile.mkdtemp(prefix="linseg-checkpoint-")
    if not spark.sparkContext.getCheckpointDir():
        spark.sparkContext.setCheckpointDir(got)
    return got


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint: cuts the lineage in a folder that every executor can read."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def pieces(batches: Iterable[pa.RecordBatch], text: str, size: int | None = None) -> Iterator[pa.RecordBatch]:
    """Arrow batches cut so that each holds about so many bytes of text, CHUNK_BYTES unless said (a longer text stands alone)."""
    size = size or CHUNK_BYTES
    for batch in batches:
        if not batch.num_rows:
            continue
        col = batch.column(batch.schema.get_field_index(text))
        if col.nbytes <= size:
            yield batch
            continue
        lengths = pc.fill_null(pc.binary_length(col), 0).to_numpy(zero_copy_only=False)
        start, held = 0, 0
        for i, n in enumerate(lengths):
            if i > start and held + n > size:
                yield batch.slice(start, i - start)
                start, held = i, 0
            held += int(n)
        yield batch.slice(start)


def texts(batch: pa.RecordBatch, name: str) -> list[str]:
    """The column's strings, null as empty."""
    return [x or "" for x in batch.column(batch.schema.get_field_index(name)).to_pylist()]


def utf8(batch: pa.RecordBatch, name: str) -> list[bytes]:
    """The column's UTF-8 bytes, null as empty, without decoding them."""
    return [x or b"" for x in batch.column(batch.schema.get_field_index(name)).cast(pa.binary()).to_pylist()]


def arrow_schema(schema: str | T.StructType) -> pa.Schema:
    struct = T._parse_datatype_string(schema) if isinstance(schema, str) else schema
    return to_arrow_schema(struct)


def map_texts(df: DataFrame, id_col: str, text_col: str, kernel: Callable, out: str) -> DataFrame:
    """One pass over (id, text), columns pruned: ``kernel(batches)`` yields dicts of columns named as in ``out``.

    Kernels see the columns as ``doc_id`` and ``text`` whatever they are called in ``df``; other columns never
    reach Python, so names cannot clash.
    """
    fields = arrow_schema(out)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for cols in kernel(pieces(batches, "text")):
            yield pa.RecordBatch.from_arrays(
                [x if isinstance(x, pa.Array) else pa.array(x, f.type) for f in fields for x in [cols[f.name]]], schema=fields
            )

    narrow = df.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return narrow.mapInArrow(run, out)


def keep_rows(df: DataFrame, text_col: str, verdicts: Callable[[Iterator[pa.RecordBatch]], Iterator[tuple[pa.RecordBatch, list[bool]]]]) -> DataFrame:
    """Rows of ``df``, all columns unchanged, for which ``verdicts`` says True; no join back, so repeated ids stay apart."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, kept in verdicts(pieces(batches, text_col)):
            yield batch.filter(pa.array(kept, pa.bool_()))

    return df.mapInArrow(run, df.schema)


def release_memory() -> None:
    """Hands freed memory back to the system, for a worker process stands beside the executor's heap."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # only where the C library has it
        ctypes.CDLL(None).malloc_trim(0)


def unit_hash(*cols) -> F.Column:
    """Uniform in [0, 1) from md5 of the columns joined by '|'; DuckDB can replay it."""
    joined = F.concat_ws("|", *[c.cast("string") if not isinstance(c, str) else F.lit(c) for c in cols])
    return F.conv(F.substring(F.md5(joined), 1, 12), 16, 10).cast("double") / F.lit(float(1 << 48))


def text_digest(text: F.Column) -> F.Column:
    """Names a text: md5 of its UTF-8 bytes, null as empty.  ``md5_of`` gives the same in Python."""
    return F.md5(F.coalesce(text.cast("string"), F.lit("")).cast("binary"))


def md5_of(text: bytes) -> str:
    return hashlib.md5(text, usedforsecurity=False).hexdigest()


def fresh(df: DataFrame, name: str) -> str:
    """A column name that ``df`` doesn't have, in any letter case."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def one_of_each(df: DataFrame, named: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Rows of ``df``, all columns unchanged, one for each root of ``named`` (doc_id, digest, root).

    The row of least id stays, any id before none, then that of least text digest; of rows that agree in both, the one of
    least hash over all columns.
    """
    order = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "digest")
    best = named.groupBy("root").agg(F.min(order).alias("b")).select(F.col("b.doc_id").alias("i"), F.col("b.digest").alias("d")).distinct()
    cols = [F.col(f"`{c}`") for c in df.columns]
    rows = df.select(F.struct(*cols).alias("r"), F.col(f"`{id_col}`").cast("long").alias("i"), text_digest(F.col(f"`{text_col}`")).alias("d"))
    kept = rows.join(best.withColumnsRenamed({"i": "bi", "d": "bd"}), (F.col("d") == F.col("bd")) & F.col("i").eqNullSafe(F.col("bi")), "left_semi")
    one = kept.groupBy("i", "d").agg(F.min_by("r", F.xxhash64("r")).alias("r"))
    return one.select(*[F.col("r").getField(c).alias(c) for c in df.columns])

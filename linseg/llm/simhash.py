"""SimHash near-duplicate groups by covering locality-sensitive hashing.

The 64 bits are dealt to the 15 nonzero vectors of four bits, and table v masks the bits whose vector has an odd
inner product with v.  Up to three differing bits have vectors that span three dimensions at most, so some nonzero v
is orthogonal to all of them: in that table the two fingerprints share their key.  Every pair within the radius thus
meets in some table.  Equal fingerprints are one class before that.  A table's group of over ``GROUP`` fingerprints
is dealt again by a second covering family over the bits its mask left out; what then shares a key differs in 16 bits
at most, so no group has more than 2**16 members whatever the data.  Groups yield a spanning forest of their links.

Defined results: a null or wordless text has fingerprint zero and is linked like any other; repeated rows are
rows of their class each; a null id is never a component's name unless no member has an id; an empty table gives no
rows; a text of any length is hashed whole; equal hash counts of a bit leave it zero; columns other than id and text are
never read, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import graph
from .common import LOWER, cut, map_texts, md5_of, one_of_each, utf8

RADIUS, SEED = 3, 42
#: Fingerprints of a first-level group that are compared there; larger groups are dealt again.
GROUP = 1024


def covering(bits: list[int], radius: int = RADIUS) -> list[int]:
    """Masks over these bit positions such that any ``radius`` of them are all outside some mask."""
    vectors = (1 << radius + 1) - 1
    return [sum(1 << bit for i, bit in enumerate(bits) if (v & (1 + i % vectors)).bit_count() % 2) for v in range(1, vectors + 1)]


MASKS = covering(list(range(64)))
#: For each first-level table, the masks of the second: the first mask and more of the bits it leaves out.
DEEPER = [[m | d for d in covering([i for i in range(64) if not m >> i & 1])] for m in MASKS]


def signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def digests(text: bytes, words: int = 3, seed: int = SEED) -> bytes:
    """Hashes of a UTF-8 text's word shingles, repeats included, eight bytes each; fewer words are one shingle, none have none."""
    w = text.translate(LOWER).split()
    if not w:
        return b""
    line = b" ".join(w)
    digest = xxhash.xxh64_digest
    if len(w) <= words:
        return digest(line, seed)
    ends = np.cumsum(np.fromiter(map(len, w), np.int64, len(w)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    return b"".join([digest(line[a:b], seed) for a, b in zip(starts[: 1 - words].tolist(), ends[words - 1 :].tolist(), strict=True)])


def folded(hashes: bytes) -> int:
    """Unsigned SimHash of shingle hashes."""
    n = len(hashes) // 8
    ones = np.zeros(64, np.int64)
    rows = np.frombuffer(hashes, np.uint8).reshape(n, 8)
    for lo in range(0, n, 16384):
        ones += np.unpackbits(rows[lo : lo + 16384], axis=1).sum(0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * ones > n).tobytes(), "big")


def fingerprint(text: bytes, words: int = 3, seed: int = SEED) -> int:
    """Unsigned SimHash of a UTF-8 text's word shingles."""
    return folded(digests(text, words, seed))


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3, digest: bool = False) -> DataFrame:
    """doc_id and fp, the fingerprint's 64 bits as a signed long; the text's digest on request."""

    def kernel(batches: Iterable[pa.RecordBatch]) -> Iterator[dict]:
        for batch in batches:
            got = utf8(batch, "text")
            yield {"doc_id": batch.column(0), "fp": [signed(fingerprint(x, words)) for x in got]} | ({"digest": [md5_of(x) for x in got]} if digest else {})

    return map_texts(df, id_col, text_col, kernel, "doc_id long, fp long" + ", digest string" * digest)


def _links(fps: np.ndarray) -> Iterator[tuple[int, int]]:
    """A spanning forest of the links among distinct fingerprints, breadth first; each is compared once with what is left."""
    rest = fps
    while len(rest):
        queue, rest = [rest[0]], rest[1:]
        while queue and len(rest):
            at = queue.pop()
            near = np.bitwise_count(rest ^ at) <= RADIUS
            if near.any():
                found = rest[near]
                rest = rest[~near]
                queue.extend(found)
                for x in found.tolist():
                    yield int(at), x


def _scan(limit: int | None):
    """Over rows sorted by (v, key, fp): links (hot false) of each group, or the rows themselves of groups over the limit (hot true)."""
    schema = pa.schema([("hot", pa.bool_()), ("v", pa.int32()), ("a", pa.int64()), ("b", pa.int64())])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        size, at, hot = 0, None, False

        def close() -> Iterator[tuple]:
            if size > 1 and not hot:
                for a, b in _links(np.unique(np.concatenate(held))):
                    yield False, 0, a, b

        for batch in batches:
            v, key, fp = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(3))
            edges = [0, *(np.flatnonzero((v[1:] != v[:-1]) | (key[1:] != key[:-1])) + 1).tolist(), len(v)]
            out: list[tuple] = []
            for lo, hi in zip(edges, edges[1:]):
                if lo == hi:
                    continue
                if (now := (v[lo], key[lo])) != at:
                    if size > 1:
                        out.extend(close())
                    held, size, at, hot = [], 0, now, False
                part = fp[lo:hi]
                if hot or (limit and size + len(part) > limit):
                    for x in part if hot else np.concatenate([*held, part]):
                        out.append((True, int(now[0]), int(now[1]), int(x)))
                    held, hot = [], True
                else:
                    held.append(part)
                size += len(part)
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), schema, strict=True)], schema=schema)
        if out := list(close()):
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), schema, strict=True)], schema=schema)

    return run


def _meet(keyed: DataFrame, limit: int | None) -> DataFrame:
    return keyed.repartition("v", "key").sortWithinPartitions("v", "key").mapInArrow(_scan(limit), "hot boolean, v int, a long, b long")


def links(fps: DataFrame, group: int = GROUP) -> DataFrame:
    """Edges (a, b) between distinct fingerprints (column fp) whose components are those of all pairs within the radius."""
    tables = F.array(*[F.struct(F.lit(i).alias("v"), F.col("fp").bitwiseAND(signed(m)).alias("key")) for i, m in enumerate(MASKS)])
    first = cut(_meet(fps.select(F.explode(tables).alias("t"), "fp").select("t.v", "t.key", "fp"), group))
    near = first.where("not hot").select("a", "b")
    hot = first.where("hot").select("v", F.col("b").alias("fp"))
    if hot.isEmpty():
        return near
    deeper = F.element_at(F.array(*[F.array(*[F.lit(signed(m)) for m in row]) for row in DEEPER]), F.col("v") + 1)
    again = hot.select("v", "fp", F.posexplode(deeper).alias("u", "mask")).select(
        (F.col("v") * len(MASKS) + F.col("u")).alias("v"), F.col("fp").bitwiseAND(F.col("mask")).alias("key"), "fp"
    )
    return near.unionByName(_meet(again, None).select("a", "b"))


def _rooted(docs: DataFrame, group: int) -> DataFrame:
    """fp, least (doc_id) and root, the least fingerprint of its component, of each class of equal fingerprints."""
    classes = cut(docs.groupBy("fp").agg(F.min("doc_id").alias("least")))
    stars = cut(graph.components(links(classes.select("fp"), group)))
    return classes.join(stars.select(F.col("a").alias("fp"), F.col("b").alias("root")), "fp", "left").withColumn("root", F.coalesce("root", "fp"))


def groups(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", words: int = 3, group: int = GROUP) -> DataFrame:
    """Per row: doc_id, fp and component_id, the least doc_id of all rows reachable through links."""
    docs = cut(fingerprints(df, id_col, text_col, words))
    rooted = _rooted(docs, group)
    tops = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    return docs.join(rooted.join(tops, "root").select("fp", "component_id"), "fp").select("doc_id", "fp", "component_id")


def hex_fingerprint(fp) -> F.Column:
    return F.lpad(F.lower(F.hex(fp)), 16, "0")


def keep_one(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each group, all columns unchanged; ``one_of_each`` says which.  Rows that share an id are rows of their own groups."""
    docs = cut(fingerprints(df, id_col, text_col, digest=True))
    return one_of_each(df, docs.join(_rooted(docs, GROUP).select("fp", "root"), "fp"), id_col, text_col)

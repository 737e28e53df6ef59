"""Near-duplicate groups by the Jaccard similarity of five-word shingle sets: every pair of 0.8 or more is linked.

SimHash comes first: the fingerprints of five-word shingles meet in the covering tables of ``simhash``, and classes whose fingerprints differ in
three bits at most are linked if their whole sets are similar.  Similar sets can differ in more bits than any such tables hold, so what SimHash
leaves apart is brought together by its shingles.

A text's shingles are hashed to 64 bits and brought into one order for the whole table.  A set of n shingles that is
similar enough to another misses n - ceil(0.8 n) of its own there at most, so of two such sets the first
n - ceil(0.8 n) + 1 of each have one in common: pairs meet at these, are sifted by sizes, places and parities (which
show at most as many differences as there are), and then compared by their whole sets.  Nothing is drawn at random but the order: shingles that many texts of a sample have come last, so that few
texts are listed under them; any order gives the same pairs.  Equal sets are one class before that.  A listing of over
``GROUP`` classes first links neighbours by size; then only classes that those links left apart are paired.

Defined results: null and wordless texts have the empty set and are one class; a text of up to five words has one shingle,
all of it; repeated rows are rows of their class each; a null id is never a group's name unless no member has an id; an empty
table gives no rows.  Two different shingles, or sets, count as the same if their 64-bit hashes are.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import graph, simhash
from .common import cut, map_texts, md5_of, one_of_each, release_memory, utf8

WORDS, SEED = 5, 42
#: One text in so many is read for the order, and shingles that this many of them have come last; the longest list of these.
SAMPLE, OFTEN, LISTED = 16, 4, 200_000
#: Classes under one shingle that are all paired at once, and neighbours that larger listings link first.
GROUP, NEIGHBOURS = 16, 4
#: Names of documents to be compared that are broadcast; more are joined by a shuffle.
NAMES = 1_000_000


def similar(shared, a, b):
    """Jaccard similarity of 0.8 or more in whole numbers: shared shingles, sizes of the sets."""
    return 9 * shared >= 4 * (a + b)


def distinct(hashes: bytes) -> np.ndarray:
    return np.unique(np.frombuffer(hashes, np.int64))


def shingles(text: bytes, words: int = WORDS) -> np.ndarray:
    """Distinct hashes of a UTF-8 text's word shingles, ascending."""
    return distinct(simhash.digests(text, words, SEED))


def set_name(s: np.ndarray) -> int:
    """The set's own hash, signed."""
    x = xxhash.xxh64_intdigest(s.tobytes(), SEED) if len(s) else 0
    return x - (1 << 64) if x >> 63 else x


def leading(s: np.ndarray, often: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """The shingles of a set at which it meets every similar one; ``often`` (ascending) come last, by their rank."""
    if not len(s):
        return s
    if len(often):
        at = np.minimum(np.searchsorted(often, s), len(often) - 1)
        late = often[at] == s
        s = np.concatenate([s[~late], s[late][np.argsort(rank[at[late]])]])
    return s[: len(s) - (4 * len(s) + 4) // 5 + 1]


def parity(s: np.ndarray) -> bytes:
    """Parities of the numbers of shingles in at least as many buckets as there are shingles, a power of two."""
    width = max(256, 1 << (max(1, len(s)) - 1).bit_length())
    return np.packbits(np.bincount(s & (width - 1), minlength=width) & 1 == 1, bitorder="little").tobytes()


def differences(a: bytes, b: bytes) -> int:
    """Shingles in one set only, at least so many; the wider parities are folded."""
    x, y = np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64)
    if len(x) < len(y):
        x, y = y, x
    return int(np.bitwise_count(np.bitwise_xor.reduce(x.reshape(-1, len(y)), 0) ^ y).sum())


def _lists(rows: list[np.ndarray]) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, rows)]), pa.int32()), pa.array(np.concatenate([np.zeros(0, np.int64), *rows])))


def sets(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """doc_id, s (the set's hash) and shingles."""

    def kernel(batches: Iterable[pa.RecordBatch]) -> Iterator[dict]:
        for batch in batches:
            found = [shingles(x) for x in utf8(batch, "text")]
            yield {"doc_id": batch.column(0), "s": [set_name(x) for x in found], "shingles": _lists(found)}
        release_memory()

    return map_texts(df, id_col, text_col, kernel, "doc_id long, s long, shingles array<long>")


def order(df: DataFrame, id_col: str, text_col: str, sample: int = SAMPLE, often: int = OFTEN) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that come last, ascending, and their ranks: the rarer, the earlier."""
    some = df.where(F.pmod(F.xxhash64(F.col(text_col)), F.lit(sample)) == 0)
    found = sets(some, id_col, text_col).dropDuplicates(["s"]).select(F.explode("shingles").alias("g")).groupBy("g").agg(F.count("*").alias("n"))
    got = found.where(F.col("n") >= often).orderBy(F.desc("n"), "g").limit(LISTED).toArrow()
    g, n = got["g"].to_numpy().astype(np.int64), got["n"].to_numpy().astype(np.int64)
    by = np.argsort(g)
    rank = np.empty(len(g), np.int64)
    rank[np.lexsort((g, n))] = np.arange(len(g))
    return g[by], rank[by]


def prefixes(df: DataFrame, id_col: str, text_col: str, last: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """doc_id, digest, s, fp (SimHash of its shingles), n (size of the set), parity, and prefix (the shingles that it is listed under)."""
    shared = df.sparkSession.sparkContext.broadcast(last)

    def kernel(batches: Iterable[pa.RecordBatch]) -> Iterator[dict]:
        often, rank = shared.value
        for batch in batches:
            given = utf8(batch, "text")
            hashes = [simhash.digests(x, WORDS, SEED) for x in given]
            found = [distinct(x) for x in hashes]
            fp = [simhash.signed(simhash.folded(x)) for x in hashes]
            yield {"doc_id": batch.column(0), "digest": [md5_of(x) for x in given], "s": [set_name(x) for x in found], "fp": fp, "n": [len(x) for x in found], "parity": [parity(x) for x in found], "prefix": _lists([leading(x, often, rank) for x in found])}
        release_memory()

    return map_texts(df, id_col, text_col, kernel, "doc_id long, digest string, s long, fp long, n int, parity binary, prefix array<long>")


def _pairs(n: np.ndarray, at: np.ndarray, s: np.ndarray, part: np.ndarray, first: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of one listing (ascending by n) that can be similar and aren't of one part yet; ``first``: neighbours only."""
    low = np.searchsorted(n, (4 * n + 4) // 5)
    for i in range(1, len(n)):
        lo = max(low[i], i - NEIGHBOURS) if first else low[i]
        j = np.arange(lo, i)
        ok = similar(np.minimum(n[i] - at[i], n[j] - at[j]), n[i], n[j]) & (part[j] != part[i])
        if ok.any():
            near = s[j[ok]]
            yield np.minimum(near, s[i]), np.maximum(near, s[i])


def _scan(limit: int | None):
    """Over rows sorted by (g, n): candidate pairs (hot false) of each listing; of those over the limit neighbours, and their shingle (hot true)."""
    schema = pa.schema([("hot", pa.bool_()), ("a", pa.int64()), ("b", pa.int64())])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []
        out: list[tuple[np.ndarray, np.ndarray]] = []
        name, size = None, 0

        def full() -> pa.RecordBatch:
            a, b = (np.concatenate(c) for c in zip(*out, strict=True))
            out.clear()
            return pa.RecordBatch.from_arrays([pa.array(np.zeros(len(a), bool)), pa.array(a), pa.array(b)], schema=schema)

        def close() -> Iterator[pa.RecordBatch]:
            nonlocal size
            if sum(len(h[0]) for h in held) > 1:
                n, at, s, part = (np.concatenate(c) for c in zip(*held, strict=True))
                once = np.concatenate([[True], s[1:] != s[:-1]])  # copies stand together
                n, at, s, part = n[once], at[once], s[once], part[once]
                first = limit is not None and len(n) > limit
                if first:
                    yield pa.RecordBatch.from_arrays([pa.array([True]), pa.array([int(name)], pa.int64()), pa.array([0], pa.int64())], schema=schema)
                for pair in _pairs(n.astype(np.int64), at.astype(np.int64), s, part, first):
                    out.append(pair)
                    size += len(pair[0])
                    if size > 100_000:
                        yield full()
                        size = 0

        for batch in batches:
            g, n, at, s, part = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1, 2, 3, batch.num_columns - 1))
            edges = [0, *(np.flatnonzero(g[1:] != g[:-1]) + 1).tolist(), len(g)]
            for lo, hi in zip(edges, edges[1:]):
                if lo == hi:
                    continue
                if g[lo] != name:
                    yield from close()
                    held, name = [], g[lo]
                held.append([n[lo:hi], at[lo:hi], s[lo:hi], part[lo:hi]])
        yield from close()
        if out:
            yield full()
        held.clear()
        release_memory()

    return run


def _meet(listed: DataFrame, limit: int | None) -> DataFrame:
    """listed: g, n, at, s and part."""
    rows = listed.repartition("g").sortWithinPartitions("g", "n", "s")
    return rows.mapInArrow(_scan(limit), "hot boolean, a long, b long")


def _sift(pairs: DataFrame, docs: DataFrame) -> DataFrame:
    """Candidate pairs, once each, whose parities allow them to be similar."""
    one = docs.select("s", "n", "parity").dropDuplicates(["s"])
    x, y = (one.select(F.col("s").alias(c), F.col("n").alias(f"n{c}"), F.col("parity").alias(f"p{c}")) for c in "ab")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            total = batch.column("na").to_numpy() + batch.column("nb").to_numpy()
            found = np.array([differences(p, q) for p, q in zip(batch.column("pa").to_pylist(), batch.column("pb").to_pylist(), strict=True)], np.int64)
            yield batch.select(["a", "b"]).filter(pa.array(9 * found <= total))

    return pairs.distinct().join(x, "a").join(y, "b").select("a", "b", "na", "nb", "pa", "pb").mapInArrow(run, "a long, b long")


def _compare(met: DataFrame, df: DataFrame, docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Those of the candidate pairs whose whole sets are similar."""
    pairs = cut(_sift(met.select("a", "b"), docs))
    ends = cut(pairs.select(F.col("a").alias("s")).unionByName(pairs.select(F.col("b").alias("s"))).distinct())
    named = cut(docs.select("s", "doc_id").join(ends, "s").groupBy("s").agg(F.min("doc_id").alias("__least")).select("__least").distinct())
    named = F.broadcast(named) if named.count() <= NAMES else named
    whole = sets(df.join(named, df[id_col].cast("long").eqNullSafe(named["__least"]), "left_semi"), id_col, text_col)
    whole = cut(whole.join(ends, "s", "left_semi").dropDuplicates(["s"]).select("s", "shingles"))
    x, y = whole.select(F.col("s").alias("a"), F.col("shingles").alias("x")), whole.select(F.col("s").alias("b"), F.col("shingles").alias("y"))
    both = pairs.join(x, "a").join(y, "b")
    return both.where(similar(F.size(F.array_intersect("x", "y")), F.size("x"), F.size("y"))).select("a", "b")


def _met_by_fingerprint(docs: DataFrame) -> DataFrame:
    """Pairs of classes whose fingerprints are equal or within the radius, by the covering tables; a class stands for its fingerprint."""
    own = cut(docs.groupBy("s").agg(F.min("fp").alias("fp")))
    heads = cut(own.groupBy("fp").agg(F.min("s").alias("head")))
    same = own.join(heads, "fp").where("s <> head").select(F.col("head").alias("x"), F.col("s").alias("y"))
    x, y = (heads.select(F.col("fp").alias(c), F.col("head").alias(f"h{c}")) for c in "ab")
    near = simhash.links(heads.select("fp")).join(x, "a").join(y, "b").select(F.col("ha").alias("x"), F.col("hb").alias("y"))
    return same.unionByName(near).select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))


def _parted(listed: DataFrame, links: DataFrame) -> DataFrame:
    """listed with part, the least name of what the links join."""
    parts = cut(graph.components(links)).select(F.col("a").alias("s"), F.col("b").alias("root"))
    return listed.join(parts, "s", "left").select("g", "n", "at", "s", F.coalesce("root", "s").alias("part"))


def _rooted(df: DataFrame, docs: DataFrame, id_col: str, text_col: str, group: int) -> DataFrame:
    """s, least (doc_id) and root, the least name of its component, of each class of equal sets."""
    links = cut(_compare(_met_by_fingerprint(docs), df, docs, id_col, text_col))
    listed = docs.select("s", "n", F.posexplode("prefix").alias("at", "g")).select("g", "n", "at", "s")
    met = cut(_meet(_parted(listed, links), group))
    links = links.unionByName(cut(_compare(met.where("not hot"), df, docs, id_col, text_col)))
    hot = met.where("hot").select(F.col("a").alias("g"))
    if not hot.isEmpty():
        again = _parted(listed.join(hot, "g", "left_semi"), links)
        links = links.unionByName(cut(_compare(_meet(again, None), df, docs, id_col, text_col)))
    stars = cut(graph.components(links))
    classes = docs.groupBy("s").agg(F.min("doc_id").alias("least"))
    return classes.join(stars.select(F.col("a").alias("s"), F.col("b").alias("root")), "s", "left").withColumn("root", F.coalesce("root", "s"))


def _docs(df: DataFrame, id_col: str, text_col: str, last: tuple[np.ndarray, np.ndarray] | None) -> DataFrame:
    return cut(prefixes(df, id_col, text_col, order(df, id_col, text_col) if last is None else last))


def groups(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", group: int = GROUP, last: tuple[np.ndarray, np.ndarray] | None = None) -> DataFrame:
    """Per row: doc_id, s and component_id, the least doc_id of all rows reachable through similar pairs."""
    docs = _docs(df, id_col, text_col, last)
    rooted = _rooted(df, docs, id_col, text_col, group)
    tops = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    return docs.select("doc_id", "s").join(rooted.join(tops, "root").select("s", "component_id"), "s").select("doc_id", "s", "component_id")


def keep_one(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each group, all columns unchanged; ``one_of_each`` says which.  Rows that share an id are rows of their own groups."""
    docs = _docs(df, id_col, text_col, None)
    rooted = _rooted(df, docs, id_col, text_col, GROUP).select("s", "root")
    return one_of_each(df, docs.select("doc_id", "digest", "s").join(rooted, "s"), id_col, text_col)

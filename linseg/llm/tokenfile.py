"""Token-id files with keyed access through a minimal perfect hash.

Documents are sorted by id over range partitions; each partition writes one shard of raw little-endian ids (two bytes
an id where the vocabulary allows, else four) and one index file.  The index maps a document's key to its slot by
a minimal perfect hash (levels of collision-free bits, ranked), and the slot holds a fingerprint of the key and the
document's place; a key that isn't there is turned away by the fingerprint or, at last, by the key stored at that place.
The manifest routes a key to its shard (``Folder``).  Files get their final names by a rename
after they are whole, and the manifest names the files of the task attempt that counted, so a lost executor leaves
no half shard behind.

Defined results: a null text is empty and still gets the end id; rows without id come first; rows that share an id
follow each other by text, and the key finds the first of them with their number; rows that are equal keep any order; an
empty table gives no rows; texts of any length are encoded whole; the vocabulary's special strings are read as the library
reads them by default; columns other than id and text are never read, whatever their names.
"""

from __future__ import annotations

import gc
import io
import os
import re
import struct
import unicodedata
import uuid
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyarrow import fs as pafs
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import ensure_checkpoint_dir, pieces, release_memory
from .stretches import GENERATION, Store, joined, payload, ragged, run_lengths, split

END_ID = 2
#: Fixed values of the file format: magic, version, header of a shard (magic, version, bytes an id, documents, ids).
MAGIC, VERSION = b"LTOK", 1
_HEAD = "<4sIIQQ"
GAMMA, LEVELS = 2.0, 24
#: Ids that the reader holds at once.
READ_IDS = 4 << 20
#: Stands for a document's end among its words; marks that are parted from an ASCII word before them.
_END, _STOPS = ("end",), (".", ",")


def _mix(keys: np.ndarray, seed: int) -> np.ndarray:
    """Splitmix finaliser of 64-bit keys."""
    with np.errstate(over="ignore"):
        x = keys.astype(np.uint64) + np.uint64((0x9E3779B97F4A7C15 * (seed + 1)) % (1 << 64))
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


@dataclass
class PerfectHash:
    """Maps n distinct keys to 0..n-1; other keys get any slot or -1."""

    levels: list[np.ndarray]  # of bits, one byte each in memory, packed on disk
    rest: np.ndarray  # the few keys that no level placed, sorted

    @classmethod
    def build(cls, keys: np.ndarray) -> PerfectHash:
        left, levels = keys.astype(np.uint64), []
        while len(left) and len(levels) < LEVELS:
            size = max(64, int(-(-GAMMA * len(left) // 64)) * 64)
            at = (_mix(left, len(levels)) % np.uint64(size)).astype(np.int64)
            alone = np.bincount(at, minlength=size) == 1
            levels.append(alone)
            left = left[~alone[at]]
        return cls(levels, np.sort(left))

    def ready(self) -> PerfectHash:
        self.base = np.cumsum([0, *[int(x.sum()) for x in self.levels]])
        self.ranks = [np.cumsum(x) - x for x in self.levels]
        return self

    def slots(self, keys: np.ndarray) -> np.ndarray:
        keys = keys.astype(np.uint64)
        out = np.full(len(keys), -1, np.int64)
        todo = np.arange(len(keys))
        for i, bits in enumerate(self.levels):
            at = (_mix(keys[todo], i) % np.uint64(len(bits))).astype(np.int64)
            hit = bits[at]
            out[todo[hit]] = self.base[i] + self.ranks[i][at[hit]]
            todo = todo[~hit]
        if len(todo) and len(self.rest):
            at = np.minimum(np.searchsorted(self.rest, keys[todo]), len(self.rest) - 1)
            hit = self.rest[at] == keys[todo]
            out[todo[hit]] = self.base[-1] + at[hit]
        return out


def _fingerprint(keys: np.ndarray) -> np.ndarray:
    return (_mix(keys, 1000) & np.uint64(0xFFFF)).astype(np.uint16)


@dataclass
class Index:
    """keys: ids in file order, the first ``unnamed`` of them null; offsets: ids before each document, and the total."""

    unnamed: int
    keys: np.ndarray
    offsets: np.ndarray
    hash: PerfectHash
    prints: np.ndarray
    places: np.ndarray
    repeats: np.ndarray

    @classmethod
    def build(cls, keys: list, lengths: np.ndarray) -> Index:
        unnamed = sum(k is None for k in keys)
        named = np.array(keys[unnamed:], np.int64)
        distinct, first, repeats = np.unique(named, return_index=True, return_counts=True)
        distinct = distinct.view(np.uint64)
        h = PerfectHash.build(distinct).ready()
        slot = h.slots(distinct)
        prints, places, times = np.empty(len(distinct), np.uint16), np.empty(len(distinct), np.int64), np.empty(len(distinct), np.int64)
        prints[slot], places[slot], times[slot] = _fingerprint(distinct), first + unnamed, repeats
        return cls(unnamed, np.concatenate([np.zeros(unnamed, np.int64), named]), np.concatenate([[0], np.cumsum(np.asarray(lengths, np.int64))]).astype(np.int64), h, prints, places, times)

    def find(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Place of each id's first document (-1: not there) and the number of documents with that id."""
        keys = np.asarray(ids, np.int64).view(np.uint64)
        slot = self.hash.slots(keys)
        good = slot >= 0
        good[good] = self.prints[slot[good]] == _fingerprint(keys[good])
        good[good] = self.keys[self.places[slot[good]]] == keys[good].view(np.int64)  # one key in 65,536 shares another's fingerprint
        place, times = np.full(len(keys), -1, np.int64), np.zeros(len(keys), np.int64)
        place[good], times[good] = self.places[slot[good]], self.repeats[slot[good]]
        return place, times

    def dump(self) -> bytes:
        out = io.BytesIO()
        out.write(struct.pack("<4sIQQI", MAGIC, VERSION, self.unnamed, len(self.keys), len(self.hash.levels)))
        for bits in self.hash.levels:
            out.write(struct.pack("<Q", len(bits)))
            out.write(np.packbits(bits).tobytes())
        for a, kind in ((self.hash.rest, "<u8"), (self.prints, "<u2"), (self.places, "<i8"), (self.repeats, "<i8"), (self.keys, "<i8"), (self.offsets, "<i8")):
            out.write(struct.pack("<Q", len(a)))
            out.write(a.astype(kind).tobytes())
        return out.getvalue()

    @classmethod
    def parse(cls, data: bytes) -> Index:
        magic, version, unnamed, _, n = struct.unpack_from("<4sIQQI", data)
        if magic != MAGIC or version != VERSION:
            raise ValueError("not an index file of this format")
        at, levels = struct.calcsize("<4sIQQI"), []
        for _ in range(n):
            (size,) = struct.unpack_from("<Q", data, at)
            levels.append(np.unpackbits(np.frombuffer(data, np.uint8, size // 8, at + 8)).astype(bool))
            at += 8 + size // 8
        arrays = []
        for kind in ("<u8", "<u2", "<i8", "<i8", "<i8", "<i8"):
            (size,) = struct.unpack_from("<Q", data, at)
            arrays.append(np.frombuffer(data, kind, size, at + 8))
            at += 8 + size * np.dtype(kind).itemsize
        rest, prints, places, repeats, keys, offsets = arrays
        return cls(unnamed, keys, offsets, PerfectHash(levels, rest).ready(), prints, places, repeats)


def open_folder(uri: str) -> tuple[pafs.FileSystem, str]:
    if uri.startswith("file:/") and not uri.startswith("file://"):
        uri = "file://" + uri[5:]
    return pafs.FileSystem.from_uri(uri)


class Encoder:
    """Ids of texts; a stretch between ASCII white space is encoded once while it is in the store.

    The tokenizer drops white space and no match of its pattern, composition or case rule crosses any, so the
    stretches' ids joined are the text's.  Neither does a match cross from a letter to a full stop or comma, and ASCII
    text has one lower case: stretches that differ in those share the ids of their word.  Special tokens' strings, which
    the library finds before it folds case, are left to it.
    """

    def __init__(self, tokenizer_file: str, end_id: int = END_ID, cache: int = 2 * GENERATION):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(tokenizer_file)
        self.kind = "<u2" if max(self.tok.get_vocab_size(), end_id + 1) <= 1 << 16 else "<u4"
        vocab = self.tok.get_vocab()
        self.ends = np.zeros(max(vocab.values()) + 1, bool)
        self.ends[[i for t, i in vocab.items() if t.endswith("</w>")]] = True
        self.odd = "|".join(re.escape(x.content) for x in self.tok.get_added_tokens_decoder().values()) or r"[^\x00-\x{10FFFF}]"
        self.end_id = end_id
        self.store = Store([ragged(np.zeros(0, self.kind), np.zeros(0, np.int64))], cache)

    def _learn(self, group: list) -> None:
        """A word of letters only is one match of the pattern, whose last token alone ends a word: such words are encoded together and parted there."""
        words = [s for s in group if isinstance(s, str)]
        plain = [s for s in words if s.isalpha() and (s.isascii() or unicodedata.normalize("NFC", s).lower().isalpha())]
        keys, rest, flat, sizes = [], set(words).difference(plain), [], []
        for lo in range(0, len(plain), 4000):
            part = plain[lo : lo + 4000]
            ids = np.array(self.tok.encode(" ".join(part), add_special_tokens=False).ids, self.kind)
            cut = np.flatnonzero(self.ends[ids]) + 1
            if len(cut) != len(part):
                rest.update(part)
                continue
            keys += part
            flat.append(ids)
            sizes.append(np.diff(cut, prepend=0))
        rest = list(rest)
        for lo in range(0, len(rest), 20_000):
            got = [e.ids for e in self.tok.encode_batch_fast(rest[lo : lo + 20_000], add_special_tokens=False)]
            keys += rest[lo : lo + 20_000]
            flat.append(np.fromiter(chain.from_iterable(got), self.kind))
            sizes.append(np.fromiter(map(len, got), np.int64, len(got)))
        if len(words) < len(group):
            keys.append(_END)
            flat.append(np.array([self.end_id], self.kind))
            sizes.append(np.ones(1, np.int64))
        self.store.new.add(keys, [ragged(np.concatenate(flat).astype(self.kind), np.concatenate(sizes))])

    def encode(self, group: pa.Array) -> pa.Array:
        """Ids of each text (null: empty), with the end id."""
        found, code, n = split(pc.ascii_split_whitespace(pc.fill_null(group, "")))
        plain = pc.and_not(pc.string_is_ascii(found), pc.match_substring_regex(found, self.odd, ignore_case=True))
        low = pc.if_else(plain, pc.ascii_lower(found), found)
        tail = pc.and_(plain, pc.match_substring_regex(low, r"[a-z][.,]\z"))
        words = pc.if_else(tail, pc.utf8_slice_codeunits(low, 0, -1), low).dictionary_encode()
        keys = words.dictionary.to_pylist()
        at = [pc.index(words.dictionary, x).as_py() for x in _STOPS]
        more = [x for x, i in zip(_STOPS, at, strict=True) if i < 0]
        place = self.store.places([*keys, *more, _END], self._learn)
        stops, end = place[[i if i >= 0 else len(keys) + more.index(x) for x, i in zip(_STOPS, at, strict=True)]], place[-1]
        first = place[words.indices.to_numpy()]
        tail = tail.to_numpy(zero_copy_only=False)
        second = stops[pc.ends_with(low, _STOPS[1]).to_numpy(zero_copy_only=False).astype(np.int64)]
        parts = 1 + tail[code].astype(np.int64)
        ends = np.concatenate([[0], np.cumsum(parts)])
        edges = ends[np.cumsum(n)]  # of the texts, among the words
        total = np.diff(edges, prepend=0) + 1
        out = np.full(int(total.sum()), end)
        start = ends[:-1] + np.repeat(np.arange(len(n)), n)
        out[start] = first[code]
        two = tail[code]
        out[start[two] + 1] = second[code[two]]
        return joined(self.store.new.columns, out, total)[0]

    def rest(self) -> None:
        self.store.rest()
        release_memory()


@lru_cache(maxsize=2)
def encoder(tokenizer_file: str, end_id: int = END_ID) -> Encoder:
    return Encoder(tokenizer_file, end_id)


_MANIFEST = "shard string, least long, unnamed long, n_docs long, n_tokens long"


def write(docs: DataFrame, tokenizer_file: str, folder: str, id_col: str = "doc_id", text_col: str = "text", end_id: int = END_ID) -> DataFrame:
    """Writes shards, indexes and the manifest below ``folder`` (any file system that all executors share); returns the manifest."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        gc.disable()
        e = encoder(tokenizer_file, end_id)
        fs, root = open_folder(folder)
        name, keys, lengths = f"shard-{uuid.uuid4().hex}", [], []
        width, out = np.dtype(e.kind).itemsize, None
        for batch in pieces(batches, "text"):
            if out is None:
                fs.create_dir(root, recursive=True)
                out = fs.open_output_stream(f"{root}/{name}.part")
            ids = e.encode(batch.column(1))
            out.write(memoryview(payload(ids)).cast("B"))
            keys += batch.column(0).to_pylist()
            lengths.append(run_lengths(ids))
        if out is None:
            return
        e.rest()
        index = Index.build(keys, np.concatenate(lengths))
        out.write(struct.pack(_HEAD, MAGIC, VERSION, width, len(keys), int(index.offsets[-1])))  # at the end: a stream can't go back
        out.close()
        with fs.open_output_stream(f"{root}/{name}.idx") as f:
            f.write(index.dump())
        fs.move(f"{root}/{name}.part", f"{root}/{name}.ids")
        named = [k for k in keys if k is not None]
        yield pa.RecordBatch.from_pydict({"shard": [name], "least": pa.array(named[:1] or [None], pa.int64()), "unnamed": [index.unnamed], "n_docs": [len(keys)], "n_tokens": [int(index.offsets[-1])]})

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    rows = rows.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    rows.mapInArrow(run, _MANIFEST).write.mode("overwrite").parquet(f"{folder}/manifest")
    return manifest(docs.sparkSession, folder)


def manifest(spark: SparkSession, folder: str) -> DataFrame:
    """A row a shard, with ``start``, the ids of all shards before it.  One row a partition written, so the running sum is small."""
    order = Window.orderBy(F.col("least").asc_nulls_first(), "shard").rowsBetween(Window.unboundedPreceding, -1)
    return spark.read.schema(_MANIFEST).parquet(f"{folder}/manifest").withColumn("start", F.coalesce(F.sum("n_tokens").over(order), F.lit(0).cast("long")))


class Shard:
    """One shard opened for reading."""

    def __init__(self, folder: str, name: str):
        fs, root = open_folder(folder)
        with fs.open_input_stream(f"{root}/{name}.idx") as f:
            self.index = Index.parse(f.read())
        self.file = fs.open_input_file(f"{root}/{name}.ids")
        self.file.seek(self.file.size() - struct.calcsize(_HEAD))
        magic, version, self.width, docs, ids = struct.unpack(_HEAD, self.file.read(struct.calcsize(_HEAD)))
        if magic != MAGIC or version != VERSION or docs != len(self.index.keys) or ids != self.index.offsets[-1]:
            raise ValueError(f"{name}: ids and index don't belong together")

    def read(self, lo: int, hi: int) -> np.ndarray:
        """The ids from place lo to hi of the shard's id sequence."""
        self.file.seek(lo * self.width)
        return np.frombuffer(self.file.read((hi - lo) * self.width), f"<u{self.width}")

    def get(self, doc_id: int) -> list[np.ndarray]:
        """The ids of the documents with this id; empty if there is none."""
        place, times = (int(x[0]) for x in self.index.find(np.array([doc_id])))
        o = self.index.offsets
        return [self.read(int(o[i]), int(o[i + 1])) for i in range(place, place + times)] if place >= 0 else []


class Folder:
    """Keyed access to all shards of a folder: the key's shard is found by the manifest, which is one row a shard, and opened once."""

    def __init__(self, spark: SparkSession, folder: str):
        rows = [r for r in manifest(spark, folder).orderBy("start").collect() if r.least is not None]
        self.folder, self.least, self.names = folder, np.array([r.least for r in rows], np.int64), [r.shard for r in rows]
        self.open: dict[str, Shard] = {}

    def get(self, doc_id: int) -> list[np.ndarray]:
        """The ids of the documents with this id; empty if there is none.  Equal ids share a shard, for shards are ranges of ids."""
        at = int(np.searchsorted(self.least, doc_id, "right")) - 1
        if at < 0:
            return []
        name = self.names[at]
        if name not in self.open:
            self.open[name] = Shard(self.folder, name)
        return self.open[name].get(doc_id)


def read_back(shards: DataFrame, folder: str) -> DataFrame:
    """Per document, from the files: doc_id, start, n_tokens, ids_crc32.  Every named document is found through its key."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                s = Shard(folder, row["shard"])
                ix, o, n = s.index, s.index.offsets, len(s.index.keys)
                place, times = ix.find(ix.keys[ix.unnamed :])
                run_start = np.arange(n)
                if ix.unnamed < n:
                    first = np.concatenate([[True], ix.keys[ix.unnamed + 1 :] != ix.keys[ix.unnamed : -1]])
                    starts = np.flatnonzero(first)
                    within = np.arange(len(first)) - starts[np.cumsum(first) - 1]
                    if (within >= times).any():
                        raise ValueError(f"{row['shard']}: index and keys disagree")
                    run_start[ix.unnamed :] = place + within
                lo = 0
                while lo < n:
                    hi = max(lo + 1, int(np.searchsorted(o, o[lo] + READ_IDS, "right")) - 1)
                    at = run_start[lo:hi]
                    base, ids = int(o[at].min()), s.read(int(o[at].min()), int(o[at + 1].max()))
                    crc = [zlib.crc32(ids[int(o[i]) - base : int(o[i + 1]) - base].astype("<u4").tobytes()) for i in at.tolist()]
                    yield pa.RecordBatch.from_pydict({
                        "doc_id": pa.array(ix.keys[lo:hi], pa.int64(), mask=np.arange(lo, hi) < ix.unnamed),
                        "start": pa.array(o[at] + row["start"], pa.int64()), "n_tokens": pa.array(o[at + 1] - o[at], pa.int64()), "ids_crc32": pa.array(crc, pa.int64()),
                    })
                    lo = hi

    tasks = max(1, shards.count())
    return shards.select("shard", "start").repartition(tasks).mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def write_and_read(docs: DataFrame, tokenizer_file: str, folder: str | None = None) -> DataFrame:
    """Writes to ``folder``, or to a fresh one in the session's shared checkpoint folder, and reads back."""
    folder = folder or f"{ensure_checkpoint_dir(docs.sparkSession)}/tokens-{uuid.uuid4().hex}"
    return read_back(write(docs, tokenizer_file, folder), folder)

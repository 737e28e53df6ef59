"""Texts cut into stretches whose results are remembered, packed, in a store bounded by bytes.

A stretch is what stands between two spaces.  Its results (ids, bytes) lie in Arrow arrays side by side, found through one
dictionary of places; the results of a batch of texts are then one ``take`` of those arrays.  The store has two generations:
when the newer one holds more than its share of bytes it becomes the older one, which goes.  The keys of one batch always stay.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Sequence
from itertools import chain

import numpy as np
import pyarrow as pa

#: Bytes of one generation, and what an entry costs besides its key's characters and its results.
GENERATION, ENTRY = 64 << 20, 160


def ragged(flat: np.ndarray, lengths: np.ndarray) -> pa.Array:
    """A list array of consecutive runs of ``flat``."""
    ends = np.zeros(len(lengths) + 1, np.int64)
    np.cumsum(lengths, out=ends[1:])
    return pa.LargeListArray.from_arrays(pa.array(ends), pa.array(flat))


def run_lengths(x: pa.Array) -> np.ndarray:
    """Of a list or binary array without nulls, the length of each value."""
    at = 1 if pa.types.is_large_binary(x.type) else 0
    offsets = np.frombuffer(x.buffers()[1], np.int64)[x.offset : x.offset + len(x) + 1] if len(x) else np.zeros(1, np.int64)
    return np.diff(offsets) if at or len(x) else np.zeros(0, np.int64)


def payload(x: pa.Array) -> np.ndarray:
    """The values of a list or binary array, end to end."""
    if not len(x):
        return np.zeros(0, np.uint8 if pa.types.is_large_binary(x.type) else x.type.value_type.to_pandas_dtype())
    if pa.types.is_large_binary(x.type):
        offsets = np.frombuffer(x.buffers()[1], np.int64)
        data = np.frombuffer(x.buffers()[2], np.uint8) if x.buffers()[2] else np.zeros(0, np.uint8)
        return data[offsets[x.offset] : offsets[x.offset + len(x)]]
    return x.flatten().to_numpy()


def joined(columns: Sequence[pa.Array], place: np.ndarray, lengths: np.ndarray) -> list[pa.Array]:
    """For runs of places of the given lengths, the runs' results end to end, in each column."""
    out = []
    starts = np.cumsum(lengths) - lengths
    at = pa.array(place)
    for c in columns:
        got = c.take(at)
        own = run_lengths(got)
        ends = np.concatenate([[0], np.cumsum(own)]).astype(np.int64)
        edges = np.concatenate([ends[starts], ends[-1:]]) if len(lengths) else np.zeros(1, np.int64)
        data = payload(got)
        if pa.types.is_large_binary(c.type):
            out.append(pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(lengths), [None, pa.py_buffer(edges.astype(np.int64)), pa.py_buffer(np.ascontiguousarray(data))]))
        else:
            out.append(pa.LargeListArray.from_arrays(pa.array(edges.astype(np.int64)), pa.array(data)))
    return out


class Generation:
    def __init__(self, empty: Sequence[pa.Array]):
        self.place: dict = {}
        self.columns = list(empty)
        self.bytes = 0

    def add(self, keys: Sequence, columns: Sequence[pa.Array]) -> None:
        """Results of keys that are not here yet."""
        n = len(self.place)
        self.place.update(zip(keys, range(n, n + len(keys)), strict=True))
        self.columns = [pa.concat_arrays([a, b]) for a, b in zip(self.columns, columns, strict=True)]
        self.bytes += sum(c.nbytes for c in columns) + ENTRY * len(keys) + sum(len(k if isinstance(k, str) else k[0]) for k in keys)


class Store:
    """``empty``: an array without rows for each column of the results (large lists or large binaries)."""

    def __init__(self, empty: Sequence[pa.Array], size: int = GENERATION):
        self.empty, self.size = list(empty), size
        self.new, self.old = Generation(self.empty), Generation(self.empty)

    def turn(self) -> None:
        if self.new.bytes > self.size:
            self.old, self.new = self.new, Generation(self.empty)

    def rest(self) -> None:
        """Lets the older generation go, between tasks."""
        self.turn()
        self.old = Generation(self.empty)

    def missing(self, keys: Iterable) -> list:
        """Those that neither generation has; the newer one takes over what only the older one had."""
        out = [k for k in keys if k not in self.new.place]
        if self.old.place:
            get = self.old.place.get
            found = [(k, i) for k in out if (i := get(k)) is not None]
            if found:
                again, at = zip(*found, strict=True)
                at = pa.array(at, pa.int64())
                self.new.add(again, [c.take(at) for c in self.old.columns])
                out = [k for k in out if k not in self.old.place]
        return out

    def places(self, keys: list, learn: Callable[[list], None]) -> np.ndarray:
        """Places of distinct keys; ``learn`` adds what is missing."""
        self.turn()
        get = self.new.place.get
        at = list(map(get, keys))
        if None in at:
            if unknown := self.missing([k for k, v in zip(keys, at, strict=True) if v is None]):
                learn(unknown)
            at = list(map(get, keys))
        return np.array(at, np.int64)


def of_texts(store: Store, keys: list[list], learn: Callable[[list], None]) -> tuple[np.ndarray, np.ndarray]:
    """Places of all keys of all texts, end to end, and the number of each text's keys."""
    flat = list(chain.from_iterable(keys))
    store.turn()
    at = list(map(store.new.place.get, flat))
    if None in at:
        holes = [i for i, v in enumerate(at) if v is None]
        if unknown := store.missing({flat[i] for i in holes}):
            learn(unknown)
        place = store.new.place
        for i in holes:
            at[i] = place[flat[i]]
    return np.array(at, np.int64), np.fromiter(map(len, keys), np.int64, len(keys))


def split(parts: pa.Array) -> tuple[pa.Array, np.ndarray, np.ndarray]:
    """Of lists of strings: the distinct strings, the number of each one's string end to end, and the lists' lengths."""
    ends = parts.offsets.to_numpy()
    codes = parts.values.slice(int(ends[0]), int(ends[-1] - ends[0])).dictionary_encode()
    return codes.dictionary, codes.indices.to_numpy().astype(np.int64), np.diff(ends).astype(np.int64)

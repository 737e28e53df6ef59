"""One signal over many tasks: blocks, mergeable moments, and refinement by half-sweeps.

The driver holds k lines, k-1 cuts and one moment row a block.  A half-sweep moves every other cut: those pairs share no
points, so they are independent while the lines are frozen, and even pairs after odd ones is one of the orders the
method allows.  A block answers with a triple (sum of the error difference, its least running sum, where); triples
join in order by an associative rule, the leftmost minimum winning.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Callable, Iterable, Iterator
from copy import copy

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel, TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..kernels import merging
from ..kernels.refine import GAMMA, SWEEPS, TOL, over_size, uniform
from ..sources.tables import cut_lineage

BLOCK = 65_536
#: Block rows that may come to the driver (about a hundred bytes a dimension each).
MOST_BLOCKS = 200_000


def with_global_position(df: DataFrame, order: list[str], partitions: int | None = None) -> DataFrame:
    """Adds pos without a window over everything: range partitions, places inside each, and offsets of the partitions before."""
    n = partitions or max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    placed = df.repartitionByRange(n, *order).withColumn("__p", F.spark_partition_id())
    placed = placed.withColumn("__i", F.row_number().over(Window.partitionBy("__p").orderBy(*order)) - 1).persist(StorageLevel.MEMORY_AND_DISK)
    before, offsets = 0, []
    for r in placed.groupBy("__p").count().orderBy("__p").collect():
        offsets.append((r["__p"], before))
        before += r["count"]
    table = df.sparkSession.createDataFrame(offsets or [(0, 0)], "__p int, __before bigint")
    return placed.join(F.broadcast(table), "__p").withColumn("pos", F.col("__i") + F.col("__before")).drop("__p", "__i", "__before")


def moments_of(t: np.ndarray, x: np.ndarray) -> np.ndarray:
    """(n, t, tt, x.., tx.., xx) of points."""
    return np.concatenate([[len(t), t.sum(), t @ t], x.sum(0), t @ x, [(x * x).sum()]])


def _packed(block: int, t: np.ndarray | None, x: np.ndarray) -> pa.RecordBatch:
    """One block as one row: its points by dimension, compressed."""
    shrink = lambda v: pa.compress(np.ascontiguousarray(v).tobytes(), "zstd", asbytes=True)
    cols = [pa.array([block], pa.int64()), pa.array([len(x)], pa.int32()), pa.array([x.shape[1]], pa.int32()), pa.array([None if t is None else shrink(t)], pa.binary()), pa.array([shrink(x.T)], pa.binary())]
    return pa.RecordBatch.from_arrays(cols, names=["block", "n", "d", "t", "x"])


PACKED = "block bigint, n int, d int, t binary, x binary"


def _flat(col: pa.Array, n: int) -> np.ndarray:
    return col.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(n, -1)


def _pack(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (block, t, x) in order, a block's together."""
    held, ts, xs = None, [], []
    for batch in batches:
        block, t, x = batch.column(0).to_numpy(), batch.column(1).to_numpy(), _flat(batch.column(2), batch.num_rows)
        edges = [0, *(np.flatnonzero(np.diff(block)) + 1).tolist(), len(block)]
        for a, b in zip(edges, edges[1:]):
            if a == b:
                continue
            if held is not None and block[a] != held:
                yield _packed(held, np.concatenate(ts), np.concatenate(xs))
                ts, xs = [], []
            held = int(block[a])
            ts.append(t[a:b].astype(float))
            xs.append(x[a:b])
    if held is not None:
        yield _packed(held, np.concatenate(ts), np.concatenate(xs))


class _Reader:
    """Points of packed blocks: (block, places, t in centred units, x).  Of every step-th place, where step is over one."""

    def __init__(self, start: dict[int, int], step: int = 1, values: Callable | None = None, t0: float = 0.0, span: float = 1.0, origin: np.ndarray | float = 0.0):
        self.start, self.step, self.values, self.t0, self.span, self.origin = start, step, values, t0, span, origin

    def raw(self, batches: Iterable[pa.RecordBatch]) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
        for batch in batches:
            for block, n, d, t, x in zip(*[batch.column(i).to_pylist() for i in range(3)], batch.column(3), batch.column(4), strict=True):
                pos = np.arange(self.start[block], self.start[block] + n)
                grow = lambda v, size: np.frombuffer(pa.decompress(v.as_buffer(), size, "zstd"))
                t = grow(t, 8 * n) if t.is_valid else pos.astype(float)
                x = grow(x, 8 * n * d).reshape(d, n).T
                first = -int(pos[0]) % self.step
                pos, t, x = pos[first :: self.step], t[first :: self.step], x[first :: self.step]
                if len(pos):
                    yield block, pos // self.step, t, x if self.values is None else self.values(pos, x)

    def __call__(self, batches: Iterable[pa.RecordBatch]) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
        for block, pos, t, x in self.raw(batches):
            yield block, pos, (t - self.t0) / self.span - 0.5, x - self.origin


class Blocks:
    """A single signal (pos, t, x) cut into blocks of so many places, packed a row a block, with a pyramid of block moments on the driver."""

    def __init__(self, sig: DataFrame, block: int = BLOCK):
        rows = sig.select(F.floor(F.col("pos") / block).cast("bigint").alias("block"), "pos", F.col("t").cast("double").alias("t"), F.col("x").cast("array<double>").alias("x"))
        rows = rows.repartition("block").sortWithinPartitions("block", "pos").select("block", "t", "x")
        self._open(rows.mapInArrow(_pack, PACKED).persist(StorageLevel.MEMORY_AND_DISK))

    @classmethod
    def ordered(cls, df: DataFrame, order: list[str], x: Column, block: int = BLOCK, values: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None) -> Blocks:
        """The signal of all rows in this order, t their places: one shuffle, by ranges, whose partitions are packed where they lie.

        The places come from the blocks' sizes, so nothing but packed x is kept; ``values`` makes the signal's values of places and x
        whenever a block is read.
        """
        n = max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            name, held, size = TaskContext.get().partitionId() << 32, [], 0
            for batch in batches:
                rest = _flat(batch.column(0), batch.num_rows)
                while len(rest):
                    part, rest = rest[: block - size], rest[block - size :]
                    held.append(part)
                    size += len(part)
                    if size == block:
                        yield _packed(name, None, np.concatenate(held))
                        name, held, size = name + 1, [], 0
            if size:
                yield _packed(name, None, np.concatenate(held))

        rows = df.repartitionByRange(n, *order).sortWithinPartitions(*order).select(x.cast("array<double>").alias("x"))
        out = cls.__new__(cls)
        out._open(rows.mapInArrow(run, PACKED).persist(StorageLevel.MEMORY_AND_DISK), values)
        return out

    def _open(self, rows: DataFrame, values: Callable | None = None) -> None:
        self.rows = rows
        if rows.count() > MOST_BLOCKS:
            raise ValueError("too many blocks for the driver; take a larger block")
        found = sorted((r.block, r.n) for r in rows.select("block", "n").collect())
        self.ids = [b for b, _ in found]
        self.first = np.concatenate([[0], np.cumsum([n for _, n in found], dtype=np.int64)])
        self.n = int(self.first[-1])
        raw = _Reader(dict(zip(self.ids, self.first.tolist())), 1, values)

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for _, _, t, x in raw.raw(batches):
                yield pa.RecordBatch.from_pydict({"lo": [float(t.min())], "hi": [float(t.max())], "total": [x.sum(0).tolist()]})

        got = self.rows.mapInArrow(run, "lo double, hi double, total array<double>").collect()
        self.t0 = min(r.lo for r in got)
        self.span = (max(r.hi for r in got) - self.t0) or 1.0
        self.origin = np.sum([r.total for r in got], 0) / self.n
        self.d = len(self.origin)
        self._measure(_Reader(raw.start, 1, values, self.t0, self.span, self.origin))

    def _measure(self, read: _Reader) -> None:
        """The blocks' moments."""
        self.read = read
        self.edges = -(-self.first // read.step)
        self.n = int(self.edges[-1])
        at = {b: i for i, b in enumerate(self.ids)}
        self.level = np.zeros((len(self.ids), self.width))
        for b, v in self._moments(self.rows, {}):
            self.level[at[b]] = v
        self.run = np.concatenate([np.zeros((1, self.width)), np.cumsum(self.level, 0)])

    def every(self, step: int) -> Blocks:
        """The signal of every step-th point: the same packed rows, thinned when they are read."""
        out, r = copy(self), self.read
        out._measure(_Reader(r.start, r.step * step, r.values, r.t0, r.span, r.origin))
        return out

    @property
    def width(self) -> int:
        return 4 + 2 * self.d

    def _moments(self, rows: DataFrame, wanted: dict[int, list[int]]) -> list[tuple[int, np.ndarray]]:
        """Moments in centred units: (block, of all its points), or (place, of its block's points before it) of the wanted places by block."""
        read = self.read

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for block, pos, t, x in read(batches):
                cut = [(p, int(np.searchsorted(pos, p))) for p in wanted[block]] if wanted else [(block, len(pos))]
                yield pa.RecordBatch.from_pydict({"key": [k for k, _ in cut], "sums": [moments_of(t[:i], x[:i]).tolist() for _, i in cut]})

        return [(r.key, np.array(r.sums)) for r in rows.mapInArrow(run, "key bigint, sums array<double>").collect()]

    def upto(self, places: list[int]) -> dict[int, np.ndarray]:
        """Moments of the points before each place: whole blocks from the pyramid, the rest of one block from the rows."""
        out, inside = {}, {}
        for p in places:
            i = int(np.searchsorted(self.edges, p, "right")) - 1
            out[p] = self.run[min(i, len(self.level))]
            if p < self.n and p > self.edges[i]:
                inside.setdefault(self.ids[i], []).append(p)
        if inside:
            for p, v in self._moments(self.rows.where(F.col("block").isin(list(inside))), inside):
                out[p] = out[p] + v
        out[self.n] = self.run[-1]
        return out

    def pieces(self, cuts: list[int]) -> np.ndarray:
        at = self.upto(cuts)
        m = np.array([at[c] for c in cuts])
        return m[1:] - m[:-1]

    def lines(self, m: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Intercepts, slopes (centred units) and costs of moment rows."""
        d = self.d
        n, st, stt, sx, stx, sxx = m[:, 0], m[:, 1], m[:, 2], m[:, 3 : 3 + d], m[:, 3 + d : 3 + 2 * d], m[:, -1]
        var, cov = stt - st * st / n, stx - (st / n)[:, None] * sx
        slope = np.where((var > 1e-18 * n)[:, None], cov / np.maximum(var, 1e-300)[:, None], 0.0)
        cost = sxx - (sx * sx).sum(1) / n - (slope * cov).sum(1)
        return (sx - slope * st[:, None]) / n[:, None], slope, np.maximum(cost, 0.0)

    def half_sweep(self, cuts: list[int], c: np.ndarray, m: np.ndarray, pairs: list[int], gamma: int) -> list[int]:
        """Moves the cuts of these (disjoint) pairs; one scan of the blocks they touch."""
        jobs = [(p, cuts[p], cuts[p + 2]) for p in pairs if cuts[p + 2] - cuts[p] >= 2 * gamma]
        if not jobs:
            return cuts
        lefts, rights = [j[1] for j in jobs], [j[2] for j in jobs]  # disjoint, so both ascend
        read = self.read
        schema = pa.schema([("pair", pa.int32()), ("block", pa.int64()), ("total", pa.float64()), ("least", pa.float64()), ("at", pa.int64())])

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            rows = []
            for block, pos, t, x in read(batches):
                for p, left, right in jobs[bisect_right(rights, pos[0]) : bisect_right(lefts, pos[-1])]:
                    i, j = np.searchsorted(pos, left), np.searchsorted(pos, right)
                    if i >= j:
                        continue
                    dc, dm = c[p] - c[p + 1], m[p] - m[p + 1]
                    tt, xx = t[i:j], x[i:j]
                    diff = -2 * (xx @ dc + tt * (xx @ dm)) + (c[p] @ c[p] - c[p + 1] @ c[p + 1]) + 2 * tt * (c[p] @ m[p] - c[p + 1] @ m[p + 1]) + tt * tt * (m[p] @ m[p] - m[p + 1] @ m[p + 1])
                    s = np.cumsum(diff)
                    cut = pos[i:j] + 1  # the running sum after a point is that of cutting behind it
                    ok = (cut >= left + gamma) & (cut <= right - gamma)
                    least = np.where(ok, s, np.inf)
                    k = int(np.argmin(least))
                    rows.append((p, block, float(s[-1]), float(least[k]), int(cut[k])))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(col, f.type) for col, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)

        lo, hi = np.searchsorted(self.edges, lefts[0], "right") - 1, np.searchsorted(self.edges, rights[-1], "left") - 1
        touched = self.rows.where(F.col("block").between(self.ids[lo], self.ids[hi]))
        got = touched.mapInArrow(run, "pair int, block bigint, total double, least double, at bigint").collect()
        cuts = list(cuts)
        folded: dict[int, tuple] = {}
        for r in sorted(got, key=lambda r: (r.pair, r.block)):
            new = (r.total, r.least, r.at)
            folded[r.pair] = _join(folded[r.pair], new) if r.pair in folded else new
        for p, (_, least, at) in folded.items():
            if np.isfinite(least):
                cuts[p + 1] = at
        return cuts


def _join(a: tuple, b: tuple) -> tuple:
    moved = a[0] + b[1]
    return (a[0] + b[0], *((a[1], a[2]) if a[1] <= moved else (moved, b[2])))


def refine(blocks: Blocks, cuts, gamma: int = GAMMA, tol: float = TOL, max_iter: int = SWEEPS) -> tuple[list[int], list[float]]:
    """Odd-even refinement; the same cuts as the one-task search with order='odd_even'."""
    cuts = [int(c) for c in cuts]
    c, m, cost = blocks.lines(blocks.pieces(cuts))
    trace = [float(cost.sum())]
    for _ in range(max_iter if len(cuts) > 2 else 0):
        before = cuts
        for first in (0, 1):
            cuts = blocks.half_sweep(cuts, c, m, list(range(first, len(cuts) - 2, 2)), gamma)
        c, m, cost = blocks.lines(blocks.pieces(cuts))
        now = float(cost.sum())
        if now > trace[-1]:
            cuts, now = before, trace[-1]
        trace.append(now)
        if trace[-2] - now <= tol * trace[-2]:
            break
    return cuts, trace


class _Merged:
    """Moments of a few pieces as a source of costs for the greedy merge."""

    def __init__(self, blocks: Blocks, cuts: list[int]):
        self.n, self.place = blocks.n, {c: i for i, c in enumerate(cuts)}
        self.run = np.concatenate([np.zeros((1, blocks.width)), np.cumsum(blocks.pieces(cuts), 0)])
        self.blocks = blocks

    def cost(self, i, j):
        at = lambda v: np.array([self.place[int(q)] for q in np.atleast_1d(v)], int)
        return self.blocks.lines(self.run[at(j)] - self.run[at(i)])[2] if np.size(i) else np.zeros(0)

    def one(self, i: int, j: int) -> float:
        return float(self.cost([i], [j])[0])


def refine_from_coarse(blocks: Blocks, k: int, step: int, gamma: int = GAMMA, **options) -> tuple[list[int], list[float]]:
    """The search on every step-th point, then a refinement on all."""
    if step <= 1:
        return refine_then_merge(blocks, k, gamma, **options)
    rough, _ = refine_then_merge(blocks.every(step), k, gamma, **options)
    return refine(blocks, [min(c * step, blocks.n) for c in rough], gamma, **options)


def merge(blocks: Blocks, cuts: list[int], k: int) -> list[int]:
    return merging.merge(_Merged(blocks, cuts), np.array(cuts), k)[0].tolist()


def refine_then_merge(blocks: Blocks, k: int, gamma: int = GAMMA, size: int | None = None, **options) -> tuple[list[int], list[float]]:
    start = uniform(blocks.n, size or over_size(blocks.n, k, gamma))
    cuts, trace = refine(blocks, start, gamma, **options)
    return merge(blocks, cuts, k), trace


def bottom_up(blocks: Blocks, k: int, cells: int) -> list[int]:
    """Greedy merging from so many even cells, whose moments come from one aggregate and fit the driver; ``bottom_up_rounds`` takes any number."""
    return merge(blocks, uniform(blocks.n, min(cells, max(k, blocks.n // 2))).tolist(), k)


def bottom_up_rounds(sig: DataFrame, d: int, delta: int, k: int, few: int = 64) -> DataFrame:
    """Approximate merging for any number of cells: each round fuses every pair whose gain is least among its neighbours.

    Not the strict greedy order: a fusion can make its neighbour cheaper.  Rounds halve the cells at best, each
    checkpointed, until every signal has ``few`` (at least 2k) or less; those go to the strict merge, which leaves k
    (all cells where there are fewer).  Returns signal_id, cell (its first place), moments.
    """
    from .fit import moments

    few = max(few, 2 * k)
    cells = cut_lineage(moments(sig.withColumn("cell", F.floor(F.col("pos") / delta) * delta), d, ["signal_id", "cell"]))
    before = None
    while True:
        most, now = cells.groupBy("signal_id").count().agg(F.max("count"), F.sum("count")).first()
        if most is None or most <= few or now == before:
            break
        before, cells = now, cut_lineage(_round(cells, d, few))
    return cells.groupBy("signal_id").applyInPandas(lambda p: _strict(p, d, k), cells.schema)


def _round(cells: DataFrame, d: int, few: int) -> DataFrame:
    """One round over the signals of more than ``few`` cells."""
    from ..functions import columns as C

    w = Window.partitionBy("signal_id").orderBy("cell")
    nxt = {n: F.lead(n).over(w) for n in C.sum_names(d)}
    gained = cells.select("*", F.count("*").over(Window.partitionBy("signal_id")).alias("cells"), *[v.alias(f"next_{n}") for n, v in nxt.items()])
    own, other = (lambda n: F.col(n)), (lambda n: F.col(f"next_{n}"))
    both = lambda n: F.col(n) + F.col(f"next_{n}")
    gain = C.line_cost(both, d) - C.line_cost(own, d) - C.line_cost(other, d)
    g = gained.withColumn("gain", F.when(F.col("next_n").isNotNull() & (F.col("cells") > few), gain)).withColumn("left", F.lag("gain").over(w)).withColumn("right", F.lead("gain").over(w))
    fuse = g.withColumn("fuse", F.col("gain").isNotNull() & (F.col("left").isNull() | (F.col("gain") < F.col("left"))) & (F.col("right").isNull() | (F.col("gain") <= F.col("right"))))
    gone = F.coalesce(F.lag("fuse").over(w), F.lit(False))
    head = fuse.withColumn("target", F.when(gone, F.lag("cell").over(w)).otherwise(F.col("cell")))
    return head.groupBy("signal_id", F.col("target").alias("cell")).agg(*[F.sum(n).alias(n) for n in C.sum_names(d)])


class _Cells:
    """Cell moments, in order, as a source of costs for the greedy merge; places are cell numbers."""

    def __init__(self, rows: np.ndarray, d: int):
        self.n, self.d = len(rows), d
        self.run = np.concatenate([np.zeros((1, rows.shape[1])), np.cumsum(rows, 0)])

    def cost(self, i, j):
        m = self.run[np.asarray(j, int)] - self.run[np.asarray(i, int)]
        n, st, stt, sx, stx, sxx = m[:, 0], m[:, 1], m[:, 2], m[:, 3::3], m[:, 4::3], m[:, 5::3]
        var, cov = stt - st * st / n, stx - st[:, None] * sx / n[:, None]
        flat = sxx - sx * sx / n[:, None] - cov * cov / np.where(var > 0, var, 1.0)[:, None]
        return np.where(n > 2, np.maximum(flat.sum(1), 0.0), 0.0)

    def one(self, i: int, j: int) -> float:
        return float(self.cost([i], [j])[0])


def _strict(p, d: int, k: int):
    from ..functions import columns as C

    p = p.sort_values("cell", ignore_index=True)
    starts = merging.merge(_Cells(p[C.sum_names(d)].to_numpy(float), d), np.arange(len(p) + 1), k)[0][:-1]
    out = p.iloc[starts].copy()
    out[C.sum_names(d)] = np.add.reduceat(p[C.sum_names(d)].to_numpy(float), starts, 0)
    return out


def pieces(blocks: Blocks, cuts: list[int], signal_id: str, method: str, trace: list[float], seconds: float) -> list[dict]:
    """The model as rows of ``spec.PIECES``, in the signal's own units."""
    c, m, cost = blocks.lines(blocks.pieces(cuts))
    slope = m / blocks.span
    level = c + blocks.origin - slope * (blocks.t0 + 0.5 * blocks.span)
    return [
        {
            "signal_id": signal_id, "method": method, "seg_no": i, "start_pos": int(a), "end_pos": int(b), "n": int(b - a), "intercept": level[i].tolist(), "slope": slope[i].tolist(), "sse": float(cost[i]), "cost": float(cost.sum()), "k": len(cuts) - 1,
            "sweeps": max(0, len(trace) - 1), "runtime_s": seconds, "trace": [float(v) for v in trace] if i == 0 else None, "exact_k": True,
        }
        for i, (a, b) in enumerate(zip(cuts, cuts[1:]))
    ]

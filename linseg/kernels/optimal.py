"""Exact searches, and dynamic programming over error-balanced cells."""

from __future__ import annotations

from itertools import combinations

import numpy as np

from .moments import Linear, Unfit
from .refine import GAMMA, partitions, refine

TABLE_BYTES = 512 << 20
#: Points up to which the costs of all ranges are held at once.
WHOLE = 1024


def table(signal: Linear, k: int, gamma: int = GAMMA, grid: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Least cost with j pieces ending at each grid place, the place before, and the grid; smaller starts win ties."""
    grid = np.arange(signal.n + 1) if grid is None else np.asarray(grid)
    m = len(grid)
    if k * m * 12 > TABLE_BYTES:
        raise Unfit("the table would be too large; use dynamic programming over cells")
    best, back = np.full((k + 1, m), np.inf), np.zeros((k + 1, m), np.int32)
    best[0, 0] = 0.0
    whole = signal.all_costs() if m == signal.n + 1 and signal.n <= WHOLE else None
    for e in range(1, m):
        s = int(np.searchsorted(grid, grid[e] - gamma, "right"))
        if s:
            if whole is not None:
                signal.count.evals += s
            sums = best[:k, :s] + (signal.upto(grid[:s], int(grid[e])) if whole is None else whole[e, :s])
            at = np.argmin(sums, 1)
            best[1:, e], back[1:, e] = sums[np.arange(k), at], at
    return best, back, grid


def trace_back(back: np.ndarray, grid: np.ndarray, k: int) -> np.ndarray:
    at, out = len(grid) - 1, [int(grid[-1])]
    for j in range(k, 0, -1):
        at = int(back[j, at])
        out.append(int(grid[at]))
    return np.array(out[::-1])


def optimal_partition(signal: Linear, k: int, gamma: int = GAMMA, grid: np.ndarray | None = None) -> np.ndarray:
    best, back, grid = table(signal, k, gamma, grid)
    return trace_back(back, grid, k)


def optimal_path(signal: Linear, k_max: int, gamma: int = GAMMA) -> list[tuple[int, float, np.ndarray]]:
    """(k, cost, cuts) of every feasible number of pieces from one table."""
    best, back, grid = table(signal, k_max, gamma)
    return [(k, float(best[k, -1]), trace_back(back, grid, k)) for k in range(1, k_max + 1) if np.isfinite(best[k, -1])]


def penalized_optimal(signal: Linear, beta: float, gamma: int = GAMMA) -> np.ndarray:
    """Least cost + beta * pieces.

    A start that does worse up to e than a cut at e would can't win an end where a piece may start at e, from e + gamma on;
    it is dropped there, not before.
    """
    n = signal.n
    best, back = np.full(n + 1, np.inf), np.zeros(n + 1, int)
    best[0] = -beta
    live = np.array([0])
    until = np.full(n + 1, n + 1)
    slack = 1e-9 * signal.total
    for e in range(gamma, n + 1):
        live = live[until[live] > e]
        ready = live[live <= e - gamma]
        sums = best[ready] + signal.upto(ready, e)
        at = int(np.argmin(sums))
        best[e], back[e] = sums[at] + beta, ready[at]
        beaten = ready[sums > best[e] + slack]
        until[beaten] = np.minimum(until[beaten], e + gamma)
        live = np.append(live, e)
    out = [n]
    while out[-1] > 0:
        out.append(int(back[out[-1]]))
    return np.array(out[::-1])


def all_costs(signal: Linear) -> np.ndarray:
    """Costs of all ranges [i, j) at row j, column i; infinite where i >= j."""
    signal.count.evals += signal.n * (signal.n + 1) // 2
    return signal.all_costs()


def _penalized_by_table(costs: np.ndarray, betas: list[float], gamma: int) -> list[np.ndarray]:
    """The cuts that ``penalized_optimal`` finds for each penalty, from the costs of all ranges."""
    n, each, beta = len(costs) - 1, np.arange(len(betas)), np.array(betas)
    best, back = np.full((len(betas), n + 1), np.inf), np.zeros((len(betas), n + 1), int)
    best[:, 0] = -beta
    for e in range(gamma, n + 1):
        sums = best[:, : e - gamma + 1] + costs[e, : e - gamma + 1]
        at = sums.argmin(1)
        best[:, e], back[:, e] = sums[each, at] + beta, at
    found = []
    for row in back:
        out = [n]
        while out[-1] > 0:
            out.append(int(row[out[-1]]))
        found.append(np.array(out[::-1]))
    return found


def penalized(signal: Linear, beta: float, gamma: int = GAMMA) -> np.ndarray:
    """``penalized_optimal``, from one table of all costs where the signal is short enough for it."""
    return _penalized_by_table(all_costs(signal), [beta], gamma)[0] if signal.n <= WHOLE else penalized_optimal(signal, beta, gamma)


def penalized_for_k(signal: Linear, k: int, gamma: int = GAMMA, steps: int = 60) -> tuple[np.ndarray, float, int]:
    """Cuts of the penalty that gives k pieces, or the nearest number if the penalties skip k; the penalty; runs.

    Where the signal is short enough, penalties are tried on one table of all costs, three halvings ahead at once.
    """
    costs = all_costs(signal) if signal.n <= WHOLE else None
    known: dict[float, np.ndarray] = {}

    def search(lo: float, hi: float) -> np.ndarray:
        """Cuts of the penalty halfway."""
        if costs is None:
            return penalized_optimal(signal, (lo + hi) / 2, gamma)
        if (lo + hi) / 2 not in known:
            spans, betas = [(lo, hi)], []
            while spans and len(betas) < 7:
                a, b = spans.pop(0)
                betas.append((a + b) / 2)
                spans += [(a, betas[-1]), (betas[-1], b)]
            known.update(zip(betas, _penalized_by_table(costs, betas, gamma), strict=True))
        return known[(lo + hi) / 2]

    lo, hi = 0.0, max(signal.one(0, signal.n), 1e-12)
    best, beta = search(hi, hi), hi
    runs = 1
    while runs < steps and len(best) - 1 != k:
        mid = (lo + hi) / 2
        cuts = search(lo, hi)
        runs += 1
        got = len(cuts) - 1
        if abs(got - k) < abs(len(best) - 1 - k):
            best, beta = cuts, mid
        lo, hi = (mid, hi) if got > k else (lo, mid)
        if hi - lo < 1e-12 * hi:
            break
    return best, beta, runs


def brute_force(signal: Linear, k: int, gamma: int = GAMMA, limit: int = 1_000_000) -> np.ndarray:
    n = signal.n
    if partitions(n, k, gamma) > limit:
        raise Unfit("too many partitions for exhaustive search")
    at = np.arange(n + 1)
    cost = np.full((n + 1, n + 1), np.inf)
    for e in range(gamma, n + 1):
        cost[: e - gamma + 1, e] = signal.cost(at[: e - gamma + 1], e)
    if k == 1:
        return np.array([0, n])
    best, chosen = np.inf, None
    inner = range(gamma, n - gamma + 1)
    for cuts in combinations(inner, k - 1):
        whole = (0, *cuts, n)
        total = sum(cost[a, b] for a, b in zip(whole, whole[1:]))
        if total < best:
            best, chosen = total, whole
    return np.array(chosen)


def bicriteria(signal: Linear, k: int, gamma: int = GAMMA) -> tuple[float, list[tuple[int, int]]]:
    """A cost scale from more than k pieces: slice what is left into about 4k even parts, bank the cheaper half, go on with the rest."""
    left, banked, total = [(0, signal.n)], [], 0.0
    while left:
        points = sum(b - a for a, b in left)
        size = max(gamma, -(-points // (4 * k)))
        parts = [(s, min(s + size, b)) for a, b in left for s in range(a, b, size)]
        cost = signal.cost([a for a, _ in parts], [b for _, b in parts])
        order = np.argsort(cost, kind="stable")
        take = len(parts) if size <= gamma or len(parts) <= 2 * k else -(-len(parts) // 2)
        banked += [parts[i] for i in order[:take]]
        total += float(cost[order[:take]].sum())
        left = sorted(parts[i] for i in order[take:])
    return total, sorted(banked)


def balanced_cells(signal: Linear, budget: float) -> np.ndarray:
    """Edges of cells grown from the left while their line cost stays within the budget.

    The best cost never falls as points are added, so the end is found by doubling and halving.
    """
    budget = max(budget, 1e-12 * signal.total)
    edges, n = [0], signal.n
    while edges[-1] < n:
        a, step = edges[-1], 1
        good = min(a + 2, n)
        while good < n and signal.one(a, min(good + step, n)) <= budget:
            good = min(good + step, n)
            step *= 2
        bad = min(good + step, n)
        while bad - good > 1:
            mid = (good + bad) // 2
            if signal.one(a, mid) <= budget:
                good = mid
            else:
                bad = mid
        edges.append(good)
    return np.array(edges)


def cell_edges(signal: Linear, k: int, sf: float | str = 50) -> tuple[np.ndarray, float]:
    """Edges of the balanced cells and the factor."""
    factor = 100 * np.log2(max(signal.n, 2)) if sf == "log" else float(sf)
    return balanced_cells(signal, bicriteria(signal, k)[0] / (k * factor)), factor


def compress_svd(points: np.ndarray) -> np.ndarray:
    """A small set of rows with the same Gram matrix as (1, t, x): any line's squared error over it is that over the points."""
    _, s, vt = np.linalg.svd(points, full_matrices=False)
    return s[:, None] * vt


class Compressed(Linear):
    """Costs of unions of cells from the cells' small point sets; gives the same numbers as the moments."""

    def __init__(self, signal: Linear, edges: np.ndarray):
        self.n, self.d, self.count, self.total = signal.n, signal.d, signal.count, signal.total
        self.place = {int(e): i for i, e in enumerate(edges)}
        rows = np.column_stack([np.ones(signal.n), signal.t, signal.x])
        grams = np.array([(g := compress_svd(rows[a:b])).T @ g for a, b in zip(edges, edges[1:])])
        self.gram = np.concatenate([np.zeros((1, *grams.shape[1:])), np.cumsum(grams, 0)])

    def cost(self, i, j):
        i, j = np.broadcast_arrays(np.asarray(i), np.asarray(j))
        self.count.evals += i.size
        out = np.zeros(i.shape)
        for at in np.ndindex(i.shape):
            g = self.gram[self.place[int(j[at])]] - self.gram[self.place[int(i[at])]]
            if int(j[at]) - int(i[at]) > 2:
                out[at] = max(0.0, float(np.trace(g[2:, 2:]) - np.sum(g[:2, 2:] * (np.linalg.pinv(g[:2, :2]) @ g[:2, 2:]))))
        return out


def optimal_over_cells(signal: Linear, k: int, sf: float | str = 50, gamma: int = GAMMA, compress: str = "moments") -> tuple[np.ndarray, int]:
    """Dynamic programming restricted to cell edges; also the number of cells.  Cells too few or too long for k pieces are halved."""
    edges, _ = cell_edges(signal, k, sf)
    while True:
        source = Compressed(signal, edges) if compress == "svd" else signal
        best, back, grid = table(source, k, gamma, edges)
        if np.isfinite(best[k, -1]):
            return trace_back(back, grid, k), len(edges) - 1
        edges = np.unique(np.concatenate([edges, (edges[:-1] + edges[1:]) // 2]))


def cells_then_refine(signal: Linear, k: int, sf: float | str = 10, gamma: int = GAMMA, **options) -> tuple[np.ndarray, list[float], int]:
    cuts, cells = optimal_over_cells(signal, k, sf, gamma)
    cuts, trace = refine(signal, cuts, gamma, **options)
    return cuts, trace, cells

"""Greedy bottom-up merging over moments, alone and after refinement."""

from __future__ import annotations

import heapq

import numpy as np

from .moments import Linear
from .refine import GAMMA, over_size, refine, uniform


def cells(n: int, delta: int = 2) -> np.ndarray:
    return uniform(n, max(1, n // max(2, delta)))


def merge(signal: Linear, edges: np.ndarray, k: int) -> tuple[np.ndarray, list[tuple[int, float]]]:
    """Fuses the neighbours of least discrepancy, the leftmost of equal ones, until k pieces stand; also the path: (cut removed, its gain)."""
    edges = np.asarray(edges)
    m = len(edges) - 1
    start, end = edges[:-1].tolist(), edges[1:].tolist()
    cost = signal.cost(edges[:-1], edges[1:]).tolist()
    after, before, alive = list(range(1, m + 1)), list(range(-1, m - 1)), [True] * m
    version = [0] * m
    both = signal.cost(edges[:-2], edges[2:]) if m > 1 else np.zeros(0)
    heap = [(float(b) - cost[i] - cost[i + 1], i, 0, float(b)) for i, b in enumerate(both)]
    heapq.heapify(heap)
    path: list[tuple[int, float]] = []

    def offer(i: int) -> None:
        j = after[i]
        version[i] += 1
        if j < m:
            whole = signal.one(start[i], end[j])
            heapq.heappush(heap, (whole - cost[i] - cost[j], i, version[i], whole))

    while len(path) < m - k and heap:
        gain, i, v, whole = heapq.heappop(heap)
        if not alive[i] or v != version[i]:
            continue
        j = after[i]
        path.append((start[j], gain))
        alive[j] = False
        end[i], cost[i], after[i] = end[j], whole, after[j]
        if after[i] < m:
            before[after[i]] = i
        offer(i)
        if before[i] >= 0:
            offer(before[i])
    return np.array([*[start[i] for i in range(m) if alive[i]], signal.n]), path


def bottom_up(signal: Linear, k: int, delta: int = 2, edges: np.ndarray | None = None) -> tuple[np.ndarray, list]:
    return merge(signal, cells(signal.n, delta) if edges is None else edges, k)


def refine_then_merge(signal: Linear, k: int, k_init: int | None = None, gamma: int = GAMMA, polish: bool = False, **options) -> tuple[np.ndarray, list[float]]:
    """Refines an even start of more pieces than asked for, then merges down to k; also the refinement's trace."""
    size = over_size(signal.n, k, gamma) if k_init is None else max(k, min(k_init, signal.n // gamma))
    cuts, trace = refine(signal, uniform(signal.n, size), gamma, **options)
    cuts, _ = merge(signal, cuts, k)
    return refine(signal, cuts, gamma, **options) if polish else (cuts, trace)


def unit_noise(signal: Linear) -> Linear:
    """The signal with each dimension divided by the noise that its second differences show, so that scales don't mix."""
    second = np.diff(signal.x, 2, axis=0)
    noise = np.median(second**2, axis=0) / 6 / 0.4549 if len(second) else np.ones(signal.d)
    spread = signal.x.var(0)
    noise = np.where(noise > 1e-12 * spread, noise, np.where(spread > 0, 1e-6 * spread, 1.0))  # a dimension without noise keeps its cuts
    out = type(signal)(signal.raw_t, signal.x / np.sqrt(noise))
    out.count = signal.count
    return out


def unknown_k(signal: Linear, beta: float | None = None, k_max: int = 20, gamma: int = GAMMA, **options) -> tuple[np.ndarray, list[float]]:
    """Number of pieces by cost + beta * pieces along the merge path, then a polish.

    Without beta, every dimension is measured by its own noise and a piece costs 3 d log(N).
    """
    k_max = max(1, min(k_max, signal.n // gamma))
    if beta is None:
        signal = unit_noise(signal)
        beta = 3 * signal.d * float(np.log(max(signal.n, 2)))
    cuts, _ = refine(signal, uniform(signal.n, over_size(signal.n, k_max, gamma)), gamma, **options)
    cuts, _ = merge(signal, cuts, k_max)
    best, chosen = signal.model_cost(cuts) + beta * (len(cuts) - 1), cuts
    while len(cuts) > 2:
        cuts, _ = merge(signal, cuts, len(cuts) - 2)
        now = signal.model_cost(cuts) + beta * (len(cuts) - 1)
        if now < best:
            best, chosen = now, cuts
    return refine(signal, chosen, gamma, **options)

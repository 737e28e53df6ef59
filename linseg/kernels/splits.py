"""Top-down splitting and sliding windows."""

from __future__ import annotations

import heapq

import numpy as np

from .moments import Linear
from .refine import GAMMA, draw


def best_cut(signal: Linear, lo: int, hi: int, gamma: int = GAMMA) -> tuple[float, int | None]:
    """(gain, cut) of the two-piece model of [lo, hi), the first of equal cuts."""
    if hi - lo < 2 * gamma:
        return 0.0, None
    p = np.arange(lo + gamma, hi - gamma + 1)
    two = signal.cost(lo, p) + signal.cost(p, hi)
    at = int(np.argmin(two))
    return signal.one(lo, hi) - float(two[at]), int(p[at])


def _split(signal: Linear, k: int, propose) -> np.ndarray:
    """Splits the piece of greatest gain, the leftmost of equal ones, until k stand or none can be split."""
    cuts, heap = {0, signal.n}, []

    def offer(lo: int, hi: int) -> None:
        gain, at = propose(lo, hi)
        if at is not None:
            heapq.heappush(heap, (-gain, lo, hi, at))

    offer(0, signal.n)
    while len(cuts) < k + 1 and heap:
        _, lo, hi, at = heapq.heappop(heap)
        cuts.add(at)
        if len(cuts) < k + 1:
            offer(lo, at)
            offer(at, hi)
    return np.array(sorted(cuts))


def binary_split(signal: Linear, k: int, gamma: int = GAMMA) -> np.ndarray:
    return _split(signal, k, lambda lo, hi: best_cut(signal, lo, hi, gamma))


def random_interval_split(signal: Linear, k: int, n_intervals: int = 100, gamma: int = GAMMA, seed="0") -> np.ndarray:
    """Each piece is split at the greatest discrepancy over random sub-ranges of it (and the piece itself)."""

    def propose(lo: int, hi: int) -> tuple[float, int | None]:
        best = best_cut(signal, lo, hi, gamma)
        for i in range(n_intervals if hi - lo > 2 * gamma else 0):
            a = lo + int(draw(seed, lo, hi, i, "a") * (hi - lo + 1))
            b = lo + int(draw(seed, lo, hi, i, "b") * (hi - lo + 1))
            found = best_cut(signal, min(a, b), max(a, b), gamma)
            if found[1] is not None and (best[1] is None or found[0] > best[0]) and lo + gamma <= found[1] <= hi - gamma:
                best = found
        return best

    return _split(signal, k, propose)


def contrast(signal: Linear, window: int = 50) -> tuple[np.ndarray, np.ndarray]:
    """Positions with a whole window about them, and the gain of cutting the window in halves there."""
    half = max(1, window // 2)
    p = np.arange(half, signal.n - half + 1)
    return p, signal.cost(p - half, p + half) - signal.cost(p - half, p) - signal.cost(p, p + half)


def sliding_contrast(signal: Linear, k: int, window: int = 50, min_gap: int | None = None, gamma: int = GAMMA) -> np.ndarray:
    """The k-1 highest gains that keep their distance; a window too long for the signal is shortened."""
    window = max(2 * gamma, min(window, signal.n // 2 * 2))
    gap = window // 2 if min_gap is None else min_gap
    p, curve = contrast(signal, window)
    taken: list[int] = []
    for i in np.lexsort((p, -curve)):
        at = int(p[i])
        if len(taken) == k - 1:
            break
        if gamma <= at <= signal.n - gamma and all(abs(at - x) >= max(gap, gamma) for x in taken):
            taken.append(at)
    return np.array([0, *sorted(taken), signal.n])

"""Pairwise boundary refinement, and the starts it takes."""

from __future__ import annotations

import hashlib
from math import comb

import numpy as np

from .moments import Linear

GAMMA, TOL, SWEEPS, STARTS = 2, 1e-4, 100, 20


def draw(*key) -> float:
    """Uniform in [0, 1) from the md5 of the key; SQL can replay it."""
    return int(hashlib.md5("|".join(map(str, key)).encode()).hexdigest()[:12], 16) / float(1 << 48)


def partitions(n: int, k: int, gamma: int = 1) -> int:
    """Ways to cut n points into k pieces of gamma points or more."""
    return comb(n - k * (gamma - 1) - 1, k - 1) if n >= k * gamma and k > 0 else 0


def printed_partitions(n: int, k: int) -> int:
    """The count as the reference prints it; it leaves out one gap."""
    return comb(n - 2, k - 1) if n >= 2 and k > 0 else 0


def uniform(n: int, k: int) -> np.ndarray:
    return (np.arange(k + 1) * n) // k


def random_cuts(n: int, k: int, gamma: int, *key) -> np.ndarray:
    """Uniform over the feasible cut sets: k-1 distinct slots, spread so that every piece holds gamma points."""
    slots = n - k * (gamma - 1) - 1
    chosen: set[int] = set()
    i = 0
    for top in range(slots - k + 1, slots):  # each step adds one slot; the sets come out equally likely
        pick = int(draw(*key, i) * (top + 1))
        chosen.add(top if pick in chosen else pick)
        i += 1
    inner = np.array(sorted(chosen), int) + 1 + (gamma - 1) * np.arange(1, k)
    return np.concatenate([[0], inner, [n]])


def over_size(n: int, k: int, gamma: int = GAMMA) -> int:
    """Pieces of the over-segmentation before merging."""
    return max(1, min(max(k, min(5 * k, n // 20)), n // gamma))


def pair_order(pairs: int, order: str, seed, sweep: int) -> list[int]:
    if order == "left_to_right":
        return list(range(pairs))
    if order == "odd_even":
        return [*range(0, pairs, 2), *range(1, pairs, 2)]
    if order == "seeded_shuffle":
        return sorted(range(pairs), key=lambda p: (draw(seed, "order", sweep, p), p))
    raise ValueError(f"unknown order {order!r}")


def best_move(signal: Linear, lo: int, hi: int, left, right, gamma: int) -> int | None:
    """Cut of [lo, hi) with least error under the two frozen lines, the first of equal ones; None if two pieces don't fit.

    Only the difference of the two errors matters, and the squared values cancel in it.
    """
    if hi - lo < 2 * gamma:
        return None
    t, x = signal.t[lo:hi], signal.x[lo:hi]
    (cl, ml), (cr, mr) = left, right
    diff = -2 * (x @ (cl - cr) + t * (x @ (ml - mr))) + (cl @ cl - cr @ cr) + 2 * t * (cl @ ml - cr @ mr) + t * t * (ml @ ml - mr @ mr)
    run = np.cumsum(diff)
    return lo + gamma + int(np.argmin(run[gamma - 1 : hi - lo - gamma]))


def refine(signal: Linear, cuts: np.ndarray, gamma: int = GAMMA, tol: float = TOL, max_iter: int = SWEEPS, order: str = "seeded_shuffle", seed="0") -> tuple[np.ndarray, list[float]]:
    """Cuts at a local optimum and the cost after each sweep (first: of the start)."""
    cuts = np.asarray(cuts).copy()
    trace = [signal.model_cost(cuts)]
    for sweep in range(max_iter if len(cuts) > 2 else 0):
        c, m = signal.lines(cuts[:-1], cuts[1:])
        before = cuts.copy()
        for p in pair_order(len(cuts) - 2, order, seed, sweep):
            at = best_move(signal, int(cuts[p]), int(cuts[p + 2]), (c[p], m[p]), (c[p + 1], m[p + 1]), gamma)
            if at is not None:
                cuts[p + 1] = at
        now = signal.model_cost(cuts)
        if now > trace[-1]:  # rounding at a fixed point
            cuts, now = before, trace[-1]
        trace.append(now)
        if trace[-2] - now <= tol * trace[-2]:
            break
    return cuts, trace


def multistart(signal: Linear, k: int, q: int = STARTS, gamma: int = GAMMA, seed="0", **options) -> tuple[np.ndarray, list[float]]:
    """The cheapest of q refined random starts; the first of equal ones."""
    runs = [refine(signal, random_cuts(signal.n, k, gamma, seed, i), gamma, seed=f"{seed}|{i}", **options) for i in range(q)]
    return min(runs, key=lambda r: r[1][-1])

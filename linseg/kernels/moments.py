"""Prefix moments of one signal: the cost and the line of any range at O(d)."""

from __future__ import annotations

import numpy as np


class Unfit(ValueError):
    """A signal that a method can't take; callers over many signals report it in the signal's row."""


class Counts:
    """Work counters: line fits and cost evaluations."""

    def __init__(self) -> None:
        self.fits = self.evals = 0


class Linear:
    """Squared error about the best line of each range.

    Time is put on a unit span about its middle and values are centred, so that differences of running sums keep
    their digits; ranges under ``SHORT`` points that matter are recomputed from the points (``exact``).
    """

    SHORT = 64
    sloped = True

    def __init__(self, t: np.ndarray, x: np.ndarray):
        self.n, self.d = x.shape
        self.raw_t = np.asarray(t, float)
        self.mid = float(self.raw_t.mean()) if self.n else 0.0
        self.span = float(np.ptp(self.raw_t)) or 1.0 if self.n else 1.0
        self.t = (self.raw_t - self.mid) / self.span
        self.origin = x.mean(0) if self.n else np.zeros(self.d)
        self.x = np.asarray(x, float) - self.origin
        self.count = Counts()
        add = lambda a: np.concatenate([np.zeros((1, *a.shape[1:])), np.cumsum(a, 0)])
        self.st, self.stt, self.sx = add(self.t), add(self.t**2), add(self.x)
        self.stx, self.sxx = add(self.t[:, None] * self.x), add((self.x**2).sum(1))
        self.total = float(self.sxx[-1])
        self._rows: np.ndarray | None = None

    def _about(self, i, j):
        n = np.asarray(j) - np.asarray(i)
        safe = np.maximum(n, 1)
        st, sx = self.st[j] - self.st[i], self.sx[j] - self.sx[i]
        vt = self.stt[j] - self.stt[i] - st * st / safe
        cov = self.stx[j] - self.stx[i] - (st / safe)[..., None] * sx
        return n, safe, st, sx, vt, cov

    def cost(self, i, j):
        """Cost of the ranges [i, j); i and j broadcast."""
        i, j = np.broadcast_arrays(np.asarray(i), np.asarray(j))
        self.count.evals += i.size
        n, safe, _, sx, vt, cov = self._about(i, j)
        out = self.sxx[j] - self.sxx[i] - (sx * sx).sum(-1) / safe
        if self.sloped:
            steep = vt > 1e-14 * safe
            out = out - np.where(steep, (cov * cov).sum(-1) / np.where(steep, vt, 1.0), 0.0)
            out = np.where(n <= 2, np.where(n <= 1, 0.0, np.where(steep, 0.0, out)), out)
        else:
            out = np.where(n <= 1, 0.0, out)
        return np.maximum(out, 0.0)

    def one(self, i: int, j: int) -> float:
        """``cost`` of one range, from sums that lie side by side."""
        n = j - i
        self.count.evals += 1
        if n <= 1:
            return 0.0
        if self._rows is None:
            self._rows = np.column_stack([self.st, self.stt, self.sxx, self.sx, self.stx])
        m = self._rows[j] - self._rows[i]
        st, stt, sxx = m[:3].tolist()
        sx = m[3 : 3 + self.d]
        out = sxx - float(sx @ sx) / n
        vt = stt - st * st / n
        if self.sloped and vt > 1e-14 * n:
            if n == 2:
                return 0.0
            cov = m[3 + self.d :] - st / n * sx
            out -= float(cov @ cov) / vt
        return max(out, 0.0)

    def upto(self, i: np.ndarray, e: int) -> np.ndarray:
        """``cost`` of the ranges [i, e), from sums that lie side by side."""
        if type(self).cost is not Linear.cost:
            return self.cost(i, e)
        self.count.evals += len(i)
        if self._rows is None:
            self._rows = np.column_stack([self.st, self.stt, self.sxx, self.sx, self.stx])
        m = self._rows[e] - self._rows[i]
        n = e - i
        safe = np.maximum(n, 1)
        st, sx = m[:, 0], m[:, 3 : 3 + self.d]
        out = m[:, 2] - np.einsum("ij,ij->i", sx, sx) / safe
        if self.sloped:
            vt = m[:, 1] - st * st / safe
            cov = m[:, 3 + self.d :] - (st / safe)[:, None] * sx
            steep = vt > 1e-14 * safe
            out -= np.where(steep, np.einsum("ij,ij->i", cov, cov) / np.where(steep, vt, 1.0), 0.0)
            out[(n <= 1) | ((n == 2) & steep)] = 0.0
        else:
            out[n <= 1] = 0.0
        return np.maximum(out, 0.0)

    def all_costs(self, step: int = 32) -> np.ndarray:
        """``cost`` of all ranges [i, j) at row j, column i, some rows at a time; infinite where i >= j.  Doesn't count them."""
        size = self.n + 1
        out, at = np.full((size, size), np.inf), np.arange(size)
        if type(self).cost is not Linear.cost:
            evals = self.count.evals
            for e in range(1, size):
                out[e, :e] = self.cost(at[:e], e)
            self.count.evals = evals
            return out
        sx, stx = np.ascontiguousarray(self.sx.T), np.ascontiguousarray(self.stx.T)
        for lo in range(1, size, step):
            hi = min(lo + step, size)
            gap = lambda v: v[lo:hi, None] - v[:hi]  # noqa: E731, B023
            n = at[lo:hi, None] - at[:hi]
            safe = np.maximum(n, 1)
            st = gap(self.st) if self.sloped else None
            vt = gap(self.stt) - st * st / safe if self.sloped else None
            share = st / safe if self.sloped else None
            level = fall = 0.0
            for r in range(self.d):
                g = gap(sx[r])
                level = level + g * g
                if self.sloped:
                    cov = gap(stx[r]) - share * g
                    fall = fall + cov * cov
            cost = gap(self.sxx) - level / safe
            flat = n <= 1
            if self.sloped:
                steep = vt > 1e-14 * safe
                cost -= np.where(steep, fall / np.where(steep, vt, 1.0), 0.0)
                flat = flat | ((n == 2) & steep)
            cost[flat] = 0.0
            out[lo:hi, :hi] = np.where(n > 0, np.maximum(cost, 0.0), np.inf)
        return out

    def lines(self, i, j):
        """(intercept, slope) in centred units, for the ranges [i, j)."""
        i, j = np.asarray(i), np.asarray(j)
        self.count.fits += i.size
        _, safe, st, sx, vt, cov = self._about(i, j)
        slope = np.where((vt > 1e-14 * safe)[..., None], cov / np.where(vt > 0, vt, 1.0)[..., None], 0.0) if self.sloped else np.zeros_like(cov)
        return (sx - slope * st[..., None]) / safe[..., None], slope

    def exact(self, i: int, j: int) -> tuple[np.ndarray, np.ndarray, float]:
        """Intercept and slope in the signal's own units, and the squared error, recomputed from the points."""
        x, t = self.x[i:j], self.raw_t[i:j]
        mean, mid = x.mean(0), t.mean()
        u = t - mid
        var = float(u @ u)
        slope = (u @ (x - mean)) / var if self.sloped and var > 0 else np.zeros(self.d)
        rest = x - mean - u[:, None] * slope
        return mean + self.origin - slope * mid, slope, float((rest * rest).sum())

    def model_cost(self, cuts: np.ndarray) -> float:
        return float(self.cost(cuts[:-1], cuts[1:]).sum())


class Constant(Linear):
    """Squared error about the mean of each range."""

    sloped = False


class Absolute(Linear):
    """Absolute error about a line fitted by reweighted least squares; costs are remembered, so small signals only."""

    LIMIT = 400
    #: Numbers that a step over many ranges holds in each array.
    BATCH = 1 << 16

    def __init__(self, t: np.ndarray, x: np.ndarray):
        super().__init__(t, x)
        if self.n > self.LIMIT:
            raise Unfit(f"absolute error is for signals of up to {self.LIMIT} points")
        self.known: dict[tuple[int, int], float] = {}

    def one(self, i: int, j: int) -> float:
        return float(self.cost(i, j))

    def _fit(self, i: int, j: int) -> tuple[np.ndarray, np.ndarray, float]:
        t, x = self.t[i:j], self.x[i:j]
        c, m = (v[0] for v in super().lines(np.array([i]), np.array([j])))
        for _ in range(25 if j - i > 2 else 0):
            w = 1 / np.maximum(np.abs(x - c - t[:, None] * m), 1e-9)
            s = w.sum(0)
            tm, xm = (w * t[:, None]).sum(0) / s, (w * x).sum(0) / s
            u = t[:, None] - tm
            m = (w * u * (x - xm)).sum(0) / np.maximum((w * u * u).sum(0), 1e-300)
            c = xm - m * tm
        return c, m, float(np.abs(x - c - t[:, None] * m).sum())

    def _errors(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """The errors that ``_fit`` finds, of many ranges of three points or more at once: rows are padded with weights of zero."""
        n = j - i
        at = i[:, None] + np.arange(int(n.max()))
        inside = (at < j[:, None]).astype(float)
        at = np.minimum(at, self.n - 1)
        t, x = self.t[at], np.ascontiguousarray(self.x.T)[:, at]
        c, m = (np.ascontiguousarray(v.T)[..., None] for v in super().lines(i, j))
        total = lambda v: v.sum(-1, keepdims=True)
        for _ in range(25):
            w = inside / np.maximum(np.abs(x - c - t * m), 1e-9)
            s, wt = total(w), w * t
            tm, xm = total(wt) / s, total(w * x) / s
            u = t - tm
            wt = w * u
            m = total(wt * (x - xm)) / np.maximum(total(wt * u), 1e-300)
            c = xm - m * tm
        return (np.abs(x - c - t * m) * inside).sum((0, 2))

    def cost(self, i, j):
        i, j = np.broadcast_arrays(np.asarray(i), np.asarray(j))
        self.count.evals += i.size
        keys = list(zip(i.ravel().tolist(), j.ravel().tolist(), strict=True))
        new = list(dict.fromkeys(k for k in keys if k not in self.known and k[1] - k[0] > 2))
        step = max(1, self.BATCH // (self.n * self.d))
        for lo in range(0, len(new), step):
            part = new[lo : lo + step]
            ends = np.array(part)
            self.known.update(zip(part, self._errors(ends[:, 0], ends[:, 1]).tolist(), strict=True))
        return np.array([self.known.get(k, 0.0) for k in keys]).reshape(i.shape)

    def lines(self, i, j):
        self.count.fits += np.asarray(i).size
        got = [self._fit(int(a), int(b)) for a, b in zip(np.atleast_1d(i), np.atleast_1d(j), strict=True)]
        return np.array([g[0] for g in got]), np.array([g[1] for g in got])

    def exact(self, i: int, j: int) -> tuple[np.ndarray, np.ndarray, float]:
        c, m, cost = self._fit(i, j)
        slope = m / self.span
        return c + self.origin - slope * self.mid, slope, cost


COSTS = {"l2_linear": Linear, "l2_constant": Constant, "l1_linear": Absolute}

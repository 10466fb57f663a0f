"""Error laws on the integers: log-concave masses, an atom at zero beside a density, and symmetric laws."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from .density import LogSpline, fit_logconcave


def _newton(at: np.ndarray, data: np.ndarray, phi: np.ndarray) -> np.ndarray:
    """Values at the knots that maximise data @ phi - sum of exp(at @ phi); `at` spreads knots over the lattice."""
    value = lambda p: data @ p - np.exp(np.minimum(at @ p, 300)).sum()
    now = value(phi)
    for _ in range(100):
        mass = np.exp(np.minimum(at @ phi, 300))
        grad = data - at.T @ mass
        step = np.linalg.solve(at.T @ (at * mass[:, None]) + 1e-12 * np.eye(len(phi)), grad)
        if grad @ step < 1e-12:
            break
        part = min(1.0, 20 / max(1e-300, np.abs(step).max()))
        while part > 1e-9 and value(phi + part * step) < now + 1e-4 * part * (grad @ step):
            part /= 2
        phi = phi + part * step
        now = value(phi)
    return phi


def fit_logconcave_discrete(x: np.ndarray, m: np.ndarray, trim: float = 0.01, tol: float = 1e-6, most_knots: int = 60, most_points: int = 4_000) -> LogSpline:
    """The log-concave mass function on the integers of greatest likelihood; knots hold log masses, and the masses sum to 1.

    Between knots log masses are linear. A lattice of more than `most_points` points is thinned to every s-th point, values going to the nearest, and
    each point's mass is shared among the s integers about it.
    """
    order = np.argsort(x)
    x, m = np.asarray(x, dtype=np.float64)[order], np.asarray(m, dtype=np.float64)[order]
    inside = np.cumsum(m) <= (1 - trim) * m.sum() + 1e-9
    inside[0] = True
    x, m = np.rint(x[inside]), m[inside]
    low = x[0]
    step = max(1, int(np.ceil((x[-1] - low + 1) / most_points)))
    z = np.rint((x - low) / step).astype(int)
    w = np.bincount(z, weights=m) / m.sum()
    if len(w) == 1:
        return LogSpline(np.asarray([low, low + 1.0]), np.asarray([0.0, -1.0]))
    grid = np.arange(len(w), dtype=np.float64)
    knots, phi = [0, len(w) - 1], np.full(2, -np.log(len(w)))
    while True:
        while True:
            t = grid[knots]
            at = np.stack([np.interp(grid, t, e) for e in np.eye(len(t))], axis=1)
            best = _newton(at, at.T @ w, phi)
            bend = np.diff(np.diff(best) / np.diff(t))
            if len(bend) == 0 or bend.max() <= 1e-9:
                phi = best
                break
            before = np.diff(np.diff(phi) / np.diff(t))
            bad = np.flatnonzero(bend > 1e-9)
            part = np.where(bend - before > 0, -before / np.maximum(bend - before, 1e-300), 1.0)
            first = bad[np.argmin(part[bad])]
            phi = np.delete(phi + max(0.0, min(1.0, part[first])) * (best - phi), first + 1)
            knots.pop(first + 1)
        if len(knots) >= most_knots:
            break
        # Gain of a kink down at each point: model less data of the sums of (y - point) beyond it.
        off = np.exp(np.interp(grid, grid[knots], phi)) - w
        beyond = np.append(np.cumsum(off[::-1])[::-1], 0.0)[1:]
        gain = np.append(np.cumsum(beyond[::-1])[::-1], 0.0)[:-1] / len(w)
        gain[knots] = -np.inf
        pick = int(np.argmax(gain))
        if gain[pick] < tol:
            break
        place = int(np.searchsorted(knots, pick))
        phi = np.insert(phi, place, np.interp(grid[pick], grid[knots], phi))
        knots.insert(place, pick)
    return LogSpline(low + step * grid[knots], phi - np.log(step))


@dataclass(frozen=True)
class ZeroAtom:
    """Log masses of a law with an atom at 0 beside a log-concave rest."""

    share: float
    rest: LogSpline | None

    def __call__(self, x: np.ndarray) -> np.ndarray:
        x = np.asarray(x, dtype=np.float64)
        with np.errstate(divide="ignore"):
            beyond = np.full(x.shape, -np.inf) if self.rest is None else np.log1p(-self.share) + self.rest(x)
            return np.where(x == 0, np.log(self.share), np.where(x < 0, -np.inf, beyond))


def fit_zero_atom(x: np.ndarray, m: np.ndarray, trim: float = 0.01) -> ZeroAtom:
    """The share of zeros, and the density of the others."""
    x, m = np.asarray(x, dtype=np.float64), np.asarray(m, dtype=np.float64)
    some = x > 0
    share = float(m[~some].sum() / m.sum())
    return ZeroAtom(share, fit_logconcave(x[some], m[some], trim).extended() if some.any() else None)


def symmetric_mle(v: np.ndarray, spline: LogSpline) -> np.ndarray:
    """Counts that maximise the likelihood of signed counters; both tails of the density go on with their last slopes."""
    v = np.asarray(v, dtype=np.float64)
    t, phi = spline.t, spline.phi
    left, right = (phi[1] - phi[0]) / (t[1] - t[0]), (phi[-1] - phi[-2]) / (t[-1] - t[-2])
    out = np.empty(len(v))
    for a in range(0, len(v), 512):
        rows = v[a : a + 512]
        spots = (rows[:, :, None] - t).reshape(len(rows), -1)
        off = rows[:, None, :] - spots[:, :, None]
        value = (np.interp(off, t, phi) + left * np.minimum(0, off - t[0]) + right * np.maximum(0, off - t[-1])).sum(axis=2)
        good = value >= value.max(axis=1, keepdims=True) - 1e-9
        out[a : a + 512] = (np.where(good, spots, np.inf).min(axis=1) + np.where(good, spots, -np.inf).max(axis=1)) / 2
    return out

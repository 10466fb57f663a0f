"""Log-concave densities by maximum likelihood, and what is computed with them.

The log density is a concave, piecewise linear function with knots at data points. An active set of knots grows by the kink that raises the likelihood
fastest and loses knots that stop being concave; between changes, Newton's method solves for the values at the knots.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

_NODES, _WEIGHTS = np.polynomial.legendre.leggauss(40)
_S, _W = (_NODES + 1) / 2, _WEIGHTS / 2


@dataclass(frozen=True)
class LogSpline:
    """Knots t and log densities phi; beyond the last knot the last slope goes on, below 0 there is nothing."""

    t: np.ndarray
    phi: np.ndarray

    def extended(self) -> LogSpline:
        """With knots that carry it down to 0 and give it a falling right tail."""
        t, phi = self.t, self.phi
        if t[0] > 0:
            slope = (phi[1] - phi[0]) / (t[1] - t[0]) if len(t) > 1 else 0.0
            t, phi = np.append(0.0, t), np.append(phi[0] - slope * t[0], phi)
        last = (phi[-1] - phi[-2]) / (t[-1] - t[-2]) if len(t) > 1 else 0.0
        if last >= 0:
            reach = max(1.0, t[-1] - t[0])
            t, phi = np.append(t, t[-1] + reach), np.append(phi, phi[-1] - 1.0)
        return LogSpline(t, phi)

    def __call__(self, x: np.ndarray) -> np.ndarray:
        x = np.asarray(x, dtype=np.float64)
        out = np.interp(x, self.t, self.phi)
        if len(self.t) > 1:
            slope = (self.phi[-1] - self.phi[-2]) / (self.t[-1] - self.t[-2])
            out = np.where(x > self.t[-1], self.phi[-1] + slope * (x - self.t[-1]), out)
        return np.where(x < min(self.t[0], 0.0) - 1e-12, -np.inf, out)

    @property
    def falling(self) -> bool:
        return bool((np.diff(self.phi) <= 0).all())


def _moments(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, ...]:
    """Integrals over a unit segment of exp(linear from a to b) times 1, 1-s, s, (1-s)^2, s(1-s), s^2."""
    e = np.exp(a[:, None] * (1 - _S) + b[:, None] * _S) * _W
    return e.sum(1), e @ (1 - _S), e @ _S, e @ (1 - _S) ** 2, e @ (_S * (1 - _S)), e @ _S**2


def _newton(t: np.ndarray, weight: np.ndarray, phi: np.ndarray) -> np.ndarray:
    """Values at knots t that maximise weight @ phi - integral of exp(phi)."""
    gap = np.diff(t)
    value = lambda p: weight @ p - gap @ _moments(p[:-1], p[1:])[0]
    now = value(phi)
    for _ in range(80):
        _, l, r, ll, lr, rr = _moments(phi[:-1], phi[1:])
        grad = weight.copy()
        grad[:-1] -= gap * l
        grad[1:] -= gap * r
        h = np.zeros((len(t), len(t)))
        at = np.arange(len(gap))
        h[at, at] += gap * ll
        h[at + 1, at + 1] += gap * rr
        h[at, at + 1] += gap * lr
        h[at + 1, at] += gap * lr
        step = np.linalg.solve(h + 1e-12 * np.eye(len(t)), grad)
        if grad @ step < 1e-12:
            break
        part = min(1.0, 20 / max(1e-300, np.abs(step).max()))
        while part > 1e-9 and value(phi + part * step) < now + 1e-4 * part * (grad @ step):
            part /= 2
        phi = phi + part * step
        now = value(phi)
    return phi


def fit_logconcave(x: np.ndarray, m: np.ndarray, trim: float = 0.01, tol: float = 1e-6, most_knots: int = 60, most_atoms: int = 4_000) -> LogSpline:
    """The log-concave maximum-likelihood density of values x with weights m, the largest `trim` of them left out.

    More than `most_atoms` distinct values are first gathered to that many quantiles' means.
    """
    order = np.argsort(x)
    x, m = np.asarray(x, dtype=np.float64)[order], np.asarray(m, dtype=np.float64)[order]
    inside = np.cumsum(m) <= (1 - trim) * m.sum() + 1e-9
    inside[0] = True
    x, m = x[inside], m[inside]
    if len(x) > most_atoms:
        part = np.minimum((np.cumsum(m) - m / 2) / m.sum() * most_atoms, most_atoms - 1).astype(int)
        total = np.bincount(part, weights=m)
        x, m = np.bincount(part, weights=m * x)[total > 0] / total[total > 0], total[total > 0]
    if len(x) == 1:
        return LogSpline(np.asarray([x[0], x[0] + 1.0]), np.asarray([0.0, -1.0]))
    low, reach = x[0], x[-1] - x[0]
    z, w = (x - low) / reach, m / m.sum()
    knots = [0, len(z) - 1]
    phi = np.zeros(2)
    done: set[tuple[int, ...]] = set()
    for _ in range(400):
        while True:
            t = z[knots]
            seg = np.clip(np.searchsorted(t, z, side="right") - 1, 0, len(t) - 2)
            right = (z - t[seg]) / (t[seg + 1] - t[seg])
            weight = np.bincount(seg, weights=w * (1 - right), minlength=len(t)) + np.bincount(seg + 1, weights=w * right, minlength=len(t))
            best = _newton(t, weight, phi)
            bend = np.diff(np.diff(best) / np.diff(t))
            if len(bend) == 0 or bend.max() <= 1e-9:
                phi = best
                break
            # Go as far towards the solution as stays concave, and drop the knot that goes straight first.
            before = np.diff(np.diff(phi) / np.diff(t))
            bad = np.flatnonzero(bend > 1e-9)
            part = np.where(bend - before > 0, -before / np.maximum(bend - before, 1e-300), 1.0)
            first = bad[np.argmin(part[bad])]
            phi = phi + max(0.0, min(1.0, part[first])) * (best - phi)
            phi = np.delete(phi, first + 1)
            knots.pop(first + 1)
        if tuple(knots) in done or len(knots) >= most_knots:
            break
        done.add(tuple(knots))
        # Derivative towards a kink at each value: what exp(phi) has beyond it, less what the data have.
        at = np.interp(z, z[knots], phi)
        gap = np.diff(z)
        mass, _, toward, *_ = _moments(at[:-1], at[1:])
        mass, first_moment = gap * mass, gap**2 * toward
        back = lambda v: np.append(np.cumsum(v[::-1])[::-1], 0.0)
        model = back(mass * z[:-1] + first_moment) - z * back(mass)
        data = back(w[1:] * z[1:]) - z * back(w[1:])
        gain = model - data
        gain[knots] = -np.inf
        pick = int(np.argmax(gain))
        if gain[pick] < tol:
            break
        place = int(np.searchsorted(knots, pick))
        phi = np.insert(phi, place, at[pick])
        knots.insert(place, pick)
    return LogSpline(low + reach * z[knots], phi - np.log(reach))


def mle(v: np.ndarray, spline: LogSpline, bounded: bool = True) -> np.ndarray:
    """Counts that maximise the likelihood of counters v (items by replicates).

    The objective is concave and piecewise linear in the count, so a best count is a counter less a knot; of equally good ones, the middle is taken. `bounded`: no more than the
    smallest counter, which the support of the errors demands.
    """
    v = np.asarray(v, dtype=np.float64)
    least = v.min(axis=1)
    spots = (v[:, :, None] - spline.t[None, None, :]).reshape(len(v), -1)
    spots = np.concatenate([np.minimum(spots, least[:, None]), least[:, None]], axis=1)
    out = np.empty(len(v))
    for a in range(0, len(v), 512):
        s = spots[a : a + 512]
        off = np.maximum(v[a : a + 512, None, :] - s[:, :, None], 0.0)
        value = spline(off).sum(axis=2)
        top = value.max(axis=1, keepdims=True)
        good = value >= top - 1e-9 * np.maximum(1.0, np.abs(top))
        out[a : a + 512] = (np.where(good, s, np.inf).min(axis=1) + np.where(good, s, -np.inf).max(axis=1)) / 2
    return out


def mle_counts(v: np.ndarray, spline: LogSpline) -> tuple[np.ndarray, np.ndarray]:
    """(evaluations, ties) of `mle` for each row: how many different counts its objective is evaluated at, and whether more than one of them is best."""
    v = np.asarray(v, dtype=np.float64)
    many, tied = np.empty(len(v), dtype=np.int64), np.empty(len(v), dtype=bool)
    for i, row in enumerate(v):
        spots = np.unique(np.append(np.minimum((row[:, None] - spline.t).ravel(), row.min()), row.min()))
        value = spline(np.maximum(row[None, :] - spots[:, None], 0.0)).sum(axis=1)
        good = value >= value.max() - 1e-9 * max(1.0, abs(value.max()))
        many[i], tied[i] = len(spots), good.sum() > 1
    return many, tied


def _window(v: np.ndarray, shape, floor: float) -> tuple[int, int]:
    """The counts between which the concave sum of shape(x - n) is within `floor` of its best, by halving; up to the smallest counter."""
    top = int(v.min())
    value = lambda n: float(np.sum(shape(v - n)))
    low, high = 0, top
    while high - low > 2:  # the best count, by thirds
        a, b = low + (high - low) // 3, high - (high - low) // 3
        low, high = (a, high) if value(a) < value(b) else (low, b)
    best = max(range(low, high + 1), key=value)
    least = value(best) - floor
    ends = []
    for end in (0, top):
        inside, outside = best, end
        if value(end) >= least:
            inside = outside
        while abs(outside - inside) > 1:
            middle = (inside + outside) // 2
            inside, outside = (middle, outside) if value(middle) >= least else (inside, middle)
        ends.append(inside)
    return ends[0], ends[1]


def posterior(v: np.ndarray, log_f, log_prior=None, floor: float = 40.0, most: int = 32_768) -> tuple[np.ndarray, np.ndarray]:
    """(counts, probabilities) of one item with integer counters v; counts `floor` nats below the best are left out.

    The window is found before anything is listed, so a counter of 10^9 costs no more than its law's spread. A window of more than `most` counts is thinned
    to so many, each with the probability of the counts around it. log_f is concave, but for an atom at 0 (`ZeroAtom`), which counts equal to a
    counter meet.
    """
    v = np.asarray(v, dtype=np.float64)
    shape, slack = log_f, 0.0
    if hasattr(log_f, "share"):
        shape, slack = log_f.rest, 0.0
    if log_prior is not None:
        ends = np.unique(np.concatenate([[0.0], np.floor(np.geomspace(1, max(1.0, v.min()), 80))]))
        told = log_prior(ends)
        slack += float(told.max() - told.min())
    low, high = _window(v, shape, floor + slack) if shape is not None else (int(v.min()), int(v.min()))
    if high - low < most:
        n, width = np.arange(low, high + 1, dtype=np.float64), np.ones(high - low + 1)
    else:
        n = np.unique(np.rint(np.linspace(low, high, most)))
        edge = np.concatenate([[low - 0.5], (n[1:] + n[:-1]) / 2, [high + 0.5]])
        width = np.diff(edge)
    if hasattr(log_f, "share"):
        own = np.unique(v[v <= v.min()])
        n, width = np.append(n[~np.isin(n, own)], own), np.append(width[~np.isin(n, own)], np.ones(len(own)))
        order = np.argsort(n)
        n, width = n[order], width[order]
    value = sum(log_f(x - n) for x in v) + (log_prior(n) if log_prior is not None else 0.0)
    keep = value >= value.max() - floor
    p = np.exp(value[keep] - value.max()) * width[keep]
    return n[keep], p / p.sum()


def bayes(n: np.ndarray, p: np.ndarray, loss: str = "l2", c: float = 10.0) -> float:
    """The count with the least expected loss: `l2` mean, `l1` median, `01` mode, `capped` absolute error up to c (ties: the smallest)."""
    if loss == "l2":
        return float(n @ p)
    if loss == "l1":
        return float(n[np.searchsorted(np.cumsum(p), 0.5 - 1e-12)])
    if loss == "01":
        return float(n[np.flatnonzero(p >= p.max() * (1 - 1e-9))[0]])
    # Running sums of p and of n p tell the near part's expected error; all else costs c.
    mass, first = np.append(0.0, np.cumsum(p)), np.append(0.0, np.cumsum(p * (n - n[0])))
    a, b = np.searchsorted(n, n - c, side="left"), np.searchsorted(n, n + c, side="right")
    at, off = np.arange(len(n)), n - n[0]
    below = off * (mass[at] - mass[a]) - (first[at] - first[a])
    above = (first[b] - first[at]) - off * (mass[b] - mass[at])
    cost = below + above + c * (1 - (mass[b] - mass[a]))
    return float(n[np.flatnonzero(cost <= cost.min() + 1e-12)[0]])


def credible(n: np.ndarray, p: np.ndarray, level: float) -> tuple[float, float]:
    cum = np.cumsum(p)
    return float(n[np.searchsorted(cum, (1 - level) / 2)]), float(n[min(len(n) - 1, np.searchsorted(cum, (1 + level) / 2))])


def conv_power(f: np.ndarray, power: float) -> np.ndarray:
    """The `power`-fold convolution of a mass function on 0, 1, ..., exact up to its length (no wrap-around).

    For a compound Poisson law with no zero-rate part, powers of the transform follow its rate: f(0) > 0 is needed for parts of a power.
    """
    l = len(f)
    if power == int(power):
        out, base, n = np.zeros(l), f.copy(), int(power)
        out[0] = 1.0
        while n:
            if n & 1:
                out = convolved(out, base)[:l]
            base = convolved(base, base)[:l]
            n >>= 1
        return out
    # Coefficients of a power series' real power, by its differential equation.
    if f[0] <= 0:
        raise ValueError("a fractional power needs mass at 0")
    out = np.zeros(l)
    out[0] = f[0] ** power
    k = np.arange(1, l)
    for n in range(1, l):
        out[n] = ((power * k[:n] - (n - k[:n])) * f[1 : n + 1] * out[n - 1 :: -1][:n]).sum() / (n * f[0])
    return np.maximum(out, 0)


def convolved(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    size = 1 << int(np.ceil(np.log2(len(a) + len(b))))
    return np.maximum(np.fft.irfft(np.fft.rfft(a, size) * np.fft.rfft(b, size), size)[: len(a) + len(b) - 1], 0)

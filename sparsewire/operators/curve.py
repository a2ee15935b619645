"""Curves of sorted values: segmentation by chords, least squares by orthogonal polynomials, double exponentials."""

from __future__ import annotations

import math

import numpy as np


def farthest(y: np.ndarray) -> tuple[int, float]:
    """Place and squared vertical gap of the point farthest from the chord through the ends."""
    n = len(y)
    if n < 3:
        return 0, 0.0
    gap = (y - (y[0] + (y[-1] - y[0]) * np.arange(n) / (n - 1))) ** 2
    k = int(gap.argmax())
    return k, float(gap[k])


def segments(y: np.ndarray, pieces: int, least: int, split: str = "largest") -> list[int]:
    """Ends (exclusive) of up to pieces segments; a knot ends its left segment and opens the right one's chord.

    largest: the segment with the greatest gap is split next; level: all at once, round by round.
    """
    ends = [len(y)]

    def cut_of(a: int, b: int) -> tuple[float, int]:
        lo = max(a - 1, 0) if a else 0
        k, gap = farthest(y[lo:b])
        at = lo + k + 1
        return (gap, at) if gap > 0 and at - a >= least and b - at >= least else (0.0, 0)

    while len(ends) < pieces:
        starts = [0, *ends[:-1]]
        found = sorted(((*cut_of(a, b), a) for a, b in zip(starts, ends, strict=True)), key=lambda x: (-x[0], x[2]))
        found = [x for x in found if x[0] > 0]
        if not found:
            break
        ends = sorted([*ends, *(x[1] for x in found[: 1 if split == "largest" else pieces - len(ends)])])
    return ends


def gram_basis(n: int, degree: int) -> np.ndarray:
    """Orthogonal polynomials on n equally spaced points, by their three-term recurrence."""
    u = np.arange(n) - (n - 1) / 2
    basis = [np.ones(n)]
    if degree:
        basis.append(u)
    for k in range(1, degree):
        basis.append(u * basis[k] - k * k * (n * n - k * k) / (4 * (4 * k * k - 1)) * basis[k - 1])
    return np.stack(basis[: degree + 1])


def gram_fit(y: np.ndarray, degree: int) -> np.ndarray:
    base = gram_basis(len(y), min(degree, len(y) - 1))
    coef = base @ y / (base * base).sum(axis=1)
    return np.concatenate((coef, np.zeros(degree + 1 - len(coef))))


def gram_value(coef: np.ndarray, n: int) -> np.ndarray:
    degree = min(len(coef) - 1, n - 1)
    return coef[: degree + 1] @ gram_basis(n, degree)


def pieces_linear(m: float, target: float | None = None) -> int:
    return max(1, math.ceil(2 * math.sqrt(m) if target is None else math.sqrt(2 * m / target)))


def pieces_constant(m: float, target: float | None = None) -> int:
    return max(1, math.ceil(m / math.sqrt(2) - 1 if target is None else m / (2 * target) - 1))


def curvature(y: np.ndarray, mode: str = "slope", scale: str = "none") -> float:
    """First slope less last slope, or the range, of a sorted curve; scale 'unit' divides by the largest magnitude."""
    if len(y) < 2:
        return 0.0
    m = abs((y[0] - y[1]) - (y[-2] - y[-1])) if mode == "slope" else abs(y[0] - y[-1])
    return float(m / max(abs(y).max(), 1e-300) if scale == "unit" else m)


def double_exponential(x: np.ndarray, p: np.ndarray) -> np.ndarray:
    return p[0] * np.exp(np.clip(p[1] * x, -60, 60)) + p[2] * np.exp(np.clip(p[3] * x, -60, 60))


def _linear_part(x: np.ndarray, y: np.ndarray, b: float, d: float) -> np.ndarray:
    e = np.stack((np.exp(np.clip(b * x, -60, 60)), np.exp(np.clip(d * x, -60, 60))), axis=1)
    (a, c), *_ = np.linalg.lstsq(e, y, rcond=None)
    return np.array([a, b, c, d])


#: About the most numbers of the curves that are fitted side by side.
BESIDE = 1 << 16


def fit_double_exponential(y: np.ndarray, iters: int = 40) -> np.ndarray:
    """a, b, c, d of a e^(bx) + c e^(dx) on x from 0 to 1.

    Starts come from a regression on running integrals, whose characteristic roots are the exponents, and from fixed
    pairs where those are not real; damped Gauss-Newton steps follow, and the best end wins.
    """
    return fit_double_exponentials(y[None], iters)[0]


def fit_double_exponentials(ys: np.ndarray, iters: int = 40) -> list[np.ndarray]:
    """The fit of each row; steps from all starts of several rows are made side by side."""
    n = ys.shape[1]
    x = np.linspace(0, 1, n)
    h = 1 / (n - 1)
    row, start = [], []
    for t, y in enumerate(ys):
        once = np.concatenate(([0], np.cumsum((y[1:] + y[:-1]) / 2 * h)))
        twice = np.concatenate(([0], np.cumsum((once[1:] + once[:-1]) / 2 * h)))
        (p, q, _, _), *_ = np.linalg.lstsq(np.stack((twice, once, x, np.ones(n)), axis=1), y, rcond=None)
        root = q * q + 4 * p
        starts = [(-2.0, 2.0), (-20.0, -1.0), (-5.0, 0.5)]
        if root > 0:
            starts.insert(0, ((q + math.sqrt(root)) / 2, (q - math.sqrt(root)) / 2))
        for b, d in starts:
            row.append(t)
            start.append(_linear_part(x, y, float(np.clip(b, -60, 60)), float(np.clip(d, -60, 60))))
    best, least = [None] * len(ys), [np.inf] * len(ys)
    beside = max(1, BESIDE // n)
    for a in range(0, len(row), beside):
        z, cost = _descend(x, ys[row[a : a + beside]], np.stack(start[a : a + beside]), iters)
        for t, end, c in zip(row[a : a + beside], z, cost.tolist(), strict=True):
            if c < least[t]:
                best[t], least[t] = end, c
    return best


def _descend(x: np.ndarray, y: np.ndarray, z: np.ndarray, iters: int) -> tuple[np.ndarray, np.ndarray]:
    """Parameters and cost of each row after damped Gauss-Newton steps; a row rests when it is done.

    Exponents are within 60 of 0 and x from 0 to 1, so no exponential is cut off here.
    """

    def at(z: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        eb, ed = (np.exp(z[:, j, None] * x) for j in (1, 3))
        gap = z[:, 0, None] * eb
        gap += z[:, 2, None] * ed
        gap -= y
        return eb, ed, gap

    def normal(z: np.ndarray, eb: np.ndarray, ed: np.ndarray, gap: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        jac = np.empty((*eb.shape, 4))
        jac[:, :, 0], jac[:, :, 2] = eb, ed
        np.multiply(z[:, 0, None] * x, eb, out=jac[:, :, 1])
        np.multiply(z[:, 2, None] * x, ed, out=jac[:, :, 3])
        turned = jac.transpose(0, 2, 1)
        return turned @ gap[:, :, None], turned @ jac

    z_out, rows = z.copy(), np.arange(len(z))
    here = at(z, y)
    cost, damp = (here[2] ** 2).sum(axis=1), np.full(len(z), 1e-3)
    cost_out = cost.copy()
    g, hess = normal(z, *here)
    for _ in range(iters):
        ridge = np.zeros_like(hess)
        ridge[:, range(4), range(4)] = hess[:, range(4), range(4)] + 1e-12
        step, stuck = _solved(hess + damp[:, None, None] * ridge, g)
        new = z - step
        new[:, [1, 3]] = np.clip(new[:, [1, 3]], -60, 60)
        there = at(new, y)
        got = (there[2] ** 2).sum(axis=1)
        better = (got < cost) & ~stuck
        done = stuck | (better & (cost - got < 1e-9 * cost))
        damp = np.where(better, damp / 3, damp * 4)
        done |= ~better & (damp > 1e8)
        z, cost = np.where(better[:, None], new, z), np.where(better, got, cost)
        z_out[rows], cost_out[rows] = z, cost
        if done.all():
            break
        # a row that did not move keeps its equations
        if better.all():
            g, hess = normal(z, *there)
        elif (moved := better & ~done).any():
            g[moved], hess[moved] = normal(z[moved], *(v[moved] for v in there))
        if done.any():
            rows, y, z, cost, damp, g, hess = (v[~done] for v in (rows, y, z, cost, damp, g, hess))
    return z_out, cost_out


def _solved(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Solutions of all systems, and which of them have none."""
    stuck = np.zeros(len(a), bool)
    try:
        return np.linalg.solve(a, b)[:, :, 0], stuck
    except np.linalg.LinAlgError:
        out = np.zeros((len(a), a.shape[1]))
        for i in range(len(a)):
            try:
                out[i] = np.linalg.solve(a[i], b[i])[:, 0]
            except np.linalg.LinAlgError:
                stuck[i] = True
        return out, stuck

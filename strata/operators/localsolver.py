"""k-means on one matrix in memory: plain refinement, and two forms that skip distances but give the same answer."""

from __future__ import annotations

import itertools
from dataclasses import dataclass

import numpy as np


@dataclass
class Solution:
    centroids: np.ndarray
    labels: np.ndarray
    d2: np.ndarray
    rounds: int
    converged: bool


def distances(x: np.ndarray, c: np.ndarray, kernel: str = "direct") -> np.ndarray:
    """Squared distances, rows by centroids. `direct` adds dimension by dimension, as the SQL forms do;
    `gemm` multiplies matrices, faster for many dimensions but not bit for bit the same."""
    if kernel == "gemm":
        return np.maximum((x * x).sum(1)[:, None] - 2 * x @ c.T + (c * c).sum(1)[None, :], 0)
    out = np.zeros((len(x), len(c)))
    for k in range(x.shape[1]):
        d = x[:, k, None] - c[None, :, k]
        out += d * d
    return out


def update(x: np.ndarray, labels: np.ndarray, c: np.ndarray, empty: str = "keep", d2: np.ndarray | None = None) -> np.ndarray:
    """Means by cluster; a cluster without points keeps its centroid, or takes the farthest point."""
    n = np.bincount(labels, minlength=len(c))
    new = c.copy()
    full = n > 0
    for k in range(x.shape[1]):
        new[full, k] = (np.bincount(labels, x[:, k], len(c)) / np.maximum(n, 1))[full]
    if empty == "farthest" and d2 is not None:
        far = iter(np.argsort(-d2, kind="stable"))
        for k in np.flatnonzero(~full):
            new[k] = x[next(far)]
    return new


def shifted(a: np.ndarray, b: np.ndarray, how: str = "max") -> float:
    moves = np.sqrt(((a - b) ** 2).sum(1))
    return float(moves.max() if how == "max" else moves.sum())


#: Rows whose distances to all centroids are held at once.
ROWS_AT_ONCE = 1 << 18


def solve(x: np.ndarray, c0: np.ndarray, max_iter: int | None = 100, tol: float = 0.0, solver: str = "plain", kernel: str = "direct", empty: str = "keep", shift: str = "max") -> Solution:
    """Refines until no centroid moves by more than `tol`, or for `max_iter` rounds; at least one. Without `max_iter`, centroids
    that come back, which rounding can bring about, end it too, not converged."""
    c = np.asarray(c0, float).copy()
    nearest = {"plain": _plain, "bounds": _Bounds(), "kdfilter": _Cells(x) if solver == "kdfilter" else None}[solver]
    rounds, converged, seen = 0, False, c
    for _ in _rounds(max_iter):
        labels, d2 = nearest(x, c, kernel)
        new = update(x, labels, c, empty, d2)
        rounds += 1
        moved = shifted(new, c, shift)
        c = new
        if moved <= tol:
            converged = True
            break
        if max_iter is None and np.array_equal(c, seen):
            break
        seen = c if rounds & (rounds - 1) == 0 else seen  # of a round that is a power of two, so that a cycle of any length is met
    labels, d2 = _plain(x, c, kernel)
    return Solution(c, labels, d2, rounds, converged)


def _rounds(max_iter: int | None):
    return itertools.count() if max_iter is None else range(max(1, max_iter))


def solve_many(x: np.ndarray, first: np.ndarray, c0: np.ndarray, max_iter: int | None = 100, tol: float = 0.0, empty: str = "keep", shift: str = "max"):
    """`solve`, plain and direct, of many matrices at once: `x` holds their rows one after another, `first` where each
    begins. Sums run in the order of rows, as they do for one matrix, so the answers are the same bit for bit.

    Gives (centroids by matrix, labels, d2, rounds, converged). Only matrices that still move are refined.
    """
    many, k, d = len(first), len(c0), x.shape[1]
    sizes = np.diff(np.r_[first, len(x)])
    c = np.repeat(np.asarray(c0, float)[None], many, 0)
    rounds, converged = np.zeros(many, int), np.zeros(many, bool)

    def nearest(rows, own):
        """Labels and squared distances of rows, each against the centroids of its own matrix."""
        best = np.full(len(rows), np.inf)
        label = np.zeros(len(rows), int)
        at = x[rows]
        for j in range(k):
            d2 = np.zeros(len(rows))
            for a in range(d):
                diff = at[:, a] - c[own, j, a]
                d2 += diff * diff
            nearer = d2 < best
            label[nearer], best[nearer] = j, d2[nearer]
        return label, best

    owner = np.repeat(np.arange(many), sizes)
    live = np.arange(many)
    rows = np.arange(len(x))
    seen = c.copy()
    for number, _ in enumerate(_rounds(max_iter), 1):
        own = owner[rows]
        label, d2 = nearest(rows, own)
        cell = own * k + label
        n = np.bincount(cell, minlength=many * k).reshape(many, k)
        new = c.copy()
        full = n > 0
        for a in range(d):
            total = np.bincount(cell, x[rows, a], many * k).reshape(many, k)
            new[..., a][full] = (total / np.maximum(n, 1))[full]
        if empty == "farthest":
            for m in live[(n[live] == 0).any(1)]:
                mine = np.flatnonzero(own == m)
                far = iter(mine[np.argsort(-d2[mine], kind="stable")])
                for j in np.flatnonzero(n[m] == 0):
                    new[m, j] = x[rows[next(far)]]
        moves = np.sqrt(((new[live] - c[live]) ** 2).sum(2))
        rounds[live] += 1
        c[live] = new[live]
        done = (moves.max(1) if shift == "max" else moves.sum(1)) <= tol
        converged[live[done]] = True
        if max_iter is None:
            done |= (c[live] == seen[live]).all((1, 2))
            seen = c.copy() if number & (number - 1) == 0 else seen
        if done.any():
            live = live[~done]
            rows = np.flatnonzero(np.isin(owner, live))
        if not len(live):
            break
    label, d2 = nearest(np.arange(len(x)), owner)
    return c, label, d2, rounds, converged


def _plain(x: np.ndarray, c: np.ndarray, kernel: str):
    labels, d2 = np.zeros(len(x), int), np.zeros(len(x))
    for a in range(0, len(x), ROWS_AT_ONCE):
        d = distances(x[a : a + ROWS_AT_ONCE], c, kernel)
        own = d.argmin(1)
        labels[a : a + ROWS_AT_ONCE], d2[a : a + ROWS_AT_ONCE] = own, d[np.arange(len(own)), own]
    return labels, d2


class _Bounds:
    """Half the distance to the nearest other centroid bounds how near any other centroid can be: points whose
    distance to their last centroid is under it keep it without further distances."""

    def __init__(self):
        self.labels: np.ndarray | None = None

    def __call__(self, x, c, kernel):
        if self.labels is None or len(c) == 1:
            self.labels, d2 = _plain(x, c, kernel)
            return self.labels, d2
        between = distances(c, c)
        np.fill_diagonal(between, np.inf)
        half = np.sqrt(between.min(1)) / 2
        own = np.zeros(len(x))
        for k in range(x.shape[1]):
            d = x[:, k] - c[self.labels, k]
            own += d * d
        open_ = np.flatnonzero(np.sqrt(own) >= half[self.labels] * (1 - 1e-12))
        labels, d2 = self.labels.copy(), own
        if len(open_):
            labels[open_], d2[open_] = _plain(x[open_], c, kernel)
        self.labels = labels
        return labels, d2


class _Cells:
    """Cells of nearby points with bounding boxes: a centroid farther from a box than another is from its
    farthest corner cannot win in it."""

    def __init__(self, x: np.ndarray, size: int = 32):
        self.cells = []
        stack = [(np.arange(len(x)), 0)]
        while stack:
            rows, level = stack.pop()
            if len(rows) <= size:
                if len(rows):
                    self.cells.append((rows, x[rows].min(0), x[rows].max(0)))
                continue
            order = rows[np.argsort(x[rows, level % x.shape[1]], kind="stable")]
            half = len(order) // 2
            stack += [(order[:half], level + 1), (order[half:], level + 1)]

    def __call__(self, x, c, kernel):
        labels, d2 = np.zeros(len(x), int), np.zeros(len(x))
        for rows, lo, hi in self.cells:
            near = np.maximum(np.maximum(lo - c, c - hi), 0)
            far = np.maximum(np.abs(c - lo), np.abs(c - hi))
            least, most = (near**2).sum(1), (far**2).sum(1).min()
            some = np.flatnonzero(least <= most * (1 + 1e-12))
            d = distances(x[rows], c[some], kernel)
            k = d.argmin(1)
            labels[rows], d2[rows] = some[k], d[np.arange(len(rows)), k]
        return labels, d2

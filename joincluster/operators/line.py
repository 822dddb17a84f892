"""Optimal clustering of weighted numbers: k-means by dynamic programming, with a penalty, and k-medians.

Clusters of an optimal solution are segments of the sorted values. best[q][e] is the least cost of
the first e values in q segments; the split that attains it does not fall as e grows, so each level
is filled by divide and conquer. Ties take the smallest split.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

#: Distinct values up to which the plain quadratic program runs, and above which buckets stand for values.
QUADRATIC_MOST, BUCKETS = 1200, 65536


@dataclass
class Line:
    """Segments in order: centers, upper ends, masses, and the total cost."""

    centers: np.ndarray
    upper: np.ndarray
    mass: np.ndarray
    cost: float


class Squares:
    """Costs of segments for p = 2, with an optional penalty lam * |center|."""

    def __init__(self, x: np.ndarray, w: np.ndarray, lam: float = 0.0, inner: np.ndarray | None = None):
        self.shift = float((w * x).sum() / w.sum())
        y = x - self.shift
        pre = lambda v: np.concatenate([[0.0], np.cumsum(v)])
        self.w, self.s, self.q, self.lam = pre(w), pre(w * y), pre(w * y * y + (inner if inner is not None else 0.0)), lam

    def center(self, a, b):
        w = self.w[b] - self.w[a]
        mean = (self.s[b] - self.s[a]) / w + self.shift
        return np.sign(mean) * np.maximum(np.abs(mean) - self.lam / (2 * w), 0) if self.lam else mean

    def cost(self, a, b):
        w, s = self.w[b] - self.w[a], self.s[b] - self.s[a]
        out = np.maximum(self.q[b] - self.q[a] - s * s / w, 0.0)
        if self.lam:
            mean = s / w + self.shift
            center = np.sign(mean) * np.maximum(np.abs(mean) - self.lam / (2 * w), 0)
            out = out + w * (mean - center) ** 2 + self.lam * np.abs(center)
        return out


class Absolutes:
    """Costs of segments for p = 1: to the weighted median, the smaller one of two."""

    def __init__(self, x: np.ndarray, w: np.ndarray):
        pre = lambda v: np.concatenate([[0.0], np.cumsum(v)])
        self.x, self.w, self.s = x, pre(w), pre(w * x)

    def _at(self, a, b):
        half = (self.w[a] + self.w[b]) / 2
        return np.clip(np.searchsorted(self.w, half, "left") - 1, a, b - 1)

    def center(self, a, b):
        return self.x[self._at(np.asarray(a), np.asarray(b))]

    def cost(self, a, b):
        a, b = np.broadcast_arrays(a, b)
        m = self._at(a, b)
        left = self.x[m] * (self.w[m + 1] - self.w[a]) - (self.s[m + 1] - self.s[a])
        right = (self.s[b] - self.s[m + 1]) - self.x[m] * (self.w[b] - self.w[m + 1])
        return left + right


def _levels(seg, n: int, kappa: int, method: str) -> list[int]:
    """Ends of the segments of an optimal clustering."""
    ends = np.arange(1, n + 1)
    best = seg.cost(np.zeros(n, np.int64), ends)
    back = np.zeros((kappa, n), np.int32)
    for q in range(1, kappa):
        new = np.full(n, np.inf)
        # best[s - 1] is the cost of the first s values; segment q is s .. e
        if method == "dp":
            for e in range(q + 1, n + 1):
                s = np.arange(q, e)
                c = best[s - 1] + seg.cost(s, np.full(len(s), e))
                i = int(c.argmin())
                new[e - 1], back[q, e - 1] = c[i], s[i]
        else:
            todo = [(q + 1, n, q, n - 1)]
            while todo:
                lo, hi, slo, shi = todo.pop()
                if lo > hi:
                    continue
                e = (lo + hi) // 2
                s = np.arange(slo, min(shi, e - 1) + 1)
                c = best[s - 1] + seg.cost(s, np.full(len(s), e))
                i = int(c.argmin())
                new[e - 1], back[q, e - 1] = c[i], s[i]
                todo += [(lo, e - 1, slo, int(s[i])), (e + 1, hi, int(s[i]), shi)]
        best = new
    out, e = [n], n
    for q in range(kappa - 1, 0, -1):
        e = int(back[q, e - 1])
        out.append(e)
    return out[::-1]


def line_kmeans(values, weights, kappa: int, method: str = "auto", p: int = 2, lam: float = 0.0, inner=None) -> Line:
    """At most kappa segments of weighted numbers.

    method: dp (quadratic), dc (divide and conquer), lloyd (quantile start, not optimal), or auto.
    Values of no weight are dropped, equal values merged; kappa at least the number of values gives
    each its own segment (no cost but a penalty). inner holds the spread inside values that stand for buckets.
    No values give an empty Line.
    """
    x, w = np.asarray(values, float), np.asarray(weights, float)
    keep = w > 0
    x, at = np.unique(x[keep], return_inverse=True)
    inside = np.bincount(at, weights=np.asarray(inner, float)[keep], minlength=len(x)) if inner is not None and len(x) else None
    w = np.bincount(at, weights=w[keep], minlength=len(x)) if len(x) else w[:0]
    n = len(x)
    if not n:
        return Line(x, x, x, 0.0)
    seg = Absolutes(x, w) if p == 1 else Squares(x, w, lam, inside)
    k = min(kappa, n)
    if method == "auto":
        method = "dp" if n <= QUADRATIC_MOST else "dc"
    if k == n:
        ends = list(range(1, n + 1))
    elif method == "lloyd":
        total = np.cumsum(w)
        cuts = np.unique(np.searchsorted(total, total[-1] * np.arange(1, k) / k) + 1)
        ends = sorted({*[int(c) for c in cuts if c < n], n})
        for _ in range(100):
            starts = np.array([0, *ends[:-1]])
            c = seg.center(starts, np.array(ends))
            new = sorted({*[int(v) for v in np.searchsorted(x, (c[1:] + c[:-1]) / 2, "right") if 0 < v < n], n})
            if new == ends:
                break
            ends = new
    else:
        ends = _levels(seg, n, k, method)
    a, b = np.array([0, *ends[:-1]]), np.array(ends)
    return Line(seg.center(a, b), x[b - 1], np.add.reduceat(w, a), float(seg.cost(a, b).sum()))

"""Direct solver of sparse symmetric positive definite systems: an order of small bandwidth, then a banded factor."""

from __future__ import annotations

import numpy as np

#: Unknowns up to which a dense inverse is as good.
DENSE = 256


def narrow_order(rows: np.ndarray, cols: np.ndarray, n: int) -> np.ndarray:
    """Breadth-first order from a far node of each part, neighbours by degree, reversed: keeps entries near the diagonal."""
    by = np.argsort(rows, kind="stable")
    start, cols = np.searchsorted(rows[by], np.arange(n + 1)), cols[by]
    degree = np.diff(start)
    done, out = np.zeros(n, bool), []

    def levels(root: int, taken: np.ndarray) -> list[int]:
        order = [root]
        taken[root] = True
        for u in order:
            near = cols[start[u]:start[u + 1]]
            near = near[~taken[near]]
            near = np.unique(near)
            taken[near] = True
            order.extend(near[np.argsort(degree[near], kind="stable")].tolist())
        return order

    for root in np.argsort(degree, kind="stable").tolist():
        if not done[root]:
            far = levels(root, done.copy())[-1]
            out += levels(far, done)
    return np.array(out[::-1], np.int64)


class Factor:
    """Cholesky factor within the band, or a dense inverse of a small or wide system."""

    def __init__(self, rows: np.ndarray, cols: np.ndarray, vals: np.ndarray, n: int):
        self.n = n
        self.order = np.arange(n) if not len(rows) or abs(rows - cols).max() <= 1 else narrow_order(rows, cols, n)
        place = np.empty(n, np.int64)
        place[self.order] = np.arange(n)
        i, j = place[rows], place[cols]
        width = int(abs(i - j).max()) if len(rows) else 0
        self.inverse = self.band = None
        if width > 1 and (n <= DENSE or width > n // 3):
            a = np.zeros((n, n))
            a[i, j] = vals
            self.inverse = np.linalg.inv(a)
            return
        low = i >= j
        band = np.zeros((n, width + 1))
        band[j[low], i[low] - j[low]] = vals[low]
        for k in range(n):
            band[k] /= np.sqrt(band[k, 0])
            v = band[k, 1:]
            for m in range(1, min(width, n - 1 - k) + 1):
                band[k + m, :width + 1 - m] -= v[m - 1] * v[m - 1:]
        self.band = band

    def __call__(self, b: np.ndarray) -> np.ndarray:
        x = b[self.order]
        if self.inverse is not None:
            x = self.inverse @ x
        elif self.band.shape[1] == 2:
            d, e = self.band[:, 0].tolist(), self.band[:, 1].tolist()
            y = x.tolist()
            for k in range(self.n - 1):
                y[k] /= d[k]
                y[k + 1] -= e[k] * y[k]
            y[-1] /= d[-1] * d[-1]
            for k in range(self.n - 2, -1, -1):
                y[k] = (y[k] - e[k] * y[k + 1]) / d[k]
            x = np.array(y)
        else:
            width = self.band.shape[1] - 1
            for k in range(self.n):
                x[k] /= self.band[k, 0]
                m = min(width, self.n - 1 - k)
                x[k + 1:k + 1 + m] -= x[k] * self.band[k, 1:m + 1]
            for k in range(self.n - 1, -1, -1):
                m = min(width, self.n - 1 - k)
                x[k] = (x[k] - self.band[k, 1:m + 1] @ x[k + 1:k + 1 + m]) / self.band[k, 0]
        out = np.empty(self.n)
        out[self.order] = x
        return out

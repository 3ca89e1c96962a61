"""Distances as Catalyst expressions and as block kernels; smaller is always nearer."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

METRICS = ("l2sq", "cosine", "ip")


def inner(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def l2sq(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x)


def score(metric: str, a: Column, b: Column) -> Column:
    """Distance of two array<double> columns."""
    if metric == "l2sq":
        return l2sq(a, b)
    if metric == "ip":
        return -inner(a, b)
    if metric == "cosine":
        return F.lit(1.0) - inner(a, b) / F.sqrt(inner(a, a) * inner(b, b))
    raise ValueError(f"unknown metric {metric!r}; one of {METRICS}")


def block(metric: str, q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Distances of all rows of q to all rows of x, in double precision."""
    if metric == "ip":
        return -(q @ x.T)
    if metric == "cosine":
        return 1.0 - (q @ x.T) / (np.linalg.norm(q, axis=1)[:, None] * np.linalg.norm(x, axis=1)[None, :])
    if metric != "l2sq":
        raise ValueError(f"unknown metric {metric!r}; one of {METRICS}")
    # differences, not the expanded square: exact for whole numbers and free of cancellation
    out = np.empty((len(q), len(x)))
    step = max(1, (4 << 20) // max(1, x.size))
    for at in range(0, len(q), step):
        d = q[at : at + step, None, :] - x[None, :, :]
        out[at : at + step] = np.einsum("qxd,qxd->qx", d, d)
    return out


def fast_l2sq(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """The expanded square, for clustering where the last digits do not matter."""
    return np.maximum((q * q).sum(1)[:, None] - 2 * (q @ x.T) + (x * x).sum(1)[None, :], 0)


#: Boxes rule out most rows in up to so many dimensions; beyond it they rule out next to none.
BOX_DIMS = 16


def boxes(x: np.ndarray, leaf: int) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """Rows of x halved along their widest side down to `leaf` rows: the rows of each box, and its least and greatest corner."""
    out, open_ = [], [np.arange(len(x))]
    while open_:
        rows = open_.pop()
        if len(rows) <= leaf:
            out.append(np.sort(rows))
            continue
        part = x[rows]
        side = part[:, int(np.ptp(part, axis=0).argmax())]
        at = np.argpartition(side, len(rows) // 2)
        open_ += [rows[at[len(rows) // 2 :]], rows[at[: len(rows) // 2]]]
    return out, np.stack([x[r].min(axis=0) for r in out]), np.stack([x[r].max(axis=0) for r in out])


def box_l2sq(q: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """Least squared distance of each row of q to each box."""
    out = np.zeros((len(q), len(low)))
    for i in range(q.shape[1]):
        v = q[:, i, None]
        out += np.maximum(np.maximum(low[None, :, i] - v, v - high[None, :, i]), 0) ** 2
    return out


def near_boxes(q: np.ndarray, tree, size: int = 256):
    """Rows of q that lie beside each other, and the boxes of the tree that can hold a nearest row of theirs (each box has more rows than are asked for)."""
    leaves, low, high = tree
    for some, lo, hi in zip(*boxes(q, size)):
        least = (np.maximum(np.maximum(low - hi, lo - high), 0) ** 2).sum(1)
        limit = (np.maximum(high - lo, hi - low) ** 2).sum(1).min()
        near = np.flatnonzero(least <= limit * (1 + 1e-9) + 1e-9)
        yield some, ([leaves[i] for i in near], low[near], high[near])


def nearest_centre(x: np.ndarray, c: np.ndarray, block: int = 2048, tree=None) -> np.ndarray:
    """Row of c nearest to each row of x: one product and one minimum a block, since the squares of x decide nothing.

    In few dimensions a box of rows (`tree`: boxes of x) meets only the centres no farther from it than its rows have centres already.
    """
    wide = np.concatenate([-2 * c, (c * c).sum(1)[:, None]], axis=1).T.copy()
    one = np.concatenate([x, np.ones((len(x), 1))], axis=1)
    own = np.empty(len(x), np.int64)
    if x.shape[1] <= BOX_DIMS and len(c) >= 256 and len(x) >= 1024:
        leaves, low, high = tree or boxes(x, 256)
        squares, flat, columns = (x * x).sum(1), wide.T.copy(), c.T.copy()
        first = min(len(c), 64 + len(c) // 64)
        step = max(1, (1 << 18) // len(c))
        for at in range(0, len(leaves), step):
            mid, half = (low[at : at + step] + high[at : at + step]) / 2, (high[at : at + step] - low[at : at + step]) / 2
            least = np.zeros((len(mid), len(c)))
            for i, column in enumerate(columns):
                far = np.abs(column[None] - mid[:, i, None]) - half[:, i, None]
                np.maximum(far, 0, out=far)
                least += far * far
            for rows, to in zip(leaves[at : at + step], least):
                some = np.argpartition(to, first - 1)[:first]  # what the rows find among these bounds where others can be nearer
                part, size = one[rows], squares[rows]
                limit = ((part @ flat[some].T).min(axis=1) + size).max()
                near = np.flatnonzero(to <= limit * (1 + 1e-9) + 1e-9 * (1 + size.max()))
                own[rows] = near[(part @ flat[near].T).argmin(axis=1)]
        return own
    for at in range(0, len(x), block):
        own[at : at + block] = (one[at : at + block] @ wide).argmin(axis=1)
    return own


def sums_by(own: np.ndarray, x: np.ndarray, n: int) -> np.ndarray:
    """Sums of the rows of x by their number in `own`."""
    return np.stack([np.bincount(own, x[:, i], n) for i in range(x.shape[1])], axis=1)


class Nearest:
    """The k nearest rows seen so far of each query, ties to the smaller id.

    A product tells which rows may come in; only these are measured (as `block` measures) and sorted.
    In few dimensions rows pass in boxes, and a query meets the boxes that reach into its circle.
    """

    NONE = np.iinfo(np.int64).max
    #: Numbers of the rows that are boxed together.
    HELD = 2 << 20

    def __init__(self, metric: str, q: np.ndarray, k: int) -> None:
        self.metric, self.q, self.k = metric, q, k
        self.ids = np.full((len(q), k), self.NONE)
        self.dist = np.full((len(q), k), np.nan)
        self.squares = (q * q).sum(1)
        self.one = np.concatenate([q, np.ones((len(q), 1))], axis=1)
        self.boxed = metric == "l2sq" and q.shape[1] <= BOX_DIMS
        self.waiting: list[tuple[np.ndarray, np.ndarray]] = []
        self.count = 0

    def add(self, ids: np.ndarray, x: np.ndarray) -> None:
        self.waiting.append((ids, x))
        self.count += x.size
        if not self.boxed or self.count >= self.HELD:
            self.flush()

    def flush(self, tree=None) -> None:
        if not self.waiting:
            return
        ids, x = (np.concatenate(c) if len(c) > 1 else c[0] for c in zip(*self.waiting))
        self.waiting, self.count = [], 0
        if not self.boxed or len(x) < 2048:
            for start in range(0, len(self.q), 4096):
                part = np.arange(start, min(start + 4096, len(self.q)))
                for at in range(0, len(x), 1024):
                    self.take(part, ids[at : at + 1024], x[at : at + 1024])
            return
        leaves, low, high = tree or boxes(x, 512)
        for start in range(0, len(self.q), 1024):
            part = np.arange(start, min(start + 1024, len(self.q)))
            far = box_l2sq(self.q[part], low, high)
            home = far.argmin(axis=1)
            for i in np.unique(home).tolist():
                self.take(part[home == i], ids[leaves[i]], x[leaves[i]])
            limit = self.dist[part, -1]
            for i in np.flatnonzero((~(far > (limit + 1e-9 * limit + 1e-9)[:, None])).any(axis=0)).tolist():
                rows, limit = leaves[i], self.dist[part, -1]
                asks = part[~(far[:, i] > limit + 1e-9 * limit + 1e-9) & (home != i)]
                if len(asks):
                    self.take(asks, ids[rows], x[rows])

    def take(self, asks: np.ndarray, ids: np.ndarray, x: np.ndarray) -> None:
        """Meet the queries `asks` with all rows of x."""
        limit = self.dist[asks, -1]
        if self.metric == "l2sq":
            own = (x * x).sum(1)
            d = self.one[asks] @ np.concatenate([-2 * x, own[:, None]], axis=1).T
            slack = 1e-9 * (1 + self.squares[asks] + own.max())
            limit = limit - self.squares[asks] + slack
        else:
            d, slack = block(self.metric, self.q[asks], x), 0.0
        if len(x) > self.k and np.isnan(limit).any():
            limit = np.fmin(limit, np.partition(d, self.k - 1, axis=1)[:, self.k - 1] + slack)
        i, j = np.nonzero(~(d > limit[:, None]))
        if not len(i):
            return
        if self.metric == "l2sq":
            d = np.concatenate([np.einsum("xd,xd->x", g, g) for g in (self.q[asks[i[n : n + 65536]]] - x[j[n : n + 65536]] for n in range(0, len(i), 65536))])
        else:
            d = d[i, j]
        met = np.unique(i)
        row = np.concatenate([i, np.repeat(met, self.k)])
        d, names = np.concatenate([d, self.dist[asks[met]].ravel()]), np.concatenate([ids[j], self.ids[asks[met]].ravel()])
        order = np.lexsort((names, d, row))
        first = np.searchsorted(row[order], met)
        best = order[first[:, None] + np.arange(self.k)]
        self.dist[asks[met]], self.ids[asks[met]] = d[best], names[best]


def nearest_rows(d: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Per row of d the columns of the k smallest, ties to the smaller id."""
    k = min(k, d.shape[1])
    if k <= 0:
        return np.zeros((len(d), 0), int)
    order = np.argsort(ids, kind="stable")
    return order[np.argsort(d[:, order], axis=1, kind="stable")[:, :k]]

"""Suffix arrays by difference-cover samples, one bucket of suffixes at a time.

Positions whose remainder modulo 7 is in {0, 1, 3} form the sample: for any two positions a shift
below 7 brings both into it.  The sample is ranked by doubling; then suffixes are taken in buckets
by their first seven symbols, and suffixes that agree in those are ordered by the sample's ranks at
the common shift.  So a long tie costs one look-up and only a bucket's suffixes are sorted at once.
"""

from __future__ import annotations

import numpy as np

V = 7
COVER = (0, 1, 3)
SHIFT = np.array([[next(d for d in range(V) if (a + d) % V in COVER and (b + d) % V in COVER) for b in range(V)] for a in range(V)])


def seven(text: np.ndarray) -> np.ndarray:
    """First seven symbols of every suffix as a number of nine bits each; 0 stands for the end."""
    n = len(text)
    padded = np.zeros(n + V, np.uint64)
    padded[:n] = text
    out = np.zeros(n, np.uint64)
    for i in range(V):
        out = out << np.uint64(9) | padded[i : i + n]
    return out


def sample_ranks(first: np.ndarray, depth: int | None) -> np.ndarray:
    """Ranks of the sample's suffixes from 1 on (by `depth` symbols at least, if given); 0 elsewhere."""
    n = len(first)
    at = np.flatnonzero(np.isin(np.arange(n) % V, COVER))
    rank = np.zeros(n + V, np.int64)
    if not n:
        return rank
    values, inverse = np.unique(first[at], return_inverse=True)
    rank[at] = inverse + 1
    reach = V
    while len(values) < len(at) and (depth is None or reach < depth):
        later = np.minimum(at + reach, n)
        ahead = np.where(at + reach < n, rank[later], 0)
        values, inverse = np.unique(rank[at] * (len(at) + 2) + ahead, return_inverse=True)
        rank[at] = inverse + 1
        reach *= 2
    return rank


def order_of(bucket: np.ndarray, first: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """The bucket's positions in suffix order."""
    bucket = bucket[np.argsort(first[bucket], kind="stable")]
    key = first[bucket]
    new = np.concatenate(([True], key[1:] != key[:-1]))
    group = np.cumsum(new) - 1
    if group[-1] == len(bucket) - 1:
        return bucket
    size = np.bincount(group)
    tied = np.flatnonzero(size[group] > 1)
    positions, owner = bucket[tied], group[tied].astype(np.int64)
    residue = positions % V
    top = np.int64(rank.max() + 1)
    n = len(rank) - V
    place = np.zeros(len(tied), np.int64)
    classes = [np.flatnonzero(residue == r) for r in range(V)]
    value = lambda c, d: owner[c] * top + rank[np.minimum(positions[c] + d, n + V - 1)]
    sorted_by = {}
    for a in range(V):
        for b in range(V):
            if len(classes[a]) and len(classes[b]):
                d = int(SHIFT[a][b])
                if (b, d) not in sorted_by:
                    sorted_by[b, d] = np.sort(value(classes[b], d))
                place[classes[a]] += np.searchsorted(sorted_by[b, d], value(classes[a], d), side="left")
    bucket[tied] = positions[np.lexsort((positions, place))]
    return bucket


def suffix_order(text: np.ndarray, starts: np.ndarray | None = None, depth: int | None = None, bucket: int = 1 << 20):
    """Yields runs of suffix starts in order, a bucket at a time; only `starts`, if given.

    `text` holds symbols from 1 to 511; a 0 ends a piece, and order past it means nothing.
    With a depth, suffixes that agree in that many symbols come in order of position.
    """
    if not len(text):
        return
    first = seven(text)
    rank = sample_ranks(first, depth)
    where = np.arange(len(text)) if starts is None else starts
    parts = max(1, -(-len(where) // bucket))
    key = first[where]
    edges = np.unique(np.quantile(key, [i / parts for i in range(1, parts)], method="nearest")) if parts > 1 else np.zeros(0, np.uint64)
    lot = np.searchsorted(edges, key, side="right")
    for i in range(len(edges) + 1):
        mine = where[lot == i]
        if len(mine):
            yield order_of(mine, first, rank)


def suffix_array(data: bytes, bucket: int = 1 << 20) -> np.ndarray:
    """Suffix array of a byte string."""
    text = np.frombuffer(data, np.uint8).astype(np.int64) + 1
    runs = list(suffix_order(text, bucket=bucket))
    return np.concatenate(runs) if runs else np.zeros(0, np.int64)

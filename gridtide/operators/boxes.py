"""Counts and sums over the points inside many boxes, without listing a pair.

A box is a rectangle and a time from which on points count.  Points in order of
time are taken in blocks of doubling length; what is left of a stretch of time
consists of one block of a length at most.  Inside a block points lie by x, and
a bit-wise partition by the rank of y tells how many of a run of them lie under
a bound, a step for each bit.  Work is (points + boxes) times two logarithms.
"""

from __future__ import annotations

import numpy as np


def _under(rank: np.ndarray, value: np.ndarray, left: np.ndarray, right: np.ndarray, bound: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(count, sum of values) of the positions [left, right) with a rank under ``bound``."""
    count, total = np.zeros(len(left), np.int64), np.zeros(len(left))
    for bit in range(bits - 1, -1, -1):
        one = (rank >> bit & 1).astype(bool)
        zeros = np.concatenate(([0], np.cumsum(~one)))
        order = np.concatenate((np.flatnonzero(~one), np.flatnonzero(one)))
        rank, value = rank[order], value[order]
        sums = np.concatenate(([0.0], np.cumsum(value[: zeros[-1]])))
        up = (bound >> bit & 1).astype(bool)
        low, high = zeros[left], zeros[right]
        count += np.where(up, high - low, 0)
        total += np.where(up, sums[high] - sums[low], 0.0)
        left, right = np.where(up, zeros[-1] + left - low, low), np.where(up, zeros[-1] + right - high, high)
    return count, total


def box_sums(points: tuple[np.ndarray, ...], boxes: tuple[np.ndarray, ...]) -> tuple[np.ndarray, np.ndarray]:
    """(count, sum of x) for each box (since, x0, x1, y0, y1), closed on all sides, of the points (time, x, y)."""
    order = np.argsort(points[0], kind="stable")
    time, x, y = (c[order] for c in points)
    since, x0, x1, y0, y1 = boxes
    n, count, total = len(time), np.zeros(len(since), np.int64), np.zeros(len(since))
    xs, ys = np.sort(x), np.unique(y)
    place, rank, bits = np.searchsorted(xs, x), np.searchsorted(ys, y), len(ys).bit_length()
    a, b = np.searchsorted(xs, x0), np.searchsorted(xs, x1, "right")
    low, high = np.searchsorted(ys, y0), np.searchsorted(ys, y1, "right")
    start, levels = np.searchsorted(time, since), max(0, n - 1).bit_length()
    live = (start < n) & (a < b) & (low < high)
    by = np.arange(n)
    for level in range(levels + 1):
        # the block of this length that begins where the shorter ones have led to
        own = np.flatnonzero(live & ((start >> level & 1 == 1) | (level == levels)) & (start < n))
        if level or n == 1:
            by = by[np.argsort((by >> level) * (n + 1) + place[by], kind="stable")]
        if len(own):
            key, block = (by >> level) * (n + 1) + place[by], (start[own] >> level) * (n + 1)
            left, right = np.searchsorted(key, block + a[own]), np.searchsorted(key, block + b[own])
            left, right = np.concatenate((left, left)), np.concatenate((right, right))
            c, t = _under(rank[by], x[by], left, right, np.concatenate((high[own], low[own])), bits)
            count[own] += c[: len(own)] - c[len(own) :]
            total[own] += t[: len(own)] - t[len(own) :]
            start[own] += 1 << level
    return count, total

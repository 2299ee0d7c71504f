"""Signatures of multisets whose agreement estimates their weighted Jaccard similarity.

Every element owns a Poisson process of points over time and over its weight axis, each point with a
signature component drawn at random. A multiset sees the points below its weights; a component's value
is the time of its first point. Two multisets agree in a component with a chance of exactly the sum of
the smaller weights over the sum of the larger.

The weight axis is discretised into unit cells and cut into [0, 1), [1, 2), [2, 4), [4, 8) and so on.
An interval's process gives its first point, with a cell at random; what follows is the process of its
two halves, and so on down to single cells, whose processes run on. A half above the weight is never
entered, so a weight costs its logarithm. Points after a time by which all components are all but sure
to be filled are not generated; a multiset that still misses one is done again with twice the time.
"""

from __future__ import annotations

import numpy as np

from .text import U, splitmix

_ROOTS = splitmix(np.arange(64, dtype=U) + U(0xBA6))


def signatures(element: np.ndarray, weight: np.ndarray, owner: np.ndarray, owners: int, size: int) -> np.ndarray:
    """Times by owner and component; element: hashes, weight: integers from 1, owner: ascending numbers.

    An owner without elements has only infinite times.
    """
    total = np.bincount(owner, weights=weight, minlength=owners)
    out = np.full((owners, size), np.inf)
    limit = size * (np.log(size) + 3) / np.maximum(total, 1)
    open_ = np.flatnonzero(total > 0)
    chosen = np.arange(len(owner))
    while len(open_):
        part = np.full(owners, -1)
        part[open_] = np.arange(len(open_))
        chosen = chosen[part[owner[chosen]] >= 0]
        held = np.full(len(open_) * size, np.inf)
        _points(element[chosen], weight[chosen], part[owner[chosen]], limit[open_], held, size)
        out[open_] = held.reshape(-1, size)
        limit *= 2
        open_ = open_[~np.isfinite(out[open_]).all(1)]
    return out


def _points(element, weight, owner, limit, held, size) -> None:
    state, low, width, top, whose = [], [], [], [], []
    start = 0
    while True:
        mine = weight > start
        if not mine.any():
            break
        root = start.bit_length()
        state.append(splitmix(element[mine] ^ _ROOTS[root]))
        low.append(np.full(mine.sum(), start, np.int64))
        width.append(np.full(mine.sum(), max(1, start), np.int64))
        top.append(weight[mine].astype(np.int64))
        whose.append(owner[mine])
        start = max(1, 2 * start)
    if not state:
        return
    state, low, width, top, whose = (np.concatenate(x) for x in (state, low, width, top, whose))
    time = np.zeros(len(state))
    while len(state):
        state = splitmix(state)
        time = time - np.log(((state >> U(11)) + U(1)) * 2.0**-53) / width
        near = time <= limit[whose]
        state, time, low, width, top, whose = (x[near] for x in (state, time, low, width, top, whose))
        mark = splitmix(state)
        component = ((mark >> U(32)) * U(size)) >> U(32)
        cell = low + (((mark & U(0xFFFFFFFF)) * width.astype(U)) >> U(32)).astype(np.int64)
        seen = cell < top
        np.minimum.at(held, whose[seen] * size + component[seen].astype(np.int64), time[seen])
        wide = width > 1
        if wide.any():
            half = width[wide] // 2
            s, t, lo, tp, wh = mark[wide], time[wide], low[wide], top[wide], whose[wide]
            right = lo + half < tp
            state = np.concatenate((mark[~wide], splitmix(s ^ U(1)), splitmix(s[right] ^ U(2))))
            time = np.concatenate((time[~wide], t, t[right]))
            low = np.concatenate((low[~wide], lo, (lo + half)[right]))
            width = np.concatenate((width[~wide], half, half[right]))
            top = np.concatenate((top[~wide], tp, tp[right]))
            whose = np.concatenate((whose[~wide], wh, wh[right]))
        else:
            state = mark

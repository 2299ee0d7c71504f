"""Distances, each as a Column expression, for numpy matrices, and in DuckDB SQL.

Payloads: ``vector`` array<double>; ``histogram`` struct<p, logp> of array<double>; ``sparse``
struct<idx array<int>, val array<double>, norm double>; ``text`` string; ``signature``
array<struct<c array<double>, w double>>. In ``d(x, y)`` of an asymmetric distance, x is the left one.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE = 1e9


def rank_key(d: Column) -> Column:
    """Distances compare as integers of a billionth, so that engines agree on ties."""
    return F.floor(d * SCALE + 0.5).cast("long")


def rank_keys(d: np.ndarray) -> np.ndarray:
    return np.floor(d * SCALE + 0.5).astype(np.int64)


def _sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0.0), lambda a, x: a + x)


def l2(x: Column, y: Column) -> Column:
    return F.sqrt(_sum(F.zip_with(x, y, lambda a, b: (a - b) * (a - b))))


def l1(x: Column, y: Column) -> Column:
    return _sum(F.zip_with(x, y, lambda a, b: F.abs(a - b)))


def cosine_dense(x: Column, y: Column) -> Column:
    """1 less the cosine; a zero vector has distance 1 from all but another zero vector (0)."""
    dot = _sum(F.zip_with(x, y, lambda a, b: a * b))
    nx, ny = F.sqrt(_sum(F.transform(x, lambda a: a * a))), F.sqrt(_sum(F.transform(y, lambda a: a * a)))
    return F.when((nx == 0) & (ny == 0), 0.0).when((nx == 0) | (ny == 0), 1.0).otherwise(1 - dot / (nx * ny))


def cosine_sparse(x: Column, y: Column) -> Column:
    held = F.map_from_arrays(y["idx"], y["val"])
    dot = _sum(F.zip_with(x["idx"], x["val"], lambda i, v: v * F.coalesce(F.element_at(held, i), F.lit(0.0))))
    return F.when((x["norm"] == 0) & (y["norm"] == 0), 0.0).when((x["norm"] == 0) | (y["norm"] == 0), 1.0).otherwise(1 - dot / (x["norm"] * y["norm"]))


def kl(x: Column, y: Column) -> Column:
    """Kullback-Leibler divergence of x from y, with the logarithms stored in the payload."""
    return _sum(F.zip_with(x["p"], F.zip_with(x["logp"], y["logp"], lambda a, b: a - b), lambda p, d: p * d))


def js(x: Column, y: Column) -> Column:
    """Jensen-Shannon divergence."""
    own = _sum(F.zip_with(x["p"], x["logp"], lambda p, g: p * g)) + _sum(F.zip_with(y["p"], y["logp"], lambda p, g: p * g))
    both = _sum(F.zip_with(x["p"], y["p"], lambda a, b: (a + b) * F.log((a + b) / 2)))
    return 0.5 * (own - both)


def norm_levenshtein(x: Column, y: Column) -> Column:
    """Edit distance over the longer length; two empty sequences have distance 0."""
    return F.coalesce(F.levenshtein(x, y) / F.nullif(F.greatest(F.length(x), F.length(y)), F.lit(0)), F.lit(0.0))


def _cross(x: Column, y: Column) -> Column:
    """Sum over pairs of centroids of weight * weight * 1 / (1 + l2)."""
    return _sum(F.transform(x, lambda a: _sum(F.transform(y, lambda b: a["w"] * b["w"] / (1 + l2(a["c"], b["c"]))))))


def sqfd(x: Column, y: Column) -> Column:
    """Signature quadratic form distance with the similarity 1 / (1 + l2)."""
    return F.sqrt(F.greatest(F.lit(0.0), _cross(x, x) + _cross(y, y) - 2 * _cross(x, y)))


def exp_decay(x: Column, y: Column) -> Column:
    """A symmetric space on the line in which nearness is not passed on."""
    return F.exp(-F.abs(x - y)) * F.abs(x - y)


# numpy: matrices of a block of points (rows) and a set of queries or pivots (columns)


def _blocks(n: int, cost: int):
    step = max(1, (4 << 20) // max(1, cost))
    for a in range(0, n, step):
        yield slice(a, min(n, a + step))


def np_l2(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """By the inner product; pairs so near that this would lose digits again, by differences."""
    xx, yy = np.einsum("ij,ij->i", x, x)[:, None], np.einsum("ij,ij->i", y, y)[None]
    size = xx + yy
    square = size - 2 * (x @ y.T)
    i, j = np.nonzero(square <= 1e-5 * size)
    for s in _blocks(len(i), x.shape[1] if x.ndim > 1 else 1):
        square[i[s], j[s]] = ((x[i[s]] - y[j[s]]) ** 2).sum(1)
    return np.sqrt(np.maximum(square, 0))


def np_l1(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    out = np.empty((len(x), len(y)))
    held = np.empty((min(len(x), max(1, (1 << 16) // max(1, x.shape[1]))), x.shape[1])) if len(x) and len(y) else None
    for a in range(0, len(x) if len(y) else 0, len(held) if held is not None else 1):
        part = x[a : a + len(held)]
        room = held[: len(part)]  # stays in the processor's cache
        for j, one in enumerate(y):
            np.subtract(part, one, out=room)
            np.abs(room, out=room).sum(1, out=out[a : a + len(part), j])
    return out


def np_cosine(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    nx, ny = np.sqrt((x * x).sum(1))[:, None], np.sqrt((y * y).sum(1))[None]
    with np.errstate(invalid="ignore", divide="ignore"):
        out = 1 - (x @ y.T) / (nx * ny)
    return np.where((nx == 0) & (ny == 0), 0.0, np.where((nx == 0) | (ny == 0), 1.0, out))


def np_kl(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    lx = np.log(x)
    return (x * lx).sum(1)[:, None] - x @ np.log(y).T


def np_js(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    ex, ey = (x * np.log(x)).sum(1)[:, None], (y * np.log(y)).sum(1)[None]
    out = np.empty((len(x), len(y)))
    for s in _blocks(len(x), y.size):
        both = x[s, None] + y[None]
        out[s] = 0.5 * (ex[s] + ey - (both * np.log(both / 2)).sum(-1))
    return out


def np_sqfd(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Of object arrays of signatures, each a pair (centroids, weights)."""

    def cross(a, b):
        return a[1] @ (1 / (1 + np.sqrt(np.maximum(((a[0][:, None] - b[0][None]) ** 2).sum(-1), 0)))) @ b[1]

    own, other = np.array([cross(a, a) for a in x]), np.array([cross(b, b) for b in y])
    sizes = np.array([len(a[1]) for a in x])
    out = np.zeros((len(x), len(y)))
    if not len(x):
        return out
    centroids, weights = np.concatenate([a[0] for a in x]), np.concatenate([a[1] for a in x])
    owner = np.repeat(np.arange(len(x)), sizes)
    for j, b in enumerate(y):
        alike = weights * ((1 / (1 + np.sqrt(((centroids[:, None] - b[0][None]) ** 2).sum(-1)))) @ b[1])
        out[:, j] = np.sqrt(np.maximum(own + other[j] - 2 * np.bincount(owner, alike, len(x)), 0))
    return out


def np_norm_lev(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Of object arrays of strings: all x at once for each y, by bits where y has 64 characters at most, else by a table."""
    sizes = np.fromiter(map(len, x), np.int64, len(x))
    width = int(sizes.max(initial=0))
    order = np.argsort(-sizes, kind="stable")  # long ones first: those that still have a character are the first so many
    codes = np.zeros((len(x), width), np.uint32)
    codes[np.arange(width)[None] < sizes[order][:, None]] = np.frombuffer("".join(x[order]).encode("utf-32-le", "surrogatepass"), np.uint32)
    codes = np.ascontiguousarray(codes.T)
    active = np.searchsorted(-sizes[order], -np.arange(width), side="left")
    out = np.zeros((len(x), len(y)))
    for j, b in enumerate(y):
        far = _by_bits(codes, active, b) if 0 < len(b) <= 64 else _by_table(codes, sizes[order], b)
        out[order, j] = far / np.maximum(np.maximum(sizes[order], len(b)), 1)
    return out


def _by_bits(codes: np.ndarray, active: np.ndarray, b: str) -> np.ndarray:
    """Edit distances of strings (columns of codes) to ``b``; a column of the table is two words of bits, its steps up and down."""
    one, last = np.uint64(1), np.uint64(len(b) - 1)
    places: dict[int, int] = {}
    for i, c in enumerate(b):
        places[ord(c)] = places.get(ord(c), 0) | 1 << i
    known = np.array(sorted(places), np.uint32)
    masks = np.array([places[int(c)] for c in known] + [0], np.uint64)
    low = np.zeros(256, np.uint64)
    small = known < 256
    low[known[small]] = masks[:-1][small]
    far = np.full(codes.shape[1], len(b), np.int64)
    up, down = np.full(codes.shape[1], ~np.uint64(0)), np.zeros(codes.shape[1], np.uint64)
    narrow = bool((codes < 256).all())
    for row, n in zip(codes, active, strict=True):
        if narrow:
            same = low[row[:n]]
        else:
            at = np.minimum(np.searchsorted(known, row[:n]), len(known) - 1)
            same = np.where(known[at] == row[:n], masks[at], np.uint64(0))
        u, v = up[:n], down[:n]
        side = same | v
        across = (((same & u) + u) ^ u) | same
        plus, minus = v | ~(across | u), u & across
        far[:n] += (plus >> last & one).astype(np.int64) - (minus >> last & one).astype(np.int64)
        plus, minus = plus << one | one, minus << one
        up[:n], down[:n] = minus | ~(side | plus), plus & side
    return far


def _by_table(codes: np.ndarray, sizes: np.ndarray, b: str) -> np.ndarray:
    width = len(codes)
    row = np.repeat(np.arange(width + 1)[:, None], codes.shape[1], 1)
    for n, c in enumerate(b, 1):
        new = np.empty_like(row)
        new[0] = n
        change = np.minimum(row[1:] + 1, row[:-1] + (codes != ord(c)))
        for i in range(width):
            new[i + 1] = np.minimum(change[i], new[i] + 1)
        row = new
    return row[sizes, np.arange(codes.shape[1])]


# SQL


def _zip_sql(a: str, b: str, body: str) -> str:
    return f"list_sum(list_transform(list_zip({a}, {b}), lambda t: {body}))"


_SQL = {
    "l2": lambda a, b: f"list_distance({a}, {b})",
    "l1": lambda a, b: _zip_sql(a, b, "abs(t[1] - t[2])"),
    "cosine": lambda a, b: f"(1 - list_cosine_similarity({a}, {b}))",
    "kl": lambda a, b: f"(list_inner_product({a}.p, {a}.logp) - list_inner_product({a}.p, {b}.logp))",
    "js": lambda a, b: f"(0.5 * (list_inner_product({a}.p, {a}.logp) + list_inner_product({b}.p, {b}.logp) - {_zip_sql(f'{a}.p', f'{b}.p', '(t[1] + t[2]) * ln((t[1] + t[2]) / 2)')}))",
    "norm_lev": lambda a, b: f"(CASE WHEN greatest(length({a}), length({b})) = 0 THEN 0.0 ELSE levenshtein({a}, {b})::DOUBLE / greatest(length({a}), length({b})) END)",
    "exp_decay": lambda a, b: f"(exp(-abs({a} - {b})) * abs({a} - {b}))",
    "sqfd": lambda a, b: f"sqrt(greatest(0.0, {_cross_sql(a, a)} + {_cross_sql(b, b)} - 2 * {_cross_sql(a, b)}))",
}


def _cross_sql(a: str, b: str) -> str:
    inner = f"list_sum(list_transform({b}, lambda v: u.w * v.w / (1 + list_distance(u.c, v.c))))"
    return f"list_sum(list_transform({a}, lambda u: {inner}))"


@dataclass(frozen=True)
class Distance:
    """name; payload; expression; numpy form over matrices, where there is one; what makes it a metric.

    transform and mu: a monotone function of the distance for which differences to a third point are at
    most mu times the distance (1 and the identity for metrics); None where no such bound is known.
    block: distances of two lists of payloads that have no matrix form.
    """

    name: str
    payload: str
    column: Callable[[Column, Column], Column]
    matrix: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None
    symmetric: bool = True
    metric: bool = False
    transform: Callable[[Column], Column] | None = None
    mu: float | None = 1.0
    block: Callable[[np.ndarray, np.ndarray], np.ndarray] | None = None

    def __call__(self, point: Column, query: Column, side: str = "left") -> Column:
        """side: ``left`` takes the point first, d(x, q); ``right`` the query first, d(q, x)."""
        return self.column(point, query) if side == "left" else self.column(query, point)

    def between(self, points: np.ndarray, queries: np.ndarray, side: str = "left") -> np.ndarray:
        if self.matrix is None and self.block is not None:
            return self.block(points, queries)
        if self.matrix is None:
            raise ValueError(f"{self.name} has no matrix form")
        return self.matrix(points, queries) if side == "left" or self.symmetric else self.matrix(queries, points).T

    def sql(self, point: str, query: str, side: str = "left") -> str:
        return _SQL[self.name](point, query) if side == "left" else _SQL[self.name](query, point)


DISTANCES = {
    d.name: d
    for d in (
        Distance("l2", "vector", l2, np_l2, metric=True),
        Distance("l1", "vector", l1, np_l1, metric=True),
        Distance("cosine", "vector", cosine_dense, np_cosine, transform=lambda d: F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), 1 - d)))),
        Distance("cosine_sparse", "sparse", cosine_sparse, transform=lambda d: F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), 1 - d)))),
        Distance("kl", "histogram", kl, np_kl, symmetric=False, transform=lambda d: F.sqrt(F.greatest(d, F.lit(0.0))), mu=None),
        Distance("js", "histogram", js, np_js, transform=lambda d: F.sqrt(F.greatest(d, F.lit(0.0)))),
        Distance("sqfd", "signature", sqfd, metric=True, block=np_sqfd),
        Distance("norm_lev", "text", norm_levenshtein, block=np_norm_lev),
        Distance("exp_decay", "number", exp_decay),
    )
}


def distance(name: str | Distance) -> Distance:
    if isinstance(name, Distance):
        return name
    if name not in DISTANCES:
        raise ValueError(f"unknown distance {name!r}; known: {', '.join(sorted(DISTANCES))}")
    return DISTANCES[name]


# distances of permutations


def rho(a: Column, b: Column) -> Column:
    """Squared difference of ranks, added up."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("long") - y) * (x.cast("long") - y)), F.lit(0).cast("long"), lambda s, v: s + v)


def footrule(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.abs(x.cast("long") - y)), F.lit(0).cast("long"), lambda s, v: s + v)


def hamming(a: Column, b: Column) -> Column:
    """Differing bits of two arrays of 64-bit words."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y)).cast("long")), F.lit(0).cast("long"), lambda s, v: s + v)


def pack_bits(rank: Column, m: int, threshold: int | None = None) -> Column:
    """Bit i is 1 if pivot i + 1 has at least the threshold's rank; 64 bits a word."""
    b = m // 2 + 1 if threshold is None else threshold
    words = []
    for a in range(0, m, 64):
        part = F.slice(rank, a + 1, min(64, m - a))
        words.append(F.aggregate(F.transform(part, lambda r, i: F.when(r >= b, F.call_function("shiftleft", F.lit(1).cast("long"), i)).otherwise(F.lit(0).cast("long"))), F.lit(0).cast("long"), lambda s, v: s.bitwiseOR(v)))
    return F.array(*words)

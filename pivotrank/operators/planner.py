"""Which method suits a search, and the tuning of its parameters on small sets."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from . import measures as M
from . import search as S
from .permutation_indexes import ExhaustivePermutations, SharedPivots


@dataclass
class Choice:
    method: str
    why: str


def choose(n: int, dist_cost: float, dim: float, queries: int, metric: bool) -> Choice:
    """dist_cost: how many times an L2 distance; dim: intrinsic dimension; queries: how many will be asked."""
    if n * dist_cost < 1e5:
        return Choice("exact", "so few cheap distances are computed faster than any index is built")
    if dim <= 8:
        return Choice("ball_tree", "pruning works in few dimensions")
    if queries > n:
        return Choice("graph", "many queries repay a graph's building")
    if dist_cost >= 10:
        return Choice("exhaustive_bits", "the distance costs far more than comparing packed permutations")
    return Choice("shared_pivots", "an index by scans and joins, cheap to build")


def in_window(recall: float, low: float = 0.85, high: float = 0.95) -> bool:
    return low <= recall <= high


def tune_gamma(index: ExhaustivePermutations, queries: DataFrame, truth: DataFrame, target: float = 0.9, k: int = 10) -> int:
    """The least number of candidates that reaches the recall, read off one ordering."""
    rows = M.fraction_for_recall(index.scores(queries), truth, index.n, k, (target,)).collect()
    return max(k, round(rows[0]["fraction"] * index.n)) if rows else k


def tune_m(points: DataFrame, queries: DataFrame, dist, grid: tuple[int, ...] = (16, 32, 64, 128), gamma: int = 100, target: float = 0.9, k: int = 10) -> tuple[int, float]:
    """The first permutation length of a grid that reaches the recall, or the best, with its recall."""
    truth, best = S.exact_knn(points, queries, dist, k), (grid[0], 0.0)
    for m in grid:
        found = M.recall(ExhaustivePermutations(points, dist, m).search(queries, k, gamma=gamma), truth, k).first()["recall"]
        if found > best[1]:
            best = (m, found)
        if found >= target:
            break
    return best


def tune_t(index: SharedPivots, queries: DataFrame, truth: DataFrame, target: float = 0.9, k: int = 10) -> tuple[int, int]:
    """(largest, smallest) number of shared pivots to ask for that still reaches the recall; (1, 1) if none does.

    One pass: the shares of the true neighbours are counted, largest first.
    """
    shared = index.shared(queries).join(truth.select("qid", "id"), ["qid", "id"]).groupBy("shared").count().collect()  # mi rows
    total, upto = truth.count(), 0
    for r in sorted(shared, key=lambda r: -r["shared"]):
        upto += r["count"]
        if upto >= target * total:
            return int(r["shared"]), 1
    return 1, 1


def pick_graph_builder(points: DataFrame, dist, k: int = 10) -> str:
    """``nn_descent`` or ``small_world``, by which finds more true neighbours on the given (small) set."""
    from .graphs import exact_graph, nn_descent, small_world

    truth = exact_graph(points, dist, k).select("src", "dst")
    hits = {name: truth.join(build(points, dist, k).select("src", "dst").distinct(), ["src", "dst"]).count() for name, build in (("nn_descent", nn_descent), ("small_world", small_world))}
    return max(sorted(hits), key=hits.__getitem__)


def tune_shared(points: DataFrame, queries: DataFrame, dist, grid: tuple[int, ...] = (500, 1000, 2000), mi: int = 32, target: float = 0.9, k: int = 10) -> tuple[int, int, float]:
    """(m, t, share of the points that are candidates): the cheapest of a grid of pivot numbers that reaches the recall.

    Numbers of pivots beyond a tenth of the points are left out; (0, 1, 1.0) if none is left.
    """
    truth, n, q, best = S.exact_knn(points, queries, dist, k), points.count(), queries.count(), (0, 1, 1.0)
    for m in grid:
        if m < mi or m > n // 10:
            continue
        index = SharedPivots(points, dist, m, mi=mi)
        t = tune_t(index, queries, truth, target, k)[0]
        share = index.candidates(queries, t=t, merge="scan").count() / max(1, n * q)
        if best[0] == 0 or share < best[2]:
            best = (m, t, share)
    return best


def tune_graph(points: DataFrame, dist, grid: tuple[int, ...] = (5, 10, 20), decays: tuple[float, ...] = (1.0, 0.7), target: float = 0.9, k: int = 10) -> tuple[int, float, float]:
    """(neighbours, decay, recall) of the first graph of a grid whose edges hold that share of the true k nearest, or the best."""
    from .graphs import exact_graph, nn_descent

    truth, best = exact_graph(points, dist, k).select("src", "dst"), (grid[0], decays[0], 0.0)
    total = truth.count()
    for size in grid:
        for decay in decays:
            found = truth.join(nn_descent(points, dist, size, decay=decay).select("src", "dst").distinct(), ["src", "dst"]).count() / max(1, total)
            if found > best[2]:
                best = (size, decay, found)
            if found >= target:
                return best
    return best

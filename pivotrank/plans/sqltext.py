"""Building blocks of the oracle's SQL: each function returns CTE text over ``pts``, ``qs`` and so on."""

from __future__ import annotations

from ..functions.distances import distance

KEY = "floor({} * 1e9 + 0.5)::BIGINT"


def key(expression: str) -> str:
    return KEY.format(f"({expression})")


def pivots(m: int, seed: int = 7, copy: int = 0, name: str = "piv", points: str = "pts") -> str:
    return f"{name} AS MATERIALIZED (SELECT row_number() OVER (ORDER BY h, id) AS pid, id, x FROM (SELECT id, x, md5('pivot{seed}:{copy}:' || id) AS h FROM {points} ORDER BY h, id LIMIT {m}))"


def seen(source: str, key_column: str, dist: str, name: str, side: str = "left", piv: str = "piv") -> str:
    """(key, pid, d, pos): every point's distance to every pivot, and the pivot's place."""
    d = distance(dist).sql("s.x", "p.x", side)
    return f"{name} AS MATERIALIZED (SELECT k, pid, d, row_number() OVER (PARTITION BY k ORDER BY {key('d')}, pid) AS pos FROM (SELECT s.{key_column} AS k, p.pid, {d} AS d FROM {source} s, {piv} p))"


def refined(candidates: str, dist: str, k: int, side: str = "left", name: str = "res") -> str:
    d = distance(dist).sql("p.x", "q.x", side)
    return f"""{name} AS (SELECT qid, id, dist, rnk FROM (SELECT qid, id, dist, row_number() OVER (PARTITION BY qid ORDER BY {key('dist')}, id) AS rnk FROM (
      SELECT c.qid, c.id, {d} AS dist FROM (SELECT DISTINCT qid, id FROM {candidates}) c JOIN pts p ON p.id = c.id JOIN qs q ON q.qid = c.qid)) WHERE rnk <= {k})"""


def everything(name: str = "cand") -> str:
    return f"{name} AS (SELECT qid, id FROM pts, qs)"


def gamma(scores: str, n: int | str, name: str = "cand") -> str:
    return f"{name} AS (SELECT qid, id, score FROM (SELECT qid, id, score, row_number() OVER (PARTITION BY qid ORDER BY score, id) AS r FROM {scores}) WHERE r <= {n})"


def permutation_scores(score: str, m: int, name: str = "scores", limit: int | None = None) -> str:
    threshold = limit or m // 2 + 1
    body = {
        "rho": "sum((a.pos - b.pos) * (a.pos - b.pos))",
        "footrule": "sum(abs(a.pos - b.pos))",
        "hamming": f"sum(CASE WHEN (a.pos >= {threshold}) = (b.pos >= {threshold}) THEN 0 ELSE 1 END)",
        "pivot_l2": key("sqrt(sum((a.d - b.d) * (a.d - b.d)))"),
    }[score]
    return f"{name} AS MATERIALIZED (SELECT b.k AS qid, a.k AS id, ({body})::BIGINT AS score FROM pseen a JOIN qseen b USING (pid) GROUP BY b.k, a.k)"


RESULT = "SELECT qid, id, round(dist, 6) + 0.0 AS dist, rnk::INT AS rnk FROM res"

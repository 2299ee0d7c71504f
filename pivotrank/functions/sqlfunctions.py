"""The distances as temporary SQL functions, and nearest-neighbour search as a table function for few queries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

_ADD = "0D, (s, v) -> s + v"
BODIES = {
    "l2_distance(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>)": ("DOUBLE", f"sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), {_ADD}))"),
    "l1_distance(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>)": ("DOUBLE", f"aggregate(zip_with(a, b, (x, y) -> abs(x - y)), {_ADD})"),
    "kl_divergence(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>)": ("DOUBLE", f"aggregate(zip_with(a, b, (x, y) -> x * (ln(x) - ln(y))), {_ADD})"),
    "js_divergence(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>)": ("DOUBLE", f"0.5D * aggregate(zip_with(a, b, (x, y) -> x * ln(x) + y * ln(y) - (x + y) * ln((x + y) / 2)), {_ADD})"),
    "norm_levenshtein(a STRING, b STRING)": ("DOUBLE", "coalesce(levenshtein(a, b) / nullif(greatest(length(a), length(b)), 0), 0D)"),
    "rank_rho(a ARRAY<SMALLINT>, b ARRAY<SMALLINT>)": ("BIGINT", "aggregate(zip_with(a, b, (x, y) -> (cast(x AS BIGINT) - y) * (cast(x AS BIGINT) - y)), 0L, (s, v) -> s + v)"),
    "rank_footrule(a ARRAY<SMALLINT>, b ARRAY<SMALLINT>)": ("BIGINT", "aggregate(zip_with(a, b, (x, y) -> abs(cast(x AS BIGINT) - y)), 0L, (s, v) -> s + v)"),
    "bits_hamming(a ARRAY<BIGINT>, b ARRAY<BIGINT>)": ("BIGINT", "aggregate(zip_with(a, b, (x, y) -> cast(bit_count(x ^ y) AS BIGINT)), 0L, (s, v) -> s + v)"),
}


def register(spark: SparkSession) -> list[str]:
    """Registers the functions for the session; returns their names."""
    for head, (kind, body) in BODIES.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURNS {kind} RETURN {body}")
    return [head.split("(")[0] for head in BODIES]


def register_views(index, prefix: str = "pivot") -> None:
    """A shared-pivot index as views: {prefix}_points, {prefix}_postings and {prefix}_pivots."""
    index.points.createOrReplaceTempView(f"{prefix}_points")
    index.postings.createOrReplaceTempView(f"{prefix}_postings")
    index.pivots.frame.createOrReplaceTempView(f"{prefix}_pivots")


def register_search(spark: SparkSession, points: DataFrame, name: str = "knn_search", most: int = 100_000) -> None:
    """A table function name(query, k) over a small point set of vectors: (id, dist, rnk) by exact L2.

    The points travel with the function, so their number is checked; larger sets are searched by an index.
    """
    import numpy as np
    from pyspark.sql.functions import udtf

    rows = points.select("id", "x").limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"the table function takes {most} points at most")
    ids, held = np.array([r["id"] for r in rows], np.int64), np.array([r["x"] for r in rows], np.float64)

    class Search:
        def eval(self, query: list, k: int):
            if query is None or k is None or not len(ids):
                return
            far = np.sqrt(((held - np.array(query, np.float64)) ** 2).sum(1))
            for n, i in enumerate(np.lexsort((ids, np.floor(far * 1e9 + 0.5)))[:k]):
                yield int(ids[i]), float(far[i]), n + 1

    spark.udtf.register(name, udtf(Search, returnType="id: bigint, dist: double, rnk: int"))

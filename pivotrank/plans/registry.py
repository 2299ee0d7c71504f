"""Names of the queries over the given tables, with their SQL."""

from __future__ import annotations

from . import experiments, methods, rivals, studies, usage

_PARTS = (methods, rivals, studies, usage, experiments)


def flagship(spark, sf_dir):
    """10-NN of held-out embeddings with the shared-pivot index."""
    return queries()["shared_threshold"](spark, sf_dir)


def queries():
    return {name: q for part in _PARTS for name, q in part.QUERIES.items()}


def oracle_sql():
    return {name: sql for part in _PARTS for name, sql in part.SQL.items()}

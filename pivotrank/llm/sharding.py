"""A uniform shuffle of all rows into shards of exact sizes, by a hypergeometric communication matrix.

Rows lie in partitions; the shards are cut into cells of exact sizes (counts of shards, and of cells
in a shard, differ by one at most). Entry (p, c) of the matrix is how many rows partition p sends to
cell c. Over a uniform permutation of all rows these counts follow the multivariate hypergeometric
law, so the matrix is drawn first, from the partitions' counts alone. Then each partition permutes
its rows and deals them out by its line of the matrix, rows move once to their cells, and each cell
permutes what it received. The slot of a row is its cell's first slot plus its place in the cell.

A line of the matrix is drawn where it is used: halves of the partitions split the cells' sizes, the
halves of those again, and so on down, each draw seeded by its place in that tree. So no task and not
the driver holds the whole matrix. The driver holds one count per partition.

All orders come from seeded hashes of the row's id and content, so a task that runs again after a
lost executor sends the same rows. Rows equal in id and content are interchangeable. Null ids and
texts hash as such. An empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .session import parts_for, text_bytes

PART_BYTES = 32 << 20


def even(total: int, into: int) -> np.ndarray:
    """Sizes of ``into`` pieces of ``total``, at most one apart."""
    return np.full(into, total // into) + (np.arange(into) < total % into)


def cell_sizes(total: int, shards: int, cells: int) -> np.ndarray:
    return np.concatenate([even(int(s), cells) for s in even(total, shards)])


def hypergeometric(rng: np.random.Generator, sizes: np.ndarray, draws: int) -> np.ndarray:
    """How many of each kind are among ``draws`` without replacement; kinds split by halves."""
    out = np.zeros(len(sizes), np.int64)
    stack = [(0, len(sizes), draws)]
    ends = np.concatenate(([0], np.cumsum(sizes)))
    while stack:
        a, b, n = stack.pop()
        if not n:
            continue
        if b - a == 1:
            out[a] = n
            continue
        m = (a + b) // 2
        good, bad = int(ends[m] - ends[a]), int(ends[b] - ends[m])
        left = n if not bad else 0 if not good else _draw(rng, good, bad, n)
        stack += [(a, m, left), (m, b, n - left)]
    return out


def _draw(rng: np.random.Generator, good: int, bad: int, n: int) -> int:
    """One hypergeometric draw; numpy's takes populations under 10^9, larger ones split first."""
    limit = 500_000_000
    if good + bad < 2 * limit:
        return int(rng.hypergeometric(good, bad, n))
    if good > limit:
        half = good // 2
        first = _draw(rng, half, good - half + bad, n)
        return first + _draw(rng, good - half, bad, n - first)
    return n - _draw(rng, bad, good, n)


def matrix_line(counts: np.ndarray, cells: np.ndarray, part: int, seed: int) -> np.ndarray:
    """The matrix's line of one partition: rows that it sends to each cell."""
    ends = np.concatenate(([0], np.cumsum(counts)))
    a, b = 0, len(counts)
    while b - a > 1:
        m = (a + b) // 2
        left = hypergeometric(np.random.Generator(np.random.PCG64([seed, a, b])), cells, int(ends[m] - ends[a]))
        a, b, cells = (a, m, left) if part < m else (m, b, cells - left)
    return cells


def shuffle_into_shards(docs: DataFrame, shards: int = 8, seed: int = 1, part_bytes: int = PART_BYTES, id: str = "doc_id", text: str = "text") -> DataFrame:
    """Every row with ``shard`` (from 0) and ``slot`` (its place in the shard, gapless from 0).

    Shard sizes are at most one row apart, and every assignment of rows to slots is equally likely
    over the seeds. All columns stay; columns of the names shard and slot are replaced.
    """
    cells = parts_for(text_bytes(docs, text), part_bytes * shards)
    parts = parts_for(shards * cells, 1)
    rows = docs.drop("shard", "slot")
    part = F.pmod(F.xxhash64(F.lit(seed), F.col(id), F.col(text)), F.lit(parts)).cast("int")
    counts = np.zeros(parts, np.int64)
    for r in rows.groupBy(part.alias("p")).count().collect():  # one row per partition
        counts[r["p"]] = r["count"]
    sizes = cell_sizes(int(counts.sum()), shards, cells)
    starts = np.concatenate([np.cumsum(x) - x for x in sizes.reshape(shards, cells)])
    random = lambda salt: F.xxhash64(F.lit(seed), F.lit(salt), F.col(id), F.col(text))

    @F.pandas_udf("int")
    def cell_of(part: pd.Series, place: pd.Series) -> pd.Series:
        out = np.empty(len(part), np.int32)
        of, at = part.to_numpy(), place.to_numpy()
        for p in np.unique(of):
            mine = of == p
            out[mine] = np.searchsorted(np.cumsum(line(int(p))), at[mine] - 1, side="right")
        return pd.Series(out)

    held: dict[int, np.ndarray] = {}

    def line(p: int) -> np.ndarray:
        if p not in held:
            if len(held) > 4:
                held.clear()
            held[p] = matrix_line(counts, sizes, p, seed)
        return held[p]

    local = Window.partitionBy("_part").orderBy("_first", id)
    dealt = rows.withColumn("_part", part).withColumn("_first", random("first")).withColumn("_place", F.row_number().over(local))
    moved = dealt.withColumn("_cell", cell_of("_part", "_place")).withColumn("_second", random("second"))
    again = Window.partitionBy("_cell").orderBy("_second", id, "_part", "_place")
    start = F.element_at(F.lit([int(x) for x in starts]), F.col("_cell") + 1)
    return (
        moved.withColumn("slot", start + F.row_number().over(again) - F.lit(1))
        .withColumn("shard", (F.col("_cell") / F.lit(cells)).cast("int"))
        .drop("_part", "_first", "_place", "_cell", "_second")
    )

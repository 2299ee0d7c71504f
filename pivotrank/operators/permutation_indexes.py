"""Filters by permutations of pivots: exhaustive comparison and five kinds of index.

Each has ``candidates(queries, ...)`` giving (qid, id, score), so a filter can be measured alone, and
``search(queries, k, ...)``, which refines the candidates by the true distance.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import distances as D
from .pivots import Pivots, see, select_pivot_copies, select_pivots
from .search import Kept, gamma_of, refine, top_gamma

MOST_KEPT = 2_000_000  # rows of 32 bytes in a task


class _Index:
    """Points, their distance, and the pivots. ``n`` is counted once, at building."""

    def __init__(self, points: DataFrame, dist, m: int, seed: int = 7, side: str = "left", pivots: Pivots | None = None):
        self.points, self.dist, self.side = points, D.distance(dist), side
        self.pivots = pivots or select_pivots(points, m, seed)
        self.m = self.pivots.m
        self._n: int | None = None

    @property
    def n(self) -> int:
        if self._n is None:
            self._n = self.points.count()
        return self._n

    def candidates(self, queries: DataFrame, **options) -> DataFrame:
        raise NotImplementedError

    def search(self, queries: DataFrame, k: int = 10, **options) -> DataFrame:
        return refine(self.candidates(queries, k=k, **options), self.points, queries, self.dist, k, self.side)

    def _see(self, points: DataFrame, mi: int | None = None, want=("ord", "rank")) -> DataFrame:
        return see(points, self.pivots, self.dist, self.side, mi, want)


class ExhaustivePermutations(_Index):
    """All permutations are compared with the query's: by rho, footrule, hamming on packed bits, or raw distances."""

    def __init__(self, *args, score: str = "rho", threshold: int | None = None, **kw):
        super().__init__(*args, **kw)
        self.score, self.threshold = score, threshold
        self.codes = self._coded(self.points, "id")

    def _coded(self, points: DataFrame, key: str) -> DataFrame:
        if self.score == "pivot_l2":
            return self._see(points.select(key, "x"), want=("pd",)).select(key, F.col("pd").alias("code"))
        ranks = self._see(points.select(key, "x"), want=("ord", "rank"))
        return ranks.select(key, (D.pack_bits(F.col("rank"), self.m, self.threshold) if self.score == "hamming" else F.col("rank")).alias("code"))

    def scores(self, queries: DataFrame) -> DataFrame:
        """(qid, id, score) for every point: a scan of the codes, with the queries' codes broadcast."""
        asked = F.broadcast(self._coded(queries, "qid").withColumnRenamed("code", "q"))
        how = {"rho": D.rho, "footrule": D.footrule, "hamming": D.hamming, "pivot_l2": lambda a, b: D.rank_key(D.l2(a, b))}[self.score]
        return self.codes.crossJoin(asked).select("qid", "id", how(F.col("code"), F.col("q")).alias("score"))

    def candidates(self, queries: DataFrame, gamma: int | float = 0.1, how: str = "counting", k: int = 1) -> DataFrame:
        return top_gamma(self.scores(queries), gamma_of(gamma, self.n, k), how)

    def best(self, queries: DataFrame, gamma: int | float = 0.1, k: int = 1) -> DataFrame:
        """The same candidates; each task keeps its own best over all its blocks of points.

        Where that would hold over MOST_KEPT rows, the scores are counted instead.
        """
        g = gamma_of(gamma, self.n, k)
        rows = self._coded(queries, "qid").collect()  # one code for each query
        if g * len(rows) > MOST_KEPT:
            return self.candidates(queries, gamma, "counting", k)
        qids, held = np.array([r["qid"] for r in rows], np.int64), np.array([r["code"] for r in rows])
        score = self.score

        def scan(source):
            best = Kept(len(qids), g)
            for batch in source:
                if not len(batch) or not len(qids):
                    continue
                ids = batch.column(0).to_numpy()
                codes = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)
                for q in range(len(qids)):
                    if score == "hamming":
                        s = np.bitwise_count((codes ^ held[q]).view(np.uint64)).sum(1).astype(np.int64)  # of signed words it would count the absolute value
                    elif score == "pivot_l2":
                        s = D.rank_keys(np.sqrt(((codes - held[q]) ** 2).sum(1)))
                    else:
                        s = np.abs(codes.astype(np.int64) - held[q])
                        s = (s * s).sum(1) if score == "rho" else s.sum(1)
                    best.add(q, s[None], ids)
            yield pa.RecordBatch.from_pydict({"qid": qids[best.q], "id": best.id, "score": best.key})

        return top_gamma(self.codes.mapInArrow(scan, "qid long, id long, score long"), g, "heap" if g <= 1000 else "counting")


class PrefixIndex:
    """Points whose closest pivots agree with the query's in a prefix; shorter ones until enough points do.

    symbols: ``order`` takes the pivots closest first, ``rank`` the ranks in order of the pivots.
    Several copies, each with its own pivots, give the union of their candidates.
    """

    def __init__(self, points: DataFrame, dist, m: int = 16, length: int = 4, copies: int = 1, symbols: str = "order", seed: int = 7, side: str = "left"):
        if not 1 <= length <= m:
            raise ValueError("the prefix must have from 1 to m symbols")
        self.points, self.dist, self.side = points, D.distance(dist), side
        self.length, self.symbols = length, symbols
        self.pivots = select_pivot_copies(points, m, copies, seed)
        self._n: int | None = None

    def _prefixes(self, points: DataFrame, key: str, pivots: Pivots) -> DataFrame:
        """(key, length, prefix) for every length from 0."""
        column = "ord" if self.symbols == "order" else "rank"
        seen = see(points.select(key, "x"), pivots, self.dist, self.side, None, (column,))
        text = F.transform(F.slice(column, 1, self.length), lambda s: s.cast("string"))
        return seen.select(key, text.alias("_t")).select(key, F.explode(F.sequence(F.lit(0), F.lit(self.length))).alias("length"), "_t").select(key, "length", F.array_join(F.slice("_t", 1, F.col("length")), ",").alias("prefix"))

    def candidates(self, queries: DataFrame, gamma: int | float = 0.1, min_length: int = 0, k: int = 1) -> DataFrame:
        """(qid, id, score): score is how many symbols fewer than the whole prefix agree, the least over copies."""
        if self._n is None:
            self._n = self.points.count()
        g, out = gamma_of(gamma, self._n, k), None
        for pivots in self.pivots:
            own = self._prefixes(self.points, "id", pivots)
            asked = self._prefixes(queries, "qid", pivots).where(F.col("length") >= min_length)
            counts = own.groupBy("length", "prefix").agg(F.count("*").alias("n"))
            met = asked.join(counts, ["length", "prefix"], "left").withColumn("enough", F.coalesce(F.col("n") >= g, F.lit(False)))
            chosen = met.groupBy("qid").agg(F.coalesce(F.max(F.when(F.col("enough"), F.col("length"))), F.lit(min_length)).alias("length"))
            some = asked.join(chosen, ["qid", "length"])
            found = some.where("length > 0").join(own.where("length > 0"), ["length", "prefix"]).select("qid", "id", (F.lit(self.length) - F.col("length")).cast("long").alias("score"))
            # the empty prefix holds every point: no key to join on
            every = self.points.select("id").crossJoin(F.broadcast(some.where("length = 0").select("qid"))).select("qid", "id", F.lit(self.length).cast("long").alias("score"))
            found = found.unionByName(every)
            out = found if out is None else out.unionByName(found)
        return out.groupBy("qid", "id").agg(F.min("score").alias("score"))

    def search(self, queries: DataFrame, k: int = 10, **options) -> DataFrame:
        return refine(self.candidates(queries, k=k, **options), self.points, queries, self.dist, k, self.side)


class RankPostings(_Index):
    """Postings (pid, pos, id) of each point's ``mi`` closest pivots, and accumulators that are hash aggregates."""

    def __init__(self, *args, mi: int = 32, **kw):
        super().__init__(*args, **kw)
        if mi > self.m:
            raise ValueError("mi may not exceed the number of pivots")
        self.mi = mi
        self.postings = self._lists(self.points, "id", mi)

    def _lists(self, points: DataFrame, key: str, length: int) -> DataFrame:
        seen = self._see(points.select(key, "x"), length, ("ord",))
        return seen.select(key, F.posexplode("ord").alias("pos", "pid")).select("pid", (F.col("pos") + 1).alias("pos"), key)

    def candidates(self, queries: DataFrame, gamma: int | float = 0.1, ms: int | None = None, score: str = "footrule", max_diff: int | None = None, k: int = 1, how: str = "counting") -> DataFrame:
        return top_gamma(self.scores(queries, ms, score, max_diff), gamma_of(gamma, self.n, k), how)

    def scores(self, queries: DataFrame, ms: int | None = None, score: str = "footrule", max_diff: int | None = None) -> DataFrame:
        """Accumulated scores of the points that stand in a list that is read.

        With whole lists (ms = mi = m) these are the exact distances of the permutations. Else a pivot
        that is not met counts as if it stood last: the accumulator begins with ms times m (m squared
        for rho), and each posting takes off m (m squared) less its difference.
        """
        ms = ms or self.mi
        if ms > self.mi:
            raise ValueError("ms may not exceed mi")
        power = {"footrule": 1, "rho": 2}[score]
        asked = F.broadcast(self._lists(queries, "qid", ms).withColumnRenamed("pos", "qpos"))
        diff = F.abs(F.col("pos") - F.col("qpos")).cast("long")
        read = self.postings.join(asked, "pid")
        if max_diff is not None:
            read = read.where(F.col("pos").between(F.col("qpos") - max_diff, F.col("qpos") + max_diff))
        value = diff if power == 1 else diff * diff
        if ms == self.mi == self.m and max_diff is None:
            total = F.sum(value)
        else:
            total = F.lit(ms * self.m**power).cast("long") - F.sum(F.lit(self.m**power) - value)
        return read.groupBy("qid", "id").agg(total.alias("score"))

    def read_counts(self, queries: DataFrame, ms: int | None = None, max_diff: int | None = None) -> DataFrame:
        """(qid, lists, postings) that a search reads."""
        asked = F.broadcast(self._lists(queries, "qid", ms or self.mi).withColumnRenamed("pos", "qpos"))
        read = self.postings.join(asked, "pid")
        if max_diff is not None:
            read = read.where(F.abs(F.col("pos") - F.col("qpos")) <= max_diff)
        return read.groupBy("qid").agg(F.count_distinct("pid").alias("lists"), F.count("*").alias("postings"))


class SharedPivots(_Index):
    """Postings without positions: a point's score is how many of its closest pivots the query shares.

    chunks: points are dealt into so many parts by hash. A point's counts all lie in one part, so a part's
    counts are whole before any shuffle if files are kept by chunk.
    """

    def __init__(self, *args, mi: int = 32, chunks: int = 1, **kw):
        super().__init__(*args, **kw)
        if mi > self.m:
            raise ValueError("mi may not exceed the number of pivots")
        self.mi, self.chunks = mi, chunks
        self.near = self._see(self.points.select("id", "x"), mi, ("ord",)).select("id", "ord")
        self.postings = self.near.select(F.pmod(F.xxhash64("id"), F.lit(chunks)).cast("int").alias("chunk"), F.explode("ord").alias("pid"), "id")

    def shared(self, queries: DataFrame, merge: str = "scancount") -> DataFrame:
        """(qid, id, shared) of the points that share a pivot."""
        asked = self._see(queries.select("qid", "x"), self.mi, ("ord",)).select("qid", F.col("ord").alias("q"))
        if merge == "forward":
            both = self.near.crossJoin(F.broadcast(asked)).select("qid", "id", F.size(F.array_intersect("ord", "q")).cast("long").alias("shared"))
            return both.where("shared > 0")
        if merge != "scancount":
            raise ValueError("merge is 'scancount' or 'forward'")
        lists = F.broadcast(asked.select("qid", F.explode("q").alias("pid")))
        return self.postings.join(lists, "pid").groupBy("chunk", "qid", "id").agg(F.count("*").alias("shared")).select("qid", "id", "shared")

    def scan(self, queries: DataFrame, t: int) -> DataFrame:
        """(qid, id, shared) with at least ``t`` shared, by one pass of bit sets in numpy: nothing is shuffled."""
        rows = self._see(queries.select("qid", "x"), self.mi, ("ord",)).select("qid", "ord").collect()  # queries' lists
        qids = np.array([r["qid"] for r in rows], np.int64)
        marks = np.zeros((self.m, len(rows)), np.float32)
        for i, r in enumerate(rows):
            marks[np.array(r["ord"]) - 1, i] = 1

        def count(source):
            for batch in source:
                if not len(batch) or not len(qids):
                    continue
                ids = batch.column(0).to_numpy()
                lists = batch.column(1).flatten().to_numpy().reshape(len(ids), -1) - 1
                own = np.zeros((len(ids), len(marks)), np.float32)
                np.put_along_axis(own, lists.astype(np.int64), 1, 1)
                shared = own @ marks
                p, q = np.nonzero(shared >= t)
                yield pa.RecordBatch.from_pydict({"qid": qids[q], "id": ids[p], "shared": shared[p, q].astype(np.int64)})

        return self.near.mapInArrow(count, "qid long, id long, shared long")

    def candidates(self, queries: DataFrame, t: int = 1, gamma: int | float | None = None, merge: str = "scancount", k: int = 1, how: str = "counting") -> DataFrame:
        """Points that share at least ``t`` pivots; with ``gamma`` only the best so many of them."""
        if not 1 <= t <= self.mi:
            raise ValueError("t must be from 1 to mi")
        kept = self.scan(queries, t) if merge == "scan" else self.shared(queries, merge).where(F.col("shared") >= t)
        scored = kept.select("qid", "id", (F.lit(self.mi) - F.col("shared")).cast("long").alias("score"))
        return scored if gamma is None else top_gamma(scored, gamma_of(gamma, self.n, k), how)


class SequenceIndex(_Index):
    """Permutations as strings with access, rank and select, which can play the other indexes' parts."""

    def __init__(self, *args, mi: int | None = None, **kw):
        super().__init__(*args, **kw)
        self.mi = mi or self.m
        self.sequence = self._see(self.points.select("id", "x"), self.mi, ("ord",)).select("id", F.posexplode("ord").alias("pos", "sym")).select("id", (F.col("pos") + 1).alias("pos"), "sym")

    def access(self, pos: int) -> DataFrame:
        """(id, sym): each point's symbol at a place."""
        return self.sequence.where(F.col("pos") == pos).select("id", "sym")

    def ids_with(self, pos: int, sym: int) -> DataFrame:
        return self.sequence.where((F.col("pos") == pos) & (F.col("sym") == sym)).select("id")

    def numbered(self) -> DataFrame:
        """(sym, id, pos, nth): the occurrences of each symbol in the concatenation by id, numbered from 1.

        Numbers come from counts of ranges of ids plus places within a range, so no symbol fills one task.
        """
        ranged = self.sequence.withColumn("part", F.shiftright(F.col("id"), 16))
        counts = ranged.groupBy("sym", "part").agg(F.count("*").alias("n"))
        before = F.coalesce(F.sum("n").over(Window.partitionBy("sym").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
        inside = F.row_number().over(Window.partitionBy("sym", "part").orderBy("id", "pos"))
        return ranged.withColumn("inside", inside).join(counts.select("sym", "part", before.alias("before")), ["sym", "part"]).select("sym", "id", "pos", (F.col("before") + F.col("inside")).alias("nth"))

    def select(self, sym: int, nth: int) -> DataFrame:
        return self.numbered().where((F.col("sym") == sym) & (F.col("nth") == nth)).select("id", "pos")

    def rank(self, sym: int, id: int, pos: int) -> DataFrame:
        """How often a symbol occurs up to a place of a point, in the concatenation by id."""
        upto = (F.col("id") < id) | ((F.col("id") == id) & (F.col("pos") <= pos))
        return self.sequence.where((F.col("sym") == sym) & upto).agg(F.count("*").alias("rank"))

    def as_prefix(self, symbols: list[int]) -> DataFrame:
        """Points whose first symbols are these."""
        first = F.create_map(*[F.lit(v) for i, s in enumerate(symbols, 1) for v in (i, s)])
        return self.sequence.where(F.element_at(first, F.col("pos")) == F.col("sym")).groupBy("id").agg(F.count("*").alias("n")).where(F.col("n") == len(symbols)).select("id")

    def as_postings(self) -> DataFrame:
        return self.sequence.select(F.col("sym").alias("pid"), "pos", "id")

    def as_shared(self, symbols: list[int], mi: int) -> DataFrame:
        """(id, shared) by the first ``mi`` symbols."""
        return self.sequence.where((F.col("pos") <= mi) & F.col("sym").isin(symbols)).groupBy("id").agg(F.count("*").alias("shared"))


class PivotTable(_Index):
    """Pruning by pivots: a point is out if its distance to a pivot differs too much from the query's.

    Exact for metrics and for distances whose transform is one. For others a monotone transform with
    differences of at most ``mu`` times the transformed distance gives the bound; no ``mu`` is known to hold
    for all points, so it must be given (measures.mu_defect measures one) and the result is approximate.
    """

    def __init__(self, *args, mu: float | None = None, **kw):
        super().__init__(*args, **kw)
        self.mu = mu if mu is not None else self.dist.mu
        if self.mu is None:
            raise ValueError(f"{self.dist.name} needs a mu: there is none that is exact")
        if not self.dist.metric and self.dist.transform is None:
            raise ValueError(f"{self.dist.name} has no transform that bounds it")
        f = self.dist.transform or (lambda d: d)
        self.table = self._see(self.points.select("id", "x"), want=("pd",)).select("id", "x", F.transform("pd", f).alias("f"))

    def within(self, queries: DataFrame, radius: DataFrame) -> DataFrame:
        """(qid, id, dist) at most as far as the query's radius (qid, r)."""
        f = self.dist.transform or (lambda d: d)
        asked = self._see(queries.select("qid", "x"), want=("pd",)).select("qid", F.col("x").alias("q"), F.transform("pd", f).alias("qf")).join(radius, "qid")
        bound = F.array_max(F.zip_with("f", "qf", lambda a, b: F.abs(a - b)))
        left = self.table.crossJoin(F.broadcast(asked)).where(bound <= self.mu * f(F.col("r")) + 1e-9)
        return left.select("qid", "id", self.dist(F.col("x"), F.col("q"), self.side).alias("dist"), "r").where(F.col("dist") <= F.col("r"))

    def search(self, queries: DataFrame, k: int = 10) -> DataFrame:
        """First the k points with the least bound give a radius, then one pass prunes by it."""
        from .search import ranked

        f = self.dist.transform or (lambda d: d)
        asked = F.broadcast(self._see(queries.select("qid", "x"), want=("pd",)).select("qid", F.transform("pd", f).alias("qf")))
        bounds = self.table.crossJoin(asked).select("qid", "id", D.rank_key(F.array_max(F.zip_with("f", "qf", lambda a, b: F.abs(a - b)))).alias("score"))
        first = refine(top_gamma(bounds, k, "heap"), self.points, queries, self.dist, k, self.side)
        radius = first.groupBy("qid").agg(F.max("dist").alias("r"))
        return ranked(self.within(queries, radius).select("qid", "id", "dist"), k)

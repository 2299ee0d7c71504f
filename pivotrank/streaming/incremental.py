"""Indexes that grow and shrink: appends by stream, deletions by tombstones, and windows of events."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.pivots import Pivots, see

KINDS = ("click", "view", "purchase", "signup", "logout")


def append_stream(spark: SparkSession, source: DataFrame, pivots: Pivots, dist, mi: int, path: str, checkpoint: str):
    """Starts a stream that adds the postings (pid, id) of arriving points (id, x) to a folder.

    The pivots stay as they are: other pivots mean another index. A batch that is run again after a
    failure overwrites its own folder, so postings come once.
    """

    def add(batch: DataFrame, number: int) -> None:
        seen = see(batch.select("id", "x"), pivots, dist, mi=mi, want=("ord",))
        seen.select(F.explode("ord").alias("pid"), "id").repartitionByRange("pid").sortWithinPartitions("pid").write.mode("overwrite").parquet(f"{path}/batch={number}")

    return source.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def live(postings: DataFrame, tombstones: DataFrame) -> DataFrame:
    """Postings without deleted ids."""
    return postings.join(tombstones.select("id").distinct(), "id", "left_anti").select(*postings.columns)


def compact(postings: DataFrame, tombstones: DataFrame, path: str) -> None:
    """Writes the live postings anew, in order of pivots."""
    live(postings, tombstones).select("pid", "id").repartitionByRange("pid").sortWithinPartitions("pid").write.mode("overwrite").parquet(path)


def mixes(events: DataFrame, window: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(window, n, and a count for each kind of event) over event time; later than ``late`` is dropped in streams."""
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    counts = [F.count(F.when(F.col("event_type") == k, 1)).alias(k) for k in KINDS]
    return events.withWatermark("ts", late).groupBy(w.alias("w")).agg(F.count("*").alias("n"), *counts).select(F.col("w.start").alias("start"), "n", *KINDS)


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """A user's sessions, with a count for each kind of event."""
    counts = [F.count(F.when(F.col("event_type") == k, 1)).alias(k) for k in KINDS]
    grouped = events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w"))
    return grouped.agg(F.count("*").alias("n"), *counts).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", *KINDS)


def views_before_purchases(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream join: a user's purchases with the views at most so long before them."""
    a = events.where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("ts").alias("view_ts"), F.col("event_id").alias("view_id")).withWatermark("view_ts", "2 hours")
    b = events.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("buy_ts"), F.col("event_id").alias("buy_id")).withWatermark("buy_ts", "2 hours")
    return b.join(a, (F.col("user_id") == F.col("u")) & (F.col("view_ts") <= F.col("buy_ts")) & (F.col("view_ts") >= F.col("buy_ts") - F.expr(f"INTERVAL {within}"))).drop("u")


def drain(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """All that a stream over files gives now, as a table in memory (for small results)."""
    query = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)


def search_stream(queries: DataFrame, index, k: int, path: str, checkpoint: str, **options):
    """Starts a stream that answers arriving queries (qid, x) from a static index; each batch's answers go to a folder of its own."""

    def answer(batch: DataFrame, number: int) -> None:
        index.search(batch.select("qid", "x"), k, **options).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return queries.writeStream.foreachBatch(answer).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def first_seen(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event_id once, however often it arrives within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def running_mix(events: DataFrame) -> DataFrame:
    """(user_id, n, and a count for each kind): a user's histogram so far, kept as state; one row a user and batch."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def update(key, batches, state):
        held = list(state.get) if state.exists else [0] * len(KINDS)
        for batch in batches:
            counts = batch["event_type"].value_counts()
            held = [h + int(counts.get(kind, 0)) for h, kind in zip(held, KINDS, strict=True)]
        state.update(tuple(held))
        yield pd.DataFrame([[key[0], sum(held), *held]], columns=["user_id", "n", *KINDS])

    kinds = ", ".join(f"{k} long" for k in KINDS)
    return events.select("user_id", "event_type").groupBy("user_id").applyInPandasWithState(update, f"user_id long, n long, {kinds}", kinds, "update", GroupStateTimeout.NoTimeout)

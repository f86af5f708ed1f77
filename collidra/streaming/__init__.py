"""Streams: arrival of items into bounded buckets, windows over events, queries against a snapshot."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import index, query
from ..operators.index import IndexParams
from ..operators.reservoir import priority


def event_time(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Events with a watermark; their time stamps come without a zone, which watermarks do not take."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    return events.groupBy(F.window("ts", width), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "1 day", step: str = "12 hours") -> DataFrame:
    return events.groupBy(F.window("ts", width, step), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "4 hours") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n")


def deduplicated(events: DataFrame) -> DataFrame:
    """Replayed events dropped by id, with state bounded by the watermark."""
    return events.dropDuplicatesWithinWatermark(["event_id"])


def arrivals(sets: DataFrame, p: IndexParams) -> DataFrame:
    """A stream of (table_id, address, seen, members) updates from a stream of sets.

    State per bucket is a counter and at most r (priority, id) pairs; it never grows with the number of items. As the
    kept items are those of smallest priority, the order of arrival does not matter. Needs output mode ``update``.
    """
    addr = index.addresses(sets, p).withColumn("pr", priority(p.seed))

    def step(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen, prs, ids = state.get if state.exists else (0, [], [])
        held = list(zip(prs, ids, strict=True))
        for pdf in parts:
            seen += len(pdf)
            held = sorted({*held, *zip(pdf["pr"].tolist(), pdf["item_id"].tolist(), strict=True)})[: p.r]
        state.update((seen, [h[0] for h in held], [h[1] for h in held]))
        yield pd.DataFrame({"table_id": [key[0]], "address": [key[1]], "seen": [seen], "members": [sorted(h[1] for h in held)]})

    return addr.groupBy("table_id", "address").applyInPandasWithState(
        step, "table_id int, address long, seen long, members array<long>", "seen long, prs array<long>, ids array<long>", "update", GroupStateTimeout.NoTimeout
    )


def run_to_table(stream: DataFrame, path: str, mode: str = "append", keys: tuple = (), version: str | None = None) -> DataFrame:
    """Runs a stream over all that is there and returns what it wrote.

    Append streams go to Parquet; updates are written per batch, and the latest row of each key (by ``version``) counts.
    """
    spark = stream.sparkSession
    if mode == "append":
        run = stream.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/state").outputMode("append").trigger(availableNow=True).start()
    else:
        save = lambda df, batch: df.withColumn("_batch", F.lit(batch)).write.mode("append").parquet(f"{path}/out")
        run = stream.writeStream.foreachBatch(save).option("checkpointLocation", f"{path}/state").outputMode(mode).trigger(availableNow=True).start()
    run.awaitTermination()
    out = spark.read.parquet(f"{path}/out")
    if mode == "append":
        return out
    rest = [c for c in out.columns if c not in (*keys, "_batch")]
    latest = out.groupBy(*keys).agg(F.max_by(F.struct(*rest), F.col(version or "_batch")).alias("r"))
    return latest.select(*keys, *[F.col(f"r.{c}").alias(c) for c in rest])


def answers(queries: DataFrame, snapshot: index.Index, k: int) -> DataFrame:
    """Candidates of a stream of query sets against a static snapshot of the index: (query_id, members) rows.

    A stream-static join; ranking needs a query's rows together, which ``foreachBatch`` with ``query.count_select`` does.
    """
    return snapshot.probe(index.addresses(queries, snapshot.params))


def answer_stream(queries: DataFrame, snapshot: index.Index, k: int, path: str) -> DataFrame:
    spark: SparkSession = queries.sparkSession

    def save(df: DataFrame, batch: int) -> None:
        query.count_select(snapshot.probe(index.addresses(df, snapshot.params)), k, exclude_self=False).write.mode("append").parquet(f"{path}/out")

    queries.writeStream.foreachBatch(save).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{path}/out")

"""The query phase: probe the reservoirs of a query's addresses, count how often each item turns up, keep the top."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..sources import merged_by
from .reservoir import BUCKET

#: Query addresses up to which they are broadcast to a stored index, which then is not moved; checked by a count.
BROADCAST_ADDRESSES = 200_000


def probe(query_addr: DataFrame, reservoirs: DataFrame, pointers: DataFrame | None = None, small: bool = False) -> DataFrame:
    """(query_id, seen, members) for each address of each query; the index has one row per bucket."""
    q = query_addr.withColumnRenamed("item_id", "query_id")
    if small and q.limit(BROADCAST_ADDRESSES + 1).count() <= BROADCAST_ADDRESSES:
        q = F.broadcast(q)
    else:
        q, reservoirs = merged_by(q), merged_by(reservoirs)
    if pointers is not None:
        return q.join(pointers, list(BUCKET)).join(reservoirs, "reservoir_id").select("query_id", "table_id", "seen", "members")
    return q.join(reservoirs, list(BUCKET)).select("query_id", "table_id", "seen", "members")


def candidate_union(probes: DataFrame) -> DataFrame:
    """(query_id, neighbor_id): every item met, once."""
    return probes.select("query_id", F.explode("members").alias("neighbor_id")).distinct()


def _ranked(counts: DataFrame, k: int, by: str = "collisions") -> DataFrame:
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.col(by).desc(), "neighbor_id"))
    return counts.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", "neighbor_id", "rank", by)


def count_select(probes: DataFrame, k: int, strategy: str = "hash", exclude_self: bool = True) -> DataFrame:
    """(query_id, neighbor_id, rank, collisions): most collisions first, ties by id.

    hash counts in aggregation tables; segment gathers a query's bag of at most tables * r ids into one row and counts
    the bags of a batch in one sort; boundary sorts the bags and takes differences of run ends. All give the same rows.
    """
    if strategy == "segment":
        bags = probes.groupBy("query_id").agg(F.flatten(F.collect_list("members")).alias("bag"))

        def run(parts: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in parts:
                for lo in range(0, batch.num_rows, 2048):
                    yield _counted_bags(batch.slice(lo, 2048), k, exclude_self)

        return bags.mapInArrow(run, "query_id long, neighbor_id long, rank int, collisions long")
    met = probes.select("query_id", F.explode("members").alias("neighbor_id"))
    if exclude_self:
        met = met.where("neighbor_id <> query_id")
    if strategy == "hash":
        return _ranked(met.groupBy("query_id", "neighbor_id").agg(F.count("*").alias("collisions")), k)
    if strategy != "boundary":
        raise ValueError(f"unknown strategy {strategy}")
    bag = W.partitionBy("query_id").orderBy("neighbor_id")
    at = met.withColumn("pos", F.row_number().over(bag)).withColumn("nxt", F.lead("neighbor_id").over(bag))
    ends = at.where("nxt IS NULL OR nxt <> neighbor_id")  # the end of a query's bag always ends a run
    before = F.lag("pos", 1, 0).over(W.partitionBy("query_id").orderBy("pos"))
    return _ranked(ends.withColumn("collisions", (F.col("pos") - before).cast("long")), k)


def _counted_bags(batch: pa.RecordBatch, k: int, exclude_self: bool) -> pa.RecordBatch:
    """The top k of each bag of a batch: runs of equal (query, id) in one sorted array, ranked by another."""
    lists = batch.column(1)
    ids, ends = lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64), np.asarray(lists.offsets)
    queries = batch.column(0).to_numpy(zero_copy_only=False)
    row = np.repeat(np.arange(batch.num_rows), np.diff(ends))
    if exclude_self:
        other = ids != queries[row]
        ids, row = ids[other], row[other]
    order = np.lexsort((ids, row))
    ids, row = ids[order], row[order]
    first = np.flatnonzero(np.concatenate(([True], (ids[1:] != ids[:-1]) | (row[1:] != row[:-1])))) if len(ids) else np.zeros(0, dtype=np.int64)
    n = np.diff(np.concatenate((first, [len(ids)]))) if len(ids) else first
    ids, row = ids[first], row[first]
    order = np.lexsort((ids, -n, row))
    ids, row, n = ids[order], row[order], n[order]
    rank = np.arange(len(row)) - np.searchsorted(row, row) + 1
    top = rank <= k
    columns = [queries[row[top]].astype(np.int64), ids[top], rank[top].astype(np.int32), n[top].astype(np.int64)]
    return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["query_id", "neighbor_id", "rank", "collisions"])


def weighted_select(probes: DataFrame, k: int, r: int) -> DataFrame:
    """As count_select, but a hit in a truncated bucket counts for all the items it stands for: max(1, seen / r)."""
    met = probes.select("query_id", F.greatest(F.lit(1.0), F.col("seen") / F.lit(float(r))).alias("w"), F.explode("members").alias("neighbor_id"))
    sums = met.where("neighbor_id <> query_id").groupBy("query_id", "neighbor_id").agg(F.round(F.sum("w"), 6).alias("weight"))
    return _ranked(sums, k, "weight")


def near_neighbors(probes: DataFrame, least: int) -> DataFrame:
    """(query_id, neighbor_id, collisions) of items met at least ``least`` times."""
    met = probes.select("query_id", F.explode("members").alias("neighbor_id")).where("neighbor_id <> query_id")
    return met.groupBy("query_id", "neighbor_id").agg(F.count("*").alias("collisions")).where(F.col("collisions") >= least)


def adaptive_sample(probes: DataFrame, draws: int, seed: int = 1) -> DataFrame:
    """(query_id, draw, neighbor_id): for each draw a random table, then a random member of the query's bucket there.

    An item comes up with a chance that rises with its similarity; draws that hit the query itself stay in.
    """
    from ..functions.portable import parameters

    a, b, c, d = parameters(seed + 500, 4)
    from ..functions.portable import P

    tables = probes.groupBy("query_id").agg(F.sort_array(F.collect_list(F.struct("table_id", "members"))).alias("buckets"))
    turn = tables.withColumn("draw", F.explode(F.sequence(F.lit(0), F.lit(draws - 1))))
    mixed = F.pmod(F.col("query_id"), F.lit(P)) * 31 + F.col("draw") * 1009
    which = (mixed % P * a + b) % P % F.size("buckets")
    turn = turn.withColumn("bucket", F.element_at("buckets", (which + 1).cast("int"))["members"])
    spot = (mixed % P * c + d) % P % F.size("bucket")
    return turn.select("query_id", "draw", F.element_at("bucket", (spot + 1).cast("int")).alias("neighbor_id"))


def rerank(graph: DataFrame, sets: DataFrame, k: int) -> DataFrame:
    """(query_id, neighbor_id, similarity, rank): the graph's items ordered by exact binary cosine."""
    from ..functions import cosine_binary

    x = sets.select(F.col("item_id").alias("query_id"), F.col("features").alias("x"))
    y = sets.select(F.col("item_id").alias("neighbor_id"), F.col("features").alias("y"))
    scored = graph.select("query_id", "neighbor_id").join(x, "query_id").join(y, "neighbor_id").select("query_id", "neighbor_id", F.round(cosine_binary(F.col("x"), F.col("y")), 6).alias("similarity"))
    return _ranked(scored, k, "similarity")

"""Bounded samples of hash buckets: (table_id, address, seen, members array<long>)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions.portable import P, HashNumbers
from ..sources import merged_by

BUCKET = ("table_id", "address")


def priority(seed: int = 1, keys: tuple = BUCKET) -> Column:
    """Number of an item in a bucket that orders the bucket's items at random, the same in every run.

    Squared, as values of a linear hash alone step evenly from item to item.
    """
    a, b = HashNumbers(seed).priority
    mixed = F.pmod(F.col("item_id"), F.lit(P)) * 31 + F.col(keys[0]) * 1009 + F.col(keys[1]) * 101
    x = ((mixed % F.lit(P)) * F.lit(a) + F.lit(b)) % F.lit(P)
    return (x * x + F.lit(a)) % F.lit(P)


def draw(seed: int = 1, keys: tuple = BUCKET, i: str = "i") -> Column:
    """floor(u * (i + 1)) for a pseudo-random u per (item, bucket)."""
    return F.floor(priority(seed + 77, keys) * (F.col(i) + 1) / F.lit(P)).cast("long")


def buckets(addr: DataFrame, most_rows: int = 1_000_000) -> DataFrame:
    """Unbounded buckets, for small data only: refuses if a bucket has more than ``most_rows`` items."""
    top = addr.groupBy(*BUCKET).count().agg(F.max("count")).first()[0] or 0
    if top > most_rows:
        raise MemoryError(f"a bucket holds {top} items; unbounded buckets stop at {most_rows}")
    return addr.groupBy(*BUCKET).agg(F.count("*").alias("seen"), F.sort_array(F.collect_list("item_id")).alias("members"))


def reservoir(addr: DataFrame, r: int, policy: str = "priority", seed: int = 1, keys: tuple = BUCKET) -> DataFrame:
    """At most ``r`` items of each bucket and how many it has seen.

    priority: the r smallest priorities. Uniform without replacement, the same for any order of arrival, mergeable; the
    optimizer cuts every task's share to r rows per bucket before the shuffle.
    arrival: reservoir sampling in the order of ids without iteration: item i takes slot i while there is room, else
    slot floor(u (i + 1)) if below r; a slot keeps its last taker. literal_add draws the slot even while there is room,
    so that items overwrite each other in buckets that would fit; kept for comparison.
    """
    seen = addr.groupBy(*keys).agg(F.count("*").alias("seen"))
    if policy == "priority":
        rank = F.row_number().over(W.partitionBy(*keys).orderBy("pr", "item_id"))
        kept = addr.withColumn("pr", priority(seed, keys)).withColumn("rk", rank).where(F.col("rk") <= r)
        members = kept.groupBy(*keys).agg(F.sort_array(F.collect_list("item_id")).alias("members"))
    elif policy in ("arrival", "literal_add"):
        order = F.row_number().over(W.partitionBy(*keys).orderBy("item_id")) - 1
        placed = addr.withColumn("i", order.cast("long"))
        slot = draw(seed, keys)
        if policy == "arrival":
            slot = F.when(F.col("i") < r, F.col("i")).otherwise(slot)
        placed = placed.withColumn("slot", slot).where(F.col("slot") < r)
        held = placed.groupBy(*keys, "slot").agg(F.max_by("item_id", "i").alias("item_id"))
        members = held.groupBy(*keys).agg(F.sort_array(F.collect_list("item_id")).alias("members"))
    else:
        raise ValueError(f"unknown policy {policy}")
    return seen.join(merged_by(members), list(keys))


def merge(left: DataFrame, right: DataFrame, r: int, seed: int = 1) -> DataFrame:
    """Of two priority reservoirs over different items: what one build over both would give."""
    both = left.unionByName(right)
    seen = both.groupBy(*BUCKET).agg(F.sum("seen").alias("seen"))
    rows = both.select(*BUCKET, F.explode("members").alias("item_id")).withColumn("pr", priority(seed))
    kept = rows.withColumn("rk", F.row_number().over(W.partitionBy(*BUCKET).orderBy("pr", "item_id"))).where(F.col("rk") <= r)
    return seen.join(kept.groupBy(*BUCKET).agg(F.sort_array(F.collect_list("item_id")).alias("members")), list(BUCKET))


def pool_size(tables: int, bits: int, share: float) -> int:
    """Reservoirs in the global pool for a share F in (0, 1]."""
    if not 0 < share <= 1:
        raise ValueError("the share of reservoirs is in (0, 1]")
    return -(-int(round(share * (1 << bits) * 1_000_000)) // 1_000_000) * tables


def share_pointers(addr: DataFrame, tables: int, bits: int, share: float, scheme: str = "global", seed: int = 1, local_fraction: float = 0.5) -> DataFrame:
    """(table_id, address, reservoir_id) of the addresses in use.

    global: every address points to a random reservoir of one pool. pooled: a table's first addresses (in the order of
    the smallest id that reached them) own local reservoirs up to a fraction of the table's room, the rest point into
    the global pool; local ids follow behind the pool's.
    """
    a, b = HashNumbers(seed).share
    pool = pool_size(tables, bits, share)
    spot = ((F.col("table_id") * (1 << bits) + F.col("address")) % F.lit(P) * F.lit(a) + F.lit(b)) % F.lit(P) % F.lit(pool)
    used = addr.groupBy(*BUCKET).agg(F.min("item_id").alias("first_item"))
    if scheme == "global":
        return used.select(*BUCKET, spot.cast("long").alias("reservoir_id"))
    if scheme != "pooled":
        raise ValueError(f"unknown sharing scheme {scheme}")
    local = int(-(-(1 << bits) * local_fraction // 1))
    rank = F.row_number().over(W.partitionBy("table_id").orderBy("first_item", "address"))
    own = F.lit(pool).cast("long") + F.col("table_id") * local + F.col("rk") - 1
    return used.withColumn("rk", rank).select(*BUCKET, F.when(F.col("rk") <= local, own).otherwise(spot).cast("long").alias("reservoir_id"))


def shared_reservoirs(addr: DataFrame, pointers: DataFrame, r: int, seed: int = 1) -> DataFrame:
    """(reservoir_id, seen, members); an item that reaches a reservoir from two tables is held twice."""
    rows = addr.join(merged_by(pointers), list(BUCKET)).withColumn("from_table", F.col("table_id"))
    pr = priority(seed, ("from_table", "reservoir_id"))
    rank = F.row_number().over(W.partitionBy("reservoir_id").orderBy("pr", "item_id", "from_table"))
    kept = rows.withColumn("pr", pr).withColumn("rk", rank).where(F.col("rk") <= r)
    members = kept.groupBy("reservoir_id").agg(F.sort_array(F.collect_list("item_id")).alias("members"))
    return rows.groupBy("reservoir_id").agg(F.count("*").alias("seen")).join(merged_by(members), "reservoir_id")

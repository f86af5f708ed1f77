"""Balanced shards by minimax contiguous partition; DataFrame operations only.

Atomic groups (rows with equal texts) are ordered by the SHA-256 of their text. The smallest capacity for which a
greedy walk fills at most ``shards`` shards is found by binary search, and the shards are cut there; a row's shard then
follows from comparing its digest with the cuts, so rows need no join.

The walk itself runs on the driver over a table of bounded size: sums over ranges of the digest. It starts with 4096
ranges. For any capacity between a lower bound and one known to be feasible, the k-th cut lies in an interval that
follows from the sums; only ranges in those intervals are summed anew, 256 times finer, until each of their ranges is
one group. Outside the intervals no cut can fall, so the result is exact.

Defined results: a null text has no bytes and groups with the empty text; an empty table gives an empty result; rows
that repeat an id get a slot each; other columns are ignored.
"""

from __future__ import annotations

from bisect import bisect_right

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import read_table, text_or_empty, written

SHARDS = 24
#: Bytes that a row costs besides its text.
ROW_BYTES = 8
FIRST_DIGITS, MORE_DIGITS = 3, 2
SLOT_BLOCKS = 512


def greedy_cuts(ends: list[int], capacity: int) -> list[int]:
    """Indices after which a greedy walk cuts; ``ends`` are the running totals behind each piece."""
    cuts, done, at = [], 0, 0
    while at < len(ends):
        nxt = bisect_right(ends, done + capacity, at)
        if nxt == at:
            return []  # one piece alone is too large
        cuts.append(nxt)
        at, done = nxt, ends[nxt - 1]
    return cuts


def smallest_capacity(ends: list[int], shards: int) -> int:
    """Least capacity that a greedy walk over whole pieces meets with at most ``shards`` shards."""
    total = ends[-1] if ends else 0
    low, high = -(-total // shards), total
    while low < high:
        mid = (low + high) // 2
        cuts = greedy_cuts(ends, mid)
        low, high = (low, mid) if cuts and len(cuts) <= shards else (mid + 1, high)
    return high


def plan_cuts(groups: DataFrame, shards: int) -> list[str]:
    """Last digest of each shard but the last, for ``groups`` of (digest, size)."""

    def summed(df: DataFrame, digits: int) -> list[tuple]:
        """Ranges of the digest; one row each, so at most 16**FIRST_DIGITS, later 256 per open range."""
        found = df.groupBy(F.substring("digest", 1, digits).alias("p")).agg(
            F.sum("size").alias("size"), F.max("digest").alias("last"), (F.min("digest") == F.max("digest")).alias("single")
        ).collect()
        return [(r["p"], r["size"], r["last"], r["single"]) for r in found]

    pieces = sorted(summed(groups, FIRST_DIGITS), key=lambda r: r[2])
    while pieces:
        ends, total = [], 0
        for p in pieces:
            total += p[1]
            ends.append(total)
        best = smallest_capacity(ends, shards)  # feasible, as cutting only between ranges is a special case
        least = max([-(-total // shards), *(p[1] for p in pieces if p[3])])
        heavy = {i for i, p in enumerate(pieces) if not p[3] and p[1] > least}  # fewer than ``shards``
        # A walk with capacity c in [least, best]: its k-th cut is not before the coarse walk's and not beyond k * best.
        floor, reach, open_ = 0, 0, set()
        for _ in range(shards):
            at = bisect_right(ends, floor + least)
            floor = max(ends[at - 1] if at else 0, floor)
            reach = min(total, reach + best)
            first, last = bisect_right(ends, floor), min(len(ends) - 1, bisect_right(ends, reach))
            open_ |= {i for i in range(first, last + 1) if not pieces[i][3]}
            if floor >= total:
                break
        open_ = heavy or open_
        if not open_:
            cuts = greedy_cuts(ends, best)
            return [pieces[i - 1][2] for i in cuts[:-1]]
        by_digits: dict[int, list[str]] = {}
        for i in open_:
            by_digits.setdefault(len(pieces[i][0]), []).append(pieces[i][0])
        fresh = []
        for digits, prefixes in by_digits.items():
            fresh += summed(groups.where(F.substring("digest", 1, digits).isin(sorted(prefixes))), digits + MORE_DIGITS)
        pieces = sorted([p for i, p in enumerate(pieces) if i not in open_] + fresh, key=lambda r: r[2])
    return []


def shard_rows(docs: DataFrame, shards: int = SHARDS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, size, text_crc32, law, shard, slot, grown_shard (null under the law ``bytes``).

    Slots count from 0 within a shard. They come from the sizes of ``SLOT_BLOCKS`` hashed blocks of a shard and a rank
    inside the block, so neither a shard nor a large group is ever ordered in one task.
    """
    body = text_or_empty(text_col)
    rows = written(
        docs.select(
            F.col(id_col).cast("long").alias("doc_id"), (F.octet_length(body) + F.lit(ROW_BYTES)).cast("long").alias("size"),
            F.crc32(body.cast("binary")).alias("text_crc32"), F.sha2(body, 256).alias("digest"),
        ),
        "sizes",
    )
    groups = written(rows.groupBy("digest").agg(F.sum("size").alias("size")), "groups")
    cuts = plan_cuts(groups, shards)
    shard = F.lit(0)
    for c in cuts:
        shard = shard + (F.col("digest") > F.lit(c)).cast("int")
    block = F.pmod(F.xxhash64("doc_id", "digest"), F.lit(SLOT_BLOCKS)).cast("int")
    placed = rows.select("doc_id", "size", "text_crc32", "digest", shard.alias("shard"), block.alias("block"))
    starts = placed.groupBy("shard", "block").agg(F.count("*").alias("n"))
    before = F.sum("n").over(W.partitionBy("shard").orderBy("block").rowsBetween(W.unboundedPreceding, -1))
    starts = starts.select("shard", "block", F.coalesce(before, F.lit(0)).alias("start"))
    rank = F.row_number().over(W.partitionBy("shard", "block").orderBy("doc_id", "digest"))
    return (
        placed.withColumn("r", rank).join(F.broadcast(starts), ["shard", "block"])  # at most shards * SLOT_BLOCKS rows
        .select(
            "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("start") + F.col("r") - 1).cast("long").alias("slot"),
            F.lit(None).cast("int").alias("grown_shard"),
        )
    )


def op6_sharding(spark, sf_dir: str) -> DataFrame:
    return shard_rows(read_table(spark, sf_dir, "documents"))

"""Mixing sources to target weights by pivotal dependent rounding.

A source's target over its size is the expected number of copies of each of its documents. The whole part is taken
outright; the fractional part is a copy probability, and the probabilities of a source are rounded together: two
documents at a time trade mass (probability times size) in one of two random directions, so that one of them becomes
0 or 1, every probability keeps its mean and the mass of the pair stays the same. Within a hashed block of a source
the duels run from large documents to small; the one document per block left in between goes up a tree of blocks, each
level a shuffle of at most one row per block. A source thus misses its target by less than one document.

Random choices are hashes of id, text, seed and level, so reruns agree whatever the partitions are.

Defined results: a null or empty text has size 0 and is taken 0 words (its copies are rounded alone); a null source is a
source of its own, ordered last; rows that repeat an id are rounded each; an empty table gives an empty result; other
columns are ignored by ``mix`` and kept by ``repeat_rows``.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import counted_broadcast, read_table, text_or_empty, written

WEIGHTS = (3.0, 1.0, 2.0)
SHARE = 1.5
MAX_COPIES = 2.0
SEED = 17
#: Documents per first-level block, and blocks per block of the next level.
BLOCK_ROWS, FAN_IN = 512, 64
#: Sources up to which their totals are broadcast; beyond, they are joined by shuffle.
BROADCAST_SOURCES = 100_000


def n_words(text: Column) -> Column:
    r"""Number of runs of ``[^\x20\x09-\x0D]``."""
    parts = F.split(text, "[\\x20\\x09-\\x0D]+")
    edges = F.when(F.element_at(parts, 1) == "", 1).otherwise(0) + F.when((F.size(parts) > 1) & (F.element_at(parts, -1) == ""), 1).otherwise(0)
    return (F.size(parts) - edges).cast("long")


def source_targets(sizes: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, most: float = MAX_COPIES) -> DataFrame:
    """(source, source_size, source_rows, target) from rows of (source, size).

    Weights repeat over the sources in order of code points, null last. A source whose part of what is left exceeds
    ``most`` times its size is held there, and the rest is shared anew until none exceeds; each turn is one sum over
    the table of sources. The rank runs over one row per source.
    """
    totals = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("source_rows"))
    place = F.row_number().over(W.orderBy(F.col("source").isNull(), F.col("source"))) - 1
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(place, F.lit(len(weights))) + 1).cast("int"))
    table = written(totals.withColumn("weight", weight).withColumn("cap", F.col("source_size") * F.lit(float(most))), "sources")
    whole = share * float(table.agg(F.sum("source_size")).first()[0] or 0)
    per_weight, held = None, F.lit(False)
    while True:
        row = table.agg(F.sum(F.when(held, F.col("cap")).otherwise(0.0)), F.sum(F.when(held, 0.0).otherwise(F.col("weight")))).first()
        if not row[1]:
            break
        nxt = (whole - row[0]) / row[1]
        if nxt == per_weight:
            break
        per_weight = nxt
        held = held | (F.col("weight") * F.lit(per_weight) > F.col("cap"))
    target = F.when(held, F.col("cap")).otherwise(F.col("weight") * F.lit(per_weight or 0.0))
    return table.select("source", "source_size", "source_rows", target.alias("target"))


def duel(p: np.ndarray, size: np.ndarray, draw: np.ndarray) -> np.ndarray:
    """Round probabilities in the order given; at most one stays strictly between 0 and 1.

    Sizes are positive. Each meeting keeps the pair's mass and both means.
    """
    p = p.astype(float).copy()
    at = -1
    for j in range(len(p)):
        if not 0.0 < p[j] < 1.0:
            continue
        if at < 0:
            at = j
            continue
        i, (si, sj) = at, (size[at], size[j])
        up = min((1 - p[i]) * si, p[j] * sj)  # mass that i can get from j
        down = min(p[i] * si, (1 - p[j]) * sj)
        move = up if draw[j] * (up + down) < down else -down
        a, b = p[i] + move / si, p[j] - move / sj
        # The one that met its bound is set to it exactly.
        if move > 0:
            i_done, j_done = (1 - p[i]) * si <= p[j] * sj, p[j] * sj <= (1 - p[i]) * si
            p[i], p[j] = (1.0 if i_done else a), (0.0 if j_done else b)
        else:
            i_done, j_done = p[i] * si <= (1 - p[j]) * sj, (1 - p[j]) * sj <= p[i] * si
            p[i], p[j] = (0.0 if i_done else a), (1.0 if j_done else b)
        at = j if i_done and not j_done else -1 if i_done else i
    return p


def _round_block(pdf: pd.DataFrame) -> pd.DataFrame:
    pdf = pdf.sort_values(["size", "tie", "doc_id"], ascending=[False, True, True], kind="stable").reset_index(drop=True)
    draw = (pdf["draw"].to_numpy() % 2**40) / 2.0**40
    p = pdf["p"].to_numpy(dtype=float)
    size = pdf["size"].to_numpy(dtype=float)
    empty = size <= 0
    out = np.where(draw < p, 1.0, 0.0)
    out[~empty] = duel(p[~empty], size[~empty], draw[~empty])
    return pdf.assign(p=out)


def mix(
    docs: DataFrame, weights: tuple = WEIGHTS, share: float = SHARE, most: float = MAX_COPIES, seed: int = SEED,
    id_col: str = "doc_id", text_col: str = "text", source_col: str = "source",
) -> DataFrame:
    """One row per document: doc_id, size, source, source_size, target, copies, taken, tie (hash of text and seed)."""
    body = text_or_empty(text_col)
    base = [F.coalesce(F.col(id_col).cast("long"), F.lit(0)).alias("doc_id"), F.col(id_col).isNull().alias("no_id"), F.col(source_col).cast("string").alias("source"), n_words(body).alias("size"), F.xxhash64(body, F.lit(seed)).alias("tie")]
    rows = written(docs.select(*base), "mix-sizes")
    targets = source_targets(rows.select("source", "size"), weights, share, most)
    largest = targets.agg(F.max("source_rows")).first()[0] or 0
    blocks = max(1, -(-largest // BLOCK_ROWS))  # of the largest source; each source has as many as its rows ask for
    t = counted_broadcast(targets.withColumnRenamed("source", "of_source"), BROADCAST_SOURCES)
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    rows = rows.join(t, F.col("source").eqNullSafe(F.col("of_source"))).withColumn("whole", F.floor(rate).cast("long"))
    rows = rows.select(
        "doc_id", "no_id", "source", "size", "tie", "source_size", "target", "whole", (rate - F.col("whole")).alias("p"),
        F.pmod(F.xxhash64("doc_id", "tie"), F.ceil(F.col("source_rows") / F.lit(BLOCK_ROWS))).cast("long").alias("block"), F.xxhash64("doc_id", "tie", F.lit(seed), F.lit(0)).alias("draw"),
    )
    open_ = (F.col("p") > 0) & (F.col("p") < 1)
    done, level = [], 0
    while True:
        rows = written(rows.groupBy("source", "block").applyInPandas(_round_block, rows.schema), f"mix-{level}")
        done.append(rows.where(~open_))
        if blocks == 1:
            break
        blocks, level = -(-blocks // FAN_IN), level + 1
        rows = rows.where(open_).withColumn("block", F.floor(F.col("block") / FAN_IN).cast("long")).withColumn("draw", F.xxhash64("doc_id", "tie", F.lit(seed), F.lit(level)))
    last = F.pmod(F.xxhash64("doc_id", "tie", F.lit(seed), F.lit(-1)), F.lit(2**40)) / F.lit(float(2**40))
    done.append(rows.where(open_).withColumn("p", F.when(last < F.col("p"), 1.0).otherwise(0.0)))
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    out = out.withColumn("copies", F.col("whole") + F.col("p").cast("long"))
    return out.select(F.when(~F.col("no_id"), F.col("doc_id")).alias("doc_id"), "size", "source", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"), "tie")


def repeat_rows(docs: DataFrame, seed: int = SEED, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """``docs`` with each row repeated as often as the mix takes it (0, 1 or 2 times), columns unchanged.

    Rows and copies meet by id and hash of the text, numbered where rows repeat both, so texts are shuffled once.
    """
    key = [F.coalesce(F.col(id_col).cast("long"), F.lit(0)).alias("_i"), F.col(id_col).isNull().alias("_n"), F.xxhash64(text_or_empty(text_col), F.lit(seed)).alias("_t")]
    number = lambda by: F.row_number().over(W.partitionBy("_i", "_n", "_t").orderBy(by))
    found = mix(docs, seed=seed, id_col=id_col, text_col=text_col, **options)
    copies = found.select(F.coalesce("doc_id", F.lit(0)).alias("_i"), F.col("doc_id").isNull().alias("_n"), F.col("tie").alias("_t"), "copies")
    copies = copies.withColumn("_k", number("copies")).where("copies > 0")
    rows = docs.select(F.struct(*docs.columns).alias("_row"), *key).withColumn("_k", number("_i"))
    times = F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))
    return rows.join(copies, ["_i", "_n", "_t", "_k"]).withColumn("_c", times).select("_row.*")


def op5_mixing(spark, sf_dir: str) -> DataFrame:
    return mix(read_table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")

"""Labelled rows for fitting: a bounded sample of whole texts, brought to the driver."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import written

#: Folds are crc32 of the id as text, modulo 3; fold 1 is held out and never read for fitting.
FOLDS, HELD_OUT_FOLD = 3, 1
#: Most texts of each class that a classifier is fitted on, and most bytes of texts.
ROWS_PER_CLASS, SAMPLE_BYTES = 2500, 48 << 20


def fold(id_col: str = "doc_id") -> Column:
    """The fold of a row; a null id counts as the empty text."""
    return F.pmod(F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")), F.lit(FOLDS)).cast("int")


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, rows_per_class: int = ROWS_PER_CLASS, sample_bytes: int = SAMPLE_BYTES) -> list[tuple[int, int, str]]:
    """(fold, label, text) of at most ``rows_per_class`` rows of each class outside the held-out fold.

    Chosen by the hash of the id, so reruns agree. Null or contradictory labels, null texts and ids are left out; of
    different texts under one id the one with the smallest hash is taken. Texts come whole; those that would pass
    ``sample_bytes`` in order of the hash are left out before any text is sent to the driver.
    """
    known = (
        labels.select(F.col("doc_id").alias("_id"), F.col(label).cast("int").alias("y")).where("_id IS NOT NULL AND y IN (0, 1)")
        .groupBy("_id").agg(F.min("y").alias("y"), F.max("y").alias("y2")).where("y = y2").where(fold("_id") != HELD_OUT_FOLD)
        .withColumn("h", F.xxhash64("_id"))
    )
    picked = None
    for y in (0, 1):
        part = known.where(F.col("y") == y).orderBy("h", "_id").limit(rows_per_class)
        picked = part if picked is None else picked.unionByName(part)
    rows = docs.select("doc_id", "text").where(F.col("text").isNotNull()).join(
        F.broadcast(picked), F.col("doc_id") == F.col("_id")  # at most twice rows_per_class rows
    )
    rows = written(rows.groupBy("_id", "y", "h").agg(F.min_by("text", F.xxhash64("text")).alias("text")), "labelled")
    total, keep = 0, []
    for r in sorted(rows.select("h", "_id", F.octet_length("text").alias("b")).collect()):
        if total + r["b"] <= sample_bytes:
            total += r["b"]
            keep.append(r["_id"])
    kept = F.broadcast(rows.sparkSession.createDataFrame([(i,) for i in keep], "_id long"))
    found = rows.join(kept, "_id").select("h", "_id", fold("_id").alias("f"), "y", "text").collect()
    return [(r["f"], r["y"], r["text"]) for r in sorted(found, key=lambda r: (r["h"], r["_id"]))]

"""Heavy entries of A^T A: neighbours by collisions first, exact products only for the pairs found."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import cosine_binary
from .index import IndexParams, knn_graph


def heavy_entries(columns: DataFrame, p: IndexParams, k: int = 20, threshold: float = 0.65, measure: str = "cosine") -> DataFrame:
    """(i, j, value) with value above the threshold among each column's top k; ``columns`` are sets of rows."""
    graph = knn_graph(columns, p, k)
    x = columns.select(F.col("item_id").alias("query_id"), F.col("features").alias("x"))
    y = columns.select(F.col("item_id").alias("neighbor_id"), F.col("features").alias("y"))
    value = cosine_binary(F.col("x"), F.col("y")) if measure == "cosine" else F.size(F.array_intersect("x", "y")).cast("double")
    pairs = graph.select("query_id", "neighbor_id").join(x, "query_id").join(y, "neighbor_id")
    return pairs.select(F.col("query_id").alias("i"), F.col("neighbor_id").alias("j"), F.round(value, 6).alias("value")).where(F.col("value") > threshold)


def exact_product(columns: DataFrame, threshold: float = 0.65, measure: str = "cosine") -> DataFrame:
    """(i, j, value) of all entries above the threshold: a join on the row and a sum per pair of columns."""
    a = columns.select(F.col("item_id").alias("i"), F.explode("features").alias("f"))
    b = a.withColumnRenamed("i", "j")
    size = columns.select("item_id", F.size("features").alias("n"))
    dots = a.join(b, "f").where("i <> j").groupBy("i", "j").agg(F.count("*").alias("a"))
    if measure == "cosine":
        dots = dots.join(size.withColumnsRenamed({"item_id": "i", "n": "x"}), "i").join(size.withColumnsRenamed({"item_id": "j", "n": "y"}), "j")
        value = F.col("a") / F.sqrt(F.col("x").cast("double") * F.col("y"))
    else:
        value = F.col("a").cast("double")
    return dots.select("i", "j", F.round(value, 6).alias("value")).where(F.col("value") > threshold)

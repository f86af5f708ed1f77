"""Column functions of the similarity engine."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def jaccard(x: Column, y: Column) -> Column:
    """Shared over all features of two sets; 0 for two empty sets."""
    both = F.size(F.array_intersect(x, y))
    whole = F.size(x) + F.size(y) - both
    return F.when(whole > 0, both / whole).otherwise(F.lit(0.0))


def cosine_binary(x: Column, y: Column) -> Column:
    """Shared features over the geometric mean of the sizes; 0 if a set is empty."""
    scale = F.sqrt(F.size(x).cast("double") * F.size(y))
    return F.when(scale > 0, F.size(F.array_intersect(x, y)) / scale).otherwise(F.lit(0.0))


def inner_product(x: Column, y: Column) -> Column:
    """Of dense vectors of equal length."""
    return F.aggregate(F.zip_with(x, y, lambda a, b: a.cast("double") * b.cast("double")), F.lit(0.0), lambda s, v: s + v)


def cosine_dense(x: Column, y: Column) -> Column:
    scale = F.sqrt(inner_product(x, x) * inner_product(y, y))
    return F.when(scale > 0, inner_product(x, y) / scale).otherwise(F.lit(0.0))


def sparse_dot(x: Column, y: Column) -> Column:
    """Of two map<long,double>."""
    return F.aggregate(F.transform(F.map_keys(x), lambda k: F.coalesce(x[k] * F.try_element_at(y, k), F.lit(0.0))), F.lit(0.0), lambda s, v: s + v)


def cosine_weighted(x: Column, y: Column) -> Column:
    norm = lambda m: F.sqrt(F.aggregate(F.map_values(m), F.lit(0.0), lambda s, v: s + v * v))
    scale = norm(x) * norm(y)
    return F.when(scale > 0, sparse_dot(x, y) / scale).otherwise(F.lit(0.0))


def register_sql_functions(spark: SparkSession) -> None:
    """``jaccard``, ``cosine_set`` and ``feature_id`` as SQL functions, inlined by the optimizer."""
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION jaccard(x ARRAY<BIGINT>, y ARRAY<BIGINT>) RETURNS DOUBLE RETURN "
        "CASE WHEN size(array_union(x, y)) = 0 THEN 0D ELSE size(array_intersect(x, y)) / size(array_union(x, y)) END"
    )
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION cosine_set(x ARRAY<BIGINT>, y ARRAY<BIGINT>) RETURNS DOUBLE RETURN "
        "CASE WHEN size(x) = 0 OR size(y) = 0 THEN 0D ELSE size(array_intersect(x, y)) / sqrt(size(x) * size(y)) END"
    )
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION feature_id(t STRING) RETURNS BIGINT RETURN CAST(conv(substring(md5(t), 1, 7), 16, 10) AS BIGINT)")

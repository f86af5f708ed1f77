"""Sets of features from text, pages, categories and edges: (item_id, features array<long>, sorted and distinct)."""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.portable import P, feature_id, linear, parameters

#: Tokens whose numbers a task remembers at a time.
_KNOWN_TOKENS = 1_000_000


class _Known(dict):
    """28-bit numbers of tokens, as ``feature_id`` gives them; a token is hashed once per task and not once per row."""

    def __missing__(self, token: str) -> int:
        if len(self) >= _KNOWN_TOKENS:
            self.clear()
        self[token] = number = int(hashlib.md5(token.encode("utf-8", "surrogatepass")).hexdigest()[:7], 16)
        return number


def _numbered(df: DataFrame, item: str, value: Column, tokens_of: Callable) -> DataFrame:
    """Sets of the numbers of the tokens that ``tokens_of`` finds in each value, in Arrow batches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = _Known()
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                found = []
                for v in part.column(1).to_pylist():
                    ids = {known[t] for t in tokens_of(v) if t} if v else set()
                    found.append(np.sort(np.fromiter(ids, dtype=np.int64, count=len(ids))))
                ends = np.concatenate(([0], np.cumsum([len(f) for f in found]))).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(found) if found else np.zeros(0, dtype=np.int64)))
                yield pa.RecordBatch.from_arrays([part.column(0), lists], names=["item_id", "features"])

    return df.select(F.col(item).cast("long").alias("item_id"), value.alias("value")).mapInArrow(run, "item_id long, features array<long>")


def as_sets(df: DataFrame, item: str, tokens: Column, mode: str = "md5_28") -> DataFrame:
    """Tokens of each row as a set of feature ids; empty and null tokens fall out.

    ``md5_28`` needs a digest and a conversion per token, so numbers are remembered by Arrow tasks; ``xx64`` stays in the JVM.
    """
    if mode == "md5_28":
        return _numbered(df, item, tokens, lambda v: v)
    ids = F.transform(F.filter(F.array_distinct(tokens), lambda t: t.isNotNull() & (t != "")), lambda t: feature_id(t, mode))
    return df.select(F.col(item).cast("long").alias("item_id"), F.sort_array(F.array_distinct(F.coalesce(ids, F.array().cast("array<long>")))).alias("features"))


def word_tokens(text: str | Column) -> Column:
    return F.split(F.lower(F.col(text) if isinstance(text, str) else text), r"\s+")


def token_set(df: DataFrame, item: str, text: str, mode: str = "md5_28") -> DataFrame:
    return as_sets(df, item, word_tokens(text), mode)


def char_ngrams(df: DataFrame, item: str, text: str, n: int = 3, mode: str = "md5_28") -> DataFrame:
    if mode == "md5_28":
        return _numbered(df, item, F.lower(F.col(text)), lambda v: {v[i : i + n] for i in range(len(v) - n + 1)})
    chars = F.filter(F.split(F.lower(F.col(text)), ""), lambda c: c != "")
    # bound by a lambda, so that the array is made once per row and not once per place
    cut = lambda cs: F.transform(F.sequence(F.lit(0), F.size(cs) - n), lambda i: F.concat(*[F.get(cs, i + j) for j in range(n)]))
    grams = F.transform(F.array(chars), lambda cs: F.when(F.size(cs) >= n, cut(cs)).otherwise(F.array().cast("array<string>")))[0]
    return as_sets(df, item, grams, mode)


def url_parts(url: str) -> Column:
    """Tagged parts of a URL: host, each path step, each query pair."""
    tagged = lambda tag, parts: F.transform(F.filter(parts, lambda p: p != ""), lambda p: F.concat(F.lit(tag), p))
    host = F.regexp_extract(url, r"^[a-z]+://([^/?#]*)", 1)
    path = F.regexp_extract(url, r"^[a-z]+://[^/?#]*([^?#]*)", 1)
    query = F.regexp_extract(url, r"\?([^#]*)", 1)
    return F.concat(tagged("h:", F.split(host, r"\.")), tagged("p:", F.split(path, "/")), tagged("q:", F.split(query, "&")))


def url_tokens(df: DataFrame, item: str, url: str, text: str | None = None, mode: str = "md5_28") -> DataFrame:
    tokens = url_parts(url)
    if text:
        tokens = F.concat(tokens, F.transform(F.filter(word_tokens(text), lambda t: t != ""), lambda t: F.concat(F.lit("t:"), t)))
    return as_sets(df, item, tokens, mode)


def categorical_set(df: DataFrame, item: str, cols: list[str], mode: str = "md5_28") -> DataFrame:
    """One tag per column: its name and value; nulls give none."""
    return as_sets(df, item, F.array(*[F.concat(F.lit(f"{c}="), F.col(c).cast("string")) for c in cols]), mode)


def merged(sets: DataFrame) -> DataFrame:
    """One set per id: that of all rows which share it."""
    return sets.groupBy("item_id").agg(F.sort_array(F.array_distinct(F.flatten(F.collect_list("features")))).alias("features"))


def adjacency_set(edges: DataFrame, src: str, dst: str) -> DataFrame:
    """The neighbours of each source as its features (ids are the neighbours' own)."""
    return edges.where(F.col(src).isNotNull() & F.col(dst).isNotNull()).groupBy(F.col(src).cast("long").alias("item_id")).agg(
        F.sort_array(F.collect_set(F.col(dst).cast("long"))).alias("features")
    )


def unit_weights(sets: DataFrame) -> DataFrame:
    """(item_id, weights map<long,double>) of unit length."""
    w = F.lit(1.0) / F.sqrt(F.size("features").cast("double"))
    return sets.where(F.size("features") > 0).select("item_id", F.map_from_arrays("features", F.transform("features", lambda _: w)).alias("weights"))


def drop_empty(sets: DataFrame) -> DataFrame:
    return sets.where(F.size("features") > 0)


def long_form(sets: DataFrame) -> DataFrame:
    return sets.select("item_id", F.explode("features").alias("feature"))


def sample_features(sets: DataFrame, m: int, seed: int = 3) -> DataFrame:
    """Only ``m`` of the features, chosen by a seeded hash; rows left empty are dropped."""
    a, b = parameters(seed, 2)
    kept = long_form(sets).select("feature").distinct().withColumn("r", linear(F.col("feature"), a, b)).orderBy("r", "feature").limit(m).select("feature")
    inside = long_form(sets).join(F.broadcast(kept), "feature", "left_semi")  # m rows
    return inside.groupBy("item_id").agg(F.sort_array(F.collect_set("feature")).alias("features"))


def to_dense(sets: DataFrame, dims: list[int], budget_bytes: int = 1 << 30) -> DataFrame:
    """(item_id, vector array<float>) over the given features; refuses what a dense method cannot hold."""
    need = sets.count() * len(dims) * 4
    if need > budget_bytes:
        raise MemoryError(f"dense form needs {need} bytes, more than {budget_bytes}: ultra-high dimensions have to stay sparse")
    return sets.select("item_id", F.array(*[F.array_contains("features", d).cast("float") for d in dims]).alias("vector"))


def binarize_top(df: DataFrame, item: str, vector: str, top: int = 16) -> DataFrame:
    """Dense vectors as sets: the places of the largest absolute values, with their signs."""
    ranked = F.transform(F.col(vector), lambda v, i: F.struct((-F.abs(v)).alias("m"), i.alias("i"), (v < 0).cast("int").alias("s")))
    best = F.slice(F.sort_array(ranked), 1, top)
    return df.select(F.col(item).cast("long").alias("item_id"), F.sort_array(F.transform(best, lambda e: (e["i"] * 2 + e["s"]).cast("long"))).alias("features"))


def asymmetric_pad(sets: DataFrame, side: str, max_size: int) -> DataFrame:
    """Data sets are filled to ``max_size`` (larger ones stay) with features that all share; queries stay as they are.

    Collisions of a query q and an item x then follow a / (max_size + |q| - a), which rises with the inner product a.
    """
    if side == "query":
        return sets
    dummies = F.transform(F.sequence(F.lit(0), F.lit(max_size)), lambda i: F.lit(P).cast("long") + i)
    return sets.select("item_id", F.concat("features", F.slice(dummies, 1, F.greatest(F.lit(max_size) - F.size("features"), F.lit(0)))).alias("features"))


def profile(sets: DataFrame) -> DataFrame:
    """n, dims, nonzeros (min, mean, max) and the largest share of rows with one feature; one row."""
    sizes = sets.agg(
        F.count("*").alias("n"), F.min(F.size("features")).alias("nnz_min"), F.round(F.avg(F.size("features")), 6).alias("nnz_mean"), F.max(F.size("features")).alias("nnz_max")
    )
    df = long_form(sets).groupBy("feature").agg(F.count("*").alias("df")).agg(F.count("*").alias("dims"), F.max("df").alias("max_df"))
    return sizes.crossJoin(df).select("n", "dims", "nnz_min", "nnz_mean", "nnz_max", F.round(F.col("max_df") / F.col("n"), 6).alias("max_df_share"))


SETS = T.StructType([T.StructField("item_id", T.LongType()), T.StructField("features", T.ArrayType(T.LongType()))])

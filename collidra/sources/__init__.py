"""Reading and writing: tables, sparse text files, graphs, streams."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def read_table(spark: SparkSession, folder: str, name: str, columns: list[str] | None = None, where: str | Column | None = None) -> DataFrame:
    """A Parquet table; filter and columns reach the scan."""
    df = spark.read.parquet(f"{folder}/{name}.parquet")
    if where is not None:
        df = df.where(where)
    return df.select(*columns) if columns else df


def dealt(df: DataFrame) -> DataFrame:
    """``df`` with its rows dealt to all cores if its table fits one split: it may be one row group, which one task would
    read, and work on, alone. Larger tables have row groups enough and stay as they are."""
    session = df.sparkSession
    size = int(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())
    if size > session._jsparkSession.sessionState().conf().filesMaxPartitionBytes():
        return df
    return df.repartition(session.sparkContext.defaultParallelism)


def scratch(spark: SparkSession) -> str:
    """A fresh path in the folder that ``spark.checkpoint.dir`` names. Where it is unset, one machine takes a temporary
    folder (tests); a cluster is refused, as its executors could not read each other's files there."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        base = tempfile.mkdtemp(prefix="collidra-")
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/{uuid.uuid4().hex}"


def merged_by(df: DataFrame) -> DataFrame:
    """``df`` as a side of a join that must not be broadcast. Spark judges by compressed bytes, in which lists and pairs
    that repeat are a fraction of what the driver would hold to broadcast them."""
    return df.hint("merge")


def stored(df: DataFrame) -> DataFrame:
    """``df`` as Parquet in the shared folder: computed once, and re-read where an executor is lost."""
    path = scratch(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def settled(df: DataFrame) -> DataFrame:
    """As ``stored``, for one of several results made in turn: the shuffle files of its run may go before the next begins,
    which Spark does once the driver's JVM has collected what referred to them."""
    out = stored(df)
    df.sparkSession.sparkContext._jvm.System.gc()
    return out


def read_libsvm(spark: SparkSession, path: str) -> DataFrame:
    """(item_id, label, features, weights) from lines ``label index:value ...``; indices from 1, of any size.

    Lines have no ids, so the id is a hash of the line; equal lines share one.
    """
    raw = spark.read.text(path).where(F.trim("value") != "")
    parts = F.split(F.trim("value"), r"\s+")
    pairs = F.transform(F.slice(parts, 2, F.greatest(F.size(parts) - 1, F.lit(0))), lambda p: F.split(p, ":"))
    return raw.select(
        F.shiftrightunsigned(F.xxhash64("value"), 1).alias("item_id"), parts[0].cast("double").alias("label"),
        F.transform(pairs, lambda p: p[0].cast("long") - 1).alias("features"), F.transform(pairs, lambda p: p[1].cast("double")).alias("weights"),
    )


def write_libsvm(sets: DataFrame, path: str, label: Column | None = None) -> None:
    body = F.array_join(F.transform("features", lambda f: F.concat((f + 1).cast("string"), F.lit(":1"))), " ")
    sets.select(F.concat_ws(" ", (label if label is not None else F.lit(0)).cast("string"), body).alias("value")).write.mode("overwrite").text(path)


def read_json(spark: SparkSession, path: str, schema: T.StructType | str) -> DataFrame:
    return spark.read.schema(schema).json(path)


def read_csv(spark: SparkSession, path: str, schema: T.StructType | str, header: bool = True) -> DataFrame:
    return spark.read.schema(schema).option("header", header).csv(path)


def write_graph(graph: DataFrame, path: str, ranges: int = 64) -> None:
    """The graph clustered by ranges of the query id, so that a look-up reads few files."""
    graph.repartitionByRange(ranges, "query_id").sortWithinPartitions("query_id", "rank").write.mode("overwrite").parquet(path)


def read_stream(spark: SparkSession, folder: str, name: str, schema: T.StructType, max_files: int = 1) -> DataFrame:
    """A stream over the files of a table, ``folder/name*.parquet``, each a file or a folder of files."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", max_files).parquet(f"{folder}/{name}*.parquet")


def sample_rows(df: DataFrame, key: str, n: int, seed: int = 7) -> DataFrame:
    """``n`` rows by a seeded hash of an integer key: the same whatever the partitions."""
    from ..functions.portable import linear, parameters

    a, b = parameters(seed, 2)
    return df.withColumn("_r", linear(F.pmod(key, F.lit(2**31)), a, b)).orderBy("_r", key).limit(n).drop("_r")

"""What the corpus operators share: tables, the shared folder, components of a link graph.

Intermediate tables are written as Parquet below the folder named by ``spark.checkpoint.dir``, which all
executors of a cluster see; a lost executor then costs a re-read and not a re-run.
"""

from __future__ import annotations

import ctypes
import tempfile
import uuid

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that ``spark.checkpoint.dir`` names. Where it is unset, one machine gets a temporary folder of its own
    (tests); a cluster is refused, as its executors could not read each other's files there."""
    folder = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not folder:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        folder = tempfile.mkdtemp(prefix="collidra-")
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


_made: list[str] = []


def written(df: DataFrame, tag: str) -> DataFrame:
    """``df`` as a table in the shared folder: cuts lineage and is computed once."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _made.append(path)
    return spark.read.schema(df.schema).parquet(path)


def tables_made() -> tuple[str, ...]:
    """The tables that ``written`` has made and nobody removed, in order."""
    return tuple(_made)


def remove(spark: SparkSession, paths: list[str] | tuple[str, ...]) -> None:
    """Delete tables of ``written``. What reads them must be done."""
    jvm = spark.sparkContext._jvm
    for path in paths:
        at = jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
        if path in _made:
            _made.remove(path)


#: Tables by name that a Python worker keeps from task to task of one operator.
KEPT: list[dict] = []


def trim() -> None:
    """Give a Python worker's free memory back: workers are used again, and idle ones count beside the next stage's work."""
    pa.default_memory_pool().release_unused()
    give_back = getattr(ctypes.CDLL(None), "malloc_trim", None)  # only the GNU library has it
    if give_back:
        give_back(0)


def spare() -> None:
    """As ``trim``, without the tables that another operator's tasks have kept."""
    for tables in KEPT:
        tables.clear()
    trim()


def shuffle_partitions(spark: SparkSession) -> int:
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


#: Tables of at most so many rows are broadcast, behind a count.
BROADCAST_ROWS = 200_000


def text_or_empty(col: str | Column) -> Column:
    return F.coalesce(F.col(col) if isinstance(col, str) else col, F.lit(""))


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, component) for each node of the undirected edges (a, b) of longs; component = smallest node.

    Alternates two star contractions: every node hands its larger neighbours to the smallest node it knows, then
    its smaller ones. The number of rounds grows with the logarithm of the longest chain; each round is a
    grouped minimum (combined before the shuffle) and one join on the node, in which AQE splits hubs.
    Edges never leave the executors; only their count and checksum do, to see that nothing moves any more. A round's
    table goes once the next is there. Links that are still moving after ``max_rounds`` are an error, never a result.
    """
    spark, before = edges.sparkSession, len(tables_made())
    star = written(
        edges.where(F.col("a") != F.col("b")).select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges"
    )
    seen = None
    for _ in range(max_rounds):
        mark = tuple(star.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if mark[0] == 0 or mark == seen:
            break
        remove(spark, tables_made()[before:-1])
        seen = mark
        both = star.unionByName(star.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        star = (
            both.join(low, "u").where(F.col("v") > F.col("u")).select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").distinct()
        )
        low = star.groupBy("u").agg(F.min("v").alias("m"))
        small = star.join(low, "u")
        star = written(
            small.where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
            .unionByName(low.select("u", F.col("m").alias("v"))).distinct(),
            "edges",
        )
    else:
        raise RuntimeError(f"components still move after {max_rounds} rounds")
    remove(spark, tables_made()[before:-1])
    low = star.groupBy("u").agg(F.min("v").alias("component"))
    roots = low.select(F.col("component").alias("node")).distinct()
    return low.select(F.col("u").alias("node"), "component").unionByName(roots.select("node", F.col("node").alias("component")))


def counted_broadcast(df: DataFrame, rows: int) -> DataFrame:
    """``df`` with a broadcast hint if a count shows that it has at most ``rows`` rows, else as it is."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def crowds(rows: DataFrame, cell_weight: int, weight: Column | None = None) -> DataFrame:
    """(k, groups) of the buckets, by ``key``, that weigh more than ``cell_weight``: groups of about that weight; a row weighs 1."""
    many = rows.groupBy(F.col("key").alias("k")).agg(F.sum(F.lit(1) if weight is None else weight).alias("n")).where(F.col("n") > cell_weight)
    return counted_broadcast(written(many.select("k", F.ceil(F.col("n") / cell_weight).cast("int").alias("groups")), "crowds"), BROADCAST_ROWS)


def cells(rows: DataFrame, crowded: DataFrame, spread: Column) -> DataFrame:
    """``rows`` with ``cell``: their bucket's key, or that of a part of it if it is crowded.

    A crowded bucket's rows fall into groups by ``spread``, and every two groups share a cell, so all pairs of rows meet.
    """
    own = F.pmod(spread, F.col("groups")).cast("int")
    parts = F.transform(F.sequence(F.lit(0), F.col("groups") - 1), lambda j: F.xxhash64(F.col("key"), F.least(own, j), F.greatest(own, j)))
    placed = rows.join(crowded, F.col("key") == F.col("k"), "left")
    return placed.withColumn("cell", F.explode(F.when(F.col("groups").isNull(), F.array(F.col("key"))).otherwise(parts))).drop("k", "groups")

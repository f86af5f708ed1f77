"""Exact duplicates by an extendible-hash index kept on shared files; DataFrame operations only.

The key of a text is its 64-bit hash. A directory over the leading bits of the key starts as one bucket; each bucket
with more than ``bucket_entries`` different keys is split by one more bit, which doubles the directory wherever its
depth is reached. Keys are counted once per different value, so copies never make a bucket overfull. The index has an
entry per key, (bucket, key, rows), and is written in ranges of buckets, one range per owner task.

A key of one row is settled by its entry. Only texts whose key has several rows move: each finds its bucket through the
directory, and the bucket's owner compares the bytes of those with the same key. Texts that collide in the key form a
chain of different texts, told apart in order. Rows then probe directory, bucket, key and chain.

Defined results: a null text counts as empty; empty texts equal each other; null ids are smaller than all others; rows
that repeat an id belong to the group like any other; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import BROADCAST_ROWS, counted_broadcast, read_table, shuffle_partitions, text_or_empty, written

#: Leading bits of a key that the directory can use; bounds it to 2**16 rows. Buckets overfull beyond keep longer chains.
DIRECTORY_BITS = 16
BUCKET_ENTRIES = 200_000
#: Bits of the hash that make a key; tests take few, so that keys collide.
KEY_BITS = 64


def key_of(text: Column, key_bits: int = KEY_BITS) -> Column:
    """The leading ``key_bits`` of a text's hash, as a 64-bit key."""
    whole = F.xxhash64(text)
    return whole if key_bits == 64 else F.shiftleft(F.shiftright(whole, 64 - key_bits), 64 - key_bits)


def cell_of(key: str) -> Column:
    return F.shiftrightunsigned(key, 64 - DIRECTORY_BITS).cast("int")


def directory(keys: DataFrame, bucket_entries: int = BUCKET_ENTRIES) -> DataFrame:
    """(cell, bucket): the bucket each cell of the full directory points to. ``keys`` needs key and cell.

    A bucket number is its leading bits behind a 1, so buckets of different depth differ. At most 2**16 rows.
    """
    cells = keys.groupBy("key", "cell").agg(F.lit(1).alias("one")).groupBy("cell").agg(F.count("*").alias("entries"))
    depths = cells.withColumn("depth", F.explode(F.sequence(F.lit(0), F.lit(DIRECTORY_BITS))))
    prefixed = depths.withColumn(
        "bucket", F.expr(f"shiftright(cell, {DIRECTORY_BITS} - depth) + shiftleft(1, depth)")
    )
    fits = (
        prefixed.groupBy("depth", "bucket").agg(F.sum("entries").alias("entries"), F.collect_list("cell").alias("cells"))
        .where((F.col("entries") <= bucket_entries) | (F.col("depth") == DIRECTORY_BITS))
        .select("depth", "bucket", F.explode("cells").alias("cell"))
    )
    return fits.groupBy("cell").agg(F.min_by("bucket", "depth").alias("bucket"))


def build_index(docs: DataFrame, text_col: str = "text", bucket_entries: int = BUCKET_ENTRIES, key_bits: int = KEY_BITS) -> tuple[DataFrame, DataFrame]:
    """The directory (cell, bucket) and the entries (bucket, key, rows), in ranges of buckets.

    Keys are counted within each task before the shuffle, so a group that holds a third of all rows is one row per task.
    """
    keys = docs.select(key_of(text_or_empty(text_col), key_bits).alias("key")).groupBy("key").agg(F.count("*").alias("rows"))
    keys = written(keys.withColumn("cell", cell_of("key")), "keys")
    cells = written(directory(keys.select("key", "cell"), bucket_entries), "directory")
    entries = keys.join(F.broadcast(cells), "cell").select("bucket", "key", "rows")  # the directory has at most 2**16 rows
    owned = entries.repartitionByRange(shuffle_partitions(docs.sparkSession), "bucket", "key").sortWithinPartitions("bucket", "key")
    return cells, written(owned, "hash-index")


def _shared_keys(entries: DataFrame) -> DataFrame:
    return counted_broadcast(entries.where("rows > 1").select("bucket", "key"), BROADCAST_ROWS)


def chains(rows: DataFrame, cells: DataFrame, entries: DataFrame, carried: dict[str, Column]) -> DataFrame:
    """(bucket, key, body, ...): the different texts of keys with several rows, ``carried`` aggregated over equal ones.

    ``rows`` have key and body. Texts of other keys stay where they are: the keys asked for are broadcast behind a count,
    and beyond it joined by shuffle. Equal texts are combined within each task before they move.
    """
    placed = rows.withColumn("cell", cell_of("key")).join(F.broadcast(cells), "cell")
    return placed.join(_shared_keys(entries), ["bucket", "key"]).groupBy("bucket", "key", "body").agg(*[c.alias(n) for n, c in carried.items()])


def find_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bucket_entries: int = BUCKET_ENTRIES, key_bits: int = KEY_BITS) -> DataFrame:
    """One row per document: doc_id, keep_id, group_size, kept, text_sha256.

    Of equal texts the row with the largest id is kept; rows that repeat that id are all marked kept.
    """
    body = text_or_empty(text_col)
    cells, entries = build_index(docs, text_col, bucket_entries, key_bits)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), key_of(body, key_bits).alias("key"), body.alias("body"))
    found = chains(rows, cells, entries, {"keep_id": F.max("doc_id"), "group_size": F.count("*")})
    order = F.row_number().over(W.partitionBy("bucket", "key").orderBy("text_sha256"))
    chain = written(found.withColumn("text_sha256", F.sha2("body", 256)).drop("body").withColumn("chain", order), "chains")
    links = chain.groupBy("bucket", "key").agg(F.sort_array(F.collect_list(F.struct("chain", "text_sha256", "keep_id", "group_size"))).alias("links"))
    probes = rows.select("doc_id", "key", F.sha2("body", 256).alias("text_sha256")).withColumn("cell", cell_of("key")).join(F.broadcast(cells), "cell")
    met = probes.join(counted_broadcast(written(links, "links"), BROADCAST_ROWS), ["bucket", "key"], "left")
    # a chain of one text was compared byte by byte when it was made; in a longer one the digest tells which it is
    own = F.when(F.size("links") == 1, F.element_at("links", 1)).otherwise(F.element_at(F.filter("links", lambda x: x["text_sha256"] == F.col("text_sha256")), 1))
    met = met.withColumn("own", F.when(F.col("links").isNotNull(), own))
    keep = F.when(F.col("own").isNull(), F.col("doc_id")).otherwise(F.col("own.keep_id"))
    return met.select("doc_id", keep.alias("keep_id"), F.coalesce("own.group_size", F.lit(1).cast("long")).alias("group_size"), F.col("doc_id").eqNullSafe(keep).alias("kept"), "text_sha256")


def drop_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bucket_entries: int = BUCKET_ENTRIES, key_bits: int = KEY_BITS) -> DataFrame:
    """The rows that stay, with all columns of ``docs`` as they were; exactly one row per different text.

    Rows alone with their key pass as they are. The owner of a chain carries the surviving row, so no join brings texts
    back. Rows that repeat both text and id are decided by their other columns, which must be comparable types.
    """
    others = [c for c in docs.columns if c not in (id_col, text_col)]
    cells, entries = build_index(docs, text_col, bucket_entries, key_bits)
    whole = F.struct(F.col(id_col).alias("i"), F.col(text_col).isNotNull().alias("t"), *[F.col(c).alias(f"c{k}") for k, c in enumerate(others)])
    rows = docs.select(text_or_empty(text_col).alias("body"), whole.alias("row")).withColumn("key", key_of(F.col("body"), key_bits))
    many = chains(rows, cells, entries, {"row": F.max("row")}).select("body", "row")
    alone = rows.join(_shared_keys(entries).select("key"), "key", "left_anti").select("body", "row")
    columns = {id_col: F.col("row.i"), text_col: F.when(F.col("row.t"), F.col("body"))} | {c: F.col(f"row.c{k}") for k, c in enumerate(others)}
    return alone.unionByName(many).select([columns[c].alias(c) for c in docs.columns])


def op9_exact_dedup(spark, sf_dir: str) -> DataFrame:
    return find_duplicates(read_table(spark, sf_dir, "documents"))


ORACLE_SQL = """
WITH t AS (SELECT doc_id, coalesce(text, '') AS body FROM documents)
SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
       doc_id = max(doc_id) OVER w AS kept, sha256(body) AS text_sha256
FROM t WINDOW w AS (PARTITION BY body)
"""

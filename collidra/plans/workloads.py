"""The given tables as the sets and vectors that the experiments run on."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import features
from ..operators.index import IndexParams
from ..sources import dealt, read_table

#: The table whose rows bound the items of each workload.
TABLE = {
    "docs_words": "documents", "docs_char3": "documents", "pages_url": "pages", "pages_full": "pages", "part_cat": "part", "lines_cat": "lineitem",
    "cust_parts": "customer", "part_custs": "part", "user_events": "customer", "turns_words": "conversations", "bench_words": "benchmark",
}
#: Settings of fewer address bits than this are crowded on purpose, to study full reservoirs.
CROWDED_BITS = 12


def grows(p: IndexParams) -> bool:
    return p.share >= 1 and p.bits >= CROWDED_BITS


def sized(spark: SparkSession, d: str, name: str, p: IndexParams) -> IndexParams:
    """``p`` with the address bits that the workload's table needs: at a fixed width, tables of reservoirs would hold a
    random sample of a large corpus."""
    return p.grown(read_table(spark, d, TABLE[name]).count()) if grows(p) else p


def _rows(spark: SparkSession, d: str, name: str, columns: list[str], deal: bool) -> DataFrame:
    rows = read_table(spark, d, name, columns)
    return dealt(rows) if deal else rows


def docs_words(spark: SparkSession, d: str, deal: bool = False) -> DataFrame:
    return features.token_set(_rows(spark, d, "documents", ["doc_id", "text"], deal), "doc_id", "text")


def docs_char3(spark: SparkSession, d: str, deal: bool = False) -> DataFrame:
    return features.char_ngrams(_rows(spark, d, "documents", ["doc_id", "text"], deal), "doc_id", "text", 3)


def pages_url(spark: SparkSession, d: str, deal: bool = False) -> DataFrame:
    return features.url_tokens(_rows(spark, d, "pages", ["page_id", "url"], deal), "page_id", "url")


def pages_full(spark: SparkSession, d: str, deal: bool = False) -> DataFrame:
    return features.url_tokens(_rows(spark, d, "pages", ["page_id", "url", "html"], deal), "page_id", "url", "html")


#: Workloads whose rows cost enough to deal a small table out.
DEALT = ("docs_words", "docs_char3", "pages_url", "pages_full")


def load(spark: SparkSession, d: str, name: str) -> DataFrame:
    """The sets of a workload, a small table's rows dealt to all cores."""
    make = globals()[name]
    return make(spark, d, deal=True) if name in DEALT else make(spark, d)


PART_COLUMNS = ["p_brand", "p_type", "p_size"]


def part_cat(spark: SparkSession, d: str) -> DataFrame:
    return features.categorical_set(read_table(spark, d, "part"), "p_partkey", PART_COLUMNS)


LINE_KEY = "concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, cast(round(l_quantity) AS bigint), cast(round(l_extendedprice * 100) AS bigint))"
LINE_TAGS = {
    "brand": "p_brand", "type": "p_type", "size": "cast(p_size AS {s})", "flag": "l_returnflag", "status": "l_linestatus", "quantity": "cast(cast(round(l_quantity) AS bigint) AS {s})",
    "discount": "cast(cast(round(l_discount * 100) AS bigint) AS {s})", "tax": "cast(cast(round(l_tax * 100) AS bigint) AS {s})",
    "month": "cast(year(l_shipdate) * 100 + month(l_shipdate) AS {s})", "priority": "o_orderpriority", "order": "o_orderstatus",
}


def lines_cat(spark: SparkSession, d: str) -> DataFrame:
    """Eleven tags per order line; the id is a hash of what tells lines apart, as no column pair is a key.

    The id has 48 bits, so some lines of a large table share one; as in the SQL they are one item with the tags of all.
    """
    line, orders, part = (read_table(spark, d, t) for t in ("lineitem", "orders", "part"))
    rows = line.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(part, F.col("l_partkey") == F.col("p_partkey"))
    ident = F.conv(F.substring(F.md5(F.expr(LINE_KEY).cast("binary")), 1, 12), 16, 10).cast("long")
    tags = {k: F.expr(v.format(s="string")) for k, v in LINE_TAGS.items()}
    return features.merged(features.categorical_set(rows.select(ident.alias("line_id"), *[c.alias(k) for k, c in tags.items()]), "line_id", list(tags)))


def cust_parts(spark: SparkSession, d: str) -> DataFrame:
    return features.adjacency_set(edges(spark, d), "o_custkey", "l_partkey")


def part_custs(spark: SparkSession, d: str) -> DataFrame:
    return features.adjacency_set(edges(spark, d), "l_partkey", "o_custkey")


def edges(spark: SparkSession, d: str) -> DataFrame:
    line = read_table(spark, d, "lineitem", ["l_orderkey", "l_partkey"])
    return line.join(read_table(spark, d, "orders", ["o_orderkey", "o_custkey"]), F.col("l_orderkey") == F.col("o_orderkey"))


def user_events(spark: SparkSession, d: str) -> DataFrame:
    ev = read_table(spark, d, "events", ["user_id", "event_type", "props"])
    tag = F.concat_ws(":", "event_type", F.get_json_object("props", "$.k"))
    return ev.groupBy(F.col("user_id").alias("item_id")).agg(F.sort_array(F.collect_set(features.feature_id(tag))).alias("features"))


def turns_words(spark: SparkSession, d: str) -> DataFrame:
    rows = read_table(spark, d, "conversations").select((F.col("conv_id") * 100 + F.col("turn")).alias("turn_id"), "text")
    return features.token_set(rows, "turn_id", "text")


def bench_words(spark: SparkSession, d: str) -> DataFrame:
    return features.token_set(read_table(spark, d, "benchmark"), "item_id", "text")


def vectors(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "embeddings").select(F.col("vec_id").alias("item_id"), F.col("embedding").alias("vector"))

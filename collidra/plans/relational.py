"""Relational operators around the engine, each on a given table and with the same question in SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from ..functions import register_sql_functions
from ..functions.portable import parameters
from ..operators import index
from ..sources import read_csv, read_json, read_libsvm, read_table, sample_rows, scratch, write_graph, write_libsvm
from . import core, sql
from . import workloads as w

QUERIES: dict = {}
ORACLES: dict = {}


def add(name: str, oracle: str | None = None):
    def keep(fn):
        QUERIES[name] = fn
        if oracle:
            ORACLES[name] = oracle
        return fn

    return keep


def _t(s, d, name, *cols):
    return read_table(s, d, name, list(cols) or None)


# ---------------------------------------------------------------- scans and filters

add("scan_filter_project", "SELECT doc_id, lang, n_chars FROM documents WHERE lang = 'en' AND n_chars BETWEEN 200 AND 5000 AND source IN ('src1', 'src2', 'src3')")(
    lambda s, d: read_table(s, d, "documents", ["doc_id", "lang", "n_chars"], (F.col("lang") == "en") & F.col("n_chars").between(200, 5000) & F.col("source").isin("src1", "src2", "src3"))
)


@add("filtered_neighbors", sql.query([("docs", "SELECT doc_id, text FROM documents WHERE lang = 'en'"), ("feats", sql.FEATURES["docs_words"].replace("FROM documents", "FROM docs")), *sql.graph(core.BASE, 5)], "SELECT query_id, neighbor_id, rank, collisions FROM graph JOIN labels ON doc_id = neighbor_id WHERE quality = 1"))
def filtered_neighbors(s, d):
    """Before hashing: one language, pushed to the scan. After ranking: only neighbours labelled as good."""
    from ..operators.features import token_set

    docs = read_table(s, d, "documents", ["doc_id", "text"], F.col("lang") == "en")
    good = read_table(s, d, "labels", ["doc_id"], "quality = 1")
    graph = index.knn_graph(token_set(docs, "doc_id", "text"), core.BASE, 5)
    return graph.join(good, F.col("neighbor_id") == F.col("doc_id")).drop("doc_id")


add("sample_rows", "SELECT doc_id FROM documents ORDER BY ((doc_id % {0}) * {1} + {2}) % 2147483647, doc_id LIMIT 100".format(2**31, *parameters(7, 2)))(lambda s, d: sample_rows(_t(s, d, "documents", "doc_id"), "doc_id", 100))

# ---------------------------------------------------------------- joins

add("join_broadcast", "SELECT p_brand, l_returnflag, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1, 2")(
    lambda s, d: _t(s, d, "lineitem", "l_partkey", "l_returnflag").join(_t(s, d, "part", "p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand", "l_returnflag").agg(F.count("*").alias("n"))
)
add("join_sort_merge", "SELECT o_custkey, count(DISTINCT l_partkey) AS parts FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")(
    lambda s, d: _t(s, d, "lineitem", "l_orderkey", "l_partkey").join(_t(s, d, "orders", "o_orderkey", "o_custkey").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey").agg(F.count_distinct("l_partkey").alias("parts"))
)
add("join_shuffle_hash", sql.query([*sql.addresses(core.HEAVY, features="docs_words"), *sql.reservoirs(core.HEAVY)], "SELECT a.item_id, count(*) AS met FROM addr a JOIN res r USING (table_id, address) GROUP BY 1"))(
    lambda s, d: _shuffle_hash(w.docs_words(s, d))
)


def _shuffle_hash(sets):
    addr = index.addresses(sets, core.HEAVY)
    res = index.index_of(addr, core.HEAVY).reservoirs
    return addr.join(res.hint("shuffle_hash"), ["table_id", "address"]).groupBy("item_id").agg(F.sum(F.size("members")).cast("long").alias("met"))


add("join_semi", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")(lambda s, d: _t(s, d, "documents", "doc_id", "lang").join(_t(s, d, "labels", "doc_id"), "doc_id", "left_semi"))
add("join_anti", "SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")(lambda s, d: _t(s, d, "documents", "doc_id", "lang").join(_t(s, d, "labels", "doc_id"), "doc_id", "left_anti"))
add("join_left_outer", sql.query(sql.graph(core.BASE, 5, features="docs_words"), "SELECT doc_id, coalesce(n, 0) AS neighbors FROM documents LEFT JOIN (SELECT query_id, count(*) AS n FROM graph GROUP BY 1) ON doc_id = query_id"))(
    lambda s, d: _t(s, d, "documents", "doc_id").join(core.graph(s, d, "docs_words", core.BASE, 5).groupBy("query_id").agg(F.count("*").alias("n")), F.col("doc_id") == F.col("query_id"), "left").select("doc_id", F.coalesce("n", F.lit(0)).alias("neighbors"))
)
add("join_theta", sql.query([*sql.feats("bench_words", "q"), *sql.feats("docs_words", "d")], "SELECT q.item_id AS query_id, count(*) AS near_sizes FROM (SELECT item_id, count(*) AS n FROM qfeats GROUP BY 1) q JOIN (SELECT item_id, count(*) AS n FROM dfeats GROUP BY 1) d ON least(q.n, d.n) >= 0.4225 * greatest(q.n, d.n) GROUP BY 1"))(
    lambda s, d: _theta(w.bench_words(s, d), w.docs_words(s, d))
)


def _theta(queries: DataFrame, data: DataFrame, tau2: float = 0.4225) -> DataFrame:
    """Pairs whose sizes allow a cosine of tau: sqrt(min/max) bounds it. The queries are a stated set and are broadcast."""
    q = F.broadcast(queries.select(F.col("item_id").alias("query_id"), F.size("features").alias("x")))
    y = data.select(F.size("features").alias("y"))
    return y.join(q, F.least("x", "y") >= F.lit(tau2) * F.greatest("x", "y")).groupBy("query_id").agg(F.count("*").alias("near_sizes"))


add("join_range", "SELECT a.event_id, count(*) AS followed FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY 1")(lambda s, d: _range_join(_t(s, d, "events", "event_id", "user_id", "ts")))


def _range_join(ev: DataFrame, seconds: int = 3600) -> DataFrame:
    """An equi-join on time buckets with the range as a filter, so that no user's events meet all others."""
    at = ev.withColumn("sec", F.unix_micros(F.col("ts").cast("timestamp")))
    a = at.withColumn("slot", F.floor(F.col("sec") / (seconds * 1_000_000)))
    b = a.select("user_id", F.col("sec").alias("later"), F.explode(F.array(F.col("slot"), F.col("slot") - 1)).alias("slot"))
    near = a.join(b, ["user_id", "slot"]).where((F.col("later") > F.col("sec")) & (F.col("later") <= F.col("sec") + seconds * 1_000_000))
    return near.groupBy("event_id").agg(F.count("*").alias("followed"))


@add("join_asof", "SELECT c.event_id, arg_max(v.event_id, v.event_id) AS before_id FROM events c JOIN events v ON c.user_id = v.user_id AND v.event_id < c.event_id AND v.event_type <> 'click' WHERE c.event_type = 'click' GROUP BY 1")
def join_asof(s, d):
    """The latest other event of the user before each click: one sort per user and no join."""
    ev = _t(s, d, "events", "event_id", "user_id", "event_type")
    past = W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") != "click", F.col("event_id")), ignorenulls=True).over(past)
    return ev.withColumn("before_id", last).where("event_type = 'click' AND before_id IS NOT NULL").select("event_id", "before_id")


add("join_self_bucket", sql.query(sql.addresses(core.BASE, features="pages_url"), "SELECT DISTINCT x.item_id AS a, y.item_id AS b FROM addr x JOIN addr y USING (table_id, address) WHERE x.item_id < y.item_id AND table_id = 0"))(
    lambda s, d: _bucket_pairs(index.addresses(w.pages_url(s, d), w.sized(s, d, "pages_url", core.BASE)).where("table_id = 0"))
)


def _bucket_pairs(addr: DataFrame) -> DataFrame:
    return addr.withColumnRenamed("item_id", "a").join(addr.withColumnRenamed("item_id", "b"), ["table_id", "address"]).where("a < b").select("a", "b").distinct()


# ---------------------------------------------------------------- aggregates

add("agg_hash", sql.query(sql.addresses(core.BASE, features="docs_words"), "SELECT table_id, address, count(*) AS n FROM addr GROUP BY 1, 2"))(lambda s, d: index.addresses(w.docs_words(s, d), w.sized(s, d, "docs_words", core.BASE)).groupBy("table_id", "address").agg(F.count("*").alias("n")))
add("agg_distinct", f"SELECT lang, count(DISTINCT f) AS features FROM ({sql.FEATURES['docs_words']}) JOIN documents ON doc_id = item_id GROUP BY 1")(
    lambda s, d: core._long(w.docs_words(s, d)).join(_t(s, d, "documents", "doc_id", "lang"), F.col("item_id") == F.col("doc_id")).groupBy("lang").agg(F.count_distinct("feature").alias("features"))
)


@add("agg_approx", sql.query(sql.feats("docs_words"), """SELECT true AS distinct_close, true AS median_close, true AS most_close, (SELECT count(DISTINCT f) FROM feats) AS features,
(SELECT max(c) FROM (SELECT count(*) AS c FROM feats GROUP BY f)) AS most, (SELECT quantile_disc(n, 0.5) FROM (SELECT count(*) AS n FROM feats GROUP BY item_id)) AS median"""))
def agg_approx(s, d):
    """Sketches beside what they estimate: distinct features within 6 %, rows of the most frequent one and the median size within 5 %."""
    long = core._long(w.docs_words(s, d))
    sizes = long.groupBy("item_id").agg(F.count("*").alias("n")).agg(F.percentile_approx("n", 0.5, 100).alias("near"), F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY n)").cast("long").alias("median"))
    near = long.agg(F.approx_count_distinct("feature", 0.02).alias("distinct_near"), F.count_distinct("feature").alias("features"), F.expr("approx_top_k(feature, 1)[0].count").alias("most_near"))
    close = lambda a, b, by: F.abs(F.col(a) - F.col(b)) <= by * F.col(b)
    most = long.groupBy("feature").count().agg(F.max("count").alias("most"))
    both = near.crossJoin(F.broadcast(sizes)).crossJoin(F.broadcast(most))
    return both.select(close("distinct_near", "features", 0.06).alias("distinct_close"), close("near", "median", 0.05).alias("median_close"), close("most_near", "most", 0.05).alias("most_close"), "features", "most", "median")


_CUBE = "SELECT lang, source, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY {}"


def _sums():
    return F.count("*").alias("n"), F.sum("n_chars").alias("chars")


add("agg_cube", _CUBE.format("CUBE (lang, source)"))(lambda s, d: _t(s, d, "documents", "lang", "source", "n_chars").cube("lang", "source").agg(*_sums()))
add("agg_rollup", _CUBE.format("ROLLUP (lang, source)"))(lambda s, d: _t(s, d, "documents", "lang", "source", "n_chars").rollup("lang", "source").agg(*_sums()))
add("agg_grouping_sets", _CUBE.format("GROUPING SETS ((lang), (source))"))(
    lambda s, d: _t(s, d, "documents", "lang", "source", "n_chars").groupingSets([["lang"], ["source"]], "lang", "source").agg(*_sums())
)
add("agg_pivot", "SELECT source, sum((lang = 'en')::INT)::BIGINT AS en, sum((lang = 'fr')::INT)::BIGINT AS fr, sum((lang = 'de')::INT)::BIGINT AS de FROM documents GROUP BY 1")(
    lambda s, d: _t(s, d, "documents", "lang", "source").groupBy("source").pivot("lang", ["en", "fr", "de"]).agg(F.count(F.lit(1))).na.fill(0)
)

# ---------------------------------------------------------------- windows, order, sets

_GOLD = [*sql.feats("pages_url"), *sql.gold(10)]


def _url_gold(s, d):
    return core.url_gold(w.load(s, d, "pages_url"), 10)


def _win(order: str = "similarity"):
    return W.partitionBy("query_id").orderBy(F.col(order).desc(), "neighbor_id")


add("win_rank", sql.query(_GOLD, "SELECT query_id, neighbor_id, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS quarter FROM gold WINDOW w AS (PARTITION BY query_id ORDER BY similarity DESC, neighbor_id), v AS (PARTITION BY query_id ORDER BY similarity DESC)"))(
    lambda s, d: _url_gold(s, d).select("query_id", "neighbor_id", F.row_number().over(_win()).alias("rn"), F.rank().over(W.partitionBy("query_id").orderBy(F.desc("similarity"))).alias("rk"), F.dense_rank().over(W.partitionBy("query_id").orderBy(F.desc("similarity"))).alias("dr"), F.ntile(4).over(_win()).alias("quarter"))
)
add("win_analytic", sql.query(_GOLD, "SELECT query_id, neighbor_id, round(similarity - lead(similarity) OVER w, 6) AS gap, first_value(neighbor_id) OVER w AS best, lag(neighbor_id) OVER w AS before FROM gold WINDOW w AS (PARTITION BY query_id ORDER BY similarity DESC, neighbor_id)"))(
    lambda s, d: _url_gold(s, d).select("query_id", "neighbor_id", F.round(F.col("similarity") - F.lead("similarity").over(_win()), 6).alias("gap"), F.first("neighbor_id").over(_win()).alias("best"), F.lag("neighbor_id").over(_win()).alias("before"))
)
add("win_rows_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS inserted FROM events")(
    lambda s, d: _t(s, d, "events", "event_id", "user_id").select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, 0)).alias("inserted"))
)
add("win_range_frame", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW), 4) AS day_sum FROM events")(
    lambda s, d: _t(s, d, "events", "event_id", "user_id", "ts", "value").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.round(F.sum("value").over(W.partitionBy("user_id").orderBy("us").rangeBetween(-86_400_000_000, 0)), 4).alias("day_sum"))
)
add("sort_limit", sql.query(sql.graph(core.BASE, 10, features="docs_words"), "SELECT query_id, neighbor_id, collisions FROM graph ORDER BY collisions DESC, query_id, neighbor_id LIMIT 25"))(
    lambda s, d: core.graph(s, d, "docs_words", core.BASE, 10).select("query_id", "neighbor_id", "collisions").orderBy(F.desc("collisions"), "query_id", "neighbor_id").limit(25)
)
add("topk_per_group", "SELECT source, doc_id, n_chars FROM documents QUALIFY row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) <= 3")(
    lambda s, d: _t(s, d, "documents", "source", "doc_id", "n_chars").withColumn("r", F.row_number().over(W.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id"))).where("r <= 3").drop("r")
)
_PAIRS = [*sql.graph(core.BASE, 5, features="pages_url"), *sql.overlaps(), ("gold", sql.ranked(f"SELECT query_id, neighbor_id, {sql.COSINE} AS similarity FROM over", 5, "similarity"))]


def _both(s, d):
    pair = ["query_id", "neighbor_id"]
    return core.graph(s, d, "pages_url", core.BASE, 5).select(*pair), core.url_gold(w.load(s, d, "pages_url"), 5).select(*pair)


for _name, _op, _fn in (("union", "UNION", lambda a, b: a.unionByName(b).distinct()), ("intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("except", "EXCEPT", lambda a, b: a.exceptAll(b))):
    add(f"set_{_name}", sql.query(_PAIRS, f"SELECT query_id, neighbor_id FROM graph {_op} SELECT query_id, neighbor_id FROM gold"))(lambda s, d, fn=_fn: fn(*_both(s, d)))

# ---------------------------------------------------------------- functions

add("fn_string", "SELECT page_id, length(html) AS size, upper(substr(url, 1, 5)) AS scheme, md5(url) AS digest, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS plain FROM pages")(
    lambda s, d: _t(s, d, "pages").select("page_id", F.length("html").cast("long").alias("size"), F.upper(F.substring("url", 1, 5)).alias("scheme"), F.md5(F.col("url").cast("binary")).alias("digest"), F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("long").alias("plain"))
)
add("fn_date", "SELECT o_orderkey, strftime(o_orderdate, '%Y-%m') AS month, quarter(o_orderdate) AS quarter, date_diff('day', DATE '1992-01-01', o_orderdate::DATE) AS age FROM orders")(
    lambda s, d: _t(s, d, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", F.date_format("o_orderdate", "yyyy-MM").alias("month"), F.quarter("o_orderdate").alias("quarter"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("age"))
)
add("fn_math", "SELECT p_partkey, round(ln(1 / (p_size / 60.0::DOUBLE)) / ln(1 / (p_size / 120.0::DOUBLE)), 6) AS rho, ceil(ln(1e6) / ln(120.0::DOUBLE / p_size))::BIGINT AS k, round(1 - pow(1 - pow(p_size / 60.0::DOUBLE, 2), 32), 6) AS retrieval FROM part")(
    lambda s, d: _t(s, d, "part", "p_partkey", "p_size").select(
        "p_partkey", F.round(F.log(1 / (F.col("p_size") / 60.0)) / F.log(1 / (F.col("p_size") / 120.0)), 6).alias("rho"), F.ceil(F.log(F.lit(1e6)) / F.log(F.lit(120.0) / F.col("p_size"))).cast("long").alias("k"),
        F.round(1 - F.pow(1 - F.pow(F.col("p_size") / 60.0, F.lit(2)), F.lit(32)), 6).alias("retrieval"),
    )
)
add("fn_array", sql.query(sql.feats("part_cat"), "SELECT x.item_id, count(*) AS shared FROM feats x JOIN feats y ON x.f = y.f AND y.item_id = 1 GROUP BY 1"))(
    lambda s, d: w.part_cat(s, d).join(F.broadcast(w.part_cat(s, d).where("item_id = 1").select(F.col("features").alias("y"))), F.size(F.array_intersect("features", "y")) > 0).select("item_id", F.size(F.array_intersect("features", "y")).cast("long").alias("shared"))
)
add("fn_map", sql.query(sql.feats("part_cat"), "SELECT x.item_id, round(count(*) / 3.0::DOUBLE, 6) AS dot FROM feats x JOIN feats y ON x.f = y.f AND y.item_id = 1 GROUP BY 1"))(lambda s, d: _weighted_dot(s, d))


def _weighted_dot(s, d):
    from ..functions import sparse_dot
    from ..operators.features import unit_weights

    u = unit_weights(w.part_cat(s, d))
    one = F.broadcast(u.where("item_id = 1").select(F.col("weights").alias("y")))
    return u.join(one, F.arrays_overlap(F.map_keys("weights"), F.map_keys("y"))).select("item_id", F.round(sparse_dot(F.col("weights"), F.col("y")), 6).alias("dot"))


add("fn_json", "SELECT json_extract_string(props, '$.k') AS k, count(*) AS n FROM events GROUP BY 1")(lambda s, d: _t(s, d, "events", "props").groupBy(F.get_json_object("props", "$.k").alias("k")).agg(F.count("*").alias("n")))


@add("sql_functions", sql.query([*sql.feats("bench_words"), *sql.overlaps()], "SELECT query_id AS a, neighbor_id AS b, round(a / (x + y - a)::DOUBLE, 6) AS jaccard, round(a / sqrt(x::DOUBLE * y), 6) AS cosine FROM over"))
def sql_functions(s, d):
    register_sql_functions(s)
    w.bench_words(s, d).createOrReplaceTempView("bench_sets")
    return s.sql("SELECT p.item_id AS a, q.item_id AS b, round(jaccard(p.features, q.features), 6) AS jaccard, round(cosine_set(p.features, q.features), 6) AS cosine FROM bench_sets p JOIN bench_sets q ON p.item_id <> q.item_id AND arrays_overlap(p.features, q.features)")


@add("udf_arrow", sql.query(sql.feats("docs_words"), "SELECT item_id, count(*) AS n FROM feats GROUP BY 1"))
def udf_arrow(s, d):
    """The same answer as size(), by way of an Arrow batch function, the form that bulk hashing uses."""
    import pyarrow as pa
    import pyarrow.compute as pc

    n = F.arrow_udf(lambda v: pc.list_value_length(v).cast(pa.int64()), "long")
    return w.docs_words(s, d).select("item_id", n("features").alias("n")).where("n > 0")


@add("udf_scalar", sql.query(sql.feats("docs_words"), "SELECT item_id, min(f) % 97 AS bucket FROM feats GROUP BY 1"))
def udf_scalar(s, d):
    """A row-at-a-time function, optimised by Arrow: the slow path, kept for what has no batch form."""
    bucket = F.udf(lambda fs: min(fs) % 97 if fs else None, "long", useArrow=True)
    return w.docs_words(s, d).where(F.size("features") > 0).select("item_id", bucket("features").alias("bucket"))


@add("udaf_reservoir", sql.query([*sql.addresses(core.HEAVY, features="docs_words"), *sql.reservoirs(core.HEAVY)], "SELECT table_id, address, item_id FROM res"))
def udaf_reservoir(s, d):
    """Reservoirs by a grouped aggregate function over Arrow batches: the r smallest priorities, as the operator's."""
    from ..operators.reservoir import priority

    @F.pandas_udf("array<long>")
    def held(ids: pd.Series, order: pd.Series) -> list:
        return ids.iloc[order.argsort(kind="stable")[: core.HEAVY.r]].tolist() if len(ids) else []

    addr = index.addresses(w.docs_words(s, d), core.HEAVY).withColumn("pr", priority(core.HEAVY.seed))
    return addr.groupBy("table_id", "address").agg(held("item_id", "pr").alias("members")).select("table_id", "address", F.explode("members").alias("item_id"))


@add("udtf_knn", sql.query([*sql.graph(core.BASE, 5, features="bench_words")], "SELECT query_id, neighbor_id, collisions FROM graph"))
def udtf_knn(s, d):
    """A graph as a table function over a query's bag of candidates, usable in SQL with LATERAL."""
    from collections import Counter

    @F.udtf(returnType="neighbor_id long, collisions long")
    class TopOf:
        def eval(self, query_id: int, bag: list, k: int):
            counts = Counter(x for x in bag if x != query_id)
            yield from sorted(counts.items(), key=lambda e: (-e[1], e[0]))[:k]

    s.udtf.register("knn_of_bag", TopOf)
    addr = index.addresses(w.bench_words(s, d), w.sized(s, d, "bench_words", core.BASE))
    index.index_of(addr, core.BASE).probe(addr).groupBy("query_id").agg(F.flatten(F.collect_list("members")).alias("bag")).createOrReplaceTempView("bags")
    return s.sql("SELECT b.query_id, t.neighbor_id, t.collisions FROM bags b, LATERAL knn_of_bag(b.query_id, b.bag, 5) t")


# ---------------------------------------------------------------- round trips

@add("roundtrip_libsvm", sql.query(sql.feats("bench_words"), "SELECT n, total, count(*) AS items FROM (SELECT count(*) AS n, sum(f)::BIGINT AS total FROM feats GROUP BY item_id) GROUP BY 1, 2"))
def roundtrip_libsvm(s, d):
    path = f"{scratch(s)}/libsvm"
    write_libsvm(w.bench_words(s, d), path)
    back = read_libsvm(s, path).select(F.size("features").cast("long").alias("n"), F.aggregate("features", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"))
    return back.groupBy("n", "total").agg(F.count("*").alias("items"))


@add("roundtrip_json", "SELECT item_id, length(text) AS size FROM benchmark")
def roundtrip_json(s, d):
    path = f"{scratch(s)}/json"
    _t(s, d, "benchmark").write.json(path)
    return read_json(s, path, "item_id long, text string").select("item_id", F.length("text").cast("long").alias("size"))


@add("roundtrip_csv", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
def roundtrip_csv(s, d):
    path = f"{scratch(s)}/csv"
    _t(s, d, "nation").write.option("header", True).csv(path)
    return read_csv(s, path, T.StructType([T.StructField("n_nationkey", T.IntegerType()), T.StructField("n_name", T.StringType()), T.StructField("n_regionkey", T.IntegerType())]))


@add("roundtrip_index", core.ORACLES["knn_query_benchmark"])
def roundtrip_index(s, d):
    path = f"{scratch(s)}/index"
    index.build_index(w.docs_words(s, d), w.sized(s, d, "docs_words", core.BASE)).save(path, 8)
    return index.Index.load(s, path).knn(w.bench_words(s, d), 5)


@add("roundtrip_graph", core.ORACLES["knn_graph_hash"])
def roundtrip_graph(s, d):
    path = f"{scratch(s)}/graph"
    write_graph(core.graph(s, d, "docs_words", core.BASE, core.TOP), path, 8)
    return s.read.parquet(path)

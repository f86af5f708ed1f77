"""The comparisons of the experiments: accuracy, size and work of the engine side by side with other methods.

Seconds are in ``bench.py``; here is what a run's result decides, each with the same question in SQL. Methods whose draws
another engine cannot repeat (graphs, codebooks, the library's hashes) are held to a recall that they must reach.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import replace
from functools import partial, reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..operators import baselines, exact, features, hashing, index, metrics, planner, query
from ..operators.index import IndexParams
from ..sources import read_table, settled, stored
from . import core, sql
from . import workloads as w

QUERIES: dict = {}
ORACLES: dict = {}
ASKED = core.ASKED


def add(name: str, oracle: str | None = None):
    def keep(fn):
        QUERIES[name] = fn
        if oracle:
            ORACLES[name] = oracle
        return fn

    return keep


def _together(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


# ---------------------------------------------------------------- unbounded buckets against the engine

LIGHT = 200
CONTRAST = replace(core.URLS, k=2, tables=32)


def _vanilla_sql(p: IndexParams, k: int, x: str = "", whole: bool = False) -> list[tuple[str, str]]:
    """Pairs of the buckets of 2 to LIGHT items, or with ``whole`` of all, ranked by exact similarity; needs addr and over of the same prefix."""
    return [
        (f"{x}light", f"SELECT table_id, address FROM {x}addr GROUP BY 1, 2 HAVING count(*) " + ("> 1" if whole else f"BETWEEN 2 AND {LIGHT}")),
        (f"{x}pairs", f"SELECT DISTINCT x.item_id AS query_id, y.item_id AS neighbor_id FROM {x}addr x JOIN {x}light USING (table_id, address) JOIN {x}addr y USING (table_id, address) WHERE x.item_id <> y.item_id"),
        (f"{x}vgraph", sql.ranked(f"SELECT query_id, neighbor_id, coalesce({sql.COSINE}, 0) AS similarity FROM {x}pairs LEFT JOIN {x}over USING (query_id, neighbor_id)", k, "similarity")),
    ]


def _similarity_sql(graph: str, x: str = "") -> str:
    """(k, similarity): mean cosine of what is returned in the first 10 and 100."""
    return f"SELECT k, round(avg(coalesce(a / sqrt(x::DOUBLE * y), 0)), 6) AS similarity FROM {graph} LEFT JOIN {x}over USING (query_id, neighbor_id), (VALUES (10), (100)) v(k) WHERE rank <= k GROUP BY k"


def _accuracy_sql(method: str, graph: str, gold: str, x: str = "") -> str:
    return f"SELECT '{method}' AS method, k, recall, similarity, n_queries FROM ({sql.recall((10, 100), graph, gold)}) JOIN ({_similarity_sql(graph, x)}) USING (k)"


def _accuracy(method: str, graph: DataFrame, gold: DataFrame, sets: DataFrame, queries: DataFrame | None = None) -> DataFrame:
    near = metrics.similarity_at(graph, sets, sets if queries is None else queries, (10, 100)).drop("returned")
    return metrics.recall_at(graph, gold, (10, 100)).join(near, "k").select(F.lit(method).alias("method"), "k", "recall", "similarity", "n_queries")


@add("table_unbounded", sql.query(
    [*sql.graph(CONTRAST, 100, features="pages_url"), *sql.gold(100), *_vanilla_sql(CONTRAST, 100, whole=True)],
    _accuracy_sql("engine", "graph", "gold") + " UNION ALL " + _accuracy_sql("unbounded buckets", "vgraph", "gold"),
))
def table_unbounded(s, d):
    """S@10, S@100, R@10 and R@100 of counting over reservoirs and of exact similarities over unbounded buckets, same addresses."""
    sets, p = w.load(s, d, "pages_url"), w.sized(s, d, "pages_url", CONTRAST)
    gold = stored(core.url_gold(sets, 100, best=True))
    engine, vanilla = settled(index.knn_graph(sets, p, 100)), settled(baselines.vanilla_lsh(sets, p, 100))
    return _accuracy("engine", engine, gold, sets).unionByName(_accuracy("unbounded buckets", vanilla, gold, sets))


# ---------------------------------------------------------------- the largest table, with and without shared reservoirs

SHARES = (1.0, 0.3)


def _largest_sql() -> str:
    """Addresses once for all shares, only the stated queries' candidates, and exact neighbours by a scan of lists."""
    parts, ends = sql.addresses(core.LINES, "", "lines_cat"), []
    parts += [
        ("asked", f"SELECT * FROM addr WHERE {ASKED}"), ("sets", "SELECT item_id, list(f) AS fs, count(*)::DOUBLE AS n FROM feats GROUP BY 1"),
        ("best", f"SELECT q.item_id AS query_id, round(max(len(list_intersect(q.fs, d.fs)) / sqrt(q.n * d.n)), 6) AS top FROM (SELECT * FROM sets WHERE {ASKED}) q JOIN sets d ON q.item_id <> d.item_id GROUP BY 1"),
    ]
    for i, f in enumerate(SHARES):
        x, p = f"s{i}", replace(core.LINES, share=f)
        parts.append((f"{x}addr", "SELECT * FROM addr"))
        if f < 1:
            parts += [*sql.pointers(p, x), *sql.shared(p, x)]
            met = f"asked a JOIN {x}ptr USING (table_id, address) JOIN {x}sres s USING (reservoir_id)"
        else:
            parts += sql.reservoirs(p, x)
            met = f"asked a JOIN {x}res s USING (table_id, address)"
        counted = f"SELECT a.item_id AS query_id, s.item_id AS neighbor_id, count(*) AS collisions FROM {met} WHERE a.item_id <> s.item_id GROUP BY 1, 2"
        parts += [
            (f"{x}graph", sql.ranked(counted, 100)),
            (f"{x}near", f"SELECT query_id, rank, round(len(list_intersect(q.fs, d.fs)) / sqrt(q.n * d.n), 6) AS s FROM {x}graph JOIN sets q ON q.item_id = query_id JOIN sets d ON d.item_id = neighbor_id"),
            (f"{x}per", f"SELECT k, query_id, coalesce(max((rank <= k AND s >= top)::INT), 0) AS hit, sum(s) FILTER (rank <= k) AS total, count(*) FILTER (rank <= k) AS n FROM best LEFT JOIN {x}near USING (query_id), (VALUES (10), (100)) v(k) GROUP BY 1, 2"),
        ]
        held = f"SELECT count(*)::BIGINT AS stored_ids FROM {x}{'res' if f >= 1 else 'sres'}"
        ends.append(f"SELECT 'F={f}' AS method, k, round(avg(hit), 6) AS recall, round(sum(total) / sum(n), 6) AS similarity, count(*) AS n_queries, ({held}) AS stored_ids FROM {x}per GROUP BY k")
    return sql.query(parts, " UNION ALL ".join(ends))


@add("table_largest", _largest_sql())
def table_largest(s, d):
    """The table with most rows: accuracy and stored ids with a reservoir per address and with 30 % of them shared."""
    sets = stored(w.lines_cat(s, d))
    asked = sets.where(ASKED)
    best = exact.brute_force(asked, sets, 1)
    out = []
    for f in SHARES:
        p = replace(core.LINES, share=f)
        built = index.build_index(sets, w.sized(s, d, "lines_cat", p))
        found = built.knn(asked, 100, exclude_self=True)
        held = built.reservoirs.agg(F.sum(F.size("members")).cast("long").alias("stored_ids"))
        accuracy = metrics.best_recall_at(found, best, sets, asked, (10, 100)).select(F.lit(f"F={f}").alias("method"), "*")
        out.append(accuracy.crossJoin(F.broadcast(held)))
    return _together(out)


# ---------------------------------------------------------------- recall against work and size

GRID = (1, 2, 4, 8, 16)
LEVELS = (0.5, 0.6, 0.7, 0.8, 0.9)


def _grid(p: IndexParams) -> list[tuple[int, IndexParams]]:
    return [(t, replace(p, tables=t)) for t in GRID]


def _work_points(method: str, x: str) -> str:
    cost = f"(SELECT count(*)::DOUBLE / count(DISTINCT query_id) FROM {x}met)" if method == "engine" else f"(SELECT count(*)::DOUBLE / (SELECT count(DISTINCT item_id) FROM {x}feats) FROM {x}pairs)"
    graph = f"{x}graph" if method == "engine" else f"{x}vgraph"
    return f"SELECT '{method}' AS method, recall, {cost} AS seconds FROM ({sql.recall((100,), graph, 'tgold')})"


def _work_sql() -> str:
    parts, ends = [*sql.feats("pages_url", "t"), *sql.gold(100, "t")], []
    for i, (_, p) in enumerate(_grid(core.URLS)):
        x = f"w{i}"
        parts += [*sql.graph(p, 100, x, "pages_url"), *sql.overlaps(x), *_vanilla_sql(p, 100, x)]
        ends += [_work_points("engine", x), _work_points("unbounded buckets", x)]
    levels = ", ".join(f"({v}::DOUBLE)" for v in LEVELS)
    parts.append(("points", " UNION ALL ".join(ends)))
    parts.append(("seg", "SELECT *, lag(recall) OVER w AS r0, lag(seconds) OVER w AS s0 FROM points WINDOW w AS (PARTITION BY method ORDER BY recall, seconds)"))
    return sql.query(parts, f"SELECT method, level, round(s0 + (seconds - s0) * (level - r0) / (recall - r0), 4) AS candidates FROM seg, (VALUES {levels}) v(level) WHERE r0 <= level AND level <= recall AND recall > r0")


@add("work_at_recall", _work_sql())
def work_at_recall(s, d):
    """Candidates per query that either method looks at for the same R@100, interpolated on curves over the number of tables."""
    sets = w.load(s, d, "pages_url")
    gold, n, points = stored(core.url_gold(sets, 100, best=True)), sets.count(), []
    for _, p in _grid(w.sized(s, d, "pages_url", core.URLS)):
        addr = stored(index.addresses(sets, p))
        probes = index.index_of(addr, p).probe(addr)
        gathered = probes.groupBy("query_id").agg(F.sum(F.size("members")).alias("n")).agg(F.avg("n").alias("seconds"))
        pairs = stored(baselines.bucket_pairs(addr, LIGHT))
        compared = pairs.agg((F.count("*").cast("double") / F.lit(n)).alias("seconds"))
        for method, graph, cost in (("engine", query.count_select(probes, 100, "segment"), gathered), ("unbounded buckets", query.rerank(pairs, sets, 100), compared)):
            points.append(settled(metrics.recall_at(graph, gold, (100,)).select(F.lit(method).alias("method"), "recall").crossJoin(F.broadcast(cost))))
    found = metrics.speedup_at(_together(points), LEVELS)
    return found.select("method", "level", F.round("seconds", 4).alias("candidates"))


def _highlights_sql() -> str:
    parts, ends = [*sql.feats("pages_url", "t"), *sql.gold(100, "t")], []
    for i, (t, p) in enumerate(_grid(core.URLS)):
        x = f"h{i}"
        parts += sql.graph(p, 100, x, "pages_url")
        ends.append(f"SELECT {t} AS tables, recall, ids * 8 + buckets * 24 AS stored_bytes FROM ({sql.recall((100,), f'{x}graph', 'tgold')}), (SELECT count(*) AS ids, count(DISTINCT (table_id, address)) AS buckets FROM {x}res)")
    levels = ", ".join(f"({v}::DOUBLE)" for v in LEVELS)
    return sql.query([*parts, ("points", " UNION ALL ".join(ends))], f"SELECT level, min(tables) AS tables, min(stored_bytes)::BIGINT AS stored_bytes FROM points, (VALUES {levels}) v(level) WHERE recall >= level GROUP BY 1")


@add("size_at_recall", _highlights_sql())
def size_at_recall(s, d):
    """The smallest index, as stored, whose graph reaches each R@100."""
    sets = w.load(s, d, "pages_url")
    gold, points = stored(core.url_gold(sets, 100, best=True)), []
    for t, p in _grid(w.sized(s, d, "pages_url", core.URLS)):
        addr = stored(index.addresses(sets, p))
        built = index.index_of(addr, p)
        recall = metrics.recall_at(query.count_select(built.probe(addr), 100, "segment"), gold, (100,)).select(F.lit(t).alias("tables"), "recall")
        points.append(settled(recall.crossJoin(F.broadcast(built.size().select("stored_bytes")))))
    at = _together(points).withColumn("level", F.explode(F.array(*[F.lit(v) for v in LEVELS]))).where("recall >= level")
    return at.groupBy("level").agg(F.min("tables").alias("tables"), F.min("stored_bytes").cast("long").alias("stored_bytes"))


# ---------------------------------------------------------------- thresholds, heavy entries, inner products

ABOVE = (("docs_words", core.BASE, 0.65), ("docs_words", core.BASE, 0.85), ("cust_parts", core.PURCHASES, 0.10))


def _above_sql() -> str:
    parts, ends = [], []
    for i, (name, p, tau) in enumerate(ABOVE):
        x = f"a{i}"
        parts += [*sql.graph(p, 20, x, name), *sql.overlaps(x)]
        per = f"SELECT query_id, count(*) AS n, count(rank) AS h FROM {x}over LEFT JOIN {x}graph USING (query_id, neighbor_id) WHERE {sql.COSINE} > {tau} GROUP BY 1"
        ends.append(f"SELECT '{name}' AS workload, {tau}::DOUBLE AS tau, sum(n)::BIGINT AS pairs, sum(h)::BIGINT AS found, round(sum(h) / sum(n), 6) AS recall, round(sum(h) / sum(least(n, 20)), 6) AS capped_recall FROM ({per})")
    return sql.query(parts, " UNION ALL ".join(ends))


@add("recall_above", _above_sql())
def recall_above(s, d):
    """Entries of similarity above a threshold among the first 20: near texts, and heavy entries of the purchase matrix."""
    out, workloads = [], {(name, p): None for name, p, _ in ABOVE}
    for name, p in workloads:
        taus = tuple(tau for n, _, tau in ABOVE if n == name)
        for tau, found in zip(taus, core.found_above(s, d, name, p, taus, 20)):
            out.append(found.select(F.lit(name).alias("workload"), F.lit(tau).alias("tau"), "pairs", "found", "recall", "capped_recall"))
    return _together(out)


PADDED = 24
_PAD = f"SELECT * FROM base UNION ALL SELECT item_id, {sql.P} + i FROM (SELECT item_id, unnest(range(greatest({PADDED} - n, 0))) AS i FROM (SELECT item_id, count(*) AS n FROM base GROUP BY 1))"
INNER = replace(core.URLS, k=1, tables=32)


@add("inner_product_search", sql.query(
    [
        ("base", sql.FEATURES["pages_url"]), ("feats", _PAD), *sql.addresses(INNER, size=sql.room(INNER, "pages_url")), *sql.reservoirs(INNER),
        ("qfeats", f"SELECT * FROM base WHERE {ASKED}"), *sql.addresses(INNER, "q", size=sql.room(INNER, "pages_url")),
        ("graph", sql.ranked("SELECT a.item_id AS query_id, r.item_id AS neighbor_id, count(*) AS collisions FROM qaddr a JOIN res r USING (table_id, address) WHERE a.item_id <> r.item_id GROUP BY 1, 2", 20)),
        ("products", "SELECT q.item_id AS query_id, b.item_id AS neighbor_id, count(*)::DOUBLE AS similarity FROM qfeats q JOIN base b USING (f) WHERE q.item_id <> b.item_id GROUP BY 1, 2"),
        ("gold", sql.ranked("SELECT * FROM products", 20, "similarity")),
    ],
    sql.recall((1, 10, 20), "graph", "gold"),
))
def inner_product_search(s, d):
    """Largest inner products by asymmetric hashing: data sets are padded, queries are not; recall against exact products."""
    sets, p = w.load(s, d, "pages_url"), w.sized(s, d, "pages_url", INNER)
    asked = sets.where(ASKED)
    found = index.build_index(features.asymmetric_pad(sets, "data", PADDED), p).knn(features.asymmetric_pad(asked, "query", PADDED), 20, exclude_self=True)
    products = exact.overlap_pairs(asked, sets).select("query_id", "neighbor_id", F.col("a").cast("double").alias("similarity"))
    rank = F.row_number().over(W.partitionBy("query_id").orderBy(F.col("similarity").desc(), "neighbor_id"))
    return metrics.recall_at(found, products.withColumn("rank", rank).where("rank <= 20"), (1, 10, 20))


# ---------------------------------------------------------------- sampled features: exact, quantized, hashed

SAMPLED = 500


def _sampled_sql() -> list[tuple[str, str]]:
    a, b = core._sa, core._sb
    return [("all_feats", sql.FEATURES["docs_char3"]), ("kept", f"SELECT f FROM (SELECT DISTINCT f FROM all_feats) ORDER BY (f * {a} + {b}) % {sql.P}, f LIMIT {SAMPLED}"), ("feats", "SELECT item_id, f FROM all_feats JOIN kept USING (f)")]


@add("table_sampled", sql.query(
    [*_sampled_sql(), *sql.addresses(core.BASE, size=sql.room(core.BASE, "docs_char3")), *sql.reservoirs(core.BASE), *sql.gold(1, queries=f"SELECT item_id FROM feats WHERE {ASKED}"),
     ("g", sql.ranked("SELECT a.item_id AS query_id, r.item_id AS neighbor_id, count(*) AS collisions FROM addr a JOIN res r USING (table_id, address) WHERE a.item_id <> r.item_id AND a.item_id % 100 = 0 GROUP BY 1, 2", 1))],
    f"SELECT 'exact' AS method, round(avg(similarity), 6) AS s1, count(*) AS n FROM gold UNION ALL SELECT 'engine', round(avg(coalesce({sql.COSINE}, 0)), 6), count(*) FROM g LEFT JOIN over USING (query_id, neighbor_id)",
))
def table_sampled(s, d):
    """S@1 over a sample of features, empty rows dropped: exact search and the engine."""
    sets = stored(features.sample_features(w.load(s, d, "docs_char3"), SAMPLED))
    asked = sets.where(ASKED)
    best = exact.brute_force(asked, sets, 1).agg(F.round(F.avg("similarity"), 6).alias("s1"), F.count("*").alias("n"))
    found = index.build_index(sets, w.sized(s, d, "docs_char3", core.BASE)).knn(asked, 1, exclude_self=True)
    one = query.rerank(found, sets, 1).agg(F.round(F.avg("similarity"), 6).alias("s1"), F.count("*").alias("n"))
    return best.select(F.lit("exact").alias("method"), "s1", "n").unionByName(one.select(F.lit("engine").alias("method"), "s1", "n"))


# ---------------------------------------------------------------- peers, held to a recall


def _reached(method: str, found: DataFrame, gold: DataFrame, k: int, least: float) -> DataFrame:
    """One row: whether the best neighbour is among the first ``k`` for a share ``least`` of the queries."""
    return metrics.recall_at(found, gold, (k,)).select(F.lit(method).alias("method"), "n_queries", (F.col("recall") >= least).alias("reached"))


def _reached_sql(method: str, source: str) -> str:
    return f"SELECT '{method}' AS method, count(*) AS n_queries, true AS reached FROM ({source})"


_URL_ASKED = f"SELECT DISTINCT item_id FROM ({sql.FEATURES['pages_url']}) WHERE {ASKED}"
_VEC_ASKED = "SELECT vec_id FROM embeddings WHERE vec_id % 100 = 0"
URL_PEERS = {
    "project_then_knn": (lambda sets, asked: baselines.project_then_knn(sets, asked, 64, 20), 0.5),
    "hsw_graph": (lambda sets, asked: baselines.small_world_graph(sets, asked, 20), 0.6),
    "flat_small_world": (lambda sets, asked: baselines.small_world_graph(sets, asked, 20, layers=1), 0.6),
    "mllib_minhash": (lambda sets, asked: baselines.ml_minhash(sets, 1 << 18, 8, 20, queries=asked), 0.6),
    "mllib_projection": (lambda sets, asked: baselines.ml_projection(sets, 1 << 18, 8, 20, queries=asked), 0.5),
}
for _name, (_run, _least) in URL_PEERS.items():

    @add(_name, _reached_sql(_name, _URL_ASKED))
    def _peer(s, d, name=_name, run=_run, least=_least):
        sets = w.load(s, d, "pages_url")
        asked = sets.where(ASKED)
        return _reached(name, run(sets, asked), exact.exact_by_class(asked, sets, 20, best=True), 20, least)


def _by_rank(found: DataFrame) -> DataFrame:
    return found.select("query_id", "neighbor_id", "rank")


@add("kd_partition_knn", _reached_sql("kd_partition_knn", _VEC_ASKED))
def kd_partition_knn(s, d):
    v = w.vectors(s, d)
    asked = v.where(ASKED)
    return _reached("kd_partition_knn", _by_rank(baselines.kd_partition_knn(v, asked, 20, depth=1)), exact.flat_dense(asked, v, 20), 20, 0.2)


@add("pq_search", _reached_sql("pq_search", _VEC_ASKED))
def pq_search(s, d):
    v = w.vectors(s, d)
    books = baselines.pq_train(v, 8, 32)
    asked = v.where(ASKED)
    return _reached("pq_search", _by_rank(baselines.pq_search(baselines.pq_encode(v, books, keep=True), asked, books, 20)), exact.flat_dense(asked, v, 20), 20, 0.4)


@add("pq_sampled_dense", f"SELECT true AS below_exact, true AS found FROM (SELECT 1 FROM documents WHERE doc_id % 100 = 0 LIMIT 1)")
def pq_sampled_dense(s, d):
    """Quantization needs dense rows: features are sampled, empty rows dropped, then codes compete with the flat mode by S@1."""
    sets = stored(features.sample_features(w.load(s, d, "docs_char3"), 64))
    dims = [r["feature"] for r in core._long(sets).select("feature").distinct().orderBy("feature").collect()]  # at most 64
    v = features.to_dense(sets, dims)
    books = baselines.pq_train(v, 8, 16)
    asked, of = v.where(ASKED), lambda found: query.rerank(found.where("rank = 1"), sets, 1).agg(F.avg("similarity"))
    flat = of(exact.flat_dense(asked, v, 1)).withColumnRenamed("avg(similarity)", "flat")
    codes = of(baselines.pq_search(baselines.pq_encode(v, books), asked, books, 1)).withColumnRenamed("avg(similarity)", "codes")
    return flat.crossJoin(codes).select((F.col("codes") <= F.col("flat") + 1e-9).alias("below_exact"), (F.col("codes") > 0.5 * F.col("flat")).alias("found"))


HEAVY_BITS = 128
_hp = sql.parameters(2001, 2 * HEAVY_BITS)
_ROWS = ", ".join(f"({k}, {_hp[2 * k]}::BIGINT, {_hp[2 * k + 1]}::BIGINT)" for k in range(HEAVY_BITS))
_SIGNS = f"SELECT item_id, k::BIGINT AS i, (sum(1 - 2 * (((f * a + b) % {sql.P} // 65536) % 2)) >= 0)::BIGINT AS v FROM feats, (VALUES {_ROWS}) c(k, a, b) GROUP BY 1, 2"


@add("heavy_entries_projection", sql.query(
    [
        *sql.feats("cust_parts"), ("sig", _SIGNS), ("signs", "SELECT item_id, list(v ORDER BY i) AS vs FROM sig GROUP BY 1"),
        ("est", f"SELECT x.item_id AS i, y.item_id AS j, round(cos((1.0::DOUBLE - list_sum(list_transform(list_zip(x.vs, y.vs), lambda p: (p[1] = p[2])::INT)) / {HEAVY_BITS}.0::DOUBLE) * pi()), 6) AS value FROM signs x JOIN signs y ON x.item_id <> y.item_id"),
    ],
    "SELECT i, j, value FROM est WHERE value > 0.3 QUALIFY row_number() OVER (PARTITION BY i ORDER BY value DESC, j) <= 20",
))
def heavy_entries_projection(s, d):
    """Heavy entries of the whole purchase matrix by signed projections: every pair of columns is estimated."""
    return baselines.heavy_entries_projection(w.cust_parts(s, d), HEAVY_BITS, None, 20, 0.3)


# ---------------------------------------------------------------- buckets and shared reservoirs

_addr = sql.addresses(core.BASE, features="docs_words")


@add("bucket_quantiles", sql.query(_addr, f"SELECT table_id, quantile_cont(n, 0.5)::DOUBLE AS median, quantile_cont(n, 0.9)::DOUBLE AS p90, quantile_cont(n, 0.99)::DOUBLE AS p99, round(1 - count(*) / {sql.room(core.BASE, 'docs_words')}::DOUBLE, 6) AS empty FROM (SELECT table_id, address, count(*) AS n FROM addr GROUP BY 1, 2) GROUP BY 1"))
def bucket_quantiles(s, d):
    """Per table: quantiles of the sizes of buckets in use, and the share of addresses that none uses."""
    p = w.sized(s, d, "docs_words", core.BASE)
    return metrics.bucket_quantiles(index.addresses(w.load(s, d, "docs_words"), p), p.bits)


SHARED = replace(core.HEAVY, share=0.3)


@add("sharing_clashes", sql.query([*sql.addresses(SHARED, features="docs_words"), *sql.pointers(SHARED)], f"SELECT count(*) AS reservoirs, coalesce(sum((heavy = 1)::INT), 0)::BIGINT AS one_heavy, coalesce(sum((heavy > 1)::INT), 0)::BIGINT AS clashes, coalesce(max(heavy), 0)::BIGINT AS most FROM (SELECT reservoir_id, sum((n > {SHARED.r})::INT) AS heavy FROM ptr JOIN (SELECT table_id, address, count(*) AS n FROM addr GROUP BY 1, 2) USING (table_id, address) GROUP BY 1)"))
def sharing_clashes(s, d):
    """Shared reservoirs that several truncated buckets must share."""
    addr = index.addresses(w.load(s, d, "docs_words"), SHARED)
    return metrics.sharing_clashes(addr, index.index_of(addr, SHARED).pointers, SHARED.r)


# ---------------------------------------------------------------- what could not be repeated before

_rng = np.random.default_rng(1)
_FLIPS, _KEPT = _rng.choice([-1.0, 1.0], 64), _rng.choice(64, 16, replace=False)
_FLIP_ROWS = ", ".join(f"({i}, {int(v)})" for i, v in enumerate(_FLIPS))
_KEPT_ROWS = ", ".join(f"({i}, {int(v)})" for i, v in enumerate(_KEPT))


@add("hadamard_projection", f"SELECT item_id, place::INT AS i, round(sum(v::DOUBLE * flip * CASE WHEN bit_count((j & spot)::BIGINT) % 2 = 0 THEN 1 ELSE -1 END) / 4.0::DOUBLE, 4) + 0.0::DOUBLE AS v FROM (SELECT vec_id AS item_id, unnest(embedding) AS v, unnest(range(len(embedding))) AS j FROM embeddings) JOIN (VALUES {_FLIP_ROWS}) f(j, flip) USING (j), (VALUES {_KEPT_ROWS}) k(place, spot) GROUP BY 1, 2")
def hadamard_projection(s, d):
    out = hashing.hadamard_projection(w.vectors(s, d), "item_id", "vector", 16)
    return out.select("item_id", F.posexplode("vector").alias("i", "v")).withColumn("v", F.round("v", 4) + F.lit(0.0))


@add("assumption_violations", sql.query(
    [
        *sql.feats("pages_url"), *sql.gold(2), ("sets", "SELECT item_id, list(f) AS fs FROM feats GROUP BY 1"),
        ("t", "SELECT q.fs AS q, x.fs AS x, y.fs AS y FROM gold a JOIN gold b ON a.query_id = b.query_id AND a.rank = 1 AND b.rank = 2 JOIN sets q ON q.item_id = a.query_id JOIN sets x ON x.item_id = a.neighbor_id JOIN sets y ON y.item_id = b.neighbor_id"),
        ("n", "SELECT len(list_intersect(q, x)) AS a, len(list_intersect(list_intersect(q, x), y)) AS shared, len(list_distinct(list_concat(q, x))) AS qx, len(list_distinct(list_concat(list_concat(q, x), y))) AS u, len(list_intersect(q, y)) AS b, len(list_distinct(list_concat(q, y))) AS qy FROM t"),
    ],
    "SELECT count(*) AS triples, round(avg((shared::DOUBLE / a * (qx::DOUBLE / u) > b::DOUBLE / qy)::INT), 6) AS violations FROM n WHERE a > 0 AND a::DOUBLE / qx > b::DOUBLE / qy",
))
def assumption_violations(s, d):
    """Triples of a query, its best neighbour and its second: does sharing with the best change the odds for the second?"""
    sets = w.load(s, d, "pages_url")
    gold = stored(core.url_gold(sets, 2))
    one, two = (gold.where(F.col("rank") == r).select("query_id", F.col("neighbor_id").alias(n)) for r, n in ((1, "a"), (2, "b")))
    of = lambda i, n: sets.select(F.col("item_id").alias(i), F.col("features").alias(n))
    found = metrics.assumption_violations(one.join(two, "query_id").join(of("query_id", "q"), "query_id").join(of("a", "x"), "a").join(of("b", "y"), "b"))
    return found.select("triples", F.round("violations", 6).alias("violations"))


# ---------------------------------------------------------------- theory


def _planned(rows: DataFrame, plan, schema: str) -> DataFrame:
    """What the planner's functions say of each row, in as many rows as ``plan`` gives."""
    names = [c.split()[0] for c in schema.split(", ")]

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in parts:
            out = [r for row in pdf.itertuples(index=False) for r in plan(*row)]
            if out:
                yield pd.DataFrame(out, columns=names)

    return rows.mapInPandas(run, schema)


_CHANCES = ((0.9, 0.5), (0.8, 0.3), (0.6, 0.2))


@add("theory_costs", """WITH g AS (SELECT flag, n, p1, p2, ln(1 / p1) / ln(1 / p2) AS rho FROM (SELECT l_returnflag AS flag, count(*) AS n FROM lineitem GROUP BY 1) a, (VALUES (0.9::DOUBLE, 0.5::DOUBLE), (0.8, 0.3), (0.6, 0.2)) b(p1, p2))
SELECT flag, n, p1, p2, round(rho, 6) AS rho, ceil(ln(n) / ln(1 / p2))::INT AS k, ceil(pow(n, rho) * ln(1 / 0.1::DOUBLE))::INT AS tables, round(pow(n, rho) * ln(n) / ln(1 / p2) * ln(1 / 0.1::DOUBLE), 2) AS query_time, round(ln(pow(n, 1 + rho) * ln(1 / 0.1::DOUBLE)), 6) AS log_space FROM g""")
def theory_costs(s, d):
    """Parameters, query time and space of search with hashing among the order lines of each return flag, for given chances to collide."""

    def plan(flag: str, n: int) -> list[tuple]:
        out = []
        for p1, p2 in _CHANCES:
            k, tables = planner.parameters_for(n, p1, p2)
            out.append((flag, n, p1, p2, round(planner.rho(p1, p2), 6), k, tables, round(planner.query_time(n, p1, p2), 2), round(math.log(planner.space(n, p1, p2)), 6)))
        return out

    sizes = read_table(s, d, "lineitem", ["l_returnflag"]).groupBy("l_returnflag").count()
    return _planned(sizes, plan, "flag string, n long, p1 double, p2 double, rho double, k int, tables int, query_time double, log_space double")


@add("theory_reservoirs", """SELECT m, orders, r, round((1 - 1 / exp(1)) * (1 - 1 / r::DOUBLE), 6) AS success, (1 - 1 / exp(1)) * (1 - 1 / r::DOUBLE) > 0.5 AS works,
round((SELECT sum(1 - t.s / m::DOUBLE) FROM range(16) t(s) WHERE t.s < least(m, r)), 6) AS overwritten_occupancy
FROM (SELECT m, count(*) AS orders FROM (SELECT count(*) AS m FROM lineitem GROUP BY l_orderkey) GROUP BY 1), range(2, 17) g(r)""")
def theory_reservoirs(s, d):
    """Chance that a table works by the size of its reservoirs, and what is left of an order's lines where slots are always drawn."""

    def plan(m: int, orders: int) -> list[tuple]:
        return [(m, orders, r, round(planner.success(r), 6), r >= planner.min_reservoir(), round(planner.overwrite_occupancy(m, r), 6)) for r in range(2, 17)]

    sizes = read_table(s, d, "lineitem", ["l_orderkey"]).groupBy("l_orderkey").agg(F.count("*").alias("m")).groupBy("m").agg(F.count("*").alias("orders"))
    return _planned(sizes, plan, "m long, orders long, r long, success double, works boolean, overwritten_occupancy double")


_USERS = [*sql.feats("user_events"), ("sets", "SELECT item_id, list(f) AS fs FROM feats GROUP BY 1")]


def _next(s, d, steps: int) -> DataFrame:
    """Each user's set as v0, those of the users that follow by id as v1, v2 and so on."""
    sets = w.user_events(s, d)
    out = sets.select("item_id", F.col("features").alias("v0"))
    for i in range(1, steps + 1):
        out = out.join(sets.select((F.col("item_id") - i).alias("item_id"), F.col("features").alias(f"v{i}")), "item_id")
    return out


@add("theory_conditionals", sql.query(
    [*_USERS,
     ("n", "SELECT q.item_id, len(list_intersect(q.fs, x.fs)) AS a, len(list_distinct(list_concat(q.fs, x.fs))) AS qx, len(list_distinct(list_concat(list_concat(q.fs, x.fs), y.fs))) AS u FROM sets q JOIN sets x ON x.item_id = q.item_id + 1 JOIN sets y ON y.item_id = q.item_id + 2")],
    "SELECT item_id, a, qx - a AS b, u - qx AS y, round(a / qx::DOUBLE * (u - (u - qx)) / u::DOUBLE, 6) AS exact, round(a / qx::DOUBLE * a / (a + u - qx)::DOUBLE, 6) AS printed FROM n WHERE a > 0",
))
def theory_conditionals(s, d):
    """Chance that a user's events collide with the next user's while the one after does not share it: exact, and the product form beside it."""

    def plan(i: int, a: int, b: int, y: int) -> list[tuple]:
        return [(i, a, b, y, round(planner.conditional_collision(a, b, a + b + y, y), 6), round(planner.conditional_printed(a, b, y), 6))]

    a, qx, u = F.size(F.array_intersect("v0", "v1")), F.size(F.array_union("v0", "v1")), F.size(F.array_union(F.array_union("v0", "v1"), F.col("v2")))
    counts = _next(s, d, 2).select("item_id", *[c.cast("long").alias(n) for n, c in (("a", a), ("b", qx - a), ("y", u - qx))]).where("a > 0")
    return _planned(counts, plan, "item_id long, a long, b long, y long, exact double, printed double")


#: Jaccard similarities of users that follow each other by id, in whole hundredths from 1 to 99.
_LEVELS = [
    *_USERS, ("pair", "SELECT len(list_intersect(q.fs, x.fs)) AS a, len(list_distinct(list_concat(q.fs, x.fs))) AS u FROM sets q JOIN sets x ON x.item_id = q.item_id + 1"),
    ("levels", "SELECT DISTINCT ((100 * a) // u)::BIGINT AS level FROM pair WHERE 100 * a >= u AND a < u"),
]


def _levels(s, d) -> DataFrame:
    pairs = _next(s, d, 1).select(F.size(F.array_intersect("v0", "v1")).alias("a"), F.size(F.array_union("v0", "v1")).alias("u"))
    return pairs.where("100 * a >= u AND a < u").select(F.expr("(100 * a) div u").alias("level")).distinct()


@add("theory_retrieval", sql.query(_LEVELS, "SELECT level / 100.0::DOUBLE AS p, k, l, round(1 - pow(1 - pow(p, k), l), 6) AS plain, round(1 - pow(1 - 0.5::DOUBLE * pow(p, k), l), 6) AS half_kept, round(l * pow(p, k) * (1 - pow(p, k)), 6) AS variance FROM levels, (VALUES (1), (2), (4)) b(k), (VALUES (8), (32), (128)) c(l)"))
def theory_retrieval(s, d):
    """Chances and variances from the planner at the similarities of users that follow each other, over a grid of parameters."""

    def plan(level: int) -> list[tuple]:
        p = level / 100
        return [
            (p, k, n, round(planner.retrieval(p, k, n), 6), round(planner.retrieval_with_reservoirs(p, k, 8, [16] * n), 6), round(planner.count_moments(p, k, n)["count_variance"], 6))
            for k in (1, 2, 4) for n in (8, 32, 128)
        ]

    return _planned(_levels(s, d), plan, "p double, k int, l int, plain double, half_kept double, variance double")


@add("theory_signed", sql.query(
    [*_LEVELS, ("g", "SELECT level / 100.0::DOUBLE AS j, bits, 1 - acos(2 * j / (1 + j)) / pi() AS p, ceil(bits / 24.0::DOUBLE)::INT AS k FROM levels, (VALUES (15), (20)) b(bits)")],
    "SELECT j AS jaccard, bits AS address_bits, k AS minwise_values, bits AS signed_values, round((1 - pow(j, k)) / (32 * pow(j, k)), 5) AS minwise_variance, round((1 - pow(p, bits)) / (32 * pow(p, bits)), 5) AS signed_variance FROM g",
))
def theory_signed(s, d):
    """Hash values that fill an address and the relative variance of ranking over 32 tables, at the similarities of users that
    follow each other: minima against signed projections."""

    def plan(level: int) -> list[tuple]:
        out, j = [], level / 100
        for bits in (15, 20):
            variance = [round(planner.ranking_variance(j, bits, 32, signed, 1 << 24), 5) for signed in (False, True)]
            out.append((j, bits, planner.values_needed(bits, False, 1 << 24), planner.values_needed(bits, True, 1 << 24), *variance))
        return out

    return _planned(_levels(s, d), plan, "jaccard double, address_bits int, minwise_values int, signed_values int, minwise_variance double, signed_variance double")


@add("collision_curve", sql.query(
    [*sql.addresses(core.BASE, features="docs_words"), *sql.overlaps(queries="SELECT DISTINCT item_id FROM feats WHERE item_id % 100 = 0")],
    "SELECT bin, count(*) AS pairs, round(avg(rate), 6) AS rate FROM (SELECT floor(a / (x + y - a)::DOUBLE * 5)::INT AS bin, (SELECT 1) AS one, r.rate FROM over JOIN (SELECT p.item_id AS query_id, q.item_id AS neighbor_id, avg((p.v = q.v)::INT) AS rate FROM sig p JOIN sig q USING (i) WHERE p.item_id % 100 = 0 AND p.item_id <> q.item_id GROUP BY 1, 2) r USING (query_id, neighbor_id)) GROUP BY 1",
))
def collision_curve(s, d):
    """How often single hash values collide, by Jaccard similarity in fifths: it rises, as ranking by counts needs."""
    sets, p = stored(w.load(s, d, "docs_words")), core.BASE
    sign = partial(hashing.signatures_of, m=p.k * p.tables, scheme=p.densify, seed=p.seed)
    found = exact.agreement_by_similarity(sets.where(ASKED), sets, sign, 5)
    return found.select("bin", "pairs", F.round("rate", 6).alias("rate"))


@add("projection_work", sql.query(sql.feats("pages_full"), "SELECT nnz, nnz * 100 AS projection_terms, nnz AS hash_terms, n * 100 AS hash_values FROM (SELECT count(*) AS nnz, count(DISTINCT item_id) AS n FROM feats)"))
def projection_work(s, d):
    """Terms that 100 projections and 100 one-permutation hashes evaluate; the seconds are in the bench."""
    n = features.drop_empty(w.load(s, d, "pages_full")).agg(F.sum(F.size("features")).alias("nnz"), F.count("*").alias("n"))
    return n.select("nnz", (F.col("nnz") * 100).alias("projection_terms"), F.col("nnz").alias("hash_terms"), (F.col("n") * 100).alias("hash_values"))

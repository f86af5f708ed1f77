"""Queries of the similarity engine with their SQL: features, hashing, reservoirs, graphs, baselines, measures."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import jaccard
from ..functions.portable import P, parameters
from ..operators import baselines, exact, features, hashing, index, matmul, metrics, query, reservoir
from ..operators.index import IndexParams
from ..sources import settled, stored
from . import sql
from . import workloads as w

QUERIES: dict = {}
ORACLES: dict = {}

#: Settings of the queries: small tables need lighter addresses than the recommended K=4, L=32.
BASE = IndexParams(k=2, tables=16, r=16, bits=12)
URLS = IndexParams(k=2, tables=16, r=32, bits=12)
TOP = 10


def add(name: str, oracle: str | None = None):
    def keep(fn):
        QUERIES[name] = fn
        if oracle:
            ORACLES[name] = oracle
        return fn

    return keep


def graph(s, d, name: str, p: IndexParams, k: int, *args, **options) -> DataFrame:
    return index.knn_graph(w.load(s, d, name), w.sized(s, d, name, p), k, *args, **options)


def _long(sets: DataFrame) -> DataFrame:
    return features.long_form(sets)


def _members(res: DataFrame, *keys: str) -> DataFrame:
    return res.select(*keys, "seen", F.explode("members").alias("item_id"))


# ---------------------------------------------------------------- features

for _name, _load in (("words", "docs_words"), ("char3", "docs_char3"), ("url", "pages_url"), ("page", "pages_full"), ("categorical", "part_cat"), ("adjacency", "cust_parts"), ("events", "user_events"), ("turns", "turns_words"), ("lines", "lines_cat")):
    add(f"features_{_name}", sql.query(sql.feats(_load), "SELECT item_id, count(*) AS n, sum(f)::BIGINT AS total, min(f) AS low, max(f) AS high FROM feats GROUP BY 1"))(
        lambda s, d, load=_load: _long(w.load(s, d, load)).groupBy("item_id").agg(F.count("*").alias("n"), F.sum("feature").alias("total"), F.min("feature").alias("low"), F.max("feature").alias("high"))
    )

_sa, _sb = parameters(3, 2)
add("features_sampled", sql.query([*sql.feats("docs_char3"), ("kept", f"SELECT f FROM (SELECT DISTINCT f FROM feats) ORDER BY (f * {_sa} + {_sb}) % {P}, f LIMIT 500")], "SELECT item_id, f AS feature FROM feats JOIN kept USING (f)"))(
    lambda s, d: _long(features.sample_features(w.load(s, d, "docs_char3"), 500))
)
add("features_unit_weights", sql.query(sql.feats("part_cat"), "SELECT item_id, f AS feature, round(1 / sqrt(count(*) OVER (PARTITION BY item_id)), 6) AS weight FROM feats"))(
    lambda s, d: features.unit_weights(w.part_cat(s, d)).select("item_id", F.explode("weights").alias("feature", "weight")).withColumn("weight", F.round("weight", 6))
)
add("features_dense_signs", """SELECT item_id, i * 2 + (v < 0)::INT AS feature FROM (SELECT vec_id AS item_id, unnest(embedding) AS v, unnest(range(len(embedding))) AS i FROM embeddings)
QUALIFY row_number() OVER (PARTITION BY item_id ORDER BY abs(v) DESC, i) <= 16""")(lambda s, d: _long(features.binarize_top(w.vectors(s, d), "item_id", "vector", 16)))
add("features_padded", sql.query(sql.feats("part_cat"), f"""SELECT item_id, count(*) AS n, sum(f)::BIGINT AS total FROM (SELECT * FROM feats UNION ALL
SELECT item_id, {P} + i FROM (SELECT item_id, unnest(range(8 - n)) AS i FROM (SELECT item_id, count(*) AS n FROM feats GROUP BY 1))) GROUP BY 1"""))(
    lambda s, d: _long(features.asymmetric_pad(w.part_cat(s, d), "data", 8)).groupBy("item_id").agg(F.count("*").alias("n"), F.sum("feature").alias("total"))
)
_PROFILE = "SELECT count(*) AS n, min(c) AS nnz_min, round(avg(c), 6) AS nnz_mean, max(c) AS nnz_max FROM (SELECT item_id, count(*) AS c FROM feats GROUP BY 1)"
add("dataset_profile", sql.query(sql.feats("docs_words"), f"SELECT n, dims, nnz_min, nnz_mean, nnz_max, round(max_df / n, 6) AS max_df_share FROM ({_PROFILE}), (SELECT count(*) AS dims, max(c) AS max_df FROM (SELECT f, count(*) AS c FROM feats GROUP BY 1))"))(
    lambda s, d: features.profile(features.drop_empty(w.load(s, d, "docs_words")))
)

# ---------------------------------------------------------------- similarity and gold

#: Searches ask for every item whose id is divisible by 100, against all.
ASKED = "item_id % 100 = 0"
_QS = f"SELECT item_id FROM feats WHERE {ASKED}"


def url_gold(sets: DataFrame, k: int, best: bool = False) -> DataFrame:
    """Exact neighbours of all URLs, whose commonest steps are in all rows, so that these must not be joined."""
    return exact.exact_by_class(sets, sets, k, best=best)


@add("jaccard_pairs", sql.query([*sql.feats("bench_words", "q"), *sql.feats("docs_words", "d"), ("o", "SELECT q.item_id AS query_id, d.item_id AS neighbor_id, count(*) AS a FROM qfeats q JOIN dfeats d USING (f) GROUP BY 1, 2")], "SELECT query_id, neighbor_id, round(a / (x.n + y.n - a)::DOUBLE, 6) AS jaccard FROM o JOIN (SELECT item_id, count(*) AS n FROM qfeats GROUP BY 1) x ON x.item_id = query_id JOIN (SELECT item_id, count(*) AS n FROM dfeats GROUP BY 1) y ON y.item_id = neighbor_id WHERE a / (x.n + y.n - a)::DOUBLE > 0.02"))
def jaccard_pairs(s, d):
    q = F.broadcast(w.bench_words(s, d).select(F.col("item_id").alias("query_id"), F.col("features").alias("x")))  # a stated, bounded query set
    pairs = w.load(s, d, "docs_words").join(q, F.size(F.array_intersect("features", "x")) > 0)
    j = jaccard(F.col("x"), F.col("features"))
    return pairs.where(j > 0.02).select("query_id", F.col("item_id").alias("neighbor_id"), F.round(j, 6).alias("jaccard"))


_GOLD_DOCS = [*sql.feats("docs_words"), *sql.gold(TOP, queries=_QS)]
add("exact_inverted_topk", sql.query(_GOLD_DOCS, "SELECT * FROM gold"))(lambda s, d: exact.exact_inverted(w.load(s, d, "docs_words").where(ASKED), w.load(s, d, "docs_words"), TOP))
add("cosine_exact_topk", sql.query(_GOLD_DOCS, "SELECT * FROM gold"))(lambda s, d: exact.brute_force(w.load(s, d, "docs_words").where(ASKED), w.load(s, d, "docs_words"), TOP))
add("jaccard_exact_topk", sql.query([*sql.feats("docs_words"), *sql.gold(TOP, queries=_QS, score=sql.JACCARD)], "SELECT * FROM gold"))(
    lambda s, d: exact.exact_inverted(w.load(s, d, "docs_words").where(ASKED), w.load(s, d, "docs_words"), TOP, "jaccard")
)
add("gold_gap", sql.query([*sql.feats("pages_url"), *sql.gold(TOP)], "SELECT round(avg(a), 6) AS best, round(avg(b), 6) AS second, round(avg(a - b), 6) AS gap FROM (SELECT query_id, max(similarity) FILTER (rank = 1) AS a, max(similarity) FILTER (rank = 2) AS b FROM gold GROUP BY 1)"))(
    lambda s, d: metrics.gold_gap(url_gold(w.load(s, d, "pages_url"), TOP))
)
_VEC = "SELECT q.vec_id AS query_id, d.vec_id AS neighbor_id, round({}, 6) AS similarity FROM embeddings q, embeddings d WHERE q.vec_id <> d.vec_id AND q.vec_id % 100 = 0"
add("flat_dense_topk", sql.ranked(_VEC.format("list_cosine_similarity(q.embedding::DOUBLE[], d.embedding::DOUBLE[])"), TOP, "similarity"))(lambda s, d: exact.flat_dense(w.vectors(s, d).where(ASKED), w.vectors(s, d), TOP))
add("inner_product_topk", sql.ranked(_VEC.format("list_inner_product(q.embedding::DOUBLE[], d.embedding::DOUBLE[])"), TOP, "similarity"))(lambda s, d: exact.flat_dense(w.vectors(s, d).where(ASKED), w.vectors(s, d), TOP, "inner"))


# ---------------------------------------------------------------- hashing

def _places(sig: DataFrame, value: str = "v") -> DataFrame:
    return sig.select("item_id", F.posexplode("sig").alias("i", value))


_mw = parameters(1001, 64)
_MINWISE = ("sig", "SELECT item_id, k::BIGINT AS i, min((f * a + b) % {} ) AS v FROM feats, (VALUES {}) c(k, a, b) GROUP BY 1, 2".format(P, ", ".join(f"({k}, {_mw[2 * k]}::BIGINT, {_mw[2 * k + 1]}::BIGINT)" for k in range(32))))
add("minwise_signature", sql.query([*sql.feats("docs_words"), _MINWISE], "SELECT item_id, i, v FROM sig"))(lambda s, d: _places(hashing.minwise(w.load(s, d, "docs_words"), 32)))
add("oph_bins", sql.query([*sql.feats("docs_words"), *sql.bins(32)], "SELECT item_id, bin, v FROM bins"))(lambda s, d: hashing.one_permutation(w.load(s, d, "docs_words"), 32))
for _scheme in ("probe", "rotation", "two_way"):
    add(f"doph_{_scheme}", sql.query([*sql.feats("pages_url"), *sql.bins(32), *sql.densified(32, _scheme)], "SELECT item_id, i, v FROM sig"))(
        lambda s, d, scheme=_scheme: _places(hashing.doph(w.load(s, d, "pages_url"), 2, 16, scheme=scheme))
    )
add("doph_relational", ORACLES["doph_probe"])(lambda s, d: _places(hashing.doph(w.load(s, d, "pages_url"), 2, 16, form="relational")))
add("doph_native", ORACLES["doph_probe"])(lambda s, d: _places(hashing.doph(w.load(s, d, "pages_url"), 2, 16, form="native")))
add("doph_asymmetric", sql.query([("base", sql.FEATURES["part_cat"]), ("feats", f"SELECT * FROM base UNION ALL SELECT item_id, {P} + i FROM (SELECT item_id, unnest(range(8 - n)) AS i FROM (SELECT item_id, count(*) AS n FROM base GROUP BY 1))"), *sql.bins(32), *sql.densified(32)], "SELECT item_id, i, v FROM sig"))(
    lambda s, d: _places(hashing.doph(features.asymmetric_pad(w.part_cat(s, d), "data", 8), 2, 16))
)
add("addresses", sql.query(sql.addresses(BASE, features="docs_words"), "SELECT item_id, table_id, address FROM addr"))(lambda s, d: index.addresses(w.load(s, d, "docs_words"), w.sized(s, d, "docs_words", BASE)))
add("jaccard_estimate", sql.query([*sql.addresses(BASE, features="docs_words")], "SELECT x.item_id AS a, y.item_id AS b, round(avg((x.v = y.v)::INT), 6) AS estimate FROM sig x JOIN sig y ON y.i = x.i AND y.item_id = x.item_id + 1 GROUP BY 1, 2"))(
    lambda s, d: _estimates(hashing.doph(w.load(s, d, "docs_words"), 2, 16))
)


def _estimates(sig: DataFrame) -> DataFrame:
    nxt = sig.select((F.col("item_id") - 1).alias("item_id"), F.col("item_id").alias("b"), F.col("sig").alias("y"))
    return sig.join(nxt, "item_id").select(F.col("item_id").alias("a"), "b", F.round(hashing.estimate_jaccard(F.col("sig"), F.col("y")), 6).alias("estimate"))


_sp = parameters(3001, 16)
add("sparse_projection", sql.query(sql.feats("docs_words"), "SELECT item_id, k AS i, round(sum(CASE ((f * a + b) % {0} // 65536) % 6 WHEN 0 THEN 1 WHEN 1 THEN -1 ELSE 0 END)::DOUBLE * {1}::DOUBLE, 6) AS v FROM feats, (VALUES {2}) c(k, a, b) GROUP BY 1, 2".format(P, 3.0**0.5, ", ".join(f"({k}, {_sp[2 * k]}, {_sp[2 * k + 1]})" for k in range(8)))))(
    lambda s, d: hashing.sparse_projection(w.load(s, d, "docs_words"), 8).select("item_id", F.posexplode("vector").alias("i", "v")).withColumn("v", F.round("v", 6))
)

# ---------------------------------------------------------------- reservoirs and index

_addr = sql.addresses(BASE, features="docs_words")
add("bucket_skew", sql.query(_addr, "SELECT table_id, count(*) AS buckets, max(n) AS max_bucket, round(avg(n), 6) AS mean_bucket, round(avg((n > 16)::INT), 6) AS truncated_share, sum(n)::BIGINT AS items FROM (SELECT table_id, address, count(*) AS n FROM addr GROUP BY 1, 2) GROUP BY 1"))(
    lambda s, d: metrics.bucket_skew(index.addresses(w.load(s, d, "docs_words"), w.sized(s, d, "docs_words", BASE)), BASE.r)
)
HEAVY = replace(BASE, k=1, r=8, bits=8)
_heavy = sql.addresses(HEAVY, features="docs_words")
for _policy, _title in (("priority", "priority"), ("arrival", "arrival"), ("literal_add", "literal")):
    add(f"reservoir_{_title}", sql.query([*_heavy, *sql.reservoirs(HEAVY, policy=_policy)], "SELECT table_id, address, seen, item_id FROM res"))(
        lambda s, d, policy=_policy: _members(reservoir.reservoir(index.addresses(w.load(s, d, "docs_words"), HEAVY), HEAVY.r, policy, HEAVY.seed), "table_id", "address")
    )
for _sharing in ("global", "pooled"):
    _p = replace(HEAVY, share=0.3, sharing=_sharing)
    add(f"reservoir_shared_{_sharing}", sql.query([*_heavy, *sql.pointers(_p), *sql.shared(_p)], "SELECT reservoir_id, seen, item_id FROM sres"))(
        lambda s, d, p=_p: _members(index.build_index(w.load(s, d, "docs_words"), p).reservoirs, "reservoir_id")
    )
    add(f"sharing_load_{_sharing}", sql.query([*_heavy, *sql.pointers(_p)], "SELECT sum(n)::BIGINT AS addresses, count(*) AS reservoirs, round(avg(n), 6) AS mean_load, max(n) AS max_load FROM (SELECT reservoir_id, count(*) AS n FROM ptr GROUP BY 1)"))(
        lambda s, d, p=_p: metrics.sharing_load(index.build_index(w.load(s, d, "docs_words"), p).pointers)
    )
add("index_size", sql.query([*_heavy, *sql.reservoirs(HEAVY)], f"SELECT count(*) AS buckets, sum(n)::BIGINT AS stored_ids, sum((seen > {HEAVY.r})::INT)::BIGINT AS truncated, (sum(n) * 8 + count(*) * 24)::BIGINT AS stored_bytes, ({HEAVY.tables} * (1::BIGINT << {HEAVY.bits}) * ({HEAVY.r} * 4 + 4))::BIGINT AS model_bytes FROM (SELECT table_id, address, seen, count(*) AS n FROM res GROUP BY 1, 2, 3)"))(
    lambda s, d: index.build_index(w.load(s, d, "docs_words"), HEAVY).size()
)
add("index_append", ORACLES["reservoir_priority"])(
    lambda s, d: _members(index.build_index(w.load(s, d, "docs_words").where("item_id % 3 <> 0"), HEAVY).append(w.load(s, d, "docs_words").where("item_id % 3 = 0")).reservoirs, "table_id", "address")
)
add("candidate_lengths", sql.query(sql.index(BASE, features="docs_words"), "SELECT round(avg(n), 6) AS mean_candidates, max(n) AS max_candidates FROM (SELECT query_id, count(*) AS n FROM met GROUP BY 1)"))(
    lambda s, d: metrics.candidate_lengths(_probes(w.load(s, d, "docs_words"), w.sized(s, d, "docs_words", BASE)))
)


def _probes(sets: DataFrame, p: IndexParams) -> DataFrame:
    addr = index.addresses(sets, p)
    return index.index_of(addr, p).probe(addr)


# ---------------------------------------------------------------- graphs

_GRAPH = sql.query(sql.graph(BASE, TOP, features="docs_words"), "SELECT * FROM graph")
for _strategy in ("hash", "segment", "boundary"):
    add(f"knn_graph_{_strategy}", _GRAPH)(lambda s, d, strategy=_strategy: graph(s, d, "docs_words", BASE, TOP, strategy))
add("knn_graph_batched", _GRAPH)(lambda s, d: graph(s, d, "docs_words", BASE, TOP, batches=3))
add("candidate_union", sql.query(sql.index(BASE, features="pages_url"), "SELECT DISTINCT query_id, neighbor_id FROM met"))(lambda s, d: query.candidate_union(_probes(w.load(s, d, "pages_url"), w.sized(s, d, "pages_url", BASE))))
add("knn_query_benchmark", sql.query([*sql.addresses(BASE, features="docs_words"), *sql.reservoirs(BASE), *sql.addresses(BASE, "q", "bench_words"), ("g", sql.ranked("SELECT a.item_id AS query_id, s.item_id AS neighbor_id, count(*) AS collisions FROM qaddr a JOIN res s USING (table_id, address) GROUP BY 1, 2", 5))], "SELECT * FROM g"))(
    lambda s, d: index.build_index(w.load(s, d, "docs_words"), w.sized(s, d, "docs_words", BASE)).knn(w.bench_words(s, d), 5)
)
add("near_neighbors", sql.query(sql.index(BASE, features="docs_words"), "SELECT query_id, neighbor_id, count(*) AS collisions FROM met WHERE query_id <> neighbor_id GROUP BY 1, 2 HAVING count(*) >= 4"))(
    lambda s, d: query.near_neighbors(_probes(w.load(s, d, "docs_words"), w.sized(s, d, "docs_words", BASE)), 4)
)
add("knn_weighted", sql.query([*sql.index(HEAVY, features="docs_words"), ("g", sql.ranked(f"SELECT query_id, neighbor_id, round(sum(greatest(1.0::DOUBLE, seen / {HEAVY.r}.0::DOUBLE)), 6) AS weight FROM met WHERE query_id <> neighbor_id GROUP BY 1, 2", TOP, "weight"))], "SELECT * FROM g"))(
    lambda s, d: query.weighted_select(_probes(w.load(s, d, "docs_words"), HEAVY), TOP, HEAVY.r)
)
_da, _db, _dc, _dd = parameters(501, 4)
add("adaptive_sample", sql.query([*sql.index(BASE, features="docs_words"), ("bk", "SELECT query_id, list(m ORDER BY table_id) AS buckets FROM (SELECT query_id, table_id, list(neighbor_id ORDER BY neighbor_id) AS m FROM met GROUP BY 1, 2) GROUP BY 1"), ("dr", f"SELECT query_id, draw, buckets, ((query_id % {P}) * 31 + draw * 1009) % {P} AS x FROM bk, range(3) r(draw)"), ("pk", f"SELECT query_id, draw, x, buckets[(x * {_da} + {_db}) % {P} % len(buckets) + 1] AS m FROM dr")], f"SELECT query_id, draw, m[(x * {_dc} + {_dd}) % {P} % len(m) + 1] AS neighbor_id FROM pk"))(
    lambda s, d: query.adaptive_sample(_probes(w.load(s, d, "docs_words"), w.sized(s, d, "docs_words", BASE)), 3)
)
add("knn_reranked", sql.query([*sql.graph(BASE, TOP, features="docs_words"), *sql.overlaps(), ("g", sql.ranked(f"SELECT query_id, neighbor_id, coalesce({sql.COSINE}, 0) AS similarity FROM graph LEFT JOIN over USING (query_id, neighbor_id)", 3, "similarity"))], "SELECT * FROM g"))(
    lambda s, d: query.rerank(graph(s, d, "docs_words", BASE, TOP), w.load(s, d, "docs_words"), 3)
)

# ---------------------------------------------------------------- baselines

add("vanilla_lsh", sql.query([*sql.addresses(BASE, features="docs_words"), ("light", "SELECT table_id, address FROM addr GROUP BY 1, 2 HAVING count(*) BETWEEN 2 AND 200"), ("pairs", "SELECT DISTINCT x.item_id AS query_id, y.item_id AS neighbor_id FROM addr x JOIN light USING (table_id, address) JOIN addr y USING (table_id, address) WHERE x.item_id <> y.item_id"), *sql.overlaps(), ("g", sql.ranked(f"SELECT query_id, neighbor_id, coalesce({sql.COSINE}, 0) AS similarity FROM pairs LEFT JOIN over USING (query_id, neighbor_id)", TOP, "similarity"))], "SELECT * FROM g"))(
    lambda s, d: baselines.vanilla_lsh(w.load(s, d, "docs_words"), w.sized(s, d, "docs_words", BASE), TOP, 200)
)


def _counted_sql(sig: tuple[str, str], p: IndexParams) -> str:
    return sql.query([*sql.feats("docs_words"), sig, *sql.fold(p.k, "sig", sql.room(p, "docs_words"), p.seed), *sql.reservoirs(p), ("met", "SELECT a.item_id AS query_id, s.item_id AS neighbor_id FROM addr a JOIN res s USING (table_id, address)"), ("g", sql.ranked("SELECT query_id, neighbor_id, count(*) AS collisions FROM met WHERE query_id <> neighbor_id GROUP BY 1, 2", TOP))], "SELECT * FROM g")


add("minwise_lsh", _counted_sql(_MINWISE, BASE))(lambda s, d: baselines.minwise_lsh(w.load(s, d, "docs_words"), w.sized(s, d, "docs_words", BASE), TOP))
SIGNS = replace(BASE, k=8, tables=8)
_sg = parameters(2001, 128)
_SIGNED = ("sig", "SELECT item_id, k::BIGINT AS i, (sum(1 - 2 * (((f * a + b) % {} // 65536) % 2)) >= 0)::BIGINT AS v FROM feats, (VALUES {}) c(k, a, b) GROUP BY 1, 2".format(P, ", ".join(f"({k}, {_sg[2 * k]}::BIGINT, {_sg[2 * k + 1]}::BIGINT)" for k in range(64))))
add("signed_projection_lsh", _counted_sql(_SIGNED, SIGNS))(lambda s, d: baselines.signed_lsh(w.load(s, d, "docs_words"), w.sized(s, d, "docs_words", SIGNS), TOP))
# ---------------------------------------------------------------- measures and sweeps

KS = (1, 10, 20, 100)


def _url_recall(p: IndexParams, s, d) -> DataFrame:
    sets = w.load(s, d, "pages_url")
    return metrics.recall_at(index.knn_graph(sets, w.sized(s, d, "pages_url", p), 100), url_gold(sets, 100, best=True), KS)


_URL_GOLD = [*sql.feats("pages_url", "t"), *sql.gold(100, "t")]
add("recall_at_k", sql.query([*sql.graph(URLS, 100, features="pages_url"), *_URL_GOLD], sql.recall(KS, "graph", "tgold")))(lambda s, d: _url_recall(URLS, s, d))
add("similarity_at_k", sql.query([*sql.graph(URLS, 100, features="pages_url"), *sql.overlaps(), ("n", "SELECT count(DISTINCT item_id) AS n FROM feats")], "SELECT k, round(avg(coalesce(a / sqrt(x::DOUBLE * y), 0)), 6) AS similarity, round(count(*) / (SELECT n FROM n), 6) AS returned FROM graph LEFT JOIN over USING (query_id, neighbor_id), (VALUES (1), (10), (100)) v(k) WHERE rank <= k GROUP BY k"))(
    lambda s, d: metrics.similarity_at(graph(s, d, "pages_url", URLS, 100), w.load(s, d, "pages_url"), w.load(s, d, "pages_url"))
)
add("threshold_recall", sql.query([*sql.graph(BASE, 20, features="docs_words"), *sql.overlaps()], f"SELECT sum(n)::BIGINT AS pairs, sum(h)::BIGINT AS found, round(sum(h) / sum(n), 6) AS recall, round(sum(h) / sum(least(n, 20)), 6) AS capped_recall FROM (SELECT query_id, count(*) AS n, count(rank) AS h FROM over LEFT JOIN graph USING (query_id, neighbor_id) WHERE {sql.COSINE} > 0.65 GROUP BY 1)"))(
    lambda s, d: found_above(s, d, "docs_words", BASE, (0.65,), 20)[0]
)


def found_above(s, d, name: str, p: IndexParams, taus: tuple[float, ...], k: int) -> list[DataFrame]:
    """For each of ``taus``, the pairs above it and those among the first ``k``; sets and graph are made once for all."""
    sets = stored(w.load(s, d, name))
    near = settled(index.knn_graph(sets, w.sized(s, d, name, p), k))
    each = settled(exact.degrees_above(sets, near, taus))
    return [metrics.recall_of_degrees(each.where(F.col("tau") == tau), k) for tau in taus]


def _sweep(grid: list[tuple[str, IndexParams]]):
    def run(s, d):
        """Gold once, addresses once for all settings that share them, and a job per setting: one plan of all would fill the driver."""
        sets = w.load(s, d, "pages_url")
        gold, addressed, out = stored(url_gold(sets, 100, best=True)), {}, []
        for label, p in grid:
            p = w.sized(s, d, "pages_url", p)
            key = (p.k, p.tables, p.bits)
            if key not in addressed:
                addressed[key] = stored(index.addresses(sets, p))
            addr = addressed[key]
            graph = query.count_select(index.index_of(addr, p).probe(addr), 100, "segment")
            out.append(settled(metrics.recall_at(graph, gold, (10,)).select(F.lit(label).alias("setting"), "recall", "n_queries")))
        return reduce(DataFrame.unionByName, out)

    parts, ends = list(_URL_GOLD), []
    for i, (label, p) in enumerate(grid):
        parts += sql.graph(p, 100, f"s{i}", "pages_url")
        ends.append(f"SELECT '{label}' AS setting, recall, n_queries FROM ({sql.recall((10,), f's{i}graph', 'tgold')})")
    return run, sql.query(parts, " UNION ALL ".join(ends))


for _name, _grid in (
    ("sweep_kl", [(f"K={k} L={t}", replace(URLS, k=k, tables=t, r=64)) for k in (1, 2, 4) for t in (8, 16, 32)]),
    ("sweep_lr", [(f"L={t} R={r}", replace(URLS, k=4, tables=t, r=r)) for t in (8, 16, 32) for r in (8, 16, 32, 64)]),
    ("sweep_f", [(f"F={f}", replace(URLS, k=4, share=f, bits=8)) for f in (1.0, 0.5, 0.3, 0.2, 0.1, 0.05)]),
):
    _run, _text = _sweep(_grid)
    add(_name, _text)(_run)

PURCHASES = IndexParams(k=1, tables=32, r=32, bits=12)
add("heavy_entries", sql.query([*sql.graph(PURCHASES, 20, features="cust_parts"), *sql.overlaps()], f"SELECT query_id AS i, neighbor_id AS j, {sql.COSINE} AS value FROM graph JOIN over USING (query_id, neighbor_id) WHERE {sql.COSINE} > 0.1"))(
    lambda s, d: matmul.heavy_entries(w.cust_parts(s, d), w.sized(s, d, "cust_parts", PURCHASES), 20, 0.1)
)
add("heavy_entries_exact", sql.query([*sql.feats("cust_parts"), *sql.overlaps()], f"SELECT query_id AS i, neighbor_id AS j, {sql.COSINE} AS value FROM over WHERE {sql.COSINE} > 0.1"))(lambda s, d: matmul.exact_product(w.cust_parts(s, d), 0.1))
add("estimator_error", sql.query([*sql.graph(BASE, TOP, features="docs_words"), *sql.overlaps()], "SELECT round(avg(e), 6) AS bias, round(avg(e * e), 6) AS mean_square, count(*) AS pairs FROM (SELECT collisions / 16.0::DOUBLE - pow(coalesce(a / (x + y - a)::DOUBLE, 0), 2) AS e FROM graph LEFT JOIN over USING (query_id, neighbor_id))"))(
    lambda s, d: metrics.estimator_error(graph(s, d, "docs_words", BASE, TOP), w.load(s, d, "docs_words"), BASE.k, BASE.tables)
)
add("recommend_parts", sql.query(sql.graph(PURCHASES, 5, features="part_custs"), "SELECT * FROM graph"))(lambda s, d: graph(s, d, "part_custs", PURCHASES, 5))
LINES = IndexParams(k=4, tables=16, r=16, bits=16)
add("workload_lines", sql.query(sql.graph(LINES, 5, features="lines_cat"), "SELECT * FROM graph"))(lambda s, d: graph(s, d, "lines_cat", LINES, 5))
add("workload_users", sql.query(sql.graph(BASE, 5, features="user_events"), "SELECT * FROM graph"))(lambda s, d: graph(s, d, "user_events", BASE, 5))
add("workload_turns", sql.query(sql.graph(BASE, 5, features="turns_words"), "SELECT * FROM graph"))(lambda s, d: graph(s, d, "turns_words", BASE, 5))
add("workload_char3", sql.query(sql.graph(BASE, 5, features="docs_char3"), "SELECT * FROM graph"))(lambda s, d: graph(s, d, "docs_char3", BASE, 5))
add("workload_pages", sql.query(sql.graph(BASE, 5, features="pages_full"), "SELECT * FROM graph"))(lambda s, d: graph(s, d, "pages_full", BASE, 5))

# ---------------------------------------------------------------- further measures and theory

add("bucket_gini", sql.query([*_addr, ("h", "SELECT table_id, n, count(*) AS c FROM (SELECT table_id, address, count(*) AS n FROM addr GROUP BY 1, 2) GROUP BY 1, 2"), ("s", "SELECT table_id, c, n, c * (2 * coalesce(sum(c * n) OVER (PARTITION BY table_id ORDER BY n ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + c * n) AS area FROM h")], "SELECT table_id, round(1 - sum(area) / (sum(c) * sum(c * n)), 6) AS gini FROM s GROUP BY 1"))(
    lambda s, d: metrics.gini(index.addresses(w.load(s, d, "docs_words"), w.sized(s, d, "docs_words", BASE))).withColumn("gini", F.round("gini", 6))
)
_ma, _mb, _mc, _md = parameters(4, 4)
_order = "(SELECT item_id, row_number() OVER (ORDER BY ((item_id % {2}) * {0} + {1}) % {3}) AS i FROM (SELECT DISTINCT item_id FROM feats) QUALIFY i <= 200)"
add("mean_similarity", sql.query([*sql.feats("docs_words"), *sql.overlaps(), ("l", _order.format(_ma, _mb, 2**31, P)), ("r", _order.format(_mc, _md, 2**31, P))], "SELECT round(avg(coalesce(a / sqrt(x::DOUBLE * y), 0)), 6) AS mean_cosine, count(*) AS pairs FROM l JOIN r USING (i) LEFT JOIN over ON query_id = l.item_id AND neighbor_id = r.item_id WHERE l.item_id <> r.item_id"))(
    lambda s, d: metrics.mean_similarity(features.drop_empty(w.load(s, d, "docs_words")), 200).withColumn("mean_cosine", F.round("mean_cosine", 6))
)

"""Laws and worked examples of hashing, reservoirs, counting, measures and theory."""

from __future__ import annotations

import math
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from collidra.functions import cosine_binary, jaccard
from collidra.operators import baselines, exact, features, hashing, index, matmul, metrics, planner, query, reservoir
from collidra.operators.index import IndexParams
from collidra.plans import workloads as w

SETS = "item_id long, features array<long>"


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def made(spark, data):
    return spark.createDataFrame(data, SETS)


# ---------------------------------------------------------------- similarities


def test_similarities_of_small_sets(spark):
    df = spark.createDataFrame([([1, 2, 3], [2, 3, 4]), ([1], [1]), ([], [1]), ([], [])], "x array<long>, y array<long>")
    got = df.select(jaccard(F.col("x"), F.col("y")), cosine_binary(F.col("x"), F.col("y"))).collect()
    assert [tuple(round(v, 6) for v in r) for r in got] == [(0.5, 0.666667), (1.0, 1.0), (0.0, 0.0), (0.0, 0.0)]


def test_empty_null_and_repeated_tokens(spark):
    df = spark.createDataFrame([(1, None), (2, ""), (3, "b a B"), (None, "x")], "id long, text string")
    got = {r["item_id"]: len(r["features"]) for r in features.token_set(df, "id", "text").collect()}
    assert got == {1: 0, 2: 0, 3: 2, None: 1}
    assert {r["item_id"]: len(r["features"]) for r in features.char_ngrams(df, "id", "text").collect()} == {1: 0, 2: 0, 3: 3, None: 0}


# ---------------------------------------------------------------- hashing


def _sets(nnz, j, rng):
    a = round(2 * nnz * j / (1 + j))
    ids = rng.choice(2**28, 2 * nnz - a, replace=False)
    return ids[:nnz], np.concatenate([ids[:a], ids[nnz:]])


@pytest.mark.parametrize("scheme", ["probe", "rotation", "two_way"])
@pytest.mark.parametrize(("nnz", "j"), [(8, 0.45), (60, 0.5), (300, 0.5)])
def test_agreement_estimates_jaccard(scheme, nnz, j):
    rng = np.random.default_rng(3)
    agree, true = [], []
    for seed in range(120):
        x, y = _sets(nnz, j, rng)
        sig = hashing.signatures_of(np.concatenate([x, y]), np.array([len(x), len(y)]), 64, scheme, seed + 1)
        agree.append((sig[0] == sig[1]).mean())
        true.append(len(np.intersect1d(x, y)) / len(np.union1d(x, y)))
    assert abs(np.mean(agree) - np.mean(true)) < 4 * np.std(agree) / len(agree) ** 0.5 + 0.01


def test_no_bin_stays_empty_and_equal_sets_agree():
    flat = np.array([5, 5, 9, 11, 9, 11], dtype=np.int64)
    for scheme in ("probe", "rotation", "two_way"):
        sig = hashing.signatures_of(flat, np.array([1, 1, 2, 2]), 128, scheme, 1)
        assert (sig >= 0).all() and (sig < 2**62).all()
        assert (sig[0] == sig[1]).all() and (sig[2] == sig[3]).all()


def test_forms_of_signatures_are_equal(spark, small):
    sets = w.pages_url(spark, small)
    forms = [rows(hashing.doph(sets, 2, 8, form=f).select("item_id", F.concat_ws(",", F.col("sig").cast("array<string>")))) for f in ("arrow", "relational", "native")]
    assert forms[0] == forms[1] == forms[2]


def test_addresses_stay_in_range(spark, small):
    addr = index.addresses(w.docs_words(spark, small), IndexParams(k=4, tables=8, bits=10))
    got = addr.agg(F.min("address"), F.max("address"), F.count_distinct("table_id")).first()
    assert 0 <= got[0] and got[1] < 1024 and got[2] == 8


def test_retrieval_rises_with_similarity():
    rng = np.random.default_rng(1)
    rates = []
    for j in (0.1, 0.3, 0.5, 0.7, 0.9):
        hit = 0
        for seed in range(150):
            x, y = _sets(100, j, rng)
            sig = hashing.signatures_of(np.concatenate([x, y]), np.array([100, len(y)]), 16, "probe", seed + 1).reshape(2, 8, 2)
            hit += bool((sig[0] == sig[1]).all(axis=1).any())
        rates.append((j, hit / 150))
    assert planner.monotone(rates, 0.05) and rates[-1][1] > 0.95
    for j, r in rates:
        assert abs(r - planner.retrieval(j, 2, 8)) < 0.15


# ---------------------------------------------------------------- reservoirs


def _addr(spark, n, buckets=1):
    return spark.range(n).select(F.col("id").alias("item_id"), F.lit(0).alias("table_id"), F.pmod("id", F.lit(buckets)).alias("address"))


@pytest.mark.parametrize("policy", ["priority", "arrival"])
def test_uniform_policies_fill_their_room(spark, policy):
    for m, r in ((5, 8), (8, 8), (40, 8)):
        got = reservoir.reservoir(_addr(spark, m), r, policy).first()
        assert got["seen"] == m and len(set(got["members"])) == min(m, r)


@pytest.mark.parametrize("policy", ["priority", "arrival"])
def test_inclusion_is_uniform(spark, policy):
    addr = spark.range(32 * 400).select(F.pmod("id", F.lit(32)).alias("item_id"), F.lit(0).alias("table_id"), F.floor(F.col("id") / 32).alias("address"))
    counts = Counter(r[0] for r in reservoir.reservoir(addr, 8, policy).select(F.explode("members")).collect())
    assert sum(counts.values()) == 3200
    chi = sum((counts[i] - 100) ** 2 / 75 for i in range(32))
    assert chi < 75  # 31 degrees of freedom


def test_overwriting_policy_loses_half_of_what_would_fit(spark):
    addr = spark.range(32 * 300).select(F.pmod("id", F.lit(32)).alias("item_id"), F.lit(0).alias("table_id"), F.floor(F.col("id") / 32).alias("address"))
    held = reservoir.reservoir(addr, 32, "literal_add").agg(F.avg(F.size("members"))).first()[0]
    assert abs(held - planner.overwrite_occupancy(32, 32)) < 0.5 and abs(planner.overwrite_occupancy(32, 32) - 16.5) < 1e-9


def test_merge_equals_one_build(spark, small):
    p = IndexParams(k=1, tables=8, r=4, bits=8)
    sets = w.docs_words(spark, small)
    one = rows(index.build_index(sets, p).reservoirs.select("table_id", "address", "seen", F.concat_ws(",", F.col("members").cast("array<string>"))))
    two = index.build_index(sets.where("item_id % 2 = 0"), p).append(sets.where("item_id % 2 = 1")).reservoirs
    assert one == rows(two.select("table_id", "address", "seen", F.concat_ws(",", F.col("members").cast("array<string>"))))


def test_rows_do_not_depend_on_partitions(spark, small):
    p = IndexParams(k=1, tables=8, r=4, bits=8)
    base = rows(index.knn_graph(w.docs_words(spark, small), p, 5))
    assert base == rows(index.knn_graph(w.docs_words(spark, small).repartition(13), p, 5))


def test_all_local_reservoirs_equal_no_sharing(spark, small):
    p = IndexParams(k=1, tables=4, r=1000, bits=8)
    addr = index.addresses(w.docs_words(spark, small), p)
    pointers = reservoir.share_pointers(addr, 4, 8, 0.5, "pooled", 1, 1.0)
    assert pointers.groupBy("reservoir_id").count().where("count > 1").count() == 0
    shared = rows(query.count_select(query.probe(addr, reservoir.shared_reservoirs(addr, pointers, 1000), pointers), 5))
    assert shared == rows(query.count_select(query.probe(addr, reservoir.reservoir(addr, 1000)), 5))


def test_unknown_settings_are_refused(spark):
    for bad in (lambda: reservoir.reservoir(_addr(spark, 3), 2, "other"), lambda: reservoir.pool_size(2, 4, 0), lambda: index.build_index(made(spark, [(1, [1])]), IndexParams(densify="x", form="relational")).reservoirs):
        with pytest.raises(ValueError):
            bad()


def test_group_limit_comes_before_the_shuffle(spark, small):
    addr = index.addresses(w.docs_words(spark, small), IndexParams(k=1, tables=4, r=4, bits=8))
    plan = reservoir.reservoir(addr, 4)._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in plan and "Partial" in plan


# ---------------------------------------------------------------- counting


def test_counting_keeps_single_hits_and_segment_edges(spark):
    probes = spark.createDataFrame(
        [(1, 0, 2, [7, 8]), (1, 1, 2, [8, 9]), (2, 0, 2, [9, 9]), (3, 0, 1, [9])], "query_id long, table_id int, seen long, members array<long>"
    )
    want = [(1, 7, 2, 1), (1, 8, 1, 2), (1, 9, 3, 1), (2, 9, 1, 2), (3, 9, 1, 1)]
    for strategy in ("hash", "segment", "boundary"):
        assert rows(query.count_select(probes, 5, strategy)) == want


def test_copies_find_each_other_first(spark):
    data = made(spark, [(i, [i * 50 + j for j in range(40)]) for i in range(20)] + [(100 + i, [i * 50 + j for j in range(40)]) for i in range(20)])
    got = index.knn_graph(data, IndexParams(k=2, tables=8, r=8, bits=12), 1).collect()
    assert {(r["query_id"], r["neighbor_id"]) for r in got} == {(i, 100 + i) for i in range(20)} | {(100 + i, i) for i in range(20)}


def test_empty_and_single_items(spark):
    p = IndexParams(k=2, tables=4, r=4, bits=8)
    assert index.knn_graph(made(spark, []), p, 3).count() == 0
    assert index.knn_graph(made(spark, [(1, [5])]), p, 3).count() == 0
    assert index.knn_graph(made(spark, [(1, []), (2, [5]), (3, [5])]), p, 3).count() == 2


def test_batches_make_the_same_graph(spark, small):
    p = IndexParams(k=1, tables=8, r=8, bits=10)
    whole = rows(index.knn_graph(w.pages_url(spark, small), p, 5))
    assert whole == rows(index.knn_graph(w.pages_url(spark, small), p, 5, batches=4))


# ---------------------------------------------------------------- exact, baselines, products


def test_inverted_join_equals_brute_force(spark, small):
    sets = w.pages_url(spark, small)
    assert rows(exact.exact_inverted(sets, sets, 5)) == rows(exact.brute_force(sets, sets, 5))


def test_heavy_entries_are_exact_where_found(spark, small):
    cols = w.cust_parts(spark, small)
    every = {(r["i"], r["j"]): r["value"] for r in matmul.exact_product(cols, 0.1).collect()}
    found = {(r["i"], r["j"]): r["value"] for r in matmul.heavy_entries(cols, IndexParams(k=1, tables=32, r=32, bits=12), 20, 0.1).collect()}
    assert found and all(every[k] == v for k, v in found.items())


def test_vanilla_finds_all_that_the_engine_finds(spark, small):
    p = IndexParams(k=2, tables=8, r=10_000, bits=12)
    sets = w.pages_url(spark, small)
    engine = {(r["query_id"], r["neighbor_id"]) for r in index.knn_graph(sets, p, 10_000).collect()}
    vanilla = {(r["query_id"], r["neighbor_id"]) for r in baselines.vanilla_lsh(sets, p, 10_000, 10_000).collect()}
    assert engine == vanilla


def test_small_world_recall(spark, small):
    sets = w.pages_url(spark, small)
    gold = exact.exact_inverted(sets, sets, 10)
    got = metrics.recall_at(baselines.small_world_graph(sets, sets, 10), gold, (10,)).first()["recall"]
    assert got > 0.9


def test_quantized_search_finds_most_of_the_best(spark, small):
    v = w.vectors(spark, small)
    books = baselines.pq_train(v, 16, 64)
    got = {(r["query_id"], r["neighbor_id"]) for r in baselines.pq_search(baselines.pq_encode(v, books), v.where("item_id < 30"), books, 10).collect()}
    best = {(r["query_id"], r["neighbor_id"]) for r in exact.flat_dense(v.where("item_id < 30"), v, 1).collect()}
    assert len(best & got) / len(best) > 0.6


def test_dense_form_refuses_what_it_cannot_hold(spark):
    with pytest.raises(MemoryError):
        features.to_dense(made(spark, [(1, [1])]), [1, 2, 3], 8)
    with pytest.raises(TypeError):
        hashing.hadamard_projection(made(spark, [(1, [1])]), "item_id", "features", 4)


# ---------------------------------------------------------------- measures and theory


def test_recall_with_ties_and_short_lists(spark):
    gold = spark.createDataFrame([(1, 2, 0.9, 1), (1, 3, 0.9, 2), (1, 4, 0.5, 3), (2, 5, 0.8, 1)], "query_id long, neighbor_id long, similarity double, rank int")
    graph = spark.createDataFrame([(1, 4, 1, 9), (1, 3, 2, 8)], "query_id long, neighbor_id long, rank int, collisions long")
    assert rows(metrics.recall_at(graph, gold, (1, 2))) == [(1, 0.0, 2), (2, 0.5, 2)]


def test_capped_recall(spark):
    gold = spark.createDataFrame([(1, i, 0.9, i) for i in range(30)], "query_id long, neighbor_id long, similarity double, rank int")
    graph = spark.createDataFrame([(1, i, i + 1, 1) for i in range(20)], "query_id long, neighbor_id long, rank int, collisions long")
    got = metrics.threshold_recall(graph, gold, 0.65, 20).first()
    assert (got["pairs"], got["found"], got["capped_recall"]) == (30, 20, 1.0) and abs(got["recall"] - 0.666667) < 1e-6


def test_similarity_of_short_lists(spark):
    sets = made(spark, [(1, [1, 2]), (2, [1, 2]), (3, [9])])
    graph = spark.createDataFrame([(1, 2, 1, 3)], "query_id long, neighbor_id long, rank int, collisions long")
    asked = sets.where("item_id < 3")
    assert rows(metrics.similarity_at(graph, sets, asked, (1,))) == [(1, 1.0, 0.5)]
    assert rows(metrics.similarity_at(graph, sets, asked, (1,), pad=True)) == [(1, 0.5, 0.5)]


def test_smallest_reservoir_and_sizes():
    assert planner.min_reservoir() == 5
    assert abs(planner.success(4) - 0.4741) < 1e-4 and abs(planner.success(5) - 0.5057) < 1e-4
    assert planner.index_bytes(32, 64, 20, counter_bytes=0) == 8 * 2**30
    assert planner.index_bytes(32, 32, 15, counter_bytes=0) == 2**27
    assert planner.index_bytes(32, 64, 20, 0.3) < 0.35 * planner.index_bytes(32, 64, 20)


def test_three_way_conditional_against_simulation():
    a, b, y = 10, 1, 20  # all of y but its common core lies outside
    core = a
    union = a + b + 2 + 2 + y
    exact_value = planner.conditional_collision(a, b + 4, union, 0)
    assert 0 < exact_value <= 1
    rng = np.random.default_rng(2)
    q, x = set(range(core + 1)) | {100, 101}, set(range(core + 1)) | {200, 201}
    other = set(range(core)) | set(range(300, 300 + y))
    everything = np.array(sorted(q | x | other))
    both = meet = 0
    for _ in range(20_000):
        order = {e: i for i, e in enumerate(rng.permutation(everything))}
        low = [min(s, key=order.get) for s in (q, x, other)]
        if low[0] == low[1]:
            both += 1
            meet += low[1] == low[2]
    jq = len(q & other) / len(q | other)
    assert meet / both > jq + 0.03  # the assumed bound fails for sets that share a core
    assert planner.conditional_printed(a, b, y) < meet / both


def test_moments_and_exponents():
    m = planner.count_moments(0.5, 2, 16)
    assert m["count_mean"] == 4 and abs(m["count_variance"] - 3) < 1e-12 and abs(m["rate_variance"] - 3 / 256) < 1e-12
    assert m["relative_variance"] < planner.count_moments(0.2, 2, 16)["relative_variance"]
    assert 0 < planner.minwise_rho(0.8, 0.5) < 1
    assert planner.retrieval_with_reservoirs(0.5, 2, 8, [8] * 16) == pytest.approx(planner.retrieval(0.5, 2, 16))
    assert planner.retrieval_with_reservoirs(0.5, 2, 8, [80] * 16) < planner.retrieval(0.5, 2, 16)
    assert math.isclose(planner.dense_work(350_000, 3728), 4.5668e14)
    k, tables = planner.parameters_for(10_000, 0.8, 0.4)
    assert k == 11 and tables >= 1


def test_url_neighbours_have_high_recall(spark):
    d = "/root/testdata/sf0.01"
    sets = w.pages_url(spark, d)
    got = {r["k"]: r["recall"] for r in metrics.recall_at(index.knn_graph(sets, IndexParams(k=2, tables=32, r=32, bits=15), 100), exact.exact_inverted(sets, sets, 100), (10, 100)).collect()}
    assert got[100] >= 0.95 and got[10] >= 0.9


def test_more_tables_and_larger_reservoirs_do_not_hurt(spark):
    d = "/root/testdata/sf0.01"
    sets = w.pages_url(spark, d).cache()
    gold = exact.exact_inverted(sets, sets, 20).cache()

    def r10(**kw):
        return metrics.recall_at(index.knn_graph(sets, IndexParams(**({"k": 2, "tables": 16, "r": 32, "bits": 12} | kw)), 20), gold, (10,)).first()["recall"]

    assert r10(tables=32) >= r10(tables=4) - 0.02 and r10(r=32) >= r10(r=2) - 0.02


# ---------------------------------------------------------------- exact pairs, blocks, sizes


def random_sets(spark, n=120, seed=3):
    import numpy as np

    rng = np.random.default_rng(seed)
    rows = [(i, sorted({1, 2, *rng.integers(0, 60, int(rng.integers(1, 25))).tolist()})) for i in range(n)]
    return spark.createDataFrame(rows, "item_id long, features array<long>"), {i: set(f) for i, f in rows}


@pytest.mark.parametrize("heavy_df", [1, 10, 60, 10**6])
def test_splitting_off_common_features_changes_nothing(spark, heavy_df):
    from collidra.operators import exact

    sets, _ = random_sets(spark)
    asked = sets.where("item_id % 7 = 0")
    rows = lambda df: sorted(map(tuple, df.collect()))
    assert rows(exact.overlap_pairs(asked, sets, heavy_df, block=5)) == rows(exact.overlap_pairs(asked, sets))
    assert rows(exact.exact_inverted(asked, sets, 5, heavy_df=heavy_df)) == rows(exact.brute_force(asked, sets, 5, block=4))


@pytest.mark.parametrize("tau", [0.1, 0.5, 0.8, 0.95])
def test_prefixes_find_all_pairs_above(spark, tau):
    from collidra.operators import exact

    sets, plain = random_sets(spark, seed=int(100 * tau))
    got = {(r["query_id"], r["neighbor_id"]): (r["a"], r["x"], r["y"]) for r in exact.pairs_above(sets, tau).collect()}
    want = {}
    for i, x in plain.items():
        for j, y in plain.items():
            if i != j and len(x & y) / (len(x) * len(y)) ** 0.5 > tau:
                want[i, j] = (len(x & y), len(x), len(y))
    assert want.items() <= got.items() and all(a / (x * y) ** 0.5 > tau - 1e-5 for a, x, y in got.values())


def test_pairs_above_are_counted_without_exchange_of_pairs(spark, monkeypatch):
    """Sums per item equal those of the pairs, over several blocks; neither plan joins or exchanges sets or pairs."""
    from collections import Counter

    from collidra.operators import exact

    sets, plain = random_sets(spark, seed=11)
    monkeypatch.setattr(exact, "BLOCK_FEATURES", 300)
    near = {(i, j) for i, x in plain.items() for j, y in plain.items() if i != j and int(len(x & y) / (len(x) * len(y)) ** 0.5 * 1e6 + 0.5) > 5e5}
    graph = spark.createDataFrame([(i, j) for i, j in sorted(near) if j % 3 == 0] + [(0, 10**9)], "query_id long, neighbor_id long")
    got = exact.degrees_above(sets, graph, (0.5, 0.9)).where("tau = 0.5").drop("tau")
    want, hits = Counter(i for i, _ in near), Counter(i for i, j in near if j % 3 == 0)
    assert sorted(map(tuple, got.collect())) == sorted((i, n, hits[i]) for i, n in want.items()) and near
    pairs = exact.pairs_above(sets, 0.5)
    assert "Exchange" not in pairs._jdf.queryExecution().executedPlan().toString() and "Join" not in got._jdf.queryExecution().executedPlan().toString()
    assert exact.pairs_above(sets.limit(0), 0.5).count() == 0 and exact.degrees_above(sets.limit(0), graph, (0.5,)).count() == 0


def test_counting_bags_in_batches_equals_aggregation(spark):
    from collidra.operators import query

    rows = [(q, 0, 9, [1, 2, q, 3 + q % 3]) for q in range(50)] + [(q, 1, 9, [2, q, 77]) for q in range(50)] + [(99, 0, 1, [99])]
    probes = spark.createDataFrame(rows, "query_id long, table_id int, seen long, members array<long>")
    same = [sorted(map(tuple, query.count_select(probes, 3, s).collect())) for s in ("hash", "segment", "boundary")]
    assert same[0] == same[1] == same[2] and all(r[0] != 99 for r in same[0])
    assert query.count_select(probes.limit(0), 3).count() == 0


def test_address_bits_grow_with_the_table():
    p = IndexParams(bits=12)
    assert p.grown(1000).bits == 12 and p.grown(10**9).bits > 24


def test_a_cluster_without_a_shared_folder_is_refused(spark, monkeypatch):
    from collidra import sources

    class Conf:
        def get(self, *_):
            return None

    class Context:
        master = "yarn"

        def getCheckpointDir(self):
            return None

    class Session:
        conf, sparkContext = Conf(), Context()

    with pytest.raises(RuntimeError):
        sources.scratch(Session())


def test_oversized_sets_are_not_padded(spark):
    from collidra.operators import features

    df = spark.createDataFrame([(1, [1, 2, 3]), (2, [1])], "item_id long, features array<long>")
    assert {r["item_id"]: len(r["features"]) for r in features.asymmetric_pad(df, "data", 2).collect()} == {1: 3, 2: 2}


def test_signed_projections_need_more_values_and_rank_worse():
    from collidra.operators import planner

    for j in (0.2, 0.5, 0.8):
        assert planner.values_needed(15, True, 1 << 24) == 15 > planner.values_needed(15, False, 1 << 24)
        assert planner.ranking_variance(j, 15, 32, True, 1 << 24) > planner.ranking_variance(j, 15, 32, False, 1 << 24)


def test_search_by_class_equals_the_join(spark):
    rng = np.random.default_rng(8)
    data = [(i, sorted({int(x) for x in np.minimum(rng.geometric(0.15, 6), 40)} | ({1000 + int(rng.integers(0, 90))} if i % 3 else set()))) for i in range(300)] + [(300, []), (301, [7777])]
    sets = made(spark, data)
    other = made(spark, [(5000, [1, 2, 9999]), (5001, []), (5002, [9999])])
    for queries, k in ((sets, 7), (sets, 400), (other, 7), (sets.where("item_id % 10 = 0"), 1)):
        want = rows(exact.exact_inverted(queries, sets, k))
        assert rows(exact.exact_by_class(queries, sets, k, heavy_df=20)) == want
    want = rows(exact.exact_inverted(sets, sets, 7))
    top = {q: s for q, _, s, r in want if r == 1}
    assert rows(exact.exact_by_class(sets, sets, 7, heavy_df=20, best=True)) == [r for r in want if r[2] == top[r[0]]]


def test_a_feature_of_all_rows_makes_no_pairs(spark):
    sets = spark.range(60_000).select(F.col("id").alias("item_id"), F.array(F.lit(1).cast("long"), F.col("id") % 50 + 10, F.col("id") + 100).alias("features"))
    found = exact.exact_by_class(sets, sets, 2)  # 3.6 billion pairs share a feature
    assert found.agg(F.count("*"), F.min("similarity"), F.max("similarity")).first()[:] == (120_000, 0.666667, 0.666667)
    assert rows(found.where("query_id = 50")) == [(50, 0, 0.666667, 1), (50, 100, 0.666667, 2)]


def test_lines_of_one_id_are_one_item(spark, small, tmp_path):
    for name in ("lineitem", "orders", "part"):
        table = spark.read.parquet(f"{small}/{name}.parquet").limit(200) if name == "lineitem" else spark.read.parquet(f"{small}/{name}.parquet")
        again = table.withColumn("l_tax", F.col("l_tax") + 0.01) if name == "lineitem" else table.limit(0)  # the tax is no part of the id
        table.unionByName(again).write.parquet(f"{tmp_path}/{name}.parquet")
    sets = w.lines_cat(spark, str(tmp_path)).select("item_id", F.size("features").alias("n")).collect()
    assert len(sets) == len({r["item_id"] for r in sets}) == 200 and {r["n"] for r in sets} == {12}


def test_streams_read_tables_of_many_files(spark, small, tmp_path):
    from collidra.sources import read_stream

    table = spark.read.parquet(f"{small}/benchmark.parquet")
    table.repartition(3).write.parquet(f"{tmp_path}/benchmark.parquet")
    for folder in (small, str(tmp_path)):
        run = read_stream(spark, folder, "benchmark", table.schema).writeStream.format("memory").queryName("seen").option("checkpointLocation", f"{tmp_path}/state{len(folder)}").trigger(availableNow=True).start()
        run.awaitTermination()
        assert spark.table("seen").count() == table.count()


def test_flat_graph_leaves_its_clusters(spark):
    sets = [frozenset(r["features"]) for r in w.pages_url(spark, "/root/testdata/sf0.1").orderBy("item_id").collect()]
    graph = baselines.SmallWorld(sets, layers=1)
    hit = []
    for i in range(0, len(sets), 20):
        near = [len(sets[i] & x) / (len(sets[i]) * len(x)) ** 0.5 for j, x in enumerate(sets) if j != i]
        hit.append(max(s for s, j in graph.search(sets[i], 21, 40) if j != i) >= max(near) - 1e-9)
    assert np.mean(hit) >= 0.9


def test_exact_check_behind_codes(spark):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(4000, 32))
    v = spark.createDataFrame([(i, [float(c) for c in r]) for i, r in enumerate(x)], "item_id long, vector array<double>").coalesce(1)
    books = baselines.pq_train(v, 4, 16)
    found = {r["query_id"]: r["neighbor_id"] for r in baselines.pq_search(baselines.pq_encode(v, books, keep=True), v.where("item_id % 100 = 0"), books, 5).where("rank = 1").collect()}
    best = {i: int(np.argsort(((x - x[i]) ** 2).sum(1))[1]) for i in range(0, 4000, 100)}
    assert np.mean([found[i] == b for i, b in best.items()]) >= 0.8


def test_library_join_pairs_stated_queries_only(spark, small):
    sets = w.pages_url(spark, small)
    asked = sets.where("item_id % 100 = 0")
    for join in (baselines.ml_minhash, baselines.ml_projection):
        of_all = [r for r in rows(join(sets, 1 << 12, 4, 5)) if r[0] % 100 == 0]
        assert rows(join(sets, 1 << 12, 4, 5, queries=asked)) == of_all and of_all


def test_heavy_entries_by_signs_are_those_of_all_pairs(spark, small):
    """Blocks of columns give what all pairs give, ties by the smaller id and few kept included, and no pair is shuffled before it is ranked."""
    columns = w.cust_parts(spark, small)
    sig = {r["item_id"]: np.array(r["sig"]) for r in hashing.signed_projection(columns, 72, 1).collect()}
    want = set()
    for i, x in sig.items():
        met = [(-round(float(np.cos((1 - (x == y).mean()) * np.pi)), 6), j) for j, y in sig.items() if i != j and (x == y).reshape(-1, 6).all(axis=1).any()]
        want |= {(i, j, -v) for v, j in sorted(met)[:3] if -v > 0.1}
    for block in (40, 1 << 20):
        found = baselines.heavy_entries_projection(columns, 72, 6, 3, 0.1, block=block)
        assert {tuple(r) for r in found.collect()} == want
        assert "Join" not in found._jdf.queryExecution().executedPlan().toString()
    assert len(want) > 100


def test_heavy_entries_by_signs_of_an_empty_table(spark):
    assert rows(baselines.heavy_entries_projection(made(spark, []), 64, 8, 3, 0.1)) == []


def test_keys_of_signs_take_no_more_than_their_bands():
    """A block of a million columns is held by every task, so keys of 8 signs are bytes."""
    packed = np.random.default_rng(1).integers(0, 256, (70_000, 16), dtype=np.uint8)
    words, keys = baselines._sign_words(pa.array([r.tobytes() for r in packed], pa.binary()), 128, 8)
    assert words.shape == (2, 70_000) and keys.dtype == np.uint8 and np.array_equal(keys.T, packed)


def test_unbounded_buckets_lose_no_partner(spark):
    """Buckets of more than a thousand items count as any other, and blocks of rows give what all pairs give."""
    from collidra.plans import registry

    sets = made(spark, [(i, [1, 2, 10 + i % 7, 1000 + i]) for i in range(1100)])
    p = IndexParams(k=1, tables=4, bits=12)
    assert index.addresses(sets, p).groupBy("table_id", "address").count().agg({"count": "max"}).first()[0] > 1000
    pick = lambda df: rows(df.select("query_id", "neighbor_id", "rank", "similarity"))
    found = pick(baselines.vanilla_lsh(sets, p, 5))
    assert found == pick(baselines.vanilla_lsh(sets, p, 5, 10_000)) and len(found) > 5 * 1000
    assert pick(baselines._by_similarity(baselines._bucket_mates(sets, p, 5, block=300), 5)) == found
    assert "BETWEEN 2 AND" not in registry.ORACLES["table_unbounded"]
    assert pick(baselines.vanilla_lsh(made(spark, []), p, 5)) == []


def test_heavy_entries_by_signs_compare_every_pair(spark, small):
    """Without bands no pair is left out: an estimate above the threshold counts where no band agrees."""
    from collidra.plans import registry

    columns = w.cust_parts(spark, small)
    sig = {r["item_id"]: np.array(r["sig"]) for r in hashing.signed_projection(columns, 72, 1).collect()}
    every = [(i, -round(float(np.cos((1 - (x == y).mean()) * np.pi)), 6), j) for i, x in sig.items() for j, y in sig.items() if i != j]
    for k in (3, 1000):
        want = set()
        for i in sig:
            want |= {(i, j, -v) for v, j in sorted(e[1:] for e in every if e[0] == i)[:k] if -v > 0.1}
        for block in (40, 1 << 20):
            assert {tuple(r) for r in baselines.heavy_entries_projection(columns, 72, None, k, 0.1, block=block).collect()} == want
    assert rows(baselines.heavy_entries_projection(made(spark, []), 64, None, 3, 0.1)) == []
    assert "met" not in registry.ORACLES["heavy_entries_projection"]


def test_library_join_takes_queries_in_blocks(spark, small, monkeypatch):
    """Blocks of queries give the rows of one join of all; what is left has no pair in it, only the best of each."""
    sets = w.pages_url(spark, small)
    whole = rows(baselines.ml_minhash(sets, 1 << 12, 2, 3))
    taken = []
    monkeypatch.setattr(baselines, "settled", lambda df: taken.append(df) or baselines.stored(df))
    monkeypatch.setattr(baselines._library_join, "__defaults__", (20,))
    found = baselines.ml_minhash(sets, 1 << 12, 2, 3)
    assert rows(found) == whole and whole and len(taken) == 3
    assert "Join" not in found._jdf.queryExecution().executedPlan().toString()

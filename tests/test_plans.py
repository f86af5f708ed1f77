"""What the plans must and must not hold."""

from __future__ import annotations

from pyspark.sql import functions as F

from collidra.operators import index
from collidra.operators.index import Index, IndexParams
from collidra.plans import workloads as w


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_filters_and_columns_reach_the_scan(spark, small):
    from collidra.plans import registry

    text = plan(registry.QUERIES["scan_filter_project"](spark, small))
    assert "PushedFilters: [IsNotNull(lang)" in text and "text" not in text.split("ReadSchema")[1]


def test_hashing_needs_no_shuffle(spark, small):
    assert "Exchange" not in plan(index.addresses(w.docs_words(spark, small), IndexParams(k=2, tables=4)))


def test_small_query_sets_leave_the_index_where_it_is(spark, small, tmp_path):
    p = IndexParams(k=2, tables=4, r=8, bits=10)
    index.build_index(w.docs_words(spark, small), p).save(str(tmp_path / "i"), 4)
    stored = Index.load(spark, str(tmp_path / "i"))
    probes = stored.probe(index.addresses(w.bench_words(spark, small), p), small=True)
    assert "BroadcastHashJoin" in plan(probes) and "Exchange hashpartitioning" not in plan(probes)


def test_one_table_prunes_the_rest(spark, small, tmp_path):
    p = IndexParams(k=2, tables=4, r=8, bits=10)
    index.build_index(w.docs_words(spark, small), p).save(str(tmp_path / "i"), 2)
    text = plan(Index.load(spark, str(tmp_path / "i")).reservoirs.where("table_id = 2"))
    assert "PartitionFilters: [isnotnull(table_id" in text


def test_bucketed_index_is_not_shuffled(spark, small):
    p = IndexParams(k=2, tables=4, r=8, bits=10)
    built = index.build_index(w.docs_words(spark, small), p)
    built.save_bucketed("stored_index", 4)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        text = plan(index.addresses(w.docs_words(spark, small), p).join(spark.table("stored_index"), ["table_id", "address"]))
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql("DROP TABLE stored_index")
    assert text.count("Exchange hashpartitioning") == 1


def test_auto_bits_follow_the_number_of_items():
    assert IndexParams().auto(1000).bits < IndexParams().auto(10**9).bits <= 30


def test_batches_restrict_the_queries(spark, small):
    p = IndexParams(k=1, tables=4, r=8, bits=10)
    part = index.knn_graph(w.pages_url(spark, small), p, 5, batches=4, batch=1)
    assert part.where(F.pmod("query_id", F.lit(4)) != 1).count() == 0 and part.count() > 0


def test_the_collision_curve_moves_no_pairs(spark, small):
    """Pairs of documents are as many as their squares; only sums of the bins are exchanged."""
    from collidra.plans import registry

    text = plan(registry.QUERIES["collision_curve"](spark, small))
    assert "Join" not in text and text.count("Exchange") == 1


def test_theory_is_asked_of_the_given_tables(spark, small):
    from collidra.plans import registry

    for name, table in (("theory_costs", "lineitem"), ("theory_reservoirs", "lineitem"), ("theory_conditionals", "events"), ("theory_retrieval", "events"), ("theory_signed", "events")):
        df = registry.QUERIES[name](spark, small)
        assert "FileScan parquet" in plan(df) and any(f.endswith(f"{table}.parquet") for f in df.inputFiles())


def test_what_grows_with_the_rows_is_not_broadcast(spark, small):
    """Lists and pairs that repeat are small as files and in a shuffle, and fill the driver when they are broadcast."""
    from collidra.plans import registry

    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "1g")
    try:
        found = registry.QUERIES["recall_at_k"](spark, small)
        found.collect()
        assert "SortMergeJoin" in plan(found) and "BroadcastHashJoin" not in plan(found)
        addr = index.addresses(w.pages_url(spark, small), IndexParams(k=1, tables=4, r=8, bits=8, share=0.3))
        probes = index.index_of(addr, IndexParams(k=1, tables=4, r=8, bits=8, share=0.3)).probe(addr)
        probes.collect()
        assert "SortMergeJoin" in plan(probes) and "BroadcastHashJoin" not in plan(probes)
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")

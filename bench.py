"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

``python bench.py`` times the similarity engine and its baselines, each to the noop sink.
``python bench.py sweep`` prints a line per setting with recall, seconds and index size.
``python bench.py measures`` prints a line per method with its init, index and query seconds, their sum and seconds per
query, speed-ups at equal recall, 100 hashes against 100 projections, and rows a second by the number of cores.
"""

from __future__ import annotations

import json
import os
import sys
import time
from dataclasses import replace
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import SparkSession  # noqa: E402

from collidra.operators import baselines, exact, hashing, index, metrics  # noqa: E402
from collidra.operators.index import IndexParams  # noqa: E402
from collidra.plans import core, registry  # noqa: E402
from collidra.plans import workloads as w  # noqa: E402

HEADLINE = [
    "features_words", "features_char3", "doph_probe", "addresses", "reservoir_priority", "index_size", "knn_graph_hash", "knn_graph_segment", "workload_pages",
    "knn_query_benchmark", "vanilla_lsh", "minwise_lsh", "signed_projection_lsh", "project_then_knn", "hsw_graph", "exact_inverted_topk", "heavy_entries",
    "workload_lines", "threshold_recall", "table_unbounded", "heavy_entries_projection",
]


def session(cpus: str | int | None = None) -> SparkSession:
    cpus = cpus or os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", str(2 * int(cpus))).config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def timed(df) -> float:
    began = time.time()
    df.write.format("noop").mode("overwrite").save()
    return time.time() - began


def headline(spark: SparkSession, folder: str) -> dict:
    out = {}
    for name in HEADLINE:
        began = time.time()
        try:
            registry.QUERIES[name](spark, folder).write.format("noop").mode("overwrite").save()
            out[name] = round(time.time() - began, 3)
            print(f"{name}: {out[name]} s", file=sys.stderr, flush=True)
        except Exception as e:  # a failing query must not hide the others' figures
            print(f"{name}: {str(e)[:300]}", file=sys.stderr)
    return out


def sweep(spark: SparkSession, folder: str) -> None:
    """Recall against time and size over K, L, R and F, and hashing against projections."""
    sets = w.load(spark, folder, "pages_url").cache()
    gold = exact.exact_inverted(sets.where(core.ASKED), sets, 100).cache()
    gold.count()
    base = IndexParams(k=2, tables=32, r=32, bits=14)
    grid = [replace(base, k=k, tables=t, r=64) for k in (1, 2, 4) for t in (8, 32, 128)]
    grid += [replace(base, k=4, tables=t, r=r) for t in (8, 32, 128) for r in (8, 16, 32, 64)]
    grid += [replace(base, k=4, share=f, bits=8) for f in (1.0, 0.5, 0.3, 0.2, 0.1, 0.05)]
    for p in grid:
        found = engine(sets, sets, p, 100)
        recall = {r["k"]: r["recall"] for r in metrics.recall_at(found.pop("graph"), gold, (10, 100)).collect()}
        print(json.dumps({"k": p.k, "tables": p.tables, "r": p.r, "share": p.share, **found, "model_mb": round(p.model_bytes() / 1e6, 2), "recall": recall}))


def engine(sets, queries, p: IndexParams, k: int) -> dict:
    """Seconds to hash, to fill the reservoirs and to answer, and the graph."""
    began = time.time()
    addr = index.addresses(sets, p).cache()
    addr.count()
    init = time.time()
    built = index.index_of(addr, p)
    reservoirs = built.reservoirs.cache()
    reservoirs.count()
    indexed = time.time()
    graph = index.Index(p, reservoirs, built.pointers).knn(queries, k, True).cache()
    n = graph.select("query_id").distinct().count()
    done = time.time()
    addr.unpersist()
    return _seconds(init - began, indexed - init, done - indexed, n) | {"graph": graph}


def _seconds(init: float, indexed: float, asked: float, queries: int) -> dict:
    return {
        "init_s": round(init, 2), "index_s": round(indexed, 2), "query_s": round(asked, 2), "total_s": round(init + indexed + asked, 2),
        "ms_per_query": round(1000 * asked / max(queries, 1), 2),
    }


def measures(folder: str) -> None:
    spark = session()
    sets = w.load(spark, folder, "pages_full").cache()
    asked = sets.where(core.ASKED).cache()
    gold = exact.exact_inverted(asked, sets, 100).cache()
    gold.count()
    curves = []

    def report(name: str, setting: str, found: dict) -> None:
        recall = metrics.recall_at(found.pop("graph"), gold, (100,)).first()["recall"]
        curves.append((name, float(recall), float(found["query_s"])))
        print(json.dumps({"method": name, "setting": setting, **found, "recall_100": recall}), flush=True)

    engine(sets, asked, core.URLS, 100)  # start-up is no method's cost
    for t in (1, 2, 4, 8, 16):
        report("engine", f"F=1, L={t}", engine(sets, asked, replace(core.URLS, tables=t), 100))
    report("engine, shared", "F=0.3, L=16", engine(sets, asked, replace(core.URLS, share=0.3), 100))
    for ef in (2, 5, 10, 40):
        began = time.time()
        graph = baselines.small_world_graph(sets, asked, 100, ef_build=ef, ef_search=ef, degree=2 + ef // 10).cache()
        n = graph.select("query_id").distinct().count()
        report("small world", f"ef={ef}", _seconds(0, 0, time.time() - began, n) | {"graph": graph})
    began = time.time()
    graph = baselines.vanilla_lsh(sets, core.URLS, 100, 200).cache()
    n = graph.select("query_id").distinct().count()
    report("unbounded buckets, all queries", "L=16", _seconds(0, 0, time.time() - began, n) | {"graph": graph})
    for r in metrics.speedup_at(spark.createDataFrame(curves, "method string, recall double, seconds double")).collect():
        print(json.dumps({"method": r["method"], "recall_100": r["level"], "seconds": round(r["seconds"], 3)}))
    print(json.dumps({"hashes_100_s": round(timed(hashing.doph(sets, 4, 25)), 2), "projections_100_s": round(timed(hashing.sparse_projection(sets, 100)), 2), "graph_s": round(timed(core.graph(spark, folder, "pages_full", core.URLS, 100)), 2)}))
    spark.stop()
    for cpus in (1, 2, 4, 8):
        spark = session(cpus)
        sets = w.load(spark, folder, "docs_words").cache()
        n = sets.count()
        timed(index.addresses(sets.limit(10), core.BASE))
        hashed, graph = timed(index.addresses(sets, core.BASE)), timed(index.knn_graph(sets, core.BASE, 10))
        print(json.dumps({"cores": cpus, "hashed_rows_per_s": round(n / hashed), "graph_rows_per_s": round(n / graph)}), flush=True)
        spark.stop()


def main() -> None:
    folder = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    if sys.argv[1:2] == ["measures"]:
        measures(folder)
        return
    spark = session()
    if sys.argv[1:2] == ["sweep"]:
        sweep(spark, folder)
        return
    timed(w.load(spark, folder, "docs_words"))  # start-up is no query's cost
    found = headline(spark, folder)
    print(json.dumps({"metric": "total seconds of headline queries", "value": round(sum(found.values()), 3), "unit": "sec", "queries": found, "sf": Path(folder).name.removeprefix("sf")}))


if __name__ == "__main__":
    main()

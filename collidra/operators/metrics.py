"""Accuracy and cost measures; each returns a small DataFrame."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import cosine_binary, jaccard
from ..sources import merged_by


def recall_at(graph: DataFrame, gold: DataFrame, ks: tuple = (1, 10, 20, 100)) -> DataFrame:
    """(k, recall, n_queries): share of queries with an item tied for best among their first k.

    ``gold`` has at least the best items of each query; queries without any similar item are not counted.
    """
    best = gold.groupBy("query_id").agg(F.max("similarity").alias("top"))
    ties = gold.join(merged_by(best), "query_id").where(F.col("similarity") == F.col("top")).select("query_id", "neighbor_id")
    hits = ties.join(merged_by(graph.select("query_id", "neighbor_id", "rank")), ["query_id", "neighbor_id"], "left").groupBy("query_id").agg(F.min("rank").alias("rank"))
    return hits.select(F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.coalesce((F.col("rank") <= k).cast("double"), F.lit(0.0)).alias("h")) for k in ks])).alias("e")).groupBy("e.k").agg(
        F.round(F.avg("e.h"), 6).alias("recall"), F.count("*").alias("n_queries")
    )


def best_recall_at(graph: DataFrame, best: DataFrame, sets: DataFrame, queries: DataFrame, ks: tuple = (1, 10, 100)) -> DataFrame:
    """(k, recall, similarity, n_queries): share of queries that get an item as near as any, and mean similarity, in the first k.

    ``best`` has the largest similarity of each query; all items tied for it count, however many there are.
    """
    x = queries.select(F.col("item_id").alias("query_id"), F.col("features").alias("x"))
    y = sets.select(F.col("item_id").alias("neighbor_id"), F.col("features").alias("y"))
    near = graph.join(x, "query_id").join(y, "neighbor_id").select("query_id", "rank", F.round(cosine_binary(F.col("x"), F.col("y")), 6).alias("s"))
    each = best.select("query_id", "similarity").join(near, "query_id", "left").withColumn("k", F.explode(F.array(*[F.lit(k) for k in ks])))
    inside = F.col("rank") <= F.col("k")
    per = each.groupBy("k", "query_id").agg(
        F.max(F.coalesce((inside & (F.col("s") >= F.col("similarity"))).cast("int"), F.lit(0))).alias("hit"), F.sum(F.when(inside, F.col("s"))).alias("total"), F.count(F.when(inside, 1)).alias("n"),
    )
    return per.groupBy("k").agg(F.round(F.avg("hit"), 6).alias("recall"), F.round(F.sum("total") / F.sum("n"), 6).alias("similarity"), F.count("*").alias("n_queries"))


def similarity_at(graph: DataFrame, sets: DataFrame, queries: DataFrame, ks: tuple = (1, 10, 100), pad: bool = False) -> DataFrame:
    """(k, similarity, returned): mean binary cosine of what is returned in the first k, and how many are.

    With ``pad`` missing places count as 0.
    """
    x = queries.select(F.col("item_id").alias("query_id"), F.col("features").alias("x"))
    y = sets.select(F.col("item_id").alias("neighbor_id"), F.col("features").alias("y"))
    s = graph.join(x, "query_id").join(y, "neighbor_id").select("query_id", "rank", cosine_binary(F.col("x"), F.col("y")).alias("s"))
    n = queries.agg(F.count("*").alias("n"))
    each = s.select("query_id", "s", F.explode(F.array(*[F.lit(k) for k in ks])).alias("k"), "rank").where("rank <= k")
    sums = each.groupBy("k").agg(F.sum("s").alias("total"), F.count("*").alias("rows"))
    down = F.col("k") * F.col("n") if pad else F.col("rows")
    return sums.crossJoin(F.broadcast(n)).select("k", F.round(F.col("total") / down, 6).alias("similarity"), F.round(F.col("rows") / F.col("n"), 6).alias("returned"))


def threshold_recall(graph: DataFrame, gold: DataFrame, tau: float, k: int) -> DataFrame:
    """One row: gold pairs above tau, found in the first k, recall, and recall capped at the k that can be returned."""
    over = gold.where(F.col("similarity") > tau).select("query_id", "neighbor_id")
    found = over.join(graph.where(F.col("rank") <= k).select("query_id", "neighbor_id").withColumn("hit", F.lit(1)), ["query_id", "neighbor_id"], "left")
    return recall_of_degrees(found.groupBy("query_id").agg(F.count("*").alias("n"), F.sum(F.coalesce("hit", F.lit(0))).alias("hits")), k)


def recall_of_degrees(each: DataFrame, k: int) -> DataFrame:
    """As ``threshold_recall``, from (query_id, n, hits): the pairs above the threshold of each query, and those found."""
    return each.agg(
        F.sum("n").alias("pairs"), F.sum("hits").alias("found"), F.round(F.sum("hits") / F.sum("n"), 6).alias("recall"),
        F.round(F.sum("hits") / F.sum(F.least("n", F.lit(k))), 6).alias("capped_recall"),
    )


def bucket_skew(addr: DataFrame, r: int) -> DataFrame:
    """(table_id, buckets, max_bucket, mean_bucket, truncated_share, items) per table."""
    b = addr.groupBy("table_id", "address").agg(F.count("*").alias("n"))
    return b.groupBy("table_id").agg(
        F.count("*").alias("buckets"), F.max("n").alias("max_bucket"), F.round(F.avg("n"), 6).alias("mean_bucket"),
        F.round(F.avg((F.col("n") > r).cast("double")), 6).alias("truncated_share"), F.sum("n").alias("items"),
    )


def bucket_quantiles(addr: DataFrame, bits: int) -> DataFrame:
    """(table_id, median, p90, p99, empty): sizes of the buckets in use, and the share of addresses that none uses."""
    b = addr.groupBy("table_id", "address").agg(F.count("*").alias("n"))
    at = {"median": 0.5, "p90": 0.9, "p99": 0.99}
    return b.groupBy("table_id").agg(*[F.percentile("n", F.lit(q)).alias(name) for name, q in at.items()], F.round(1 - F.count("*") / F.lit(float(1 << bits)), 6).alias("empty"))


def sharing_clashes(addr: DataFrame, pointers: DataFrame, r: int) -> DataFrame:
    """One row: reservoirs in use, those of one truncated bucket, those that several share, and most of them in one."""
    b = addr.groupBy("table_id", "address").agg(F.count("*").alias("n"))
    heavy = pointers.join(b, ["table_id", "address"]).groupBy("reservoir_id").agg(F.sum((F.col("n") > r).cast("long")).alias("heavy"))
    of = lambda c: F.coalesce(F.sum(c.cast("long")), F.lit(0)).cast("long")
    return heavy.agg(F.count("*").alias("reservoirs"), of(F.col("heavy") == 1).alias("one_heavy"), of(F.col("heavy") > 1).alias("clashes"), F.coalesce(F.max("heavy"), F.lit(0)).alias("most"))


def gini(addr: DataFrame) -> DataFrame:
    """(table_id, gini): inequality of bucket sizes, from a histogram of sizes, so no table of buckets is ordered in one task."""
    from pyspark.sql import Window as W

    h = addr.groupBy("table_id", "address").agg(F.count("*").alias("n")).groupBy("table_id", "n").agg(F.count("*").alias("c"))
    w = W.partitionBy("table_id").orderBy("n").rowsBetween(W.unboundedPreceding, -1)
    mass = F.coalesce(F.sum(F.col("c") * F.col("n")).over(w), F.lit(0))
    area = h.withColumn("area", F.col("c") * (mass * 2 + F.col("c") * F.col("n")))
    return area.groupBy("table_id").agg((F.lit(1.0) - F.sum("area") / (F.sum("c") * F.sum(F.col("c") * F.col("n")))).alias("gini"))


def candidate_lengths(probes: DataFrame) -> DataFrame:
    """One row: mean and largest number of ids a query gathers."""
    per = probes.groupBy("query_id").agg(F.sum(F.size("members")).alias("n"))
    return per.agg(F.round(F.avg("n"), 6).alias("mean_candidates"), F.max("n").alias("max_candidates"))


def sharing_load(pointers: DataFrame) -> DataFrame:
    """One row: addresses in use, reservoirs in use, mean and most addresses per reservoir."""
    per = pointers.groupBy("reservoir_id").agg(F.count("*").alias("n"))
    return per.agg(F.sum("n").alias("addresses"), F.count("*").alias("reservoirs"), F.round(F.avg("n"), 6).alias("mean_load"), F.max("n").alias("max_load"))


def gold_gap(gold: DataFrame) -> DataFrame:
    """One row: mean similarity of the best and second neighbours and of their gap."""
    two = gold.groupBy("query_id").agg(F.max(F.when(F.col("rank") == 1, F.col("similarity"))).alias("a"), F.max(F.when(F.col("rank") == 2, F.col("similarity"))).alias("b"))
    return two.agg(F.round(F.avg("a"), 6).alias("best"), F.round(F.avg("b"), 6).alias("second"), F.round(F.avg(F.col("a") - F.col("b")), 6).alias("gap"))


def estimator_error(graph: DataFrame, sets: DataFrame, k: int, tables: int) -> DataFrame:
    """One row: mean and mean square of count / tables - J**k over the graph's pairs; reservoirs bias it downward."""
    x = sets.select(F.col("item_id").alias("query_id"), F.col("features").alias("x"))
    y = sets.select(F.col("item_id").alias("neighbor_id"), F.col("features").alias("y"))
    e = F.col("collisions") / F.lit(float(tables)) - F.pow(jaccard(F.col("x"), F.col("y")), F.lit(k))
    return graph.join(x, "query_id").join(y, "neighbor_id").select(e.alias("e")).agg(
        F.round(F.avg("e"), 6).alias("bias"), F.round(F.avg(F.col("e") * F.col("e")), 6).alias("mean_square"), F.count("*").alias("pairs")
    )


def assumption_violations(triples: DataFrame) -> DataFrame:
    """One row from (q, x, y) feature sets with J(q,x) > J(q,y): how often y's collision given x's exceeds J(q,y)."""
    a = F.size(F.array_intersect("q", "x"))
    u = F.size(F.array_union(F.array_union("q", "x"), F.col("y")))
    qx = F.size(F.array_union("q", "x"))
    shared = F.size(F.array_intersect(F.array_intersect("q", "x"), F.col("y")))
    given = shared / a * (F.lit(1.0) * qx / u)
    bad = (given > jaccard(F.col("q"), F.col("y"))).cast("double")
    return triples.where((a > 0) & (jaccard(F.col("q"), F.col("x")) > jaccard(F.col("q"), F.col("y")))).agg(F.count("*").alias("triples"), F.avg(bad).alias("violations"))


def mean_similarity(sets: DataFrame, pairs: int, seed: int = 4) -> DataFrame:
    """One row: mean binary cosine of pairs made by two seeded orders of the same items (at most ``pairs``)."""
    from ..functions.portable import linear, parameters
    from pyspark.sql import Window as W

    p = parameters(seed, 4)
    pick = lambda a, b: sets.withColumn("_r", linear(F.pmod("item_id", F.lit(2**31)), a, b)).orderBy("_r").limit(pairs)
    left = pick(p[0], p[1]).select(F.row_number().over(W.orderBy("_r")).alias("i"), F.col("item_id").alias("l"), F.col("features").alias("x"))
    right = pick(p[2], p[3]).select(F.row_number().over(W.orderBy("_r")).alias("i"), F.col("item_id").alias("r"), F.col("features").alias("y"))
    return left.join(right, "i").where("l <> r").agg(F.avg(cosine_binary(F.col("x"), F.col("y"))).alias("mean_cosine"), F.count("*").alias("pairs"))


def speedup_at(curves: DataFrame, levels: tuple = (0.5, 0.6, 0.7)) -> DataFrame:
    """(method, level, seconds) interpolated on (method, recall, seconds) curves, for speed-ups at equal recall."""
    from pyspark.sql import Window as W

    w = W.partitionBy("method").orderBy("recall", "seconds")
    seg = curves.withColumn("r0", F.lag("recall").over(w)).withColumn("s0", F.lag("seconds").over(w))
    at = seg.withColumn("level", F.explode(F.array(*[F.lit(x) for x in levels]))).where("r0 <= level AND level <= recall AND recall > r0")
    return at.select("method", "level", (F.col("s0") + (F.col("seconds") - F.col("s0")) * (F.col("level") - F.col("r0")) / (F.col("recall") - F.col("r0"))).alias("seconds"))

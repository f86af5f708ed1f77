"""The index: parameters, building, saving, appending, querying, and the k-nearest-neighbour graph."""

from __future__ import annotations

import json
import math
from dataclasses import asdict, dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import stored
from . import hashing, query, reservoir


@dataclass(frozen=True)
class IndexParams:
    """k values per address, tables, reservoir size r, address bits, share of reservoirs (1: none shared)."""

    k: int = 2
    tables: int = 32
    r: int = 32
    bits: int = 15
    share: float = 1.0
    sharing: str = "global"
    densify: str = "probe"
    form: str = "arrow"
    policy: str = "priority"
    seed: int = 1

    def auto(self, n: int, bucket: int = 16) -> IndexParams:
        """Address bits that keep the mean bucket near ``bucket`` items: a fixed width would turn reservoirs of a large
        corpus into random samples."""
        return replace(self, bits=max(8, min(30, math.ceil(math.log2(max(2, n / bucket))))))

    def grown(self, n: int) -> IndexParams:
        """These parameters with as many address bits as ``n`` items need, and no fewer than they have."""
        return replace(self, bits=max(self.bits, self.auto(n).bits))

    def model_bytes(self, id_bytes: int = 4, pointer_bytes: int = 4, counter_bytes: int = 4) -> int:
        """Bytes of the dense layout: slots, one counter per reservoir, and pointers if reservoirs are shared."""
        slots = self.tables * (1 << self.bits)
        pool = slots if self.share >= 1 else reservoir.pool_size(self.tables, self.bits, self.share)
        return pool * (self.r * id_bytes + counter_bytes) + (slots * pointer_bytes if self.share < 1 else 0)


def addresses(sets: DataFrame, p: IndexParams) -> DataFrame:
    return hashing.addresses(hashing.doph(sets, p.k, p.tables, p.seed, p.densify, p.form), p.k, p.tables, p.bits, p.seed)


@dataclass
class Index:
    """Reservoirs (and pointers where they are shared); features are not kept."""

    params: IndexParams
    reservoirs: DataFrame
    pointers: DataFrame | None = None

    def probe(self, addr: DataFrame, small: bool = False) -> DataFrame:
        return query.probe(addr, self.reservoirs, self.pointers, small)

    def knn(self, queries: DataFrame, k: int, exclude_self: bool = False, strategy: str = "segment", small: bool = True) -> DataFrame:
        """Top k of each query set; the queries need not be in the index."""
        return query.count_select(self.probe(addresses(queries, self.params), small), k, strategy, exclude_self)

    def append(self, sets: DataFrame) -> Index:
        """With more items; equals one build over all (priority reservoirs that are not shared)."""
        if self.pointers is not None or self.params.policy != "priority":
            raise ValueError("only unshared priority reservoirs merge")
        fresh = reservoir.reservoir(addresses(sets, self.params), self.params.r, seed=self.params.seed)
        return Index(self.params, reservoir.merge(self.reservoirs, fresh, self.params.r, self.params.seed))

    def save(self, path: str, files: int = 64) -> None:
        """Parquet below ``path``, partitioned by table and clustered by address, so that one table or range prunes."""
        spark = self.reservoirs.sparkSession
        spark.createDataFrame([(json.dumps(asdict(self.params)),)], "params string").write.mode("overwrite").parquet(f"{path}/params")
        if self.pointers is None:
            self.reservoirs.repartition(files, "table_id", "address").sortWithinPartitions("address").write.mode("overwrite").partitionBy("table_id").parquet(f"{path}/reservoirs")
        else:
            self.reservoirs.write.mode("overwrite").parquet(f"{path}/reservoirs")
            self.pointers.write.mode("overwrite").parquet(f"{path}/pointers")

    def save_bucketed(self, table: str, buckets: int = 64) -> None:
        """As a table bucketed by (table_id, address): a join with it leaves it where it is."""
        self.reservoirs.write.mode("overwrite").bucketBy(buckets, "table_id", "address").sortBy("table_id", "address").saveAsTable(table)

    @staticmethod
    def load(spark: SparkSession, path: str) -> Index:
        params = IndexParams(**json.loads(spark.read.parquet(f"{path}/params").first()[0]))
        shared = params.share < 1
        return Index(params, spark.read.parquet(f"{path}/reservoirs"), spark.read.parquet(f"{path}/pointers") if shared else None)

    def size(self) -> DataFrame:
        """One row: buckets in use, stored ids, truncated buckets, bytes as stored (8 per number) and of the dense layout."""
        s = self.reservoirs.agg(
            F.count("*").alias("buckets"), F.sum(F.size("members")).alias("stored_ids"), F.sum((F.col("seen") > self.params.r).cast("long")).alias("truncated"),
        )
        return s.select("*", (F.col("stored_ids") * 8 + F.col("buckets") * 24).alias("stored_bytes"), F.lit(self.params.model_bytes()).cast("long").alias("model_bytes"))


def index_of(addr: DataFrame, p: IndexParams) -> Index:
    if p.share < 1:
        pointers = reservoir.share_pointers(addr, p.tables, p.bits, p.share, p.sharing, p.seed)
        return Index(p, reservoir.shared_reservoirs(addr, pointers, p.r, p.seed), pointers)
    return Index(p, reservoir.reservoir(addr, p.r, p.policy, p.seed))


def build_index(sets: DataFrame, p: IndexParams = IndexParams()) -> Index:
    return index_of(addresses(sets, p), p)


def knn_graph(sets: DataFrame, p: IndexParams = IndexParams(), k: int = 100, strategy: str = "segment", batches: int = 1, batch: int | None = None) -> DataFrame:
    """The k-nearest-neighbour graph of all items by collision counts; no similarity is computed.

    With ``batches``, only queries with id mod batches == batch, or all, batch by batch: a restartable unit that bounds
    the shuffle of candidates. Addresses are stored, as counting, sampling and probing each read them: features and
    signatures are computed once.
    """
    addr = stored(addresses(sets, p))
    index = index_of(addr, p)
    parts = [addr] if batches == 1 else [addr.where(F.pmod("item_id", F.lit(batches)) == b) for b in (range(batches) if batch is None else [batch])]
    out = None
    for part in parts:
        found = query.count_select(index.probe(part), k, strategy, True)
        out = found if out is None else out.unionByName(found)
    return out

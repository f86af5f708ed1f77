"""Near duplicates by SimHash fingerprints and bit-sliced Hamming distances.

Fingerprints: words of the lower-cased text (A-Z only), shingles of ``width`` words, a hash of each; a bit is set if more
than half of the shingle hashes set it. Two relations are offered:

``near_duplicates``: 64 bits of XXH64 with seed 42; documents whose fingerprints differ in at most ``radius`` bits link.
Different fingerprints are split into ``radius + b`` blocks of bits; two that link agree on at least ``b`` blocks, so every
combination of ``b`` blocks is a table of buckets, and links are found inside buckets, none by chance. ``b`` is 1, and 2
where there are so many fingerprints that single blocks would fill the buckets.

``similar_documents``: texts whose sets of shingles have a Jaccard similarity of 0.8 or more link. Fingerprints have
``BITS`` bits; tables are keyed by random choices of bits, as many as find a pair at the limit with a chance of
1 - ``MISS``; fingerprints within ``REACH`` bits make classes. Inside a class the whole sets of shingles are compared, and
all pairs of a similarity of 0.8 link.

Inside a task the fingerprints of sorted buckets lie in blocks of 64 lanes, one word per bit plane. A query XORs eight
planes at a time with its own bits and adds them by carry-save adders to counters held bit by bit, for many queries at
once; after every eight planes the blocks in which all lanes exceed the radius are abandoned. From each bucket leave only
edges, never all pairs.

A bucket of more than ``BUCKET_ROWS`` fingerprints, or a class of more than ``CELL_SHINGLES`` shingles, is dealt to several tasks: its rows fall into groups, and each pair of
groups is compared as a bucket of its own, so no pair is lost. At radius 2 there is a cheaper exact way: two values
within distance 2 both lie within distance 1 of a common value, so each is linked to itself and its 64 one-bit neighbours
as nodes, and sharing a node is the link.

Defined results: null and empty texts have fingerprint 0 and link like any other; the class is the smallest id
reachable; null ids are left out of that minimum and their rows are never dropped; rows that repeat are classed alike; an
empty table gives an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, cells, components, counted_broadcast, crowds, read_table, spare, text_or_empty, trim, written
from .set_join import by_cell

WIDTH, RADIUS, SEED = 3, 2, 42
BUCKET_ROWS = 4096
#: Different fingerprints from which on buckets are keyed by two blocks of bits.
TWO_BLOCKS_FROM = 1 << 27
#: Words of a shingle of the sets that are compared, and shingles of a class that a task holds twice of.
SHINGLE, CELL_SHINGLES = 5, 1_000_000
#: Bits of their fingerprints, bits in which candidates may differ, and the chance to miss a pair at the limit, where
#: a bit agrees with the chance ``AGREE`` (0.85 by the angle between large sets, less between small ones).
BITS, REACH, MISS, AGREE = 256, 63, 0.004, 0.82
#: Rows that an average bucket of a table holds; tables take more bits, and are more, as rows grow.
MEAN_BUCKET = 1024
_LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")
_PART, _TEXTS_AT_ONCE, _COMPARED_AT_ONCE = 65_536, 256, 40_000


def fingerprint(text: str | None, width: int = WIDTH, seed: int = SEED) -> int:
    """64-bit fingerprint of a text; long texts are counted in parts."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()
    if not words:
        return 0
    flat = memoryview(b" ".join(words))
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = np.concatenate(([0], ends[:-1] + 1)).tolist()
    ends = ends.tolist()
    n = max(1, len(words) - width + 1)
    k = min(width, len(words)) - 1
    digest, counts = xxhash.xxh64_intdigest, np.zeros(64, dtype=np.int64)
    for lo in range(0, n, _PART):
        hi = min(n, lo + _PART)
        h = np.array([digest(flat[a:b], seed) for a, b in zip(starts[lo:hi], ends[lo + k : hi + k], strict=True)], dtype="<u8")
        counts += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(counts * 2 > n, bitorder="little").view("<u8")[0])


def with_fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH) -> DataFrame:
    """(doc_id, unit, fp): a hash of the text, and its fingerprint as a signed 64-bit number."""

    @F.pandas_udf("long")
    def fp(texts: pd.Series) -> pd.Series:
        return pd.Series(np.array([fingerprint(t, width) for t in texts], dtype=np.uint64).view(np.int64))

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text_or_empty(text_col)).alias("unit"), fp(F.col(text_col)).alias("fp"))


# ---------------------------------------------------------------- bit-sliced comparison

_LANE = np.uint64(1) << np.arange(64, dtype=np.uint64)
_ALL = np.uint64(0xFFFFFFFFFFFFFFFF)
#: For each byte of a query the eight words that turn its planes.
_TURN = np.where((np.arange(256)[:, None] >> np.arange(8)) & 1 == 1, _ALL, np.uint64(0))


def bit_planes(values: np.ndarray) -> np.ndarray:
    """(blocks, planes): word b of a block holds bit b of its 64 values, one lane each; ``values`` is (rows, words)."""
    n, words = values.shape
    padded = np.zeros((-(-n // 64) * 64, words), dtype="<u8")
    padded[:n] = values
    bits = np.unpackbits(padded.view(np.uint8).reshape(-1, 64, 8 * words), axis=2, bitorder="little")  # block, lane, bit
    packed = np.packbits(bits.transpose(0, 2, 1), axis=2, bitorder="little")
    return np.ascontiguousarray(packed).view("<u8").reshape(-1, 64 * words)


def _add(a: np.ndarray, b: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A full adder of three words of bits: sums and carries."""
    half = a ^ b
    return half ^ c, (a & b) | (half & c)


def near_lanes(queries: np.ndarray, blocks: np.ndarray, lanes: np.ndarray, planes: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """For comparisons (query, block, wanted lanes): indices of those with lanes in reach, and these lanes.

    Counters start so far above zero that a distance beyond the radius carries out of their last bit.
    """
    m, size = len(blocks), max(3, radius.bit_length())
    start = (1 << size) - 1 - radius
    counters = [np.full(m, _ALL if start >> i & 1 else 0, dtype=np.uint64) for i in range(size)]
    over = np.zeros(m, dtype=np.uint64)
    own = np.ascontiguousarray(queries).view(np.uint8).reshape(m, -1)
    by_eight = planes.reshape(len(planes), -1, 8)
    alive, wanted = np.arange(m), lanes
    for g in range(by_eight.shape[1]):
        p = np.ascontiguousarray((by_eight[blocks[alive], g] ^ _TURN[own[alive, g]]).T)
        ones, a = _add(counters[0], p[0], p[1])
        ones, b = _add(ones, p[2], p[3])
        twos, low = _add(counters[1], a, b)
        ones, a = _add(ones, p[4], p[5])
        counters[0], b = _add(ones, p[6], p[7])
        counters[1], high = _add(twos, a, b)
        counters[2], carry = _add(counters[2], low, high)
        for i in range(3, size):
            counters[i], carry = counters[i] ^ carry, counters[i] & carry
        over |= carry
        if 8 * (g + 1) > radius:
            keep = (~over & wanted) != 0
            if keep.sum() < 0.8 * len(keep):
                alive, wanted, over = alive[keep], wanted[keep], over[keep]
                counters = [c[keep] for c in counters]
            if not len(alive):
                break
    reach = ~over & wanted
    hit = np.flatnonzero(reach)
    return alive[hit], reach[hit]


def reachable(values: np.ndarray, low: np.ndarray, high: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs (row, place) with low[row] <= place < high[row] and distance at most ``radius``, piece by piece."""
    planes = bit_planes(values)
    rows = np.flatnonzero(high > low)
    span = (high[rows] - 1) // 64 - low[rows] // 64 + 1
    ends, at = np.cumsum(span), 0
    upto = lambda k: np.where(k >= 64, _ALL, (np.uint64(1) << np.clip(k, 0, 63).astype(np.uint64)) - np.uint64(1))
    total = int(ends[-1]) if len(ends) else 0
    while at < total:
        k = np.arange(at, min(at + _COMPARED_AT_ONCE, total))
        i = np.searchsorted(ends, k, "right")
        r = rows[i]
        block = low[r] // 64 + k - (ends[i] - span[i])
        lanes = upto(high[r] - block * 64) & ~upto(low[r] - block * 64)
        hit, reach = near_lanes(values[r], block, lanes, planes, radius)
        for lo in range(0, len(hit), 20_000):
            which, lane = np.nonzero((reach[lo : lo + 20_000, None] & _LANE[None, :]) != 0)
            x = hit[lo : lo + 20_000][which]
            yield r[x], block[x] * 64 + lane
        at = int(k[-1]) + 1


def _starts(change: np.ndarray) -> np.ndarray:
    """For each row the first of its run, where ``change`` tells of each row but the first if a run begins."""
    first = np.concatenate(([0], np.flatnonzero(change) + 1))
    return np.repeat(first, np.diff(np.concatenate((first, [len(change) + 1]))))


def bucket_edges(key: np.ndarray, values: np.ndarray, radius: int = RADIUS) -> tuple[np.ndarray, np.ndarray]:
    """Edges (row, first row linked to it within its bucket) for rows of ``values`` (rows, words) sorted by bucket key."""
    n = len(values)
    parent = np.arange(n)
    if n > 1:
        for a, b in reachable(values, _starts(key[1:] != key[:-1]), np.arange(n), radius):
            _union(parent, a, b)
    root = _roots(parent)
    moved = np.flatnonzero(root != np.arange(n))
    return moved, root[moved]


def _roots(parent: np.ndarray) -> np.ndarray:
    while True:
        nxt = parent[parent]
        if (nxt == parent).all():
            return nxt
        parent = nxt


def _union(parent: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    """Merge the classes of a[i] and b[i] in place; the smaller row is the root."""
    while len(a):
        flat = _roots(parent)
        parent[:] = flat
        x, y = flat[a], flat[b]
        far = x != y
        a, b, x, y = a[far], b[far], x[far], y[far]
        np.minimum.at(parent, np.maximum(x, y), np.minimum(x, y))


def _whole_buckets(parts: Iterator[pd.DataFrame], names: list[str]) -> Iterator[np.ndarray]:
    """Rows sorted by their first column as arrays that do not cut a run of equal values."""
    held: list[np.ndarray] = []
    for pdf in parts:
        if not len(pdf):
            continue
        now = pdf[names].to_numpy(dtype=np.int64)
        if held and held[-1][-1, 0] != now[0, 0]:
            yield np.concatenate(held)
            held = []
        other = np.flatnonzero(now[:, 0] != now[-1, 0])
        cut = int(other[-1]) + 1 if len(other) else 0
        if cut:
            yield np.concatenate([*held, now[:cut]])
            held = []
        held.append(now[cut:])
    if held:
        yield np.concatenate(held)


# ---------------------------------------------------------------- fingerprints within a radius


def _compare(radius: int, node: str, words: list[str]):
    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        spare()
        for rows in _whole_buckets(parts, ["cell", node, *words]):
            values = np.ascontiguousarray(rows[:, 2:] if words != [node] else rows[:, 1:2]).view(np.uint64)
            a, b = bucket_edges(rows[:, 0], values, radius)
            if len(a):
                yield pd.DataFrame({"a": rows[a, 1], "b": rows[b, 1]})
            del rows, values
        trim()

    return run


def fingerprint_edges(prints: DataFrame, radius: int = RADIUS, bucket_rows: int = BUCKET_ROWS, take: int | None = None) -> DataFrame:
    """Edges (a, b) that join linked ones of the different fingerprints ``fp``; a node may be a value no document has."""
    if take is None:
        take = 1 if prints.count() < TWO_BLOCKS_FROM else 2
    parts = radius + take
    bounds = [round(64 * i / parts) for i in range(parts + 1)]
    masks = [sum(((1 << (bounds[i + 1] - bounds[i])) - 1) << bounds[i] for i in c) for c in combinations(range(parts), take)]
    signed = [m - (1 << 64) if m >= 1 << 63 else m for m in masks]
    # A bucket's key is a hash of the table's number and of what its mask leaves of the fingerprint.
    tables = F.explode(F.array(*[F.xxhash64(F.lit(i), F.col("fp").bitwiseAND(F.lit(m))) for i, m in enumerate(signed)]))
    rows = prints.select("fp", tables.alias("key"))
    sizes = rows.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
    shared = written(rows.join(sizes, "key"), "bands")
    if radius == 2:
        compared = shared.where(F.col("n") <= bucket_rows).withColumn("cell", F.col("key"))
    else:
        compared = cells(shared, crowds(shared, bucket_rows), F.xxhash64("fp", F.lit(3)))
    dealt = compared.select("cell", "fp").repartition("cell").sortWithinPartitions("cell", "fp")
    found = dealt.mapInPandas(_compare(radius, "fp", ["fp"]), "a long, b long")
    if radius != 2:
        return found
    crowd = shared.where(F.col("n") > bucket_rows).select("fp").distinct()
    flips = F.explode(F.concat(F.array(F.lit(0).cast("long")), F.transform(F.sequence(F.lit(0), F.lit(63)), lambda i: F.call_function("shiftleft", F.lit(1).cast("long"), i))))
    around = crowd.withColumn("flip", flips).select(F.col("fp").alias("a"), F.col("fp").bitwiseXOR(F.col("flip")).alias("b"))
    return found.unionByName(around)


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = WIDTH, radius: int = RADIUS, bucket_rows: int = BUCKET_ROWS) -> DataFrame:
    """One row per document: doc_id, unit (hash of the text), fp (signed), component_id, group_size (rows in the class)."""
    rows = written(with_fingerprints(docs, id_col, text_col, width), "fingerprints")
    return _classed(rows, "fp", fingerprint_edges(rows.select("fp").distinct(), radius, bucket_rows))


def _classed(rows: DataFrame, node: str, edges: DataFrame) -> DataFrame:
    """``rows``, which have doc_id and a node, with component_id, the smallest doc_id reachable over the edges, and group_size."""
    nodes = rows.groupBy(node).agg(F.min("doc_id").alias("low"), F.count("*").alias("n"))
    linked = components(edges).select(F.col("node").alias(node), "component")
    member = nodes.join(linked, node, "left").withColumn("component", F.coalesce("component", node))
    classes = member.groupBy("component").agg(F.min("low").alias("component_id"), F.sum("n").alias("group_size"))
    return rows.join(member.join(classes, "component").select(node, "component_id", "group_size"), node).select(*rows.columns, "component_id", "group_size")


# ---------------------------------------------------------------- similarity of shingle sets


def shingle_set(text: str | None, width: int = SHINGLE) -> np.ndarray:
    """Sorted hashes of the different shingles of a text; a text of fewer words is one shingle, one without words too."""
    words = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()
    if not words:
        return np.zeros(1, dtype=np.uint64)
    h = np.fromiter(map(xxhash.xxh64_intdigest, words), dtype=np.uint64, count=len(words))
    k = min(width, len(h))
    out = np.zeros(len(h) - k + 1, dtype=np.uint64)
    for i in range(k):
        out = out * np.uint64(0x9E3779B97F4A7C15) + h[i : len(h) - k + 1 + i]
    return np.unique((out ^ (out >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93))


def long_fingerprint(shingles: np.ndarray) -> np.ndarray:
    """The ``BITS`` bits of a set of shingles as words."""
    counts = np.zeros(BITS, dtype=np.int64)
    for lo in range(0, len(shingles), _PART):
        h = shingles[lo : lo + _PART, None] + np.arange(1, BITS // 64 + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        h ^= h >> np.uint64(31)
        counts += np.unpackbits(h.astype("<u8").view(np.uint8).reshape(len(h), -1), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return np.packbits(counts * 2 > len(shingles), bitorder="little").view("<u8")


_WORDS = [f"f{i}" for i in range(BITS // 64)]


def _slices(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """The rows in pieces whose shingles take little memory."""
    spare()
    for pdf in parts:
        for lo in range(0, len(pdf), _TEXTS_AT_ONCE):
            yield pdf.iloc[lo : lo + _TEXTS_AT_ONCE]
        del pdf
    trim()


def _printed(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for pdf in _slices(parts):
        words = np.array([long_fingerprint(shingle_set(t)) for t in pdf["text"]], dtype=np.uint64).reshape(-1, BITS // 64)
        yield pd.DataFrame({"unit": pdf["unit"].to_numpy()} | {w: words[:, i].view(np.int64) for i, w in enumerate(_WORDS)})


def _shingled(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for pdf in _slices(parts):
        sets = [shingle_set(t).view(np.int64) for t in pdf["text"]]
        yield pd.DataFrame({"unit": pdf["unit"].to_numpy(), "key": pdf["key"].to_numpy(), "s": sets})


def table_bits(rows: int, seed: int = 7) -> list[list[int]]:
    """The bits that key each table: enough to keep buckets near ``MEAN_BUCKET``, in enough tables to reach 1 - ``MISS``."""
    bits = min(30, max(4, math.ceil(math.log2(max(2, rows / MEAN_BUCKET)))))
    tables = math.ceil(math.log(MISS) / math.log1p(-(AGREE**bits)))
    rng = np.random.default_rng(seed)
    return [sorted(rng.choice(BITS, bits, replace=False).tolist()) for _ in range(tables)]


def _keys(tables: list[list[int]]) -> Column:
    """An array of the row's bucket keys, one per table."""

    def masked(bits: list[int]) -> list[Column]:
        masks = [sum(1 << (b % 64) for b in bits if b // 64 == w) for w in range(BITS // 64)]
        return [F.col(_WORDS[w]).bitwiseAND(F.lit(m - (1 << 64) if m >= 1 << 63 else m)) for w, m in enumerate(masks) if m]

    return F.array(*[F.xxhash64(F.lit(t), *masked(bits)) for t, bits in enumerate(tables)])


def similar_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bucket_rows: int = BUCKET_ROWS, cell_shingles: int = CELL_SHINGLES) -> DataFrame:
    """One row per document: doc_id, unit (hash of the text), component_id, group_size, by similarity of shingle sets."""
    text = text_or_empty(text_col)
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("text"), F.xxhash64(text).alias("unit"))
    words = ", ".join(f"{w} long" for w in _WORDS)
    prints = written(base.select("unit", "text").mapInPandas(_printed, f"unit long, {words}").dropDuplicates(["unit"]), "prints")
    keyed = prints.withColumn("key", F.explode(_keys(table_bits(prints.count()))))
    dealt = cells(keyed, crowds(keyed, bucket_rows), F.xxhash64("unit", F.lit(3))).select("cell", "unit", *_WORDS)
    met = dealt.repartition("cell").sortWithinPartitions("cell", "unit").mapInPandas(_compare(REACH, "unit", _WORDS), "a long, b long")
    classes = written(components(met).select(F.col("node").alias("unit"), F.col("component").alias("key")), "classes")
    texts = base.join(counted_broadcast(classes, BROADCAST_ROWS), "unit")
    sets = written(texts.select("unit", "key", "text").mapInPandas(_shingled, "unit long, key long, s array<long>").dropDuplicates(["unit"]), "sets")
    dealt = cells(sets, crowds(sets, cell_shingles, F.size("s")), F.xxhash64("unit", F.lit(3))).select("cell", "unit", "s")
    links = dealt.repartition("cell").sortWithinPartitions("cell", "unit").mapInPandas(by_cell(np.asarray, ["unit", "s"]), "a long, b long")
    return _classed(base.select("doc_id", "unit"), "unit", links)


def _drop(docs: DataFrame, classes: DataFrame, id_col: str, text_col: str) -> DataFrame:
    gone = classes.where(F.col("doc_id") != F.col("component_id")).select(F.col("doc_id").alias("_id"), F.col("unit").alias("_unit")).distinct()
    gone = counted_broadcast(written(gone, "dropped"), BROADCAST_ROWS)
    same = (F.col(id_col).cast("long") == F.col("_id")) & (F.xxhash64(text_or_empty(text_col)) == F.col("_unit"))
    return docs.join(gone, same, "left_anti")


def drop_near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """``docs`` without all but one document (the smallest id) of each class of near fingerprints."""
    return _drop(docs, near_duplicates(docs, id_col, text_col, **options), id_col, text_col)


def drop_similar(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """``docs`` without all but one document (the smallest id) of each class of similar texts."""
    return _drop(docs, similar_documents(docs, id_col, text_col, **options), id_col, text_col)


def op7_simhash(spark, sf_dir: str) -> DataFrame:
    found = near_duplicates(read_table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")

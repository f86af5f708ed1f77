"""Signatures: minwise, one-permutation with three densifications, projections; addresses from signatures."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.portable import P, HashNumbers, linear, parameters

_EMPTY = np.int64(2**62)


def tries(m: int) -> int:
    """Probes before an empty bin falls back to rotation; far fewer leave bins of tiny sets empty."""
    return 4 * m


def offset(m: int) -> int:
    """What a rotation adds per bin of distance, so that borrowed values differ from own ones."""
    return P // m + 1


def probe_table(m: int, seed: int = 1) -> np.ndarray:
    """(m, tries) bins that an empty bin borrows from, in order; the same for all items."""
    a, b = HashNumbers(seed).probe
    t = tries(m)
    i = np.arange(m, dtype=np.int64)[:, None] * t + np.arange(t, dtype=np.int64)[None, :]
    return (a * i + b) % P % m


def directions(m: int, seed: int = 1) -> np.ndarray:
    """1 where a bin borrows from its right, 0 from its left."""
    a, b = HashNumbers(seed).probe
    return (a * np.arange(m, dtype=np.int64) + b) % P // 7 % 2


def _per_set(sets: DataFrame, fn, kind: str) -> DataFrame:
    """(item_id, out) where ``fn(features, starts)`` gives a row per set from non-empty sets laid end to end.

    Sets are taken in slices, so that a batch of large sets does not widen into one huge matrix.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 256):
                part = batch.slice(lo, 256)
                lists = part.column(1)
                flat, ends = lists.flatten().to_numpy(zero_copy_only=False), np.asarray(lists.offsets)
                out = fn(flat.astype(np.int64), (ends[:-1] - ends[0]).astype(np.int64))
                offsets = pa.array(np.arange(0, out.size + 1, out.shape[1], dtype=np.int32))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(offsets, pa.array(out.ravel()))], names=["item_id", "out"])

    return sets.where(F.size("features") > 0).select("item_id", "features").mapInArrow(run, f"item_id long, out array<{kind}>")


def minwise(sets: DataFrame, m: int, seed: int = 1) -> DataFrame:
    """(item_id, sig): ``m`` independent minima; empty sets drop out. Work grows with m times the set."""
    n = np.array(parameters(seed + 1000, 2 * m), dtype=np.int64).reshape(m, 2)

    def least(x: np.ndarray, starts: np.ndarray) -> np.ndarray:
        return np.stack([np.minimum.reduceat((x * a + b) % P, starts) for a, b in n], axis=1)

    return _per_set(sets, least, "long").withColumnRenamed("out", "sig")


def one_permutation(sets: DataFrame, m: int, seed: int = 1) -> DataFrame:
    """(item_id, bin, v): smallest value of each bin that got one, from a single hash per feature."""
    a, b = HashNumbers(seed).feature
    h = sets.select("item_id", F.explode("features").alias("f")).select("item_id", linear(F.col("f"), a, b).alias("h"))
    return h.select("item_id", (F.col("h") % m).cast("int").alias("bin"), F.floor(F.col("h") / m).cast("long").alias("v")).groupBy("item_id", "bin").agg(F.min("v").alias("v"))


def _distance(to: Column, at: Column, m: int) -> Column:
    return F.pmod(to - at, F.lit(m))


def densify(bins: DataFrame, m: int, scheme: str = "probe", seed: int = 1) -> DataFrame:
    """(item_id, sig) from one-permutation bins, as joins; the form that other engines can redo."""
    items = bins.select("item_id").distinct()
    every = items.select("item_id", F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias("i"))
    own = every.join(bins.withColumnRenamed("bin", "i"), ["item_id", "i"], "left")
    empty = own.where("v IS NULL").select("item_id", "i")
    have = bins.select("item_id", F.col("bin").alias("j"), F.col("v").alias("w"))
    near = empty.join(have, "item_id")
    right = _distance(F.col("j"), F.col("i"), m)
    if scheme == "two_way":
        turn = F.element_at(F.array(*[F.lit(int(d)) for d in directions(m, seed)]), F.col("i") + 1)
        dist = F.when(turn == 1, right).otherwise(_distance(F.col("i"), F.col("j"), m))
    else:
        dist = right
    rotated = near.groupBy("item_id", "i").agg(F.min_by(F.col("w") + dist * F.lit(offset(m)), dist).alias("r"))
    filled = own.join(rotated, ["item_id", "i"], "left")
    if scheme == "probe":
        table = F.array(*[F.array(*[F.lit(int(x)) for x in row]) for row in probe_table(m, seed)]) if m <= 16 else None
        if table is not None:
            steps = empty.select("item_id", "i", F.posexplode(F.element_at(table, F.col("i") + 1)).alias("t", "j"))
        else:
            a, b = HashNumbers(seed).probe
            t = tries(m)
            steps = empty.select("item_id", "i", F.explode(F.sequence(F.lit(0), F.lit(t - 1))).alias("t")).withColumn(
                "j", (linear(F.col("i").cast("long") * t + F.col("t"), a, b) % m).cast("int")
            )
        probed = steps.join(have, ["item_id", "j"]).groupBy("item_id", "i").agg(F.min_by("w", "t").alias("p"))
        filled = filled.join(probed, ["item_id", "i"], "left").withColumn("r", F.coalesce("p", "r"))
    elif scheme not in ("rotation", "two_way"):
        raise ValueError(f"unknown densification {scheme}")
    value = F.coalesce("v", "r")
    sig = F.transform(F.sort_array(F.collect_list(F.struct("i", value.alias("v")))), lambda e: e["v"])
    return filled.groupBy("item_id").agg(sig.alias("sig"))


def signatures_of(flat: np.ndarray, lengths: np.ndarray, m: int, scheme: str, seed: int) -> np.ndarray:
    """(rows, m) signatures of sets laid end to end; rows of empty sets are all -1."""
    a, b = HashNumbers(seed).feature
    n = len(lengths)
    h = (flat.astype(np.int64) % P * a + b) % P if len(flat) and flat.max() >= 2**32 else (flat.astype(np.int64) * a + b) % P
    own = np.full((n, m), _EMPTY)
    np.minimum.at(own, (np.repeat(np.arange(n), lengths), h % m), h // m)
    sig = own.copy()
    rows = np.flatnonzero((lengths > 0) & (own == _EMPTY).any(axis=1))
    if scheme == "probe":
        table = probe_table(m, seed)
        left = rows
        for t in range(table.shape[1]):
            if not len(left):
                break
            borrowed = own[left][:, table[:, t]]
            part = sig[left]
            sig[left] = np.where(part == _EMPTY, borrowed, part)
            left = left[(sig[left] == _EMPTY).any(axis=1)]
        rows = left
    if len(rows):
        d = np.arange(1, m)
        at = np.arange(m)
        turn = np.where(directions(m, seed) == 1, 1, -1) if scheme == "two_way" else np.ones(m, dtype=np.int64)
        todo = sig[rows]
        for dist in d:
            borrowed = own[rows][:, (at + turn * dist) % m]
            todo = np.where((todo == _EMPTY) & (borrowed != _EMPTY), borrowed + dist * offset(m), todo)
            if not (todo == _EMPTY).any():
                break
        sig[rows] = todo
    sig[lengths == 0] = -1
    return sig


def doph(sets: DataFrame, k: int, tables: int, seed: int = 1, scheme: str = "probe", form: str = "arrow") -> DataFrame:
    """(item_id, sig array<long>) with k * tables values per item; empty sets drop out.

    ``relational`` is aggregates and joins; ``arrow`` hashes each set in its row, in numpy, without a shuffle;
    ``native`` does so in the JVM with array functions, which costs m passes over a set.
    """
    m = k * tables
    if form == "relational":
        return densify(one_permutation(sets, m, seed), m, scheme, seed)
    if form == "native":
        a, b = HashNumbers(seed).feature
        hashed = sets.where(F.size("features") > 0).select("item_id", F.transform("features", lambda f: linear(f, a, b)).alias("h"))
        own = F.transform(F.sequence(F.lit(0), F.lit(m - 1)), lambda i: F.array_min(F.transform(F.filter("h", lambda x: x % m == i), lambda x: F.floor(x / m).cast("long"))))
        bins = hashed.select("item_id", F.posexplode(own).alias("bin", "v")).where("v IS NOT NULL")
        return densify(bins, m, scheme, seed)
    if form != "arrow":
        raise ValueError(f"unknown form {form}")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(1)
            flat, ends = lists.flatten().to_numpy(zero_copy_only=False), np.asarray(lists.offsets)
            lengths = np.diff(ends)
            sig = signatures_of(flat, lengths, m, scheme, seed)
            offsets = pa.array(np.arange(0, len(sig) * m + 1, m, dtype=np.int32))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(offsets, pa.array(sig.ravel()))], names=["item_id", "sig"])

    return sets.where(F.size("features") > 0).select("item_id", "features").mapInArrow(run, "item_id long, sig array<long>")


def signed_projection(sets: DataFrame, bits: int, seed: int = 1) -> DataFrame:
    """(item_id, sig): signs of ``bits`` random +-1 projections of the binary vector; a sum of 0 counts as positive."""
    n = np.array(parameters(seed + 2000, 2 * bits), dtype=np.int64).reshape(bits, 2)

    def signs(x: np.ndarray, starts: np.ndarray) -> np.ndarray:
        return np.stack([(np.add.reduceat(1 - 2 * ((x * a + b) % P // 65536 % 2), starts) >= 0).astype(np.int64) for a, b in n], axis=1)

    return _per_set(sets, signs, "long").withColumnRenamed("out", "sig")


def sparse_projection(sets: DataFrame, d: int, seed: int = 1) -> DataFrame:
    """(item_id, vector array<double>): entries are sqrt(3), 0, -sqrt(3) with chances 1/6, 2/3, 1/6, made from hashes."""
    n = np.array(parameters(seed + 3000, 2 * d), dtype=np.int64).reshape(d, 2)
    entry = np.array([1, -1, 0, 0, 0, 0], dtype=np.int64)

    def sums(x: np.ndarray, starts: np.ndarray) -> np.ndarray:
        return np.stack([np.add.reduceat(entry[(x * a + b) % P // 65536 % 6], starts) * 3.0**0.5 for a, b in n], axis=1)

    return _per_set(sets, sums, "double").withColumnRenamed("out", "vector")


def hadamard_projection(df: DataFrame, item: str, vector: str, d: int, seed: int = 1) -> DataFrame:
    """(item_id, vector) of a fast Walsh-Hadamard projection of dense vectors to ``d`` sampled places."""
    if dict(df.dtypes)[vector] not in ("array<float>", "array<double>"):
        raise TypeError("the fast transform needs dense vectors; for sparse sets it would fill all dimensions")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = np.array(batch.column(1).to_pylist(), dtype=float)
            if not len(x):
                continue
            size = 1 << max(1, (x.shape[1] - 1).bit_length())
            rng = np.random.default_rng(seed)
            y = np.zeros((len(x), size))
            y[:, : x.shape[1]] = x * rng.choice([-1.0, 1.0], x.shape[1])
            step = 1
            while step < size:
                y = y.reshape(len(x), -1, 2, step)
                y = np.stack([y[:, :, 0] + y[:, :, 1], y[:, :, 0] - y[:, :, 1]], axis=2).reshape(len(x), size)
                step *= 2
            keep = rng.choice(size, min(d, size), replace=False)
            out = y[:, keep] / np.sqrt(len(keep))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(list(out))], names=["item_id", "vector"])

    return df.select(F.col(item).cast("long").alias("item_id"), vector).mapInArrow(run, "item_id long, vector array<double>")


def address_lists(signatures: DataFrame, k: int, tables: int, bits: int, seed: int = 1) -> DataFrame:
    """(item_id, addresses array): the k values of each table folded to a number below 2**bits."""
    a = HashNumbers(seed).fold
    fold = lambda l: F.aggregate(
        F.slice("sig", l * k + 1, k), (l + 1).cast("long"), lambda acc, v: (acc * F.lit(a) + v + 1) % F.lit(P)
    )
    return signatures.select("item_id", F.transform(F.sequence(F.lit(0), F.lit(tables - 1)), lambda l: fold(l) % F.lit(1 << bits)).alias("addresses"))


def addresses(signatures: DataFrame, k: int, tables: int, bits: int, seed: int = 1) -> DataFrame:
    """(item_id, table_id, address) of ``address_lists``."""
    return address_lists(signatures, k, tables, bits, seed).select("item_id", F.posexplode("addresses").alias("table_id", "address"))


def estimate_jaccard(x: Column, y: Column) -> Column:
    """Share of equal places of two signatures."""
    return F.aggregate(F.zip_with(x, y, lambda a, b: (a == b).cast("int")), F.lit(0), lambda s, v: s + v) / F.size(x)

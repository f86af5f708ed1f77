"""What theory says: exponents, parameters, retrieval chances, variances, sizes. Plain functions of numbers."""

from __future__ import annotations

import math


def rho(p1: float, p2: float) -> float:
    """Exponent of the query time: log(1/p1) / log(1/p2)."""
    return math.log(1 / p1) / math.log(1 / p2)


def minwise_rho(s0: float, c: float) -> float:
    return rho(s0, c * s0)


def parameters_for(n: int, p1: float, p2: float, delta: float = 0.1) -> tuple[int, int]:
    """(k, tables) for n items and failure chance delta."""
    return math.ceil(math.log(n) / math.log(1 / p2)), math.ceil(n ** rho(p1, p2) * math.log(1 / delta))


def query_time(n: int, p1: float, p2: float, delta: float = 0.1) -> float:
    return n ** rho(p1, p2) * math.log(n) / math.log(1 / p2) * math.log(1 / delta)


def space(n: int, p1: float, p2: float, delta: float = 0.1) -> float:
    return n ** (1 + rho(p1, p2)) * math.log(1 / delta)


def success(r: int) -> float:
    """Chance that a table works: found in the bucket and kept by a reservoir of r (failure at most 1/r by Markov)."""
    return (1 - 1 / math.e) * (1 - 1 / r)


def min_reservoir() -> int:
    """Smallest reservoir that works with a chance above one half."""
    r = 2
    while success(r) <= 0.5:
        r += 1
    return r


def retrieval(p: float, k: int, tables: int) -> float:
    return 1 - (1 - p**k) ** tables


def retrieval_with_reservoirs(p: float, k: int, r: int, seen: list[int]) -> float:
    """With one bucket of ``seen`` items per table, of which r are kept."""
    miss = 1.0
    for m in seen:
        miss *= 1 - min(1.0, r / m) * p**k
    return 1 - miss


def count_moments(p: float, k: int, tables: int) -> dict[str, float]:
    """Mean and variance of the collision count and of count / tables; relative variance of either."""
    q = p**k
    return {
        "count_mean": tables * q, "count_variance": tables * q * (1 - q), "rate_mean": q, "rate_variance": q * (1 - q) / tables,
        "relative_variance": (1 - q) / (tables * q) if q > 0 else math.inf,
    }


def conditional_collision(a: int, b: int, union: int, y: int) -> float:
    """Chance that q and x collide while y does not share it: a/(a+b) (U-y)/U with a = |q and x|, b the rest of theirs."""
    return a / (a + b) * (union - y) / union


def conditional_printed(a: int, b: int, y: int) -> float:
    """The product form printed beside the exact one; smaller where sets share a core."""
    return a / (a + b) * a / (a + y)


def overwrite_occupancy(m: int, r: int) -> float:
    """Expected items held after m adds if slots are drawn even while there is room."""
    return sum(1 - s / m for s in range(min(m, r)))


def index_bytes(tables: int, r: int, bits: int, share: float = 1.0, id_bytes: int = 4, pointer_bytes: int = 4, counter_bytes: int = 4) -> float:
    slots = tables * 2**bits
    return slots * share * (r * id_bytes + counter_bytes) + (slots * pointer_bytes if share < 1 else 0)


def projection_collision(cosine: float) -> float:
    """Chance that one signed projection agrees."""
    return 1 - math.acos(max(-1.0, min(1.0, cosine))) / math.pi


def values_needed(address_bits: int, signed: bool, dims: int) -> int:
    """Hash values that fill an address: one bit each from signed projections, log2(dims) bits each from minima."""
    return address_bits if signed else max(1, math.ceil(address_bits / math.log2(dims)))


def ranking_variance(jaccard: float, address_bits: int, tables: int, signed: bool, dims: int) -> float:
    """Relative variance of count / tables at a Jaccard similarity of two sets of equal size, for addresses filled either way."""
    p = projection_collision(2 * jaccard / (1 + jaccard)) if signed else jaccard
    return count_moments(p, values_needed(address_bits, signed, dims), tables)["relative_variance"]


def dense_work(n: int, nnz: float) -> float:
    """Multiply-adds of all pairs when only nonzeros count."""
    return n * n * nnz


def monotone(points: list[tuple[float, float]], slack: float = 0.0) -> bool:
    """Whether collision rates rise with similarity, up to ``slack``."""
    ordered = sorted(points)
    return all(b[1] >= a[1] - slack for a, b in zip(ordered, ordered[1:], strict=False))

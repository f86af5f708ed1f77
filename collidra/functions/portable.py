"""Hash arithmetic that Spark and other SQL engines compute alike.

All intermediate values stay below 2**63: feature ids have 28 bits, the modulus P is 2**31 - 1, multipliers are below P.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

P = 2**31 - 1


def parameters(seed: int, n: int) -> list[int]:
    """``n`` numbers in [1, P) that follow from a seed."""
    out, x = [], (seed * 2654435761 + 12345) % P or 1
    for _ in range(n):
        x = x * 48271 % P
        out.append(x)
    return out


def feature_id(token: Column, mode: str = "md5_28") -> Column:
    """Number of a token: 28 bits that any engine can redo, or 63 bits ("xx64") for production, where 28 would clash."""
    if mode == "md5_28":
        return F.conv(F.substring(F.md5(token.cast("binary")), 1, 7), 16, 10).cast("long")
    if mode == "xx64":
        return F.shiftrightunsigned(F.xxhash64(token), 1)
    raise ValueError(f"unknown feature id mode {mode}")


def linear(x: Column, a: int, b: int) -> Column:
    """(a x + b) mod P for 0 <= x < 2**32."""
    return (x * F.lit(a) + F.lit(b)) % F.lit(P)


@dataclass(frozen=True)
class HashNumbers:
    """All constants of one hashing scheme: feature hash, probing, folding, priority."""

    seed: int = 1

    def draw(self) -> list[int]:
        return parameters(self.seed, 12)

    @property
    def feature(self) -> tuple[int, int]:
        return self.draw()[0], self.draw()[1]

    @property
    def probe(self) -> tuple[int, int]:
        return self.draw()[2], self.draw()[3]

    @property
    def fold(self) -> int:
        return self.draw()[4]

    @property
    def priority(self) -> tuple[int, int]:
        return self.draw()[5], self.draw()[6]

    @property
    def share(self) -> tuple[int, int]:
        return self.draw()[7], self.draw()[8]

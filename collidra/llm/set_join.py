"""Exact links of similar sets inside one task, and how buckets of sets are dealt to tasks of bounded size."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd

from .common import spare

#: The least Jaccard similarity as a fraction, so that no rounding decides.
NUM, DEN = 4, 5
#: Sets that every other meets first, and pairs that are looked at together.
FIRST, _PAIRS = 32, 1_000_000


class _Classes:
    def __init__(self, n: int):
        self.parent = list(range(n))

    def root(self, i: int) -> int:
        parent = self.parent
        while parent[i] != i:
            parent[i] = i = parent[parent[i]]
        return i

    def roots(self) -> np.ndarray:
        return np.array([self.root(i) for i in range(len(self.parent))])


def _ends(change: np.ndarray) -> np.ndarray:
    """For each row the end of its run, where ``change`` tells of each row but the first if a run begins."""
    starts = np.concatenate(([0], np.flatnonzero(change) + 1))
    ends = np.concatenate((starts[1:], [len(change) + 1]))
    return np.repeat(ends, ends - starts)


def links_within(sets: list[np.ndarray], num: int = NUM, den: int = DEN) -> list[tuple[int, int]]:
    """Links (i, j) of similar sets, given as arrays without repeats, whose classes are those of all similar pairs.

    First each set meets the first ones, which joins most of a large class by a line of links. Then pairs of different
    classes follow by their rarest elements, of which similar sets of n and m elements share one of the first
    n - ceil(0.8 n) + 1 of either. A pair is verified by counting, unless its classes have met by then.
    """
    n = len(sets)
    size = np.array([len(s) for s in sets])
    if n < 2 or not size.sum():
        return [(i, i + 1) for i in range(n - 1)]  # sets without elements are equal
    _, token, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    token = token.astype(np.int32)
    start = np.cumsum(size) - size
    own = [token[a : a + s] for a, s in zip(start.tolist(), size.tolist(), strict=True)]
    marked = np.zeros(len(count), dtype=bool)
    classes, out = _Classes(n), []
    empty = np.flatnonzero(size == 0).tolist()
    for i, j in zip(empty[1:], empty, strict=False):
        classes.parent[i] = empty[0]
        out.append((i, j))

    def meet(i: int, others: np.ndarray, once: bool = False) -> None:
        """Link set i to all of the others that are similar, or to the first such."""
        marked[own[i]] = True
        edges = np.concatenate(([0], np.cumsum(size[others])))
        both = np.concatenate([own[j] for j in others.tolist()] + [own[i][:0]])
        common = np.concatenate(([0], np.cumsum(marked[both])))[edges]
        hit = others[(num + den) * np.diff(common) >= num * (size[i] + size[others])]
        marked[own[i]] = False
        for j in hit.tolist()[: 1 if once else None]:
            a, b = classes.root(i), classes.root(j)
            if a != b:
                classes.parent[max(a, b)] = min(a, b)
                out.append((i, j))

    def fits(i: np.ndarray | int, j: np.ndarray) -> np.ndarray:
        return den * np.minimum(size[i], size[j]) >= num * np.maximum(size[i], size[j])

    for i in range(1, n):
        j = np.arange(min(i, FIRST))
        j = j[fits(i, j)]
        if len(j):
            meet(i, j, True)
    if n <= 2:
        return out
    component = classes.roots()
    if (component == component[0]).all():
        return out
    row = np.repeat(np.arange(n, dtype=np.int32), size)
    rank = np.argsort(np.argsort(count, kind="stable"), kind="stable").astype(np.int32)[token]
    order = np.lexsort((rank, row))
    rank, row = rank[order], row[order]
    prefix = size + (-num * size) // den + 1
    keep = np.arange(len(row)) - start[row] < prefix[row]
    rank, row = rank[keep], row[keep]
    order = np.lexsort((row, component[row], rank))
    rank, row = rank[order], row[order]
    fresh = rank[1:] != rank[:-1]
    stop, follow = _ends(fresh), _ends(fresh | (component[row[1:]] != component[row[:-1]]))
    total = np.cumsum(stop - follow)
    for lo in range(0, int(total[-1]) if len(total) else 0, _PAIRS):
        k = np.arange(lo, min(lo + _PAIRS, int(total[-1])))
        at = np.searchsorted(total, k, "right")
        a, b = row[at].astype(np.int64), row[stop[at] - (total[at] - k)].astype(np.int64)
        good = fits(a, b)
        pairs = np.unique(np.minimum(a, b)[good] * n + np.maximum(a, b)[good])
        a, b = pairs // n, pairs % n
        cuts = np.flatnonzero(np.diff(a)) + 1
        for i, others in zip(a[np.concatenate(([0], cuts))].tolist() if len(a) else [], np.split(b, cuts), strict=False):
            mine = classes.root(i)
            others = np.array([j for j in others.tolist() if classes.root(j) != mine], dtype=np.int64)
            if len(others):
                meet(i, others)
    return out


def by_cell(make, names: list[str]):
    """A function over rows sorted by cell: rows of a cell (unit, value) become sets by ``make`` and leave as links (a, b)."""

    def links(held: list[tuple]) -> list[tuple[int, int]]:
        units = [u for u, _ in held]
        return [(units[i], units[j]) for i, j in links_within([make(v) for _, v in held])]

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        spare()
        cell, held, edges = None, [], []
        for pdf in parts:
            for c, unit, value in zip(pdf["cell"], pdf[names[0]], pdf[names[1]], strict=True):
                if c != cell:
                    if len(held) > 1:
                        edges += links(held)
                    cell, held = c, []
                held.append((unit, value))
            if edges:
                yield pd.DataFrame(edges, columns=["a", "b"])
                edges = []
            del pdf
        if len(held) > 1 and (edges := links(held)):
            yield pd.DataFrame(edges, columns=["a", "b"])
        held.clear()
        spare()

    return run

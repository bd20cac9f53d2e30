"""Pattern codes, dimension tables and classifiers.

Positions 0..k-1 of an embedding; the pair (i, j), i < j, has bit j(j-1)/2 + i of its
mask, so that a new vertex j appends `bits << j(j-1)/2`.
"""

from __future__ import annotations

from functools import lru_cache
from itertools import permutations, product

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# Names of the connected patterns by (vertices, edges, largest degree).
NAMES = {
    (2, 1, 1): "edge", (3, 2, 2): "wedge", (3, 3, 2): "triangle",
    (4, 3, 3): "3-star", (4, 3, 2): "4-path", (4, 4, 2): "4-cycle", (4, 4, 3): "tailed-triangle", (4, 5, 3): "diamond", (4, 6, 3): "4-clique",
}


def offset(j: int) -> int:
    return j * (j - 1) // 2


def pairs(k: int) -> list[tuple[int, int]]:
    """Pairs by bit number."""
    return [(i, j) for j in range(k) for i in range(j)]


def degrees_of(mask: int, k: int) -> list[int]:
    d = [0] * k
    for b, (i, j) in enumerate(pairs(k)):
        if mask >> b & 1:
            d[i] += 1
            d[j] += 1
    return d


def connected(mask: int, k: int) -> bool:
    reach, grown = 1, True
    while grown:
        grown = False
        for b, (i, j) in enumerate(pairs(k)):
            if mask >> b & 1 and (reach >> i & 1) != (reach >> j & 1):
                reach |= 1 << i | 1 << j
                grown = True
    return reach == (1 << k) - 1


@lru_cache
def canonical_codes(k: int) -> np.ndarray:
    """Least mask over all renumberings, for every mask of k vertices."""
    bits = pairs(k)
    at = {p: b for b, p in enumerate(bits)}
    masks = np.arange(1 << len(bits))
    best = masks.copy()
    for perm in permutations(range(k)):
        moved = np.zeros_like(masks)
        for b, (i, j) in enumerate(bits):
            x, y = sorted((perm[i], perm[j]))
            moved |= (masks >> b & 1) << at[x, y]
        np.minimum(best, moved, out=best)
    return best


def automorphisms(mask: int, k: int) -> int:
    bits = pairs(k)
    on = {frozenset(p) for b, p in enumerate(bits) if mask >> b & 1}
    return sum(all(frozenset((perm[i], perm[j])) in on for i, j in map(tuple, on)) for perm in permutations(range(k)))


def name_of(mask: int, k: int) -> str:
    d = degrees_of(mask, k)
    return NAMES.get((k, sum(d) // 2, max(d)), f"k{k}:{canonical_codes(k)[mask]}")


@lru_cache
def dimension(k: int) -> list[tuple[int, int, int, str]]:
    """(mask, pattern_id, n_edges, name) of every connected mask."""
    code = canonical_codes(k)
    return [(m, int(code[m]), bin(m).count("1"), name_of(m, k)) for m in range(1 << offset(k)) if connected(m, k)]


def dimension_df(spark: SparkSession, k: int) -> DataFrame:
    return spark.createDataFrame(dimension(k), "mask int, pattern_id long, n_edges int, pattern string")


def pattern_names(k: int) -> list[str]:
    return sorted({row[3] for row in dimension(k)})


@lru_cache
def walk_signature(mask: int, k: int) -> tuple[int, ...]:
    """Closed walk counts of lengths 2..k+1, which stand for the spectrum."""
    a = np.zeros((k, k), np.int64)
    for b, (i, j) in enumerate(pairs(k)):
        if mask >> b & 1:
            a[i, j] = a[j, i] = 1
    out, p = [], a
    for _ in range(k):
        p = p @ a
        out.append(int(np.trace(p)))
    return tuple(out)


def spectrum_df(spark: SparkSession, k: int) -> DataFrame:
    """mask -> pattern by spectrum; refuses sizes where different patterns share one."""
    by: dict[tuple[int, ...], set[str]] = {}
    for m, _, _, name in dimension(k):
        by.setdefault(walk_signature(m, k), set()).add(name)
    if any(len(v) > 1 for v in by.values()):
        raise ValueError(f"patterns of {k} vertices are not told apart by their spectrum")
    return spark.createDataFrame([(m, next(iter(by[walk_signature(m, k)]))) for m, *_ in dimension(k)], "mask int, pattern string")


def transition_table(spark: SparkSession, k: int) -> DataFrame:
    """(parent_mask, bits) -> (child_mask, pattern) for growing k-1 to k vertices."""
    names = {m: name for m, _, _, name in dimension(k)}
    rows = [(p, b, p | b << offset(k - 1), names[p | b << offset(k - 1)]) for p, *_ in dimension(k - 1) for b in range(1, 1 << (k - 1))]
    return spark.createDataFrame(rows, "parent_mask int, bits int, mask int, pattern string")


def classify3(mask: Column) -> Column:
    return F.when(F.bit_count(mask) == 3, "triangle").otherwise("wedge")


def classify4(mask: Column) -> Column:
    """By the number of edges and the largest degree."""
    touching = [sum(1 << b for b, p in enumerate(pairs(4)) if v in p) for v in range(4)]
    top = F.greatest(*[F.bit_count(mask.bitwiseAND(t)) for t in touching])
    n = F.bit_count(mask)
    return (
        F.when(n == 3, F.when(top == 3, "3-star").otherwise("4-path")).when(n == 4, F.when(top == 2, "4-cycle").otherwise("tailed-triangle"))
        .when(n == 5, "diamond").otherwise("4-clique")
    )


@lru_cache(1 << 16)
def _canonical_ranked(mask: int, ranks: tuple[int, ...]) -> tuple[tuple, tuple[int, ...]]:
    """(edges, orbit of each position) for labels that are given by their ranks."""
    k = len(ranks)
    on = [(i, j) for b, (i, j) in enumerate(pairs(k)) if mask >> b & 1]
    groups = [[i for i in range(k) if ranks[i] == r] for r in sorted(set(ranks))]
    best, maps = None, []
    for orders in product(*(permutations(g) for g in groups)):
        perm = [0] * k  # new place of each position: sorted by label, all orders within one
        for place, i in enumerate(i for order in orders for i in order):
            perm[i] = place
        code = tuple(sorted(tuple(sorted((perm[i], perm[j]))) for i, j in on))
        if best is None or code < best:
            best, maps = code, [perm]
        elif code == best:
            maps.append(perm)
    return best, tuple(min(p[i] for p in maps) for i in range(k))


def canonical_labelled(mask: int, labels: list[int]) -> tuple[str, list[int]]:
    """(code, orbit of each position) of a labelled pattern, over all renumberings that
    keep labels sorted.  Positions of one orbit are exchanged by automorphisms."""
    word = sorted(labels)
    order = sorted(set(labels))
    edges, orbit = _canonical_ranked(mask, tuple(order.index(x) for x in labels))
    return "-".join(map(str, word)) + "|" + ",".join(f"{i}.{j}" for i, j in edges), list(orbit)


def of_code(code: str) -> tuple[int, list[int]]:
    """(mask, labels) of a code."""
    word, edges = code.split("|")
    mask = 0
    for e in edges.split(","):
        i, j = map(int, e.split("."))
        mask |= 1 << offset(max(i, j)) + min(i, j)
    return mask, [int(x) for x in word.split("-")]

"""Connected sets of four of dense graphs, counted from their parents of three over bits.

A dense graph has so many sets of three that none may be a row.  Vertices stand by id and
grow as in the canonical rule.  The sets (v0, v1, v2) of an edge (v0, v1) are met
together: v2 runs over the rows of a matrix of bits, and neighbours of v2 are intersected
there with the candidates for the fourth place.  These are neighbours of v0 (_inside:
the columns are those of v0) or neighbours of v1 only (_beside: those of v1), which
keeps rows as short as a neighbour list; what remains of v2's neighbours is adjacent to
v2 alone.  As elsewhere only sizes of candidate sets are added up.

down: vertices above v0 stand in descending order, the order in which a depth-first search
takes the last one of its extension set first and leaves those before it to the branch.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import PropertyGraph
from ..session import ship
from .connect import BROADCAST_BYTES, flat_lists

LEAST_EDGES, SPARSE = 1 << 16, 128  # fewer edges, or fewer than one cell in SPARSE: rows are cheaper
BITS_BYTES = 64 << 20  # of all vertices against all, in each worker
ROWS, TASKS = 512, 240

WEDGE, TRIANGLE, CHAIN = 3, 7, 5  # masks of three: v0 in the middle, closed, v1 in the middle


def fits(graph: PropertyGraph) -> bool:
    """Whether the graph is large and dense enough for bits, and these fit their bounds."""
    m = graph.n_edges
    return LEAST_EDGES <= m <= BROADCAST_BYTES // 8 and holds(graph.degrees.count(), m)


def holds(n: int, m: int) -> bool:
    """Whether n vertices with m edges are dense enough and within the bounds."""
    return m <= BROADCAST_BYTES // 8 and n * n <= SPARSE * m and n * n <= BITS_BYTES * 8


def _words(flags: np.ndarray) -> np.ndarray:
    """Rows of flags as words, the first flag as the lowest bit."""
    wide = -flags.shape[1] % 64
    if wide:
        flags = np.concatenate([flags, np.zeros((len(flags), wide), flags.dtype)], 1)
    return np.ascontiguousarray(np.packbits(flags, axis=1, bitorder="little")).view(np.uint64)


def _flags(words: np.ndarray, n: int) -> np.ndarray:
    return np.unpackbits(words.view(np.uint8), axis=-1, count=n, bitorder="little")


def _after(at: np.ndarray, words: int) -> np.ndarray:
    """For each number a row of bits, set from that number on."""
    left = np.clip(at[:, None] - 64 * np.arange(words), 0, 64)
    full = np.uint64(0xFFFFFFFFFFFFFFFF)
    return np.where(left == 64, np.uint64(0), full << np.minimum(left, 63).astype(np.uint64))


def _met(rows: np.ndarray, at: np.ndarray, words: np.ndarray) -> int:
    """Bits that the rows at these places have in common with words, all together."""
    return int(np.bitwise_count(rows.take(at, 0) & words).sum(dtype=np.uint64))


class Bits:
    """Adjacency of positions 0..n-1 as lists and as bits."""

    def __init__(self, first: np.ndarray, nbrs: np.ndarray):
        self.n, self.first, self.nbrs, self.made = len(first) - 1, first, nbrs, None

    def __reduce__(self):
        return Bits, (self.first, self.nbrs)

    @property
    def words(self) -> np.ndarray:
        if self.made is None:
            self.made = np.zeros((self.n, -(-self.n // 64)), np.uint64)
            for lo in range(0, self.n, ROWS):
                hi = min(self.n, lo + ROWS)
                flags = np.zeros((hi - lo, self.n), bool)
                size = np.diff(self.first[lo : hi + 1])
                flags[np.repeat(np.arange(hi - lo), size), self.nbrs[self.first[lo] : self.first[hi]]] = True
                self.made[lo:hi] = _words(flags)
        return self.made

    def near(self, v: int) -> np.ndarray:
        return self.nbrs[self.first[v] : self.first[v + 1]]

    def near_of(self, own: np.ndarray) -> np.ndarray:
        """Of all vertices the neighbours among own, as bits: rows of len(own)."""
        out = np.zeros((self.n, -(-len(own) // 64) * 8), np.uint8)
        for lo in range(0, len(own), ROWS):
            flags = _flags(self.words[own[lo : lo + ROWS]], self.n)
            part = flags[::8].copy()
            for j in range(1, min(8, len(flags))):  # what packbits does along the other axis, in longer strides
                more = flags[j::8]
                part[: len(more)] |= more << j
            out[:, lo // 8 : lo // 8 + len(part)] = part.T
        return out.view(np.uint64)

    def over(self, v: int) -> np.ndarray:
        """Of all vertices the number of neighbours above v."""
        w = (v + 1) // 64
        part = self.words[:, w:]
        tail = _after(np.array([v + 1 - 64 * w]), part.shape[1]) if part.shape[1] else np.zeros((1, 0), np.uint64)
        return np.bitwise_count(part & tail).sum(1, dtype=np.int64)

    def above(self, v: int) -> np.ndarray:
        own = self.near(v)
        return own[np.searchsorted(own, v, "right") :]


def _inside(bits: Bits, v0: int, tally: dict, down: bool) -> None:
    """Candidates among v0's neighbours for sets v0, v1, v2 of v0 and two of them; also, for v2
    among v0's or v1's neighbours, all of v2's neighbours above v0 but those of v0."""
    own = bits.above(v0)[::-1] if down else bits.above(v0)
    d = len(own)
    if not d:
        return
    local = np.concatenate([_words(_flags(bits.words[own[lo : lo + ROWS]], bits.n).take(own, 1)) for lo in range(0, d, ROWS)])
    place = np.arange(d)
    upper = local & _after(place + 1, local.shape[1])
    degree, up = (np.bitwise_count(x).sum(1, dtype=np.int64) for x in (local, upper))
    low = degree - up  # a v1 each that closes a triangle with this v2
    over = bits.over(v0)
    rest = over[own] - degree
    for mask, times in ((TRIANGLE, low), (WEDGE, place - low)):
        tally[mask, 0, 0] += int((times * (d - 1 - place)).sum())
        tally[mask, 0, 4] += int((times * up).sum())
        tally[mask, 2, 0] += int((times * rest).sum())
    closed = int((up * (up - 1) // 2).sum())
    tally[TRIANGLE, 0, 2] += closed
    tally[WEDGE, 0, 2] += int(((place - 1) * low - place * up).sum()) - closed
    for i in range(d - 1):
        w = (i + 1) // 64
        met = np.bitwise_count(upper[i + 1 :, w:] & upper[i, w:]).sum(1, dtype=np.int64)
        both = int(met @ _flags(local[i], d)[i + 1 :])
        tally[TRIANGLE, 0, 6] += both
        tally[WEDGE, 0, 6] += int(met.sum()) - both
    over[: v0 + 1] = 0
    over[own] = 0
    tally[CHAIN, 2, 0] += sum(int(over[bits.near(v1)].sum()) for v1 in own.tolist())


def _beside(bits: Bits, v1: int, tally: dict, down: bool) -> None:
    """Candidates among the neighbours of v1 but not of v0, for every v0 before v1."""
    own = bits.near(v1)
    p1, n = int(np.searchsorted(own, v1)), len(own)
    if not p1:
        return
    near = bits.near_of(own)
    words = near.shape[1]
    until = np.searchsorted(own, np.arange(bits.n), "right")  # of own, those up to a vertex
    later = _after(until, words)
    later = near & (~later if down else later)
    tail = _after(np.arange(1, p1 + 1), words) & _words(np.ones((1, n), bool))
    inside = np.zeros(bits.n, bool)
    inside[own] = True
    upto = np.zeros(n + 1, np.int64)
    follow = np.zeros(n, np.int64)  # of each of own, neighbours in own that come after v0
    for lo in range(p1, n, ROWS):
        follow += _flags(near[own[lo : lo + ROWS]], n).sum(0, dtype=np.int64)
    for p in range(p1 - 1, -1, -1):
        v0 = int(own[p])
        beside = tail[p] & ~near[v0]
        flags = _flags(beside, n)
        m = int(np.count_nonzero(flags))
        if m:
            up = bits.above(v0)
            at = int(np.searchsorted(up, v1))
            before, after = (up[at + 1 :], up[:at]) if down else (up[:at], up[at + 1 :])
            here, there = inside.take(before), inside.take(after)
            np.cumsum(flags, out=upto[1:])
            met = {"low": _met(near, before[here], beside)}
            lone = _met(near, before[~here], beside)
            edges = {}
            for mask, x in ((TRIANGLE, after[there]), (WEDGE, after[~there])):
                met[mask], more = _met(near, x, beside), _met(later, x, beside)
                least = int(upto.take(until.take(x)).sum())
                least = least if down else m * len(x) - least
                tally[mask, 1, 0] += least
                tally[mask, 1, 4] += more
                tally[mask, 2, 0] -= met[mask]
                edges[mask] = (m * len(x) - least, met[mask] - more)
            tally[CHAIN, 0, 0] += edges[TRIANGLE][0] + edges[WEDGE][0]
            tally[CHAIN, 0, 2] += edges[TRIANGLE][0]
            tally[CHAIN, 0, 4] += edges[TRIANGLE][1] + edges[WEDGE][1]
            tally[CHAIN, 0, 6] += edges[TRIANGLE][1]
            among = int(follow[flags.view(bool)].sum()) - met["low"] - met[TRIANGLE]  # twice the edges beside
            tally[CHAIN, 1, 0] += m * (m - 1) // 2
            tally[CHAIN, 1, 4] += among // 2
            tally[CHAIN, 2, 0] -= met["low"] + lone + met[TRIANGLE] + met[WEDGE] + m + among
        follow += _flags(near[v0], n)


def _masks(tally: dict) -> dict[int, int]:
    """Sets of four by mask: candidates adjacent to some positions and no others, by inclusion and exclusion."""
    out = {}
    for (mask, h, met), _ in tally.items():
        more = [(o, n) for (own, at, o), n in tally.items() if (own, at) == (mask, h) and o & met == met]
        out[mask | (1 << h | met) << 3] = sum(n * (-1) ** (o ^ met).bit_count() for o, n in more)
    return out


def tallied(bits: Bits, vertices, down: bool = False) -> dict[int, int]:
    """What these vertices, as v0 and as v1, add to the numbers of sets by mask; only the sum over all is one."""
    tally = {(mask, h, met): 0 for mask in (WEDGE, TRIANGLE, CHAIN) for h, mets in enumerate(((0, 2, 4, 6), (0, 4), (0,))) for met in mets}
    for v in vertices:
        _inside(bits, v, tally, down)
        _beside(bits, v, tally, down)
    return _masks(tally)


def connected_fours(graph: PropertyGraph, down: bool = False) -> DataFrame:
    """mask, n of the connected sets of four."""
    spark = graph.edges.sparkSession
    ship(spark)
    _, first, nbrs = flat_lists(graph)
    held = spark.sparkContext.broadcast(Bits(first, nbrs))
    n = len(first) - 1

    def some(batches):
        for batch in batches:
            for t in batch.column(0).to_pylist():
                found = tallied(held.value, range(t, n, TASKS), down)
                yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.int32()), pa.array(list(found.values()), pa.int64())], ["mask", "n"])

    found = spark.range(0, TASKS, 1, TASKS).mapInArrow(some, "mask int, n long")
    return found.groupBy("mask").agg(F.sum("n").alias("n")).where("n > 0")

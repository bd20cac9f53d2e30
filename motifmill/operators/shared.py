"""Triangles of graphs whose edges join nodes that share a key, from the (key, node) rows.

A dense graph has many more edges than rows: a key of s nodes makes s * s / 2 pairs.  Here
no edge is ever a row.  The groups (4 bytes a row) are broadcast behind a check of their
size, and a task makes the adjacency bits of a range of vertices from them: for each vertex
u it cuts the bits of u's out-neighbours in the range down to those of u (u's local graph)
and counts what is left.  Windows with few neighbours a vertex have lists for bits.  Orientation is by position in the ids.  Sparse graphs and those
beyond the bound take the plan over edges that the caller gives.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import PropertyGraph
from ..plans.planning import number_rows
from ..session import cut, keep, ship
from .connect import BROADCAST_BYTES

LEAST_PAIRS, SPARSE = 1 << 20, 4096  # fewer pairs, or fewer than one cell in SPARSE: edges are cheaper
TILE_BYTES, CHUNK_WORDS, TASKS = 96 << 20, 1 << 15, 48


def _distinct(values: np.ndarray) -> np.ndarray:
    """np.unique of integers, by sorting: it hashes them, which is slower here."""
    values = np.sort(values)
    return values[np.append(True, values[1:] != values[:-1])] if len(values) else values


def thin(n: int, pairs: int) -> bool:
    """Whether lists of neighbours are shorter work than bits of all vertices."""
    return pairs * 128 < n * n


class Groups:
    """Members (positions of vertices) of the groups of each window, in flat arrays."""

    def __init__(self, n: int, windows: np.ndarray, sizes: np.ndarray, members: np.ndarray):
        order = np.argsort(windows, kind="stable")
        self.n, self.names = n, np.unique(windows)
        self.first = np.append(np.searchsorted(windows[order], self.names), len(windows))
        self.members = members[np.argsort(np.repeat(windows, sizes), kind="stable")]
        self.start = np.append(0, np.cumsum(sizes[order]))
        self.last: tuple[int, Window] | None = None

    def pairs(self, i: int) -> int:
        """Pairs in the groups of window i: its edges at most."""
        size = np.diff(self.start[self.first[i] : self.first[i + 1] + 1])
        return int((size * (size - 1) // 2).sum())

    def window(self, i: int) -> Window:
        """The window i; the one made last is kept, tasks of one worker often ask for it again."""
        if self.last is None or self.last[0] != i:
            self.last = i, Window(self, i)
        return self.last[1]


class Window:
    """The graph of one window: neighbours of a vertex come from its groups."""

    def __init__(self, groups: Groups, i: int):
        lo, hi = groups.first[i], groups.first[i + 1]
        start = groups.start[lo : hi + 1]
        self.n, self.members, self.start = groups.n, groups.members[start[0] : start[-1]], start - start[0]
        order = np.argsort(self.members, kind="stable")
        self.group = np.repeat(np.arange(hi - lo, dtype=np.int32), np.diff(start))[order]
        self.at = np.append(0, np.cumsum(np.bincount(self.members, minlength=self.n)))
        self.pairs = groups.pairs(i)

    def near(self, v: int, least: int) -> np.ndarray:
        """Neighbours of v from least on, with repeats."""
        own = self.group[self.at[v] : self.at[v + 1]].tolist()
        if not own:
            return self.members[:0]
        all_of = np.concatenate([self.members[self.start[g] : self.start[g + 1]] for g in own])
        return all_of[all_of >= least]

    def triangles(self, lo: int, hi: int, first: int, step: int) -> int:
        """Triangles u < x < w with x in [lo, hi), u one of range(first, hi, step)."""
        return (self._by_lists if thin(self.n, self.pairs) else self._by_bits)(lo, hi, first, step)

    def _by_lists(self, lo: int, hi: int, first: int, step: int) -> int:
        above = [_distinct(self.near(x, x + 1)) for x in range(lo, hi)]
        mark, total = np.zeros(self.n, bool), 0
        for u in range(first, hi, step):
            near = _distinct(self.near(u, u + 1))
            inside = near[slice(*np.searchsorted(near, (lo, hi)))].tolist()
            if inside:
                mark[near] = True
                total += int(np.count_nonzero(mark.take(np.concatenate([above[x - lo] for x in inside]))))
                mark[near] = False
        return total

    def _by_bits(self, lo: int, hi: int, first: int, step: int) -> int:
        base = lo & ~63
        buf = np.zeros((self.n + 63 & ~63) - base, bool)
        words = len(buf) // 64
        tile = np.zeros((hi - lo, words), np.uint64)
        for x in range(lo, hi):
            near = self.near(x, x + 1) - base
            if len(near):
                buf[near] = True
                tile[x - lo] = np.packbits(buf).view(np.uint64)
                buf[near] = False
        total = 0
        for u in range(first, hi, step):
            near = self.near(u, max(u + 1, lo)) - base
            if not len(near):
                continue
            buf[near] = True
            row = np.packbits(buf).view(np.uint64)
            inside = np.flatnonzero(buf[lo - base : hi - base])
            buf[near] = False
            many = max(1, CHUNK_WORDS // words)
            for i in range(0, len(inside), many):
                local = tile[inside[i : i + many]]
                local &= row
                total += int(np.bitwise_count(local).sum(dtype=np.int64))
        return total


def _gather(rows: DataFrame, ids: np.ndarray) -> Groups:
    sc = rows.sparkSession.sparkContext
    named = sc.broadcast(ids)

    def encode(batches):
        for batch in batches:
            lists = batch.column(1)
            members = np.searchsorted(named.value, lists.flatten().to_numpy()).astype(np.int32)
            parts = (batch.column(0).to_numpy().astype(np.int64), lists.value_lengths().to_numpy().astype(np.int32), members)
            yield pa.RecordBatch.from_arrays([pa.array([p.tobytes()], pa.binary()) for p in parts], ["w", "size", "member"])

    lists = rows.groupBy("w", "k").agg(F.collect_list("n").alias("l")).where(F.size("l") > 1).select("w", "l")
    made = lists.mapInArrow(encode, "w binary, size binary, member binary").toArrow()
    named.unpersist()
    flat = [np.frombuffer(b"".join(made.column(i).to_pylist()), t) for i, t in enumerate((np.int64, np.int32, np.int32))]
    return Groups(len(ids), *flat)


def _tasks(groups: Groups, tile_bytes: int) -> list[tuple[int, int, int, int, int]]:
    """(window, range of the middle vertices, first vertex and step of the lowest ones)."""
    n, ranges = groups.n, []
    for w in range(len(groups.names)):
        lo, pairs = 0, groups.pairs(w)
        while lo < n:
            many = tile_bytes * n // (8 * pairs + 1) if thin(n, pairs) else tile_bytes * 8 // (n + 64 - lo)
            hi = min(n, lo + max(1, many))
            ranges.append((w, lo, hi))
            lo = hi
    step = -(-TASKS // len(ranges))
    return [(*r, first, step) for r in ranges for first in range(step)]


def window_triangles(rows: DataFrame, plain, apply: bool = False, least_pairs: int = LEAST_PAIRS, most: int = BROADCAST_BYTES, tile_bytes: int = TILE_BYTES) -> DataFrame:
    """w, triangles of the graph of each window w that has any; rows: w, k, n without nulls or repeats.

    plain(rows): the same over edges.  apply: tasks are groups of applyInArrow."""
    spark = rows.sparkSession
    ship(spark)
    rows = keep(rows.select("w", "k", "n"), "rows")
    sizes = rows.groupBy("w", "k").agg(F.count("*").alias("c"))
    total = sizes.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("rows"), F.coalesce(F.expr("sum(c * (c - 1) / 2)"), F.lit(0)).alias("pairs")).first()
    if total["pairs"] < max(1, least_pairs) or total["rows"] * 4 > most:
        return plain(rows)
    ids = np.sort(rows.select("n").distinct().toArrow().column("n").to_numpy())
    if len(ids) ** 2 > SPARSE * total["pairs"]:
        return plain(rows)
    groups = _gather(rows, ids)
    tasks = _tasks(groups, tile_bytes)
    held = spark.sparkContext.broadcast((groups, tasks))

    def run(numbers):
        groups, tasks = held.value
        mine = [tasks[t] for t in numbers]
        n = [groups.window(i).triangles(*task) for i, *task in mine]
        return [pa.array([int(groups.names[i]) for i, *_ in mine], pa.int64()), pa.array(n, pa.int64())]

    def some(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays(run(batch.column(0).to_pylist()), ["w", "n"])

    numbers = spark.range(0, len(tasks), 1, len(tasks))
    if apply:
        found = numbers.repartition(len(tasks), "id").groupBy("id").applyInArrow(lambda table: pa.table(run(table.column(0).to_pylist()), ["w", "n"]), "w long, n long")
    else:
        found = numbers.mapInArrow(some, "w long, n long")
    return found.groupBy("w").agg(F.sum("n").alias("triangles")).where("triangles > 0")


def triangles(rows: DataFrame, plain, name: str = "triangles", apply: bool = False, **bounds) -> DataFrame:
    """One row: triangles of the graph of rows k, n; plain(edges) gives the same from edges."""
    whole = rows.select(F.lit(0).cast("long").alias("w"), "k", F.col("n").cast("long").alias("n")).dropna().distinct()
    found = window_triangles(whole, lambda kept: plain(pairs(kept)).toDF("triangles"), apply, **bounds)
    return found.agg(F.coalesce(F.sum("triangles"), F.lit(0)).cast("long").alias(name))


def pairs(rows: DataFrame) -> DataFrame:
    """Edges of rows k, n without repeats."""
    a, b = rows.select("k", F.col("n").alias("src")), rows.select("k", F.col("n").alias("dst"))
    return a.join(b, "k").where("src < dst").select("src", "dst").distinct()


def fold(rows: DataFrame) -> PropertyGraph:
    """The graph of rows (k, n) with nodes of the same keys folded to one vertex.

    Such nodes have the same neighbours and are neighbours of each other, as they share every
    key; a vertex (numbered from 0) has their number as its weight.  No edge between nodes is made."""
    rows = rows.select("k", "n").where("k is not null and n is not null")
    keys = rows.groupBy("n").agg(F.sort_array(F.collect_set("k")).alias("ks"))
    classes = cut(number_rows(keys.groupBy("ks").agg(F.count("*").alias("weight")), "id").withColumn("id", F.col("id").cast("int")))
    d = classes.select("id", F.explode("ks").alias("k"))
    pairs = d.alias("x").join(d.alias("y"), F.expr("x.k = y.k and x.id < y.id"))
    return PropertyGraph(cut(pairs.select(F.col("x.id").alias("src"), F.col("y.id").alias("dst")).distinct()), None, classes.select("id", "weight"))


def unfolded_size(graph: PropertyGraph) -> tuple[int, int]:
    """Vertices that have neighbours, and edges, of the graph that a weighted one stands for."""
    a, b = (graph.weights.select(F.col("id").alias(v), F.col("weight").alias(f"_{v}")) for v in ("src", "dst"))
    between = graph.edges.join(a, "src").join(b, "dst").agg(F.coalesce(F.sum(F.col("_src") * F.col("_dst")), F.lit(0))).first()[0]
    near = graph.weights.join(graph.degrees.withColumnRenamed("degree", "d"), "id", "left").where("d is not null or weight > 1")
    own = near.agg(F.coalesce(F.sum("weight"), F.lit(0)), F.coalesce(F.expr("sum(weight * (weight - 1) div 2)"), F.lit(0))).first()
    return own[0], between + own[1]


def unfold(graph: PropertyGraph) -> PropertyGraph:
    """The graph that a weighted one stands for: each vertex as often as it weighs."""
    copies = graph.weights.select("id", F.explode(F.sequence(F.lit(1).cast("long"), "weight")).alias("c")).select("id", (F.col("id") * F.lit(graph.most_weight) + F.col("c")).alias("own"))
    src, dst = (copies.select(F.col("id").alias(v), F.col("own").alias(f"_{v}")) for v in ("src", "dst"))
    between = graph.edges.join(src, "src").join(dst, "dst").select(F.least("_src", "_dst").alias("src"), F.greatest("_src", "_dst").alias("dst"))
    among = src.join(dst, F.expr("src = dst and _src < _dst")).select(F.col("_src").alias("src"), F.col("_dst").alias("dst"))
    return PropertyGraph.of(between.unionByName(among))

"""Connectivity: adjacency of a candidate u to each vertex of its embedding, as bits."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..graph import PropertyGraph
from ..session import plan_bytes, ship

STRATEGIES = ("join", "linear", "binary", "intersect")
BROADCAST_BYTES = 256 << 20
BROADCAST_EDGES = 1 << 20  # a hash table of arcs takes some 50 bytes each
LIST_PARTS = 16  # of a neighbour list that is scanned; a power of two


def _bits(tests: list[Column]) -> Column:
    out = F.lit(0)
    for j, t in enumerate(tests):
        out = out.bitwiseOR(F.when(t, F.lit(1 << j)).otherwise(F.lit(0)))
    return out


def spread(df: DataFrame, graph: PropertyGraph, fused: bool) -> DataFrame:
    """df, made of the arcs, as a broadcast where rows are not to be shuffled and the arcs are few enough."""
    return F.broadcast(df) if fused and graph.n_edges <= BROADCAST_EDGES else df


def weight_of(graph: PropertyGraph, vertex: str, weight: str) -> DataFrame:
    """The graph's weights under these names, as a broadcast where they are few enough."""
    out = graph.weights.select(F.col("id").alias(vertex), F.col("weight").alias(weight))
    return F.broadcast(out) if graph.n_weights <= BROADCAST_EDGES else out


def position_bits(cand: DataFrame, size: int, graph: PropertyGraph, strategy: str = "join", fused: bool = False, first: bool = False) -> DataFrame:
    """cand (v0.., u) with the column bits.

    first: cand has h, a position that u is adjacent to; rows with an earlier such position
    are dropped, so that only later positions are left to test."""
    if strategy == "binary":
        out = _binary(cand, size, graph)
        return out.where(F.col("bits").bitwiseAND(F.call_function("shiftleft", F.lit(1), F.col("h")) - 1) == 0) if first else out
    if strategy == "join":
        out = cand
        for j in range(size):
            probe = graph.arcs.select(F.col("src").alias(f"v{j}"), F.col("dst").alias("u"), F.lit(True).alias(f"_b{j}"))
            out = out.join(spread(probe, graph, fused), [f"v{j}", "u"], "left")
        tests, extra = [F.col(f"_b{j}").isNotNull() for j in range(size)], [f"_b{j}" for j in range(size)]
    elif strategy in ("linear", "intersect"):
        near = graph.adjacency().select(F.col("id").alias("u"), F.col("nbrs").alias("_n"))
        parted = fused and strategy == "linear"
        out = cand.join(spread(_parted(near) if parted else near, graph, fused), "u")
        if strategy == "intersect":
            out = out.withColumn("_n", F.array_intersect("_n", F.array(*[f"v{j}" for j in range(size)])))
        ends = [F.col(f"v{j}") for j in range(size)]
        tests, extra = [F.array_contains(F.get("_n", _part(v)) if parted else F.col("_n"), v) for v in ends], ["_n"]
    else:
        raise ValueError(f"unknown strategy {strategy!r}")
    if first:
        for j in range(size - 1):
            out = out.where((F.col("h") <= j) | ~tests[j])
        tests = [F.when(F.col("h") >= j, F.col("h") == j).otherwise(t) for j, t in enumerate(tests)]
    return out.withColumn("bits", _bits(tests)).drop(*extra)


def _part(v: Column) -> Column:
    return v.bitwiseAND(LIST_PARTS - 1).cast("int")


def _parted(near: DataFrame) -> DataFrame:
    """near with each list dealt into LIST_PARTS lists by the low bits of the ids, so that a scan reads one of them."""
    own = lambda p: F.filter("_n", lambda v: _part(v) == p)
    return near.select("u", F.transform(F.sequence(F.lit(0), F.lit(LIST_PARTS - 1)), own).alias("_n"))


def _over(nbrs: Column, floor: Column) -> Column:
    return F.filter(nbrs, lambda u: u > floor)


def met_lists(level: DataFrame, size: int, graph: PropertyGraph, fused: bool = False) -> DataFrame:
    """Canonical children of a level, u and bits: neighbour lists are intersected once a
    parent, which gives all of its children with the same bits together."""
    kept = level.columns
    out = level
    for j in range(size):
        near = graph.adjacency().select(F.col("id").alias(f"v{j}"), F.col("nbrs").alias(f"_n{j}"))
        out = out.join(spread(near, graph, fused), f"v{j}")
    cells = []
    for h in range(size):
        floor = [F.col("v0"), *[F.col(f"v{j}") for j in range(h + 1, size)]]
        floor = F.greatest(*floor) if len(floor) > 1 else floor[0]
        own = _over(F.col(f"_n{h}"), floor)
        if h:
            own = F.array_except(own, F.array(*[f"v{j}" for j in range(h)]))
        for j in range(h):
            own = F.array_except(own, F.col(f"_n{j}"))
        out = out.withColumn(f"_p{h}_{1 << h}", own)
        parts = [1 << h]
        for j in range(h + 1, size):
            for bits in parts:
                whole, near = F.col(f"_p{h}_{bits}"), F.col(f"_n{j}")
                out = out.withColumns({f"_p{h}_{bits | 1 << j}": F.array_intersect(whole, near), f"_p{h}_{bits}": F.array_except(whole, near)})
            parts += [bits | 1 << j for bits in parts]
        cells += [F.struct(F.lit(bits).alias("bits"), F.col(f"_p{h}_{bits}").alias("us")) for bits in parts]
    out = out.select(*kept, F.explode(F.array(*cells)).alias("_c"))
    return out.select(*kept, F.col("_c.bits").alias("bits"), F.explode("_c.us").alias("u"))


def met_counts(level: DataFrame, size: int, graph: PropertyGraph, fused: bool = False) -> DataFrame:
    """mask, bits, n: the weights of the canonical children of a level of a weighted graph, added up.

    As met_lists, but no child becomes a row: entries of the lists hold id and weight, and of
    each set of positions only the weight of those adjacent to all of it is taken; what is
    adjacent to no more than a set follows by inclusion and exclusion, once a mask."""
    if graph.most_weight >= 1 << 32 or graph.most_id >= 1 << 31:
        cand = met_lists(level, size, graph, fused).join(weight_of(graph, "u", "_w"), "u")
        return cand.groupBy("mask", "bits").agg(F.sum(F.col("weight") * F.col("_w")).alias("n"))
    arcs = graph.arcs.join(weight_of(graph, "dst", "_w"), "dst")
    entry = F.shiftleft(F.col("dst").cast("long"), 32).bitwiseOR(F.col("_w"))
    near = arcs.groupBy(F.col("src").alias("id")).agg(F.sort_array(F.collect_list(entry)).alias("nbrs"))
    out = level
    for j in range(size):
        out = out.join(spread(near.select(F.col("id").alias(f"v{j}"), F.col("nbrs").alias(f"_n{j}")), graph, fused), f"v{j}")
    total = lambda us: F.aggregate(us, F.lit(0).cast("long"), lambda n, u: n + u.bitwiseAND((1 << 32) - 1))
    sums, cells = {}, []
    for h in range(size):
        floor = [F.col("v0"), *[F.col(f"v{j}") for j in range(h + 1, size)]]
        floor = F.greatest(*floor) if len(floor) > 1 else floor[0]
        out = out.withColumn("_floor", F.shiftleft(floor.cast("long") + 1, 32))
        own = F.filter(F.col(f"_n{h}"), lambda u: u >= F.col("_floor"))
        for j in range(h):  # that takes out v1 and later ones too: each is a neighbour of an earlier one
            own = F.array_except(own, F.col(f"_n{j}"))
        out = out.withColumn(f"_p{h}_{1 << h}", own)
        parts = [1 << h]
        for j in range(h + 1, size):
            for bits in list(parts):
                out = out.withColumn(f"_p{h}_{bits | 1 << j}", F.array_intersect(f"_p{h}_{bits}", f"_n{j}"))
                parts.append(bits | 1 << j)
        sums |= {f"s{h}_{bits}": F.sum(F.col("weight") * total(F.col(f"_p{h}_{bits}"))) for bits in parts}
        for bits in parts:
            more = [F.col(f"s{h}_{o}") * (-1) ** (o ^ bits).bit_count() for o in parts if o & bits == bits]
            cells.append(F.struct(F.lit(bits).alias("bits"), sum(more, F.lit(0).cast("long")).alias("n")))
    by = out.groupBy("mask").agg(*[s.alias(name) for name, s in sums.items()])
    return by.select("mask", F.explode(F.array(*cells)).alias("_c")).select("mask", "_c.bits", "_c.n").where("n > 0")


PART_ARCS = 1 << 19  # arcs that one task of flat_lists sorts


def flat_lists(graph: PropertyGraph, order: str = "id", upper: bool = False, most: int = BROADCAST_BYTES) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, offsets, neighbours) in flat arrays, for graphs that fit the broadcast bound; else an error.

    Vertices stand by id, or by (degree, id); neighbours are positions in ids (32 bits), in
    order; upper: only those that follow.  Lists are made by tasks, for a range of
    positions each: the driver gets 4 bytes a neighbour and 16 a vertex, and no rows."""
    spark = graph.edges.sparkSession
    ship(spark)
    arrow = graph.degrees.toArrow()
    ids, degree = arrow.column("id").to_numpy(), arrow.column("degree").to_numpy()
    n_arcs = int(degree.sum()) // (2 if upper else 1)
    if n_arcs * 4 + len(ids) * 16 > most:
        raise ValueError(f"{len(ids)} vertices with {n_arcs} neighbours exceed the broadcast bound of {most} bytes; use strategy='join'")
    at = np.argsort(ids)
    ids, degree = ids[at], degree[at]
    place = np.arange(len(ids), dtype=np.int32)
    if order == "degree":
        place[np.lexsort((ids, degree))] = np.arange(len(ids), dtype=np.int32)
    width = -(-len(ids) // max(1, -(-n_arcs // PART_ARCS)))
    named = spark.sparkContext.broadcast((ids, place))

    def number(batches):
        ids, place = named.value
        for batch in batches:
            x, y = (place[np.searchsorted(ids, batch.column(i).to_numpy())] for i in (0, 1))
            x, y = (np.minimum(x, y), np.maximum(x, y)) if upper else (np.concatenate([x, y]), np.concatenate([y, x]))
            yield pa.RecordBatch.from_arrays([pa.array(x // width), pa.array(x), pa.array(y)], ["part", "x", "y"])

    def lists(key, table):
        lo = key[0].as_py() * width
        x, y = table.column("x").to_numpy() - lo, table.column("y").to_numpy()
        size = np.bincount(x, minlength=width).astype(np.int32)
        near = y[np.lexsort((y, x))]
        return pa.table({"part": pa.array([key[0].as_py()], pa.int32()), "size": pa.array([size.tobytes()], pa.binary()), "near": pa.array([near.tobytes()], pa.binary())})

    made = graph.edges.select("src", "dst").mapInArrow(number, "part int, x int, y int").groupBy("part").applyInArrow(lists, "part int, size binary, near binary").toArrow()
    named.unpersist()
    size, pieces = np.zeros(len(ids) + width, np.int64), {}
    for part, own, near in zip(*(made.column(c) for c in ("part", "size", "near"))):
        part = part.as_py()
        size[part * width : (part + 1) * width] = np.frombuffer(own.as_buffer(), np.int32)
        pieces[part] = np.frombuffer(near.as_buffer(), np.int32)
    first = np.append(0, np.cumsum(size[: len(ids)]))
    nbrs = np.empty(int(first[-1]), np.int32)
    for part, near in pieces.items():
        nbrs[first[part * width] : first[part * width] + len(near)] = near
    if order == "degree":
        ids = ids[np.argsort(place)]
    return ids, first, nbrs


def broadcast_csr(graph: PropertyGraph, order: str = "id", upper: bool = False, most: int = BROADCAST_BYTES):
    """flat_lists as a broadcast."""
    return graph.edges.sparkSession.sparkContext.broadcast(flat_lists(graph, order, upper, most))


def arc_keys(first: np.ndarray, nbrs: np.ndarray) -> np.ndarray:
    """Arcs as single numbers in order, so that a probe is one binary search."""
    n = len(first) - 1
    return np.repeat(np.arange(n) * n, np.diff(first)) + nbrs


def _binary(cand: DataFrame, size: int, graph: PropertyGraph) -> DataFrame:
    held = broadcast_csr(graph)
    names = cand.columns
    at_u, at_v = names.index("u"), [names.index(f"v{j}") for j in range(size)]

    def probe(batches):
        ids, *lists = held.value
        keys = arc_keys(*lists)
        for batch in batches:
            u = np.searchsorted(ids, batch.column(at_u).to_numpy())
            bits = np.zeros(batch.num_rows, np.int32)
            for j, col in enumerate(at_v):
                v = np.searchsorted(ids, batch.column(col).to_numpy())
                want = v * len(ids) + u
                at = np.minimum(np.searchsorted(keys, want), max(0, len(keys) - 1))
                bits |= (keys[at] == want).astype(np.int32) << j
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(bits)], names=[*names, "bits"])

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in cand.schema.fields) + ", bits int"
    return cand.mapInArrow(probe, schema)


def is_connected(df: DataFrame, u: str, v: str, graph: PropertyGraph) -> DataFrame:
    """df with the boolean column connected for its vertex columns u and v."""
    probe = graph.arcs.select(F.col("src").alias(u), F.col("dst").alias(v), F.lit(True).alias("_c"))
    return df.join(probe, [u, v], "left").withColumn("connected", F.col("_c").isNotNull()).drop("_c")


def common_neighbours(pairs: DataFrame, graph: PropertyGraph) -> DataFrame:
    """src, dst, n_common of pairs(src, dst)."""
    near = graph.adjacency()
    left, right = near.select(F.col("id").alias("src"), F.col("nbrs").alias("x")), near.select(F.col("id").alias("dst"), F.col("nbrs").alias("y"))
    return pairs.join(left, "src").join(right, "dst").select("src", "dst", F.size(F.array_intersect("x", "y")).cast("long").alias("n_common"))


def fits_broadcast(df: DataFrame, most: int = BROADCAST_BYTES) -> bool:
    return plan_bytes(df) <= most

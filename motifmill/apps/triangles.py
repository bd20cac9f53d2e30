"""Triangle counting and listing."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import PropertyGraph
from ..operators import engine
from ..operators.rules import AppSpec, last_position


def _arrays(graph: PropertyGraph, orient: str) -> DataFrame:
    """Oriented edges with the out-neighbours of both ends: two joins, no candidate rows."""
    o = graph.orient(orient)
    near = graph.adjacency(o)
    return o.join(near.select(F.col("id").alias("src"), F.col("nbrs").alias("x")), "src").join(near.select(F.col("id").alias("dst"), F.col("nbrs").alias("y")), "dst")


def listing(graph: PropertyGraph, orient: str | None = "degree", method: str = "intersect") -> DataFrame:
    """v0, v1, v2 of every triangle once (v0 < v1 < v2 in the chosen order)."""
    if orient is None:
        level = engine.mine(graph, AppSpec(), 3).levels[3]
        return level.where("mask = 7").select("v0", "v1", "v2")
    if method == "intersect":
        a = _arrays(graph, orient)
        return a.select(F.col("src").alias("v0"), F.col("dst").alias("v1"), F.explode(F.array_intersect("x", "y")).alias("v2"))
    if method == "join":
        o = graph.orient(orient)
        step = o.select(F.col("src").alias("v1"), F.col("dst").alias("v2"))
        close = o.select(F.col("src").alias("v0"), F.col("dst").alias("v2"))
        return o.select(F.col("src").alias("v0"), F.col("dst").alias("v1")).join(step, "v1").join(close, ["v0", "v2"], "left_semi").select("v0", "v1", "v2")
    if method == "engine":
        app = AppSpec(orient=orient, expand=last_position, admit=lambda vids, bits, u: bits == (1 << len(vids)) - 1)
        return engine.mine(graph, app, 3).levels[3].select("v0", "v1", "v2")
    raise ValueError(f"unknown method {method!r}")


def count(graph: PropertyGraph, orient: str | None = "degree", method: str = "intersect") -> DataFrame:
    """One row: triangles."""
    if orient is not None and method == "intersect":
        n = F.sum(F.size(F.array_intersect("x", "y")))
        return _arrays(graph, orient).agg(F.coalesce(n, F.lit(0)).cast("long").alias("triangles"))
    return listing(graph, orient, method).agg(F.count("*").alias("triangles"))


def per_vertex(graph: PropertyGraph) -> DataFrame:
    t = listing(graph)
    return t.select(F.explode(F.array("v0", "v1", "v2")).alias("id")).groupBy("id").agg(F.count("*").alias("triangles"))


def per_edge(graph: PropertyGraph) -> DataFrame:
    """src, dst, triangles of the edges that have any."""
    pair = lambda a, b: F.struct(F.least(a, b).alias("src"), F.greatest(a, b).alias("dst"))
    t = listing(graph)
    return t.select(F.explode(F.array(pair("v0", "v1"), pair("v0", "v2"), pair("v1", "v2"))).alias("e")).groupBy("e.src", "e.dst").agg(F.count("*").alias("triangles"))


def local_coefficient(graph: PropertyGraph) -> DataFrame:
    w = graph.wedges_by_vertex().where("wedges > 0")
    return w.join(per_vertex(graph), "id", "left").select("id", (F.coalesce("triangles", F.lit(0)) / F.col("wedges")).alias("coefficient"))

"""Motif counts from wedges, triangles, cliques and 4-cycles by closed formulas."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..apps import cliques, triangles
from ..graph import PropertyGraph

#: sums of choices outgrow 64 bits on hubs
_WIDE = "decimal(38,0)"


def _choose(n, r: int):
    n = n.cast(_WIDE)
    return (n * (n - 1) / 2 if r == 2 else n * (n - 1) * (n - 2) / 6).cast(_WIDE)


def _sum(expr, name: str):
    return F.coalesce(F.sum(expr), F.lit(0).cast(_WIDE)).cast(_WIDE).alias(name)


def count(graph: PropertyGraph, k: int) -> DataFrame:
    if k == 3:
        return count3(graph)
    if k == 4:
        return count4(graph)
    raise ValueError("formulas cover 3 and 4 vertices, counting only")


def _rows(values: DataFrame, named: dict) -> DataFrame:
    cells = F.array(*[F.struct(F.lit(p).alias("pattern"), e.cast("long").alias("n")) for p, e in named.items()])
    return values.select(F.explode(cells).alias("r")).select("r.pattern", "r.n")


def count3(graph: PropertyGraph) -> DataFrame:
    d = graph.degrees.agg(_sum(_choose(F.col("degree"), 2), "w"))
    t = triangles.count(graph).select(F.col("triangles").cast(_WIDE).alias("t"))
    both = d.crossJoin(t)  # one row each
    return _rows(both, {"wedge": F.col("w") - 3 * F.col("t"), "triangle": F.col("t")})


def count4(graph: PropertyGraph) -> DataFrame:
    deg = graph.degrees
    te, tv = triangles.per_edge(graph), triangles.per_vertex(graph)
    one = deg.agg(_sum(_choose(F.col("degree"), 3), "s3"))
    ends = graph.edges.join(deg.select(F.col("id").alias("src"), F.col("degree").alias("a")), "src").join(deg.select(F.col("id").alias("dst"), F.col("degree").alias("b")), "dst")
    one = one.crossJoin(ends.agg(_sum(((F.col("a") - 1) * (F.col("b") - 1)).cast(_WIDE), "pe")))
    one = one.crossJoin(te.agg(_sum(_choose(F.col("triangles"), 2), "de"), _sum(F.col("triangles").cast(_WIDE), "t3")))
    one = one.crossJoin(tv.join(deg, "id").agg(_sum((F.col("triangles") * (F.col("degree") - 2)).cast(_WIDE), "pv")))
    # every wedge once, grouped by its two ends
    a = graph.arcs
    ends2 = a.select("src", F.col("dst").alias("x")).join(a.select("src", F.col("dst").alias("y")), "src").where("x < y").groupBy("x", "y").agg(F.count("*").alias("c"))
    one = one.crossJoin(ends2.agg(_sum(_choose(F.col("c"), 2), "cc")))
    one = one.crossJoin(cliques.count(graph, 4).select(F.col("cliques").cast(_WIDE).alias("k4")))
    c = F.col
    one = one.withColumn("t", c("t3") / 3).withColumn("d", c("de") - 6 * c("k4"))
    one = one.withColumn("q", c("cc") / 2 - c("d") - 3 * c("k4")).withColumn("p", c("pv") - 4 * c("d") - 12 * c("k4"))
    return _rows(one, {
        "4-clique": c("k4"), "diamond": c("d"), "4-cycle": c("q"), "tailed-triangle": c("p"),
        "3-star": c("s3") - c("p") - 2 * c("d") - 4 * c("k4"),
        "4-path": c("pe") - 3 * c("t") - 2 * c("p") - 4 * c("q") - 6 * c("d") - 12 * c("k4"),
    })

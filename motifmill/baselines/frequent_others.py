"""Frequent subgraphs the way the comparison systems mine them, as independent cross-checks.

Each takes (graph, max_edges, sigma) and gives n_edges, pattern, support like
apps.frequent.mine; patterns of up to 3 edges have its names, larger ones their code.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..apps import frequent
from ..functions import patterns
from ..graph import PropertyGraph
from ..operators import connect, engine, support
from ..operators.rules import AppSpec
from ..session import cut, ship
from . import others

#: positions of a bitmap (as Spark's bitmaps have), and bitmaps that a task holds before it sends them
BLOCK, BLOCKS_HELD = 8 * 4096, 1 << 14


def _named(found: DataFrame) -> DataFrame:
    """Codes of small patterns as the shape names of frequent.mine; found has one row a pattern."""

    def rename(frames):
        for f in frames:
            parsed = [patterns.of_code(c) for c in f["pattern"]]
            f["pattern"] = [frequent.shape_name(m, ls) if bin(m).count("1") <= 3 else c for (m, ls), c in zip(parsed, f["pattern"])]
            yield f

    return found.mapInPandas(rename, found.schema)


def _frequent(levels: list[tuple[int, DataFrame]], sigma: int) -> DataFrame:
    """Minimum-image supports of (edges, domains) pairs, filtered once at the end."""
    out = None
    for n, domains in levels:
        part = support.mni(domains).where(F.col("support") >= sigma).select(F.lit(n).alias("n_edges"), "pattern", "support")
        out = part if out is None else out.unionByName(part)
    return _named(out)


# -- distributed filter-process framework ----------------------------------


def filter_process_frequent(graph: PropertyGraph, max_edges: int, sigma: int) -> DataFrame:
    """Candidates are written before they are filtered, and every embedding is classified by
    a canonical search of its own; what is infrequent is filtered before the next level."""
    ship(graph.edges.sparkSession)
    app = AppSpec(mode="edge", materialize_candidates=True)

    def classify(frames):
        for f in frames:
            found = [patterns.canonical_labelled(int(m), [int(x) for x in ls]) for m, ls in zip(f["mask"], f["labels"])]
            f["pattern"], f["orbits"] = [x[0] for x in found], [x[1] for x in found]
            yield f

    level, out = engine.seed(graph, app), None
    for n in range(1, max_edges + 1):
        if n > 1:
            level = engine.grow_edges(level, graph, app)
        schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in level.schema.fields)
        # the edges travel as text: a pandas column of arrays of structs would lose their type
        flat = level.withColumn("edges", F.to_json("edges"))
        kept = flat.mapInPandas(classify, ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in flat.schema.fields) + ", pattern string, orbits array<int>")
        edge_type = dict(level.dtypes)["edges"]
        level = cut(kept.withColumn("edges", F.from_json("edges", edge_type)).select(*[c.split(" ")[0] for c in schema.split(", ") if c.split(" ")[0] in level.columns], "pattern", "orbits"))
        found = cut(support.mni(frequent.orbit_rows(level)).where(F.col("support") >= sigma))
        part = found.select(F.lit(n).alias("n_edges"), "pattern", "support")
        out = part if out is None else out.unionByName(part)
        level = cut(level.join(F.broadcast(found.select("pattern")), "pattern", "left_semi").drop("pattern", "orbits"))
    return _named(out)


# -- relational out-of-core framework --------------------------------------


def relational_frequent(graph: PropertyGraph, max_edges: int, sigma: int, partitions: int = 20) -> DataFrame:
    """Edge sets grow by self joins; the sets that are made more than once are removed by a
    shuffle, intermediates rest on disk, supports are compared with sigma at the end only."""
    e = graph.labelled_edges()
    edge = F.struct(F.col("src").alias("lo"), F.col("dst").alias("hi"), F.col("la").alias("ll"), F.col("lb").alias("lh"))
    edges = e.select(edge.alias("edge"))
    ends = edges.select(F.explode(F.array("edge.lo", "edge.hi")).alias("x"), "edge")
    level, levels = edges.select(F.array("edge").alias("edges")), []
    for n in range(1, max_edges + 1):
        if n > 1:
            own = level.select("edges", F.explode(F.array_distinct(F.flatten(F.transform("edges", lambda d: F.array(d["lo"], d["hi"]))))).alias("x"))
            grown = own.join(ends, "x").where(~F.array_contains("edges", F.col("edge"))).select(F.array_sort(F.array_append("edges", F.col("edge"))).alias("edges"))
            level = grown.repartition(partitions, "edges").distinct().persist(StorageLevel.DISK_ONLY)
        points = F.array_sort(F.array_distinct(F.flatten(F.transform("edges", lambda d: F.array(F.struct(d["lo"].alias("v"), d["ll"].alias("l")), F.struct(d["hi"].alias("v"), d["lh"].alias("l")))))))
        rows = level.withColumn("points", points)
        rows = rows.withColumns({"vids": F.transform("points", lambda p: p["v"]), "labels": F.transform("points", lambda p: p["l"])})
        place = lambda v: F.array_position("vids", v).cast("int") - 1
        bit = lambda d: F.expr("1L") * F.pow(F.lit(2), place(d["hi"]) * (place(d["hi"]) - 1) / 2 + place(d["lo"])).cast("long")
        rows = rows.withColumn("mask", F.aggregate(F.transform("edges", bit), F.lit(0).cast("long"), lambda a, b: a + b).cast("int"))
        levels.append((n, frequent.domains_generic(rows.select("vids", "labels", "mask"))))
    return _frequent(levels, sigma)


# -- depth-first framework -------------------------------------------------


def dfs_frequent(graph: PropertyGraph, max_edges: int, sigma: int) -> DataFrame:
    """Each connected edge set once, from its least edge, by exclusive extension over a
    broadcast adjacency (small graphs: size is checked); nothing is dropped between sizes.

    The edges that complete a set are taken by their end and label.  A task sends a domain
    as bitmaps over blocks of vertex positions, those it holds whenever they are many."""
    spark = graph.edges.sparkSession
    ids, first, nbrs = connect.flat_lists(graph)
    lab = np.zeros(len(ids), np.int32)
    if graph.labels is not None:
        known = graph.labels.select("id", "label").join(graph.degrees.select("id"), "id", "left_semi").toArrow()
        if len(known) < len(ids):
            raise ValueError(f"{len(ids) - len(known)} vertices have no label")
        lab[np.searchsorted(ids, known.column("id").to_numpy())] = known.column("label").to_numpy()
    held = spark.sparkContext.broadcast((ids, first, nbrs, lab))

    def walk(frames):
        ids, first, nbrs, lab = held.value
        near = others.near_sets(first, nbrs)
        lab, codes = lab.tolist(), {}
        out: dict[tuple[int, str, int, int], bytearray] = {}

        def put(n, code, orbit, vids):
            for v in vids:
                at = n, code, orbit, v // BLOCK
                own = out.get(at)
                if own is None:
                    own = out[at] = bytearray(BLOCK // 8)
                v %= BLOCK
                own[v >> 3] |= 1 << (v & 7)

        def sent():
            rows = pd.DataFrame([(*at, bytes(own)) for at, own in out.items()], columns=["n", "pattern", "orbit", "block", "bits"])
            out.clear()
            return rows.astype({"n": "int32", "orbit": "int32", "block": "int64"})

        def code_of(mask, labels):
            found = codes.get((mask, labels))
            if found is None:
                found = codes[mask, labels] = patterns.canonical_labelled(mask, list(labels))
            return found

        def touching(edge):
            a, b = edge
            return {(v, x) if v < x else (x, v) for v in edge for x in near(v)} - {(a, b)}

        def parts_of(own):
            at = {v: i for i, v in enumerate(dict.fromkeys(v for e in own for v in e))}
            return at, sum(1 << patterns.offset(max(at[a], at[b])) + min(at[a], at[b]) for a, b in own), tuple(lab[v] for v in at)

        def emit(own):
            at, mask, labels = parts_of(own)
            code, orbit = code_of(mask, labels)
            for o, v in zip(orbit, at):
                put(len(own), code, o, (v,))

        def complete(own, ext):
            at, mask, labels = parts_of(own)
            new: dict[tuple[int, int], list[int]] = {}
            for a, b in ext:
                if a in at and b in at:
                    emit([*own, (a, b)])
                elif a in at:
                    new.setdefault((at[a], lab[b]), []).append(b)
                else:
                    new.setdefault((at[b], lab[a]), []).append(a)
            for (i, label), vids in new.items():
                code, orbit = code_of(mask | 1 << patterns.offset(len(at)) + i, (*labels, label))
                for o, v in zip(orbit, at):
                    put(max_edges, code, o, (v,))
                put(max_edges, code, orbit[-1], vids)

        def extend(own, ext, seen, root):
            emit(own)
            if len(own) >= max_edges - 1:
                return complete(own, ext)
            ext = sorted(ext)
            while ext:
                e = ext.pop()
                fresh = {x for x in touching(e) if x > root and x not in seen}
                extend([*own, e], [*ext, *fresh], seen | fresh, root)

        for f in frames:
            for root in zip(np.searchsorted(ids, f["src"]).tolist(), np.searchsorted(ids, f["dst"]).tolist()):
                if max_edges == 1:
                    emit([root])
                else:
                    start = {x for x in touching(root) if x > root}
                    extend([root], start, start | {root}, root)
                if len(out) > BLOCKS_HELD:
                    yield sent()
        yield sent()

    # seeds by range: the vertices around a task's edges are then fewer, and with them its bitmaps
    seeds = graph.edges.repartitionByRange(32, "src", "dst")
    rows = cut(seeds.mapInPandas(walk, "n int, pattern string, orbit int, block long, bits binary").groupBy("n", "pattern", "orbit", "block").agg(F.bitmap_or_agg("bits").alias("bits")))
    least = rows.groupBy("n", "pattern", "orbit").agg(F.sum(F.bitmap_count("bits")).alias("size")).groupBy("n", "pattern").agg(F.min("size").alias("support"))
    return _named(least.where(F.col("support") >= sigma).select(F.col("n").alias("n_edges"), "pattern", "support"))


# -- compiled counter ------------------------------------------------------

#: join orders of the small shapes: edges over positions, and the positions in the order of the name
SHAPES = {
    1: {"edge": ([(0, 1)], [0, 1])}, 2: {"wedge": ([(0, 1), (1, 2)], [1, 0, 2])},
    3: {"triangle": ([(0, 1), (1, 2), (0, 2)], [0, 1, 2]), "3-star": ([(0, 1), (0, 2), (0, 3)], [0, 1, 2, 3]), "3-path": ([(0, 1), (1, 2), (2, 3)], [0, 1, 2, 3])},
}


def compiled_frequency(graph: PropertyGraph, max_edges: int, sigma: int) -> DataFrame:
    """Embeddings of every labelled pattern: ordered matches of its shape, divided by the
    shape's automorphisms; shapes share their joins, and a pattern is kept by its count alone."""
    lab = graph.vertex_labels()
    done, out = {}, None
    for n in range(1, max_edges + 1):
        for name, (edges, order) in SHAPES[n].items():
            k = 1 + max(max(e) for e in edges)
            level = others.matches_of(graph, edges, shared=done)
            for v in range(k):
                level = level.join(lab.select(F.col("id").alias(f"v{v}"), F.col("label").alias(f"l{v}")), f"v{v}")
            word = [F.col(f"l{v}") for v in order]
            if name in ("edge", "triangle"):
                own = F.array_sort(F.array(*word))
            elif name == "3-path":
                own = F.least(F.array(*word), F.array(*word[::-1]))
            else:
                own = F.concat(F.array(word[0]), F.array_sort(F.array(*word[1:])))
            part = level.groupBy(F.concat(F.lit(name + ":"), F.concat_ws("-", own.cast("array<string>"))).alias("pattern")).agg(F.expr(f"count(*) div {others.automorphisms_of(edges)}").alias("support"))
            part = part.where(F.col("support") >= sigma).select(F.lit(n).alias("n_edges"), "pattern", "support")
            out = part if out is None else out.unionByName(part)
    return out

"""The comparison systems' ways to the same answers, as independent cross-checks."""

from __future__ import annotations

import math
from functools import reduce
from itertools import combinations_with_replacement, permutations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..apps import frequent, motifs
from ..functions import patterns
from ..graph import PropertyGraph
from ..operators import connect, dense, engine, levels, shared
from ..operators.rules import AppSpec
from ..session import cut, ship


# -- distributed filter-process framework ----------------------------------


def filter_process_motifs(graph: PropertyGraph, k: int) -> DataFrame:
    """Hooks locked: all vertices grow, candidates are written, and each embedding is
    classified by canonical search."""
    return motifs.count(graph, k, how="generic", method="engine", materialize_candidates=True)


def filter_process_cliques(graph: PropertyGraph, k: int) -> DataFrame:
    full = lambda vids, bits, u: (bits == (1 << len(vids)) - 1) & (u > vids[-1])
    app = AppSpec(admit=full, materialize_candidates=True)
    return engine.mine(graph, app, k).levels[k].agg(F.count("*").alias("cliques"))


def overapproximation(graph: PropertyGraph, k: int = 3) -> DataFrame:
    """rows of the level, rows that its compressed pair store expands to."""
    level = motifs.listing(graph, k).select(*[f"v{j}" for j in range(k)])
    level = cut(level)
    grown = levels.expand_overapprox(levels.overapprox_store(level, k))
    return level.agg(F.count("*").alias("stored")).crossJoin(grown.agg(F.count("*").alias("expanded")))  # one row each


# -- relational out-of-core framework --------------------------------------


def relational_cliques(graph: PropertyGraph, k: int, partitions: int = 20) -> DataFrame:
    """Edge-by-edge self joins on disk-resident intermediates, filtered at the end of each vertex."""
    e = graph.edges
    level = e.select(F.col("src").alias("v0"), F.col("dst").alias("v1"))
    for size in range(2, k):
        level = level.join(e.select(F.col("src").alias(f"v{size - 1}"), F.col("dst").alias(f"v{size}")), f"v{size - 1}").repartition(partitions, f"v{size}").persist(StorageLevel.DISK_ONLY)
        for j in range(size - 1):
            level = level.join(e.select(F.col("src").alias(f"v{j}"), F.col("dst").alias(f"v{size}")), [f"v{j}", f"v{size}"])
    return level.agg(F.count("*").alias("cliques"))


def relational_motifs(graph: PropertyGraph, k: int, partitions: int = 20) -> DataFrame:
    """Edge-induced growth of vertex sets without canonical order: duplicates are removed
    after the join, and sets are turned into induced subgraphs at the end."""
    level = graph.edges.select(F.array("src", "dst").alias("s"))
    for _ in range(2, k):
        step = level.select("s", F.explode("s").alias("src")).join(graph.arcs, "src").where(~F.array_contains("s", F.col("dst")))
        level = step.select(F.array_sort(F.array_append("s", F.col("dst"))).alias("s")).repartition(partitions, "s").distinct().persist(StorageLevel.DISK_ONLY)
    pairs = [F.struct(F.lit(1 << b).alias("bit"), F.col("s")[i].alias("src"), F.col("s")[j].alias("dst")) for b, (i, j) in enumerate(patterns.pairs(k))]
    bits = level.select("s", F.explode(F.array(*pairs)).alias("p")).select("s", "p.*").join(graph.edges, ["src", "dst"])
    masks = bits.groupBy("s").agg(F.sum("bit").cast("int").alias("mask"))
    found = motifs.classify(masks.groupBy("mask").agg(F.count("*").alias("n")), k).groupBy("pattern").agg(F.sum("n").alias("n"))
    names = graph.edges.sparkSession.createDataFrame([(x,) for x in patterns.pattern_names(k)], "pattern string")
    return names.join(found, "pattern", "left").select("pattern", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


# -- depth-first framework -------------------------------------------------


NEAR_HELD = 1 << 21  # neighbours that a task of a depth-first baseline keeps as sets


def near_sets(first, nbrs, most: int = NEAR_HELD):
    """Position -> set of its neighbours; sets are made when asked for, and of what is kept
    all is forgotten at a bound."""
    made: dict[int, set[int]] = {}
    held = 0

    def near(v: int) -> set[int]:
        nonlocal held
        if v not in made:
            found = nbrs[first[v] : first[v + 1]].tolist()
            held += len(found)
            if held > most:
                made.clear()
                held = len(found)
            made[v] = set(found)
        return made[v]

    return near


def dfs_cliques(graph: PropertyGraph, k: int) -> DataFrame:
    """Recursion per seed edge over a broadcast adjacency (small graphs: size is checked).
    Only neighbours that follow are broadcast: a clique is met in the order of its vertices."""
    held = connect.broadcast_csr(graph, upper=True)

    def walk(frames):
        ids, *lists = held.value
        near = near_sets(*lists)

        def extend(cand, size):
            if size == k:
                return len(cand)
            return sum(extend(cand & near(u), size + 1) for u in cand)

        for f in frames:
            n = 0
            for a, b in zip(np.searchsorted(ids, f["src"]).tolist(), np.searchsorted(ids, f["dst"]).tolist()):
                n += extend(near(a) & near(b), 3)
            yield pd.DataFrame({"n": [n]})

    return graph.edges.repartition(32, "src", "dst").mapInPandas(walk, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("cliques"))


def dfs_motifs(graph: PropertyGraph, k: int) -> DataFrame:
    """Each connected set once, by exclusive-neighbourhood extension from its least vertex;
    the vertices that complete a set are split by adjacency and only counted.  Of large dense
    graphs the extension set of a root and a second vertex is rows of bits, completed together."""
    if k == 4 and dense.fits(graph):
        return motifs.every_pattern(motifs.classify(dense.connected_fours(graph, down=True), k).groupBy("pattern").agg(F.sum("n").alias("n")), k)
    held = connect.broadcast_csr(graph)

    def walk(frames):
        ids, *lists = held.value
        near = near_sets(*lists)
        bits = patterns.pairs(k - 1)
        tally: dict[int, int] = {}

        def complete(own, ext):
            parts = {sum(1 << b for b, (i, j) in enumerate(bits) if own[i] in near(own[j])): ext}
            for j, v in enumerate(own):
                bit, by = 1 << patterns.offset(k - 1) + j, near(v)
                parts = {m: x for mask, part in parts.items() for m, x in ((mask | bit, part & by), (mask, part - by)) if x}
            for mask, part in parts.items():
                tally[mask] = tally.get(mask, 0) + len(part)

        def extend(own, ext, seen, root):
            if len(own) == k - 1:
                return complete(own, ext)
            left = set(ext)
            for u in sorted(ext, reverse=True):
                left.discard(u)
                fresh = {x for x in near(u) if x > root and x not in seen}
                extend([*own, u], left | fresh, seen | fresh, root)

        for f in frames:
            tally.clear()
            for v in np.searchsorted(ids, f["id"]).tolist():
                start = {x for x in near(v) if x > v}
                extend([v], start, start | {v}, v)
            yield pd.DataFrame({"mask": list(tally), "n": list(tally.values())}).astype({"mask": "int32", "n": "int64"})

    masks = graph.degrees.select("id").repartition(32, "id").mapInPandas(walk, "mask int, n long").groupBy("mask").agg(F.sum("n").alias("n"))
    found = motifs.classify(masks, k).groupBy("pattern").agg(F.sum("n").alias("n"))
    names = graph.edges.sparkSession.createDataFrame([(x,) for x in patterns.pattern_names(k)], "pattern string")
    return names.join(found, "pattern", "left").select("pattern", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


# -- hand-written triangle counter -------------------------------------------


def hand_triangles(graph: PropertyGraph, chunk: int = 1 << 20) -> DataFrame:
    """Ordered adjacency in flat arrays, broadcast behind a check of its size; a task takes
    edges and closes the wedges above them by a hash-free probe of sorted arc numbers."""
    spark = graph.edges.sparkSession
    lists = connect.flat_lists(graph, "degree", upper=True)[1:]
    held, n_arcs = spark.sparkContext.broadcast(lists), len(lists[1])

    def close(batches):
        begin, out = held.value
        arcs, n = connect.arc_keys(begin, out), len(begin) - 1
        owner = arcs // max(n, 1)
        for batch in batches:
            at = batch.column(0).to_numpy()
            at = np.concatenate([np.arange(x * chunk, min((x + 1) * chunk, len(out))) for x in at.tolist()])
            total = 0
            for lo in range(0, len(at), 1 << 14):
                own = at[lo : lo + (1 << 14)]
                # the wedge (a; b, c): c runs over what follows b in a's list
                left = begin[owner[own] + 1] - own - 1
                ends = np.cumsum(left)
                third = np.arange(ends[-1]) - np.repeat(ends - left, left) + np.repeat(own + 1, left)
                want = np.repeat(out[own].astype(np.int64) * n, left) + out[third]
                place = np.minimum(np.searchsorted(arcs, want), len(arcs) - 1)
                total += int((arcs[place] == want).sum())
            yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], ["n"])

    parts = -(-n_arcs // chunk)
    return spark.range(0, parts, 1, max(1, parts)).mapInArrow(close, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("triangles"))


# -- triangle counters -----------------------------------------------------


def task_triangles(graph: PropertyGraph) -> DataFrame:
    """A task per vertex pulls the out-lists of its out-neighbours."""
    o = graph.orient("degree")
    near = graph.adjacency(o)
    pulled = o.join(near.select(F.col("id").alias("dst"), "nbrs"), "dst")

    def task(key, frame):
        own = np.sort(frame["dst"].to_numpy())
        # a pulled vertex without out-neighbours is absent from the join, so own needs the full list
        full = np.sort(np.asarray(frame["mine"].iloc[0]))
        n = sum(len(np.intersect1d(full, np.asarray(x), assume_unique=True)) for x in frame["nbrs"])
        return pd.DataFrame({"n": [n if len(own) else 0]})

    both = pulled.join(near.select(F.col("id").alias("src"), F.col("nbrs").alias("mine")), "src")
    return both.groupBy("src").applyInPandas(task, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("triangles"))


def colours_for(edges: int, budget: int) -> int:
    """Colours c so that a part, which holds the edges among three colours (9 in c * c), has
    about `budget` edges at most."""
    return max(3, math.ceil(3 * math.sqrt(edges / budget)))


def coloured_triangles(graph: PropertyGraph, colours: int | None = None, budget: int = 50_000) -> DataFrame:
    """Vertices get hashed colours, as many as keep a part within a budget of edges; each multiset of three colours is a partition that
    holds the edges among its colours and counts the triangles of exactly these colours."""
    colours = colours or colours_for(graph.edges.count(), budget)
    c = lambda v: F.pmod(F.xxhash64(v), F.lit(colours)).cast("int")
    triples = [list(t) for t in combinations_with_replacement(range(colours), 3)]
    e = graph.edges.select("src", "dst", c("src").alias("a"), c("dst").alias("b"))
    table = graph.edges.sparkSession.createDataFrame(
        [(x, y, i) for i, t in enumerate(triples) for x in range(colours) for y in range(colours) if _inside((x, y), t)], "a int, b int, part int"
    )

    def local(key, frame):
        t = sorted(triples[int(key[0])])
        colour = dict(zip(frame["src"], frame["a"])) | dict(zip(frame["dst"], frame["b"]))
        out: dict[int, set[int]] = {}
        for x, y in zip(frame["src"].tolist(), frame["dst"].tolist()):
            out.setdefault(x, set()).add(y)
        n = 0
        for x, near in out.items():
            for y in near:
                n += sum(sorted((colour[x], colour[y], colour[z])) == t for z in near & out.get(y, set()))
        return pd.DataFrame({"n": [n]})

    return e.join(F.broadcast(table), ["a", "b"]).groupBy("part").applyInPandas(local, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("triangles"))


def _inside(pair, triple) -> bool:
    left = list(triple)
    for x in pair:
        if x not in left:
            return False
        left.remove(x)
    return True


# -- local-graph clique lister ---------------------------------------------


def local_graph_cliques(graph: PropertyGraph, k: int) -> DataFrame:
    """A vertex's out-neighbours and the edges among them form a local graph, which shrinks
    along the recursion.  Local edges are cut out of the out-lists inside generated code;
    only neighbours that have local edges, with their local lists, go to Python."""
    ship(graph.edges.sparkSession)
    o = graph.orient("degree")
    near = cut(graph.adjacency(o))
    left = near.where(F.size("nbrs") >= k - 1).select(F.col("id").alias("src"), F.col("nbrs").alias("own"))
    right = near.select(F.col("id").alias("x"), F.col("nbrs").alias("other"))
    ego = o.select("src", F.col("dst").alias("x")).join(left, "src").join(right, "x").select("src", "x", F.array_intersect("own", "other").alias("common"))
    local = ego.where(F.size("common") > 0).groupBy("src").agg(F.collect_list(F.struct("x", "common")).alias("g")).select("g")

    def recurse(batches):
        def grow(cand, out, size):
            if size == 1:
                return len(cand)
            return sum(grow(cand & near, out, size - 1) for near in map(out.get, cand) if near)

        for batch in batches:
            total = 0
            for g in batch.column(0).to_pylist():
                out = {e["x"]: set(e["common"]) for e in g}
                total += sum(grow(c, out, k - 2) for c in out.values() if len(c) >= k - 2)
            yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], ["n"])

    return local.mapInArrow(recurse, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("cliques"))


def local_graph_triangles(rows: DataFrame, **bounds) -> DataFrame:
    """local_graph_cliques(graph, 3) of the graph of rows k, n, dense ones without its edges: a
    group is some vertices, whose local graphs are bits."""
    return shared.triangles(rows, lambda e: local_graph_cliques(PropertyGraph.of(e), 3), "cliques", apply=True, **bounds)


# -- compiled counter ------------------------------------------------------

#: Pattern edges by name, over positions in join order.
COMPILED = {
    "wedge": [(0, 1), (1, 2)], "triangle": [(0, 1), (1, 2), (0, 2)], "4-cycle": [(0, 1), (1, 2), (2, 3), (0, 3)],
    "4-clique": [(0, 1), (0, 2), (0, 3), (1, 2), (1, 3), (2, 3)], "5-clique": [(i, j) for j in range(5) for i in range(j)],
    "diamond": [(0, 1), (0, 2), (1, 2), (1, 3), (2, 3)], "tailed-triangle": [(0, 1), (0, 2), (1, 2), (0, 3)],
    "3-star": [(0, 1), (0, 2), (0, 3)], "4-path": [(0, 1), (1, 2), (2, 3)],
}


def automorphisms_of(edges: list[tuple[int, int]]) -> int:
    on, k = {frozenset(e) for e in edges}, 1 + max(max(e) for e in edges)
    return sum(all(frozenset(p[i] for i in e) in on for e in on) for p in permutations(range(k)))


def matches_of(graph: PropertyGraph, edges: list[tuple[int, int]], induced: bool = False, shared: dict | None = None) -> DataFrame:
    """All ordered matches of a pattern, no symmetry test while extending.

    shared: joins that patterns have in common, by their edges; what is in it is read, what
    is made here is added (and materialised, as it is there to be read again)."""
    k = 1 + max(max(e) for e in edges)
    level = graph.arcs.select(F.col("src").alias("v0"), F.col("dst").alias("v1"))
    for size in range(2, k):
        part = frozenset(frozenset(e) for e in edges if max(e) <= size)
        if shared is not None and part in shared:
            level = shared[part]
            continue
        back = [i for i in range(size) if (i, size) in edges]
        step = graph.arcs.select(F.col("src").alias(f"v{back[0]}"), F.col("dst").alias(f"v{size}"))
        level = level.join(step, f"v{back[0]}")
        for j in range(size):
            if j not in back:
                level = level.where(F.col(f"v{j}") != F.col(f"v{size}"))
        for j in back[1:]:
            level = level.join(graph.arcs.select(F.col("src").alias(f"v{j}"), F.col("dst").alias(f"v{size}")), [f"v{j}", f"v{size}"], "left_semi")
        if shared is not None and size < k - 1:
            level = shared[part] = cut(level)
    if induced:
        for i, j in patterns.pairs(k):
            if (i, j) not in edges:
                level = level.join(graph.arcs.select(F.col("src").alias(f"v{i}"), F.col("dst").alias(f"v{j}")), [f"v{i}", f"v{j}"], "left_anti")
    return level


def matches(graph: PropertyGraph, pattern: str, induced: bool = False, shared: dict | None = None) -> DataFrame:
    return matches_of(graph, COMPILED[pattern], induced, shared)


def compiled_count(graph: PropertyGraph, pattern: str, induced: bool = False, shared: dict | None = None) -> DataFrame:
    """pattern, n: ordered matches divided by the automorphisms of the pattern."""
    found = matches(graph, pattern, induced, shared)
    return found.agg(F.expr(f"count(*) div {automorphisms_of(COMPILED[pattern])}").alias("n")).select(F.lit(pattern).alias("pattern"), "n")


def compiled_motifs(graph: PropertyGraph, names: tuple[str, ...]) -> DataFrame:
    """Induced counts of several patterns, whose common joins are done once."""
    shared: dict = {}
    return reduce(DataFrame.unionByName, [compiled_count(graph, p, True, shared) for p in names])


# -- recursive frequent-subgraph miner --------------------------------------


def _grown(matches: DataFrame, arcs: DataFrame, k: int, mask: int) -> DataFrame:
    """All one-edge extensions of ordered matches: at (position), new label and vertex, or
    the pair bit that an edge closes (then u is null)."""
    vids = [f"v{i}" for i in range(k)]
    out = None
    for i in range(k):
        step = arcs.select(F.col("src").alias(vids[i]), F.col("dst").alias("u"), F.col("ld").alias("lu"))
        new = matches.join(step, vids[i]).select(*vids, "u", F.lit(i).alias("at"), "lu", F.lit(-1).alias("bit"))
        for v in vids:
            new = new.where(F.col("u") != F.col(v))
        out = new if out is None else out.unionByName(new)
    for b, (i, j) in enumerate(patterns.pairs(k)):
        if not mask >> b & 1:
            close = matches.join(arcs.select(F.col("src").alias(vids[i]), F.col("dst").alias(vids[j])), [vids[i], vids[j]], "left_semi")
            out = out.unionByName(close.select(*vids, F.lit(None).cast("long").alias("u"), F.lit(-1).alias("at"), F.lit(None).cast("int").alias("lu"), F.lit(b).alias("bit")))
    return out


def recursive_frequent(graph: PropertyGraph, max_edges: int, sigma: int) -> DataFrame:
    """Depth first, pattern by pattern: a frequent pattern's ordered matches are extended by
    one edge, the extensions' supports are counted over all mappings (so no orbits are
    needed), and each frequent pattern not met before is visited in its turn."""
    e = graph.labelled_edges()
    arcs = cut(e.select("src", "dst", F.col("la").alias("ls"), F.col("lb").alias("ld")).unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("lb").alias("ls"), F.col("la").alias("ld"))))
    met: dict[str, tuple[int, int]] = {}

    def visit(n_edges: int, mask: int, labels: list[int], matches: DataFrame) -> None:
        if n_edges == max_edges:
            return
        k = len(labels)
        grown = _grown(matches, arcs, k, mask)
        counts = grown.groupBy("at", "lu", "bit").agg(*[F.count_distinct(v).alias(v) for v in [*(f"v{i}" for i in range(k)), "u"]])
        for row in counts.collect():  # a row for each extension of one pattern
            domains = [row[f"v{i}"] for i in range(k)] + ([row["u"]] if row["bit"] < 0 else [])
            if min(domains) < sigma:
                continue
            if row["bit"] < 0:
                child, own = mask | 1 << patterns.offset(k) + row["at"], [*labels, row["lu"]]
            else:
                child, own = mask | 1 << row["bit"], labels
            name = frequent.shape_name(child, own)
            if name in met:
                continue
            met[name] = (n_edges + 1, min(domains))
            if n_edges + 1 < max_edges:
                picked = grown.where((F.col("bit") == row["bit"]) & (F.col("at") == row["at"]) & F.col("lu").eqNullSafe(F.lit(row["lu"])))
                names = [F.col(f"v{i}") for i in range(k)] + ([F.col("u").alias(f"v{k}")] if row["bit"] < 0 else [])
                visit(n_edges + 1, child, own, cut(picked.select(*names)))

    roots = arcs.where("ls <= ld").groupBy("ls", "ld").agg(F.count_distinct("src").alias("x"), F.count_distinct("dst").alias("y"))
    for row in roots.orderBy("ls", "ld").collect():  # an alphabet's worth of rows
        if min(row["x"], row["y"]) >= sigma:
            met[frequent.shape_name(1, [row["ls"], row["ld"]])] = (1, min(row["x"], row["y"]))
            visit(1, 1, [row["ls"], row["ld"]], arcs.where((F.col("ls") == row["ls"]) & (F.col("ld") == row["ld"])).select(F.col("src").alias("v0"), F.col("dst").alias("v1")))
    rows = [(n, name, s) for name, (n, s) in met.items()]
    return graph.edges.sparkSession.createDataFrame(rows, "n_edges int, pattern string, support long")

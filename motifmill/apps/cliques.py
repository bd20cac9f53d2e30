"""k-cliques: counting and listing.

Default plan (`carry`): a row keeps the set of vertices that extend it; one join a level
fetches the new vertex's out-neighbours and an intersection narrows the set; the last
level is only the size of the sets.  `engine` runs the same through the level engine.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import PropertyGraph
from ..operators import engine
from ..operators.rules import AppSpec, all_positions, last_position
from ..session import cut


def _carry(graph: PropertyGraph, k: int, orient: str) -> DataFrame:
    """Cliques of k-1 vertices with the set `more` that extends each to k."""
    o = graph.orient(orient)
    near = cut(graph.adjacency(o))
    level = near.select(F.col("id").alias("v0"), F.col("nbrs").alias("more"))
    for size in range(1, k - 1):
        # a vertex of out-degree under what is still missing cannot be in a k-clique
        step = near.where(F.size("nbrs") >= k - 1 - size).select(F.col("id").alias(f"v{size}"), F.col("nbrs").alias("_n"))
        grown = level.where(F.size("more") >= k - size).select(*[f"v{j}" for j in range(size)], "more", F.explode("more").alias(f"v{size}")) if k - size > 1 else level
        level = grown.join(step, f"v{size}").select(*[f"v{j}" for j in range(size + 1)], F.array_intersect("more", "_n").alias("more"))
        level = level.where(F.size("more") >= k - 1 - size)
    return level


def app_for(orient: str | None, eager: bool, connectivity: str = "join") -> AppSpec:
    """The four ways to keep cliques exact: with or without orientation and last-only growth."""
    full = lambda vids, bits: bits == (1 << len(vids)) - 1
    if orient:
        admit = lambda vids, bits, u: full(vids, bits)
        # all-vertices growth over an orientation: out-neighbours of the first vertex that follow the last
        expand = last_position if eager else all_positions
        return AppSpec(orient=orient, expand=expand, admit=admit, connectivity=connectivity)
    admit = lambda vids, bits, u: full(vids, bits) & (u > vids[-1])
    return AppSpec(expand=last_position if eager else all_positions, admit=admit, connectivity=connectivity)


def listing(graph: PropertyGraph, k: int, orient: str | None = "degree", method: str = "carry", eager: bool = True, connectivity: str = "join", materialize_candidates: bool = False) -> DataFrame:
    """v0..v{k-1} of every k-clique once."""
    if k < 2:
        raise ValueError("a clique has at least 2 vertices")
    vids = [f"v{j}" for j in range(k)]
    if k == 2:
        return graph.edges.select(F.col("src").alias("v0"), F.col("dst").alias("v1"))
    if method == "carry":
        level = _carry(graph, k, orient or "id")
        return level.select(*vids[:-1], F.explode("more").alias(vids[-1]))
    app = app_for(orient, eager, connectivity)
    app.materialize_candidates = materialize_candidates
    out = engine.mine(graph, app, k).levels[k].select(*vids)
    if orient and not eager:  # a new vertex may come before earlier ones in the order: one arrangement stays
        ordered = F.sort_array(F.array(*vids))
        out = out.select(ordered.alias("s")).distinct().select(*[F.col("s")[j].alias(v) for j, v in enumerate(vids)])
    return out


def count(graph: PropertyGraph, k: int, **how) -> DataFrame:
    """One row: cliques."""
    if how.get("method", "carry") == "carry" and k >= 3:
        level = _carry(graph, k, how.get("orient") or ("degree" if "orient" not in how else "id"))
        return level.agg(F.coalesce(F.sum(F.size("more")), F.lit(0)).cast("long").alias("cliques"))
    return listing(graph, k, **how).agg(F.count("*").alias("cliques"))

"""Canonical growth: which parent may produce an embedding.

Vertex form: with h the first position adjacent to the new vertex u, u must be greater
than the first vertex and than every vertex after position h.  Edge form: the same over
edges ordered by (lower id, higher id), adjacent meaning a shared end.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def vertex_canonical(vids: list[Column], bits: Column, u: Column) -> Column:
    """bits: adjacency of u to each position."""
    size = len(vids)
    ok = u > vids[0]
    for h in range(size):
        lowest = bits.bitwiseAND((1 << (h + 1)) - 1) == (1 << h)
        later = F.lit(True)
        for v in vids[h + 1 :]:
            later = later & (u > v)
        ok = ok & (~lowest | later)
    for v in vids:
        ok = ok & (u != v)
    return ok


def edge_canonical(edges: Column, lo: Column, hi: Column) -> Column:
    """edges: array of struct(lo, hi) in order of arrival; the new edge is (lo, hi)."""
    new = F.struct(lo.alias("lo"), hi.alias("hi"))
    touches = lambda e: (e["lo"] == lo) | (e["lo"] == hi) | (e["hi"] == lo) | (e["hi"] == hi)
    place = F.array_position(F.transform(edges, lambda e: touches(e)), F.lit(True))
    after = F.slice(edges, place.cast("int") + 1, F.size(edges))
    return (new > edges[0]) & F.forall(after, lambda e: new > e) & ~F.exists(edges, lambda e: e == new)

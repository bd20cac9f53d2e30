"""Frequent labelled subgraphs by minimum-image support.

Edge mode of the level engine.  Patterns of 1-3 edges are classified by expressions over
labels in a canonical order of positions (`custom`); larger ones, or all with plan
`generic`, by canonical search over distinct quick patterns.  A domain is keyed by orbit: positions that an automorphism
exchanges share one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import patterns
from ..graph import PropertyGraph
from ..operators import engine, support
from ..operators.rules import AppSpec
from ..session import cut, ship
from . import triangles


def _by_degree(k: int, n_edges: int) -> dict[int, tuple[str, list[int]]]:
    """mask -> (shape, positions in canonical order) of the tree and triangle shapes."""
    out = {}
    for m in range(1 << patterns.offset(k)):
        if bin(m).count("1") != n_edges or not patterns.connected(m, k):
            continue
        d = patterns.degrees_of(m, k)
        on = {frozenset(p) for b, p in enumerate(patterns.pairs(k)) if m >> b & 1}
        if k == n_edges:
            out[m] = ("triangle", list(range(k)))
        elif max(d) == n_edges:
            centre = d.index(n_edges)
            out[m] = ("edge" if n_edges == 1 else "wedge" if n_edges == 2 else "3-star", [centre, *[i for i in range(k) if i != centre]])
        else:
            walk = [d.index(1)]
            while len(walk) < k:
                walk.append(next(i for i in range(k) if i not in walk and frozenset((walk[-1], i)) in on))
            out[m] = ("3-path", walk)
    return out


def _shapes() -> dict[int, dict[int, tuple[str, list[int]]]]:
    return {2: _by_degree(2, 1), 3: _by_degree(3, 2) | _by_degree(3, 3), 4: _by_degree(4, 3)}


def shape_name(mask: int, labels: list[int]) -> str:
    """Pattern text of local positions with labels, as named() gives it."""
    shape, places = _shapes()[len(labels)][mask]
    word = [labels[p] for p in places]
    if shape in ("edge", "triangle"):
        word.sort()
    elif shape == "3-path":
        word = min(word, word[::-1])
    else:
        word[1:] = sorted(word[1:])
    return f"{shape}:" + "-".join(map(str, word))


def named(level: DataFrame) -> DataFrame:
    """level with shape, own (struct(label, vid) in canonical order) and pattern text.

    Ends of an edge, leaves of a star and corners of a triangle are sorted by label; a
    path is read from the side that gives the smaller word."""
    n = F.size("vids")
    shape, order = F.lit(None).cast("string"), F.lit(None).cast("array<int>")
    for k, table in _shapes().items():
        for m, (s, places) in table.items():
            hit = (n == k) & (F.col("mask") == m)
            shape, order = F.when(hit, F.lit(s)).otherwise(shape), F.when(hit, F.array(*map(F.lit, places))).otherwise(order)
    df = level.withColumns({"shape": shape, "_order": order})
    item = lambda p: F.struct(F.element_at("labels", p + 1).alias("label"), F.element_at("vids", p + 1).alias("vid"))
    df = df.withColumn("own", F.transform("_order", item))
    word = lambda c: F.transform(c, lambda x: x["label"])
    tail = F.array_sort(F.slice("own", 2, 3))
    star = F.concat(F.slice("own", 1, 1), tail)
    back = F.reverse("own")
    own = (
        F.when(F.col("shape").isin("edge", "triangle"), F.array_sort("own")).when(F.col("shape") == "3-path", F.when(word(F.col("own")) <= word(back), F.col("own")).otherwise(back)).otherwise(star)
    )
    df = df.withColumn("own", own)
    return df.withColumn("pattern", F.concat_ws(":", "shape", F.concat_ws("-", F.transform("own", lambda x: x["label"].cast("string"))))).drop("_order")


def domains(df: DataFrame) -> DataFrame:
    """pattern, orbit, vid of named(level)."""
    labels = F.transform("own", lambda x: x["label"])
    n = F.size("own")

    def orbit(i: Column) -> Column:
        flat = F.array_position(labels, F.element_at(labels, i + 1)).cast("int") - 1
        star = F.when(i == 0, F.lit(0)).otherwise(F.array_position(F.slice(labels, 2, 4), F.element_at(labels, i + 1)).cast("int"))
        path = F.when(labels == F.reverse(labels), F.least(i, n - 1 - i)).otherwise(i)
        return F.when(F.col("shape").isin("edge", "triangle"), flat).when(F.col("shape") == "3-path", path).otherwise(star)

    rows = F.transform("own", lambda x, i: F.struct(orbit(i).alias("orbit"), x["vid"].alias("vid")))
    return df.select("pattern", F.explode(rows).alias("d")).select("pattern", "d.orbit", "d.vid")


def named_generic(level: DataFrame) -> DataFrame:
    """level with pattern and orbits, from distinct quick patterns by canonical search in a pandas function."""
    import pandas as pd

    ship(level.sparkSession)
    quick = level.select("mask", "labels").distinct()

    def canonical(frames):
        for f in frames:
            found = [patterns.canonical_labelled(int(m), [int(x) for x in ls]) for m, ls in zip(f["mask"], f["labels"])]
            yield pd.DataFrame({"mask": f["mask"], "labels": f["labels"], "pattern": [x[0] for x in found], "orbits": [x[1] for x in found]})

    table = quick.mapInPandas(canonical, "mask int, labels array<int>, pattern string, orbits array<int>")
    return level.join(cut(table), ["mask", "labels"])


def domains_generic(level: DataFrame) -> DataFrame:
    """pattern, orbit, vid of a level, by named_generic."""
    return orbit_rows(named_generic(level))


def orbit_rows(both: DataFrame) -> DataFrame:
    return both.select("pattern", F.explode(F.arrays_zip("orbits", "vids")).alias("d")).select("pattern", F.col("d.orbits").alias("orbit"), F.col("d.vids").alias("vid"))


# -- shape plans: the same domains by joins per shape, all inside generated code ----------

BITS, MOST_EDGES = 12, 7  # a mask of 8 vertices fits 32 bits
SHAPES = {1: ("edge", 2), 2: ("wedge", 3), 3: ("triangle", 3), 4: ("3-star", 4), 5: ("3-path", 4)}


def _pack(shape: int, *labels: Column) -> Column:
    out = F.lit(shape << 4 * BITS).cast("long")
    for i, x in enumerate(labels):
        out = out + x.cast("long") * (1 << (3 - i) * BITS)
    return out


def _unpack(pid: Column) -> Column:
    part = lambda i: F.shiftright(pid, (3 - i) * BITS).bitwiseAND((1 << BITS) - 1).cast("string")
    name = F.lit(None).cast("string")
    for shape, (text, k) in SHAPES.items():
        name = F.when(F.shiftright(pid, 4 * BITS) == shape, F.concat(F.lit(text + ":"), F.concat_ws("-", *[part(i) for i in range(k)]))).otherwise(name)
    return name


def _below(x: Column, *others: Column) -> Column:
    """How many of others are smaller: the place of x in the sorted labels."""
    return sum(((o < x).cast("int") for o in others), F.lit(0))


def _places(df: DataFrame, pid: Column, *places: tuple[Column, Column]) -> DataFrame:
    rows = F.array(*[F.struct(o.cast("int").alias("orbit"), v.alias("vid")) for o, v in places])
    return df.select(pid.alias("pattern"), F.explode(rows).alias("d")).select("pattern", "d.orbit", "d.vid")


def _kept(df: DataFrame, pid: Column, keep: DataFrame) -> DataFrame:
    return df.withColumn("_pid", pid).join(F.broadcast(keep.select(F.col("pattern").alias("_pid"))), "_pid", "left_semi").drop("_pid")


def _sorted3(a: Column, b: Column, c: Column) -> tuple[Column, Column, Column]:
    low, high = F.least(a, b, c), F.greatest(a, b, c)
    return low, a + b + c - low - high, high


def _mine_shapes(graph: PropertyGraph, max_edges: int, sigma: int, support_of) -> DataFrame:
    e = graph.labelled_edges()
    arcs = e.select("src", "dst", F.col("la").alias("ls"), F.col("lb").alias("ld")).unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.col("lb").alias("ls"), F.col("la").alias("ld")))
    arcs = cut(arcs)
    c = F.col
    edge_id = _pack(1, F.least("ls", "ld"), F.greatest("ls", "ld"))
    found = support_of(_places(arcs, edge_id, (_below(c("ls"), c("ld")), c("src"))))
    keep1 = cut(found.where(c("support") >= sigma))
    out = keep1.withColumn("n_edges", F.lit(1))
    if max_edges > 1:
        arcs = cut(_kept(arcs, edge_id, keep1))
        # wedges and stars need no listing: a domain only asks which labels a centre's neighbours have, and how often
        seen = cut(arcs.groupBy(c("src").alias("c"), c("ls").alias("lc"), c("ld").alias("l")).agg(F.count("*").alias("n")))
        first = arcs.select(c("src").alias("c"), c("ls").alias("lc"), c("dst").alias("a"), c("ld").alias("la"))
        x, y = seen.select("c", "lc", c("l").alias("lx"), c("n").alias("nx")), seen.select("c", c("l").alias("ly"), c("n").alias("ny"))
        pairs = x.join(y, "c").where((c("lx") < c("ly")) | ((c("lx") == c("ly")) & (c("nx") > 1)))
        leaf = first.join(y, "c").where((c("la") != c("ly")) | (c("ny") > 1))
        leaf_id = _pack(2, c("lc"), F.least("la", "ly"), F.greatest("la", "ly"))
        pair_id = _pack(2, c("lc"), c("lx"), c("ly"))
        found = support_of(_places(pairs, pair_id, (F.lit(0), c("c"))).unionByName(_places(leaf, leaf_id, (1 + _below(c("la"), c("ly")), c("a")))))
        keep2 = cut(found.where(c("support") >= sigma))
        out = out.unionByName(keep2.withColumn("n_edges", F.lit(2)))
    if max_edges > 2:
        pairs = cut(_kept(pairs, pair_id, keep2))
        z = seen.select("c", c("l").alias("lz"), c("n").alias("nz"))
        times = lambda own, *others: 1 + sum(((own == o).cast("int") for o in others), F.lit(0))
        triple = pairs.join(z, "c").where((c("ly") <= c("lz")) & (c("ny") >= times(c("ly"), c("lx"), c("lz"))) & (c("nz") >= times(c("lz"), c("lx"), c("ly"))))
        # every wedge inside a star must be frequent for all of its domains alike
        side = lambda a, b: _pack(2, c("lc"), F.least(a, b), F.greatest(a, b))
        triple = _kept(_kept(triple, side("lx", "lz"), keep2), side("ly", "lz"), keep2)
        centres = _places(triple, _pack(4, c("lc"), c("lx"), c("ly"), c("lz")), (F.lit(0), c("c")))
        point = first.drop("lc").join(pairs, "c").where((c("nx") >= times(c("lx"), c("la"), c("ly"))) & (c("ny") >= times(c("ly"), c("la"), c("lx"))))
        point = _kept(_kept(point, side("la", "lx"), keep2), side("la", "ly"), keep2)
        leaves = _places(point, _pack(4, c("lc"), *_sorted3(c("la"), c("lx"), c("ly"))), (1 + _below(c("la"), c("lx"), c("ly")), c("a")))
        stars = centres.unionByName(leaves)
        lab = graph.vertex_labels()
        corner = triangles.listing(PropertyGraph(arcs.where("src < dst").select("src", "dst")))
        for v in ("v0", "v1", "v2"):
            corner = corner.join(lab.select(c("id").alias(v), c("label").alias(f"l{v}")), v)
        tri_id = _pack(3, *_sorted3(c("lv0"), c("lv1"), c("lv2")))
        corners = _places(corner, tri_id, *[(_below(c(f"l{v}"), *[c(f"l{u}") for u in ("v0", "v1", "v2") if u != v]), c(v)) for v in ("v0", "v1", "v2")])
        # a path is its middle edge p < q with an outer neighbour on either side; both wedges must be frequent.
        # Paths are not listed: each side is folded to its labels, with a count and one neighbour, so that what a
        # hub's edge costs grows with its neighbours and labels, not with pairs of neighbours.
        hop = first.join(arcs.select(c("src").alias("c"), c("dst").alias("o"), c("ld").alias("lo")), "c").where("a <> o")
        hop = _kept(hop, _pack(2, c("lc"), F.least("la", "lo"), F.greatest("la", "lo")), keep2)
        left = hop.where("c < a").select(c("c").alias("p"), c("a").alias("q"), c("lc").alias("lp"), c("la").alias("lq"), c("o").alias("x"), c("lo").alias("lx"))
        right = hop.where("c > a").select(c("a").alias("p"), c("c").alias("q"), c("o").alias("y"), c("lo").alias("ly"))
        left, right = cut(left), cut(right)
        lefts = left.groupBy("p", "q", "lp", "lq", "lx").agg(F.count("*").alias("nx"), F.min("x").alias("one_x"))
        rights = right.groupBy("p", "q", "ly").agg(F.count("*").alias("ny"), F.min("y").alias("one_y"))
        middle = lefts.join(rights, ["p", "q"]).where("nx > 1 or ny > 1 or one_x <> one_y")
        outer_x = left.join(rights, ["p", "q"]).where("ny > 1 or one_y <> x")
        outer_y = right.drop("lp", "lq").join(lefts, ["p", "q"]).where("nx > 1 or one_x <> y")
        ahead = (c("lx") < c("ly")) | ((c("lx") == c("ly")) & (c("lp") <= c("lq")))
        mirrored = (c("lx") == c("ly")) & (c("lp") == c("lq"))
        pick = lambda a, b: F.when(ahead, c(a)).otherwise(c(b))
        path_id = _pack(5, pick("lx", "ly"), pick("lp", "lq"), pick("lq", "lp"), pick("ly", "lx"))
        place = lambda i: F.when(mirrored, F.lit(min(i, 3 - i))).otherwise(F.when(ahead, F.lit(i)).otherwise(F.lit(3 - i)))
        paths = _places(middle, path_id, (place(1), c("p")), (place(2), c("q"))).unionByName(_places(outer_x, path_id, (place(0), c("x")))).unionByName(_places(outer_y, path_id, (place(3), c("y"))))
        found = support_of(stars.unionByName(corners).unionByName(paths))
        out = out.unionByName(found.where(c("support") >= sigma).withColumn("n_edges", F.lit(3)))
    return out.select("n_edges", _unpack(c("pattern")).alias("pattern"), "support")


def mine(graph: PropertyGraph, max_edges: int, sigma: int, mode: str = "rows", kind: str = "mni", unsafe: bool = False, plan: str = "shapes") -> DataFrame:
    """n_edges, pattern, support of every frequent pattern of up to max_edges edges.

    plan: `shapes` joins shape by shape (up to 3 edges); `engine` grows edge by edge in the
    level engine; `generic` does so too and classifies by canonical search at every size, as
    the others do past 3 edges.  Patterns of generic search are named by their code.
    mode `early` stops a domain at sigma, which then is the support told.
    Both drop what has an infrequent part before they grow it - except for kind
    `frequency`, which is not anti-monotone: there nothing is dropped unless unsafe=True,
    which loses patterns."""
    if kind not in ("mni", "mni_approx", "frequency"):
        raise ValueError(f"unknown support {kind!r}")
    if not 1 <= max_edges <= MOST_EDGES:
        raise ValueError(f"patterns of 1 to {MOST_EDGES} edges are covered")
    if plan not in ("shapes", "engine", "generic"):
        raise ValueError(f"unknown plan {plan!r}")
    if plan == "shapes" and max_edges <= 3 and kind != "frequency":
        top = graph.vertex_labels().agg(F.min("label").alias("x"), F.max("label").alias("y")).first()
        if top["x"] is not None and (top["x"] < 0 or top["y"] >= 1 << BITS):
            raise ValueError(f"labels outside 0..{(1 << BITS) - 1} need plan='engine'")
        return _mine_shapes(graph, max_edges, sigma, lambda d: _support(d, sigma, mode, kind))
    return _mine_engine(graph, max_edges, sigma, mode, kind, kind != "frequency" or unsafe, plan == "generic")


def _support(domains: DataFrame, sigma: int, mode: str, kind: str) -> DataFrame:
    if mode == "early":
        return support.mni_at_least(domains, sigma)
    return support.mni(domains, "approx" if kind == "mni_approx" else mode)


def _mine_engine(graph: PropertyGraph, max_edges: int, sigma: int, mode: str, kind: str, drop: bool, generic: bool) -> DataFrame:
    app = AppSpec(mode="edge")
    level, out, g = engine.seed(graph, app), None, graph
    for n in range(1, max_edges + 1):
        if n > 1:
            level = engine.grow_edges(level, g, app)
        searched = generic or n > 3
        if searched:
            level = cut(level)
        level = named_generic(level) if searched else named(level)
        if kind == "frequency":
            found = level.groupBy("pattern").agg(F.count("*").alias("support"))
        else:
            if n < max_edges:
                level = cut(level)
            found = _support(orbit_rows(level) if searched else domains(level), sigma, mode, kind)
        keep = cut(found.where(F.col("support") >= sigma))
        part = keep.select(F.lit(n).alias("n_edges"), "pattern", "support")
        out = part if out is None else out.unionByName(part)
        if n < max_edges and not drop:
            level = cut(level.drop("shape", "own", "pattern", "orbits"))
        elif n < max_edges:
            level = cut(level.join(F.broadcast(keep.select("pattern")), "pattern", "left_semi").drop("shape", "own", "pattern", "orbits"))
            if n == 1:  # no frequent pattern has an infrequent edge: grow in what is left
                g = PropertyGraph(cut(level.select(F.col("vids")[0].alias("src"), F.col("vids")[1].alias("dst"))), graph.labels)
    return out

"""k-vertex motifs: induced connected subgraphs by isomorphism class.

Default plan (`carry`): rows keep the neighbour arrays of their vertices - as far as they
are above the first vertex, which no later one is below - so that growth, adjacency bits
and the canonical rule are array functions inside one stage; the last level
is never stored, not even as rows: for each parent the candidates are split by adjacency
and only the sizes of the parts are added up per pattern code.  Of large dense graphs the
parents of three are no rows either, but bits (operators/dense.py); where neighbour lists
are stored, those of an edge's ends meet in blocks (operators/listed.py).
"""

from __future__ import annotations

from functools import reduce
from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import patterns
from ..graph import PropertyGraph
from ..operators import connect, dense, engine, listed, shared
from ..operators.rules import AppSpec
from ..session import cut

CLASSIFIERS = ("custom", "two_step", "memo", "spectrum", "generic")


def classify(level: DataFrame, size: int, how: str = "two_step") -> DataFrame:
    """level with the column pattern, from its mask."""
    spark = level.sparkSession
    if how == "custom":
        rule = {2: lambda m: F.lit("edge"), 3: patterns.classify3, 4: patterns.classify4}.get(size)
        if rule is None:
            raise ValueError("custom classification covers up to 4 vertices")
        return level.withColumn("pattern", rule(F.col("mask")))
    if how in ("two_step", "generic"):
        return level.join(F.broadcast(patterns.dimension_df(spark, size).select("mask", "pattern")), "mask")
    if how == "spectrum":
        return level.join(F.broadcast(patterns.spectrum_df(spark, size)), "mask")
    if how == "memo":
        keep = (1 << patterns.offset(size - 1)) - 1
        pair = level.withColumns({"parent_mask": F.col("mask").bitwiseAND(keep), "bits": F.shiftright("mask", patterns.offset(size - 1))})
        table = patterns.transition_table(spark, size).drop("mask")
        return pair.join(F.broadcast(table), ["parent_mask", "bits"]).drop("parent_mask", "bits")
    raise ValueError(f"unknown classifier {how!r}")


def _candidates(size: int, h: int) -> Column:
    """Vertices that join at position h as the first adjacent one, by the canonical rule."""
    above = [F.col("v0"), *[F.col(f"v{j}") for j in range(h + 1, size)]]
    floor = F.greatest(*above) if len(above) > 1 else above[0]
    new = F.filter(F.col(f"n{h}"), lambda u: u > floor)
    # later vertices are not above the floor; earlier ones may be, and do not join again
    if h:
        new = F.array_except(new, F.array(*[F.col(f"v{j}") for j in range(h)]))
    for j in range(h):
        new = F.array_except(new, F.col(f"n{j}"))
    return new


def _marked(candidates: Column, h: int) -> Column:
    return F.transform(candidates, lambda u: F.struct(F.lit(h).alias("h"), u.alias("u")))


def _seeds(graph: PropertyGraph) -> tuple[DataFrame, DataFrame]:
    near = cut(graph.adjacency())
    first = near.select(F.col("id").alias("v0"), _above(F.col("nbrs"), F.col("id")).alias("n0"))
    level = graph.edges.select(F.col("src").alias("v0"), F.col("dst").alias("v1"), F.lit(1).alias("mask")).join(first, "v0")
    return _joined(level, near, 1), near


def _above(nbrs: Column, v: Column) -> Column:
    return F.filter(nbrs, lambda u: u > v)


def _joined(level: DataFrame, near: DataFrame, j: int) -> DataFrame:
    """level with n{j}: the neighbours of v{j} above v0."""
    level = level.join(near.select(F.col("id").alias(f"v{j}"), F.col("nbrs").alias(f"n{j}")), f"v{j}")
    return level.withColumn(f"n{j}", _above(F.col(f"n{j}"), F.col("v0")))


def _carry_level(graph: PropertyGraph, k: int) -> DataFrame:
    """The level of k vertices with v0.., n0.. and mask."""
    level, near = _seeds(graph)
    for size in range(2, k):
        both = [_marked(_candidates(size, h), h) for h in range(size)]
        grown = level.select("*", F.explode(F.concat(*both)).alias("_c")).select(*level.columns, F.col("_c.h").alias("_h"), F.col("_c.u").alias(f"v{size}"))
        bits = F.call_function("shiftleft", F.lit(1), F.col("_h"))
        for j in range(1, size):
            later = F.when((F.col("_h") < j) & F.array_contains(f"n{j}", F.col(f"v{size}")), F.lit(1 << j)).otherwise(F.lit(0))
            bits = bits.bitwiseOR(later)
        grown = grown.withColumn("mask", F.col("mask").bitwiseOR(F.shiftleft(bits, patterns.offset(size)))).drop("_h")
        level = _joined(grown, near, size)
    return level


def _met(size: int, h: int) -> dict[int, Column]:
    """Numbers of candidates at h that are adjacent to all of a set of later positions."""
    sets = {0: _candidates(size, h)}
    for j in range(h + 1, size):
        sets |= {bits | 1 << j: F.array_intersect(part, F.col(f"n{j}")) for bits, part in sets.items()}
    return {bits: F.size(part) for bits, part in sets.items()}


def _exactly(met: dict[int, str], bits: int) -> Column:
    """Candidates adjacent to these later positions and no others, by inclusion and exclusion."""
    more = [other for other in met if other & bits == bits]
    return sum((F.col(met[o]) * (-1) ** bin(o ^ bits).count("1") for o in more), F.lit(0))


def _count_carry(graph: PropertyGraph, k: int) -> DataFrame:
    """mask, n of the last level, from the sizes of candidate sets."""
    if k == 4 and dense.fits(graph):
        return dense.connected_fours(graph)
    if k == 3 and graph.lists is not None:
        found = listed.connected_threes(graph.lists)
        if found is not None:
            return found
    size = k - 1
    level = _carry_level(graph, size)
    sums, names = [], []
    for h in range(size):
        met = _met(size, h)
        own = {bits: f"h{h}_{bits}" for bits in met}
        sums += [F.sum(n).alias(own[bits]) for bits, n in met.items()]
        names.append((h, own))
    by = level.groupBy("mask").agg(*sums)
    cells = [F.struct(F.lit(1 << h | bits).alias("bits"), _exactly(own, bits).cast("long").alias("n")) for h, own in names for bits in own]
    rows = F.array(*cells)
    flat = by.select("mask", F.explode(rows).alias("r")).select(F.col("mask").bitwiseOR(F.shiftleft(F.col("r.bits"), patterns.offset(size))).alias("mask"), F.col("r.n").alias("n"))
    return flat.groupBy("mask").agg(F.sum("n").alias("n")).where("n > 0")


def _chosen(weight: Column, m: int) -> Column:
    """Ways to take m of a vertex's equal ones."""
    out = weight
    for i in range(1, m):  # exact at every step: a binomial coefficient times i + 1
        out = F.call_function("div", out * (weight - i), F.lit(i + 1))
    return out


def _blown_up(mask: int, taken: tuple[int, ...]) -> int:
    """The mask where taken[i] equal, adjacent vertices stand at position i."""
    at = [i for i, m in enumerate(taken) for _ in range(m)]
    pairs = enumerate(patterns.pairs(len(at)))
    return sum(1 << b for b, (x, y) in pairs if at[x] == at[y] or mask >> patterns.offset(at[y]) + at[x] & 1)


def unfolded(levels: dict[int, DataFrame], graph: PropertyGraph, k: int) -> DataFrame:
    """mask, n of the connected sets of k that the vertices of a weighted graph stand for.

    levels have a column weight, the product of the weights; a connected set of k lies in a
    connected set of vertices, of which it takes one or more equal ones each."""
    spark, weights = graph.edges.sparkSession, graph.weights
    if k in levels:
        parts = [levels[k].groupBy("mask").agg(F.sum("weight").alias("n"))]
    else:  # the last level is counted from its parents
        met = connect.met_counts(levels[k - 1], k - 1, graph, fused=True)
        parts = [met.select(F.col("mask").bitwiseOR(F.shiftleft("bits", patterns.offset(k - 1))).alias("mask"), "n")]
    for size in range(1, k):
        level = levels[size] if size > 1 else weights.select(F.col("id").alias("v0"), F.lit(0).alias("mask"))
        for j in range(size):
            level = level.join(connect.weight_of(graph, f"v{j}", f"w{j}"), f"v{j}")
        takes = [t for t in product(range(1, k), repeat=size) if sum(t) == k] if size > 1 else [(k,)]
        sums = [F.sum(reduce(Column.__mul__, [_chosen(F.col(f"w{j}"), m) for j, m in enumerate(t)])).alias(f"t{i}") for i, t in enumerate(takes)]
        by = level.groupBy("mask").agg(*sums).select("mask", F.posexplode(F.array(*[f"t{i}" for i in range(len(takes))])).alias("t", "n"))
        masks = [m for m in range(1 << patterns.offset(size)) if patterns.connected(m, size)]
        table = spark.createDataFrame([(m, i, _blown_up(m, t)) for m in masks for i, t in enumerate(takes)], "mask int, t int, whole int")
        parts.append(by.join(F.broadcast(table), ["mask", "t"]).select(F.col("whole").alias("mask"), "n"))
    return reduce(DataFrame.unionByName, parts).groupBy("mask").agg(F.sum("n").alias("n")).where("n > 0")


def listing(graph: PropertyGraph, k: int, method: str = "carry", connectivity: str = "join") -> DataFrame:
    """v0..v{k-1}, mask of every connected induced k-set once."""
    vids = [f"v{j}" for j in range(k)]
    if method == "carry":
        return _carry_level(graph, k).select(*vids, "mask")
    return engine.mine(graph, AppSpec(connectivity=connectivity), k).levels[k].select(*vids, "mask")


def count(graph: PropertyGraph, k: int, how: str = "custom", method: str = "carry", connectivity: str = "join", materialize_candidates: bool = False, fused: bool = False) -> DataFrame:
    """pattern, n with a row for every pattern of k vertices, 0 included.

    method: `carry` and `engine` enumerate; `formula` derives counts of 3 and 4 vertices;
    `auto` takes the formula where there is one, as only counts are asked for.  Of a
    weighted graph (shared.fold) `engine` counts the sets that its vertices stand for; fused: see AppSpec."""
    if graph.weights is not None and (method != "engine" or how == "generic"):
        raise ValueError("a weighted graph is counted by method='engine' and a quick classifier")
    if method == "auto":
        method = "formula" if k in (3, 4) else "carry"
    if method == "formula":
        from ..baselines import formula_motifs

        return formula_motifs.count(graph, k)
    if how == "custom" and k > 4:
        how = "two_step"
    if method == "carry":
        quick = _count_carry(graph, k) if k > 2 else graph.edges.agg(F.lit(1).alias("mask"), F.count("*").alias("n"))
        found = classify(quick, k, how).groupBy("pattern").agg(F.sum("n").alias("n"))
    else:
        app = AppSpec(connectivity=connectivity, materialize_candidates=materialize_candidates, fused=fused)
        met = fused and graph.weights is not None and connectivity == "intersect" and k > 2 and not materialize_candidates
        if met and k == 4 and graph.n_edges >= dense.LEAST_EDGES and dense.holds(*shared.unfolded_size(graph)):
            whole = shared.unfold(graph)
            if dense.fits(whole):
                return every_pattern(classify(dense.connected_fours(whole), k, how).groupBy("pattern").agg(F.sum("n").alias("n")), k)
        levels = engine.mine(graph, app, k - 1 if met else k).levels
        level = levels.get(k)
        if how == "generic":  # every embedding is classified by itself
            found = generic_per_row(level, k).groupBy("pattern").agg(F.count("*").alias("n"))
        else:
            quick = level.groupBy("mask").agg(F.count("*").alias("n")) if graph.weights is None else unfolded(levels, graph, k)
            found = classify(quick, k, how).groupBy("pattern").agg(F.sum("n").alias("n"))
    return every_pattern(found, k)


def every_pattern(found: DataFrame, k: int) -> DataFrame:
    """pattern, n with a row for every pattern of k vertices."""
    names = reduce(DataFrame.unionByName, [found.sparkSession.createDataFrame([(x,) for x in patterns.pattern_names(k)], "pattern string")])
    return names.join(found, "pattern", "left").select("pattern", F.coalesce("n", F.lit(0)).cast("long").alias("n"))


def generic_per_row(level: DataFrame, k: int) -> DataFrame:
    """pattern of each row by canonical search over all renumberings (no quick pattern)."""
    import pandas as pd
    from pyspark.sql.functions import pandas_udf

    bits = patterns.pairs(k)
    at = {p: b for b, p in enumerate(bits)}
    from itertools import permutations

    perms = list(permutations(range(k)))

    def canonical(mask: pd.Series) -> pd.Series:
        m = mask.to_numpy()
        best = None
        for perm in perms:
            moved = 0
            for b, (i, j) in enumerate(bits):
                x, y = sorted((perm[i], perm[j]))
                moved = moved | (m >> b & 1) << at[x, y]
            best = moved if best is None else moved.clip(max=best)
        return pd.Series(best)

    canonical.__annotations__ = {"mask": pd.Series, "return": pd.Series}
    names = patterns.dimension_df(level.sparkSession, k).select(F.col("mask").alias("code"), "pattern")
    return level.withColumn("code", pandas_udf(canonical, "int")("mask")).join(F.broadcast(names), "code").drop("code")

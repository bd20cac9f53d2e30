"""Graph methods against brute force, worked examples, exact literals and invariants."""

import itertools
import math
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from motifmill import catalogue
from motifmill.apps import cliques, frequent, motifs, triangles
from motifmill.baselines import formula_motifs, frequent_others, others
from motifmill.functions import patterns
from motifmill.graph import PropertyGraph, dense_ids, normalise
from motifmill.operators import blocking, connect, dense, engine, levels, listed, shared, support
from motifmill.operators.rules import AppSpec
from motifmill.plans import planning
from motifmill.sources import graphs

SF = "/root/testdata/sf0.001"
# Induced 4-vertex counts of the co-return graph at sf0.001.
COPART_R = {"4-clique": 180, "diamond": 1477, "4-cycle": 2310, "tailed-triangle": 25888, "3-star": 47245, "4-path": 143494}


def graph_of(spark, pairs, labels=None):
    return PropertyGraph(spark.createDataFrame(pairs, "src long, dst long"), spark.createDataFrame(labels, "id long, label int") if labels else None)


def complete(n):
    return list(itertools.combinations(range(n), 2))


PETERSEN = [(i, (i + 1) % 5) for i in range(5)] + [(i, i + 5) for i in range(5)] + [(i + 5, (i + 2) % 5 + 5) for i in range(5)]
PETERSEN = [tuple(sorted(p)) for p in PETERSEN]


@pytest.fixture(scope="module")
def copart(spark):
    return graphs.load(spark, SF, "copart_r", "p_type")


@pytest.fixture(scope="module")
def comin(spark):
    return graphs.load(spark, "/root/testdata/sf0.01", "comin")


def counted(df):
    return {r[0]: r[1] for r in df.collect()}


def one(df):
    return df.first()[0]


def brute_motifs(pairs, k):
    near = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    out = {n: 0 for n in patterns.pattern_names(k)}
    for own in itertools.combinations(sorted(near), k):
        m = sum(1 << b for b, (i, j) in enumerate(patterns.pairs(k)) if own[j] in near[own[i]])
        if patterns.connected(m, k):
            out[patterns.name_of(m, k)] += 1
    return out


# -- patterns ------------------------------------------------------------


def test_numbers_of_patterns():
    assert [len(patterns.pattern_names(k)) for k in (3, 4, 5, 6)] == [2, 6, 21, 112]
    assert [len({patterns.walk_signature(m, k) for m, *_ in patterns.dimension(k)}) for k in (3, 4, 5)] == [2, 6, 21]
    assert patterns.automorphisms(7, 3) == 6 and patterns.automorphisms(63, 4) == 24


def test_classifiers_agree(spark):
    rows = [(m, name) for m, _, _, name in patterns.dimension(4)]
    df = spark.createDataFrame(rows, "mask int, name string")
    assert df.where(patterns.classify4(F.col("mask")) != F.col("name")).count() == 0
    for how in ("two_step", "memo", "spectrum"):
        assert motifs.classify(df, 4, how).where("pattern <> name").count() == 0
    with pytest.raises(ValueError):
        patterns.spectrum_df(spark, 6)


def test_child_of_wedge_and_triangle(spark):
    table = {(r.parent_mask, r.bits): r.pattern for r in patterns.transition_table(spark, 4).collect()}
    wedge = 0b011  # 0-1 and 0-2
    assert table[wedge, 0b110] == "4-cycle" and table[7, 0b110] == "diamond"


def test_labelled_codes_and_orbits():
    code, orbit = patterns.canonical_labelled(0b011, [2, 1, 1])
    assert orbit[1] == orbit[2] != orbit[0]
    assert code == patterns.canonical_labelled(0b101, [1, 2, 1])[0]


# -- worked examples -----------------------------------------------------


def test_examples(spark):
    t = catalogue.tiny
    g = t(spark, [(0, 1), (0, 2), (1, 2), (1, 3)])
    assert sorted(r[0] for r in catalogue.grown_once(g, catalogue.least_edge(g)).collect()) == ["[0, 1, 2]", "[0, 1, 3]"]
    assert [r[0] for r in catalogue.kept_orders(t(spark, [(2, 5), (3, 5), (4, 5)])).collect()] == ["[2, 5, 3, 4]"]
    chain = t(spark, [(1, 4), (2, 4), (2, 5), (3, 5), (4, 6), (5, 6)], [(1, 1), (2, 1), (3, 1), (4, 2), (5, 2), (6, 3)])
    assert [tuple(r) for r in catalogue.chain_support(chain).collect()] == [("wedge:2-1-3", 1)]
    level = spark.createDataFrame([(0, 1, 2, 7), (1, 2, 3, 7), (2, 3, 4, 3)], "v0 long, v1 long, v2 long, mask int")
    assert {tuple(r) for r in catalogue.folded(level).collect()} == {("triangle", 2), ("wedge", 1)}


def test_examples_read_the_given_tables(spark):
    for name in ("example_grow", "example_auto", "example_mni", "example_reduce", "op_rmat_stats"):
        with pytest.raises(Exception, match="PATH_NOT_FOUND|does not exist"):
            catalogue.QUERIES[name](spark, "/root/testdata/none").collect()


def test_symmetric_positions_share_a_domain(spark):
    g = graph_of(spark, [(1, 2), (2, 3), (3, 4), (1, 4)], [(1, 0), (3, 0), (2, 1), (4, 1)])
    for plan in ("shapes", "engine"):
        found = counted(frequent.mine(g, 2, 1, plan=plan).select("pattern", "support"))
        assert found["wedge:1-0-0"] == 2 and found["wedge:0-1-1"] == 2


def test_position_bits(spark):
    g = graph_of(spark, [(2, 9), (5, 9), (2, 5), (5, 8)])
    cand = spark.createDataFrame([(2, 5, 8, 9)], "v0 long, v1 long, v2 long, u long")
    for s in connect.STRATEGIES:
        assert connect.position_bits(cand, 3, g, s).first()["bits"] == 0b011


def test_prefix_sum(spark):
    df = spark.createDataFrame([(1, 1), (2, 2), (3, 1), (4, 3)], "k int, n int")
    assert [r.start_offset for r in planning.prefix_sum(df, ["k"], "n").orderBy("k").collect()] == [0, 1, 3, 4]


# -- special graphs ------------------------------------------------------


@pytest.mark.parametrize("name,pairs", {"k5": complete(5), "c5": [(0, 1), (1, 2), (2, 3), (3, 4), (0, 4)], "star": [(0, i) for i in range(1, 5)], "petersen": PETERSEN, "edge": [(0, 1)], "empty": []}.items())
def test_special_graphs(spark, name, pairs):
    g = graph_of(spark, pairs)
    for k in (3, 4):
        expected = brute_motifs(pairs, k)
        assert counted(motifs.count(g, k)) == expected
        assert counted(motifs.count(g, k, method="engine")) == expected
        if pairs:
            assert counted(formula_motifs.count(g, k)) == expected
    for k in (3, 4, 5):
        n = math.comb(5, k) if name == "k5" else 0
        assert one(cliques.count(g, k)) == n
        assert one(cliques.count(g, k, method="engine")) == n
    assert one(triangles.count(g)) == (10 if name == "k5" else 0)
    if name == "petersen":
        assert counted(motifs.count(g, 3)) == {"wedge": 30, "triangle": 0}


def test_bounds_are_checked(spark):
    g = graph_of(spark, [(0, 1)])
    with pytest.raises(ValueError):
        cliques.count(g, 1, method="engine")
    with pytest.raises(ValueError):
        engine.mine(g, AppSpec(), 1)
    with pytest.raises(ValueError):
        frequent.mine(g, 0, 1)
    with pytest.raises(ValueError):
        engine.mine(g, AppSpec(prune=lambda s: s > 1, anti_monotone=False), 3)
    with pytest.raises(ValueError):
        blocking.run(g, AppSpec(prune=lambda s: s > 1), 3)
    with pytest.raises(ValueError):
        formula_motifs.count(g, 5)
    with pytest.raises(ValueError):
        graph_of(spark, [(1, 0)]).validate()
    assert one(cliques.count(g, 2, method="engine")) == 1


# -- the co-return graph -------------------------------------------------


def test_literals(copart):
    for how in ({"method": "intersect"}, {"method": "join"}, {"method": "engine"}, {"orient": "id"}, {"orient": None}, {"orient": "random"}, {"orient": "degeneracy"}):
        assert one(triangles.count(copart, **how)) == 830
    assert [one(cliques.count(copart, k)) for k in (3, 4, 5)] == [830, 180, 35]
    assert counted(motifs.count(copart, 3)) == {"wedge": 13769, "triangle": 830}
    assert counted(motifs.count(copart, 4)) == COPART_R == counted(motifs.count(copart, 4, method="formula"))


def test_ways_to_four_cliques(copart):
    for orient, eager in itertools.product(("degree", None), (True, False)):
        assert one(cliques.count(copart, 4, method="engine", orient=orient, eager=eager)) == 180
    for fn in (others.relational_cliques, others.dfs_cliques, others.local_graph_cliques, others.filter_process_cliques):
        assert one(fn(copart, 4)) == 180
    assert others.compiled_count(copart, "4-clique").first()["n"] == 180
    listed = cliques.listing(copart, 4)
    sets = listed.select(F.array_sort(F.array("v0", "v1", "v2", "v3")).alias("s"))
    assert listed.count() == sets.distinct().count() == 180


@pytest.mark.parametrize("least, users", [(3, 20), (1, 400)])
def test_triangles_of_shared_keys_make_no_edges(spark, least, users):
    """Few users: bits; many users in small groups: lists.  Null keys and nodes join nothing, repeats count once."""
    rng = np.random.default_rng(users)
    rows = [(int(k), int(n) * 7) for k in range(40) for n in rng.choice(users, rng.integers(least, 6))] + [(None, 0), (None, 7), (3, None)]
    rows = spark.createDataFrame(rows + rows[:9], "k long, n int")
    expected = one(triangles.count(PropertyGraph(shared.pairs(rows.dropna().distinct()))))

    def no_edges(edges):
        raise AssertionError("edges of a dense graph became rows")

    def by_edges(edges):
        return triangles.count(PropertyGraph(edges))

    assert expected > 0 and shared.triangles(rows, by_edges).first()["triangles"] == expected
    for bounds in ({"tile_bytes": 1 << 20}, {"tile_bytes": 40}, {"apply": True}):
        assert shared.triangles(rows, no_edges, least_pairs=1, **bounds).first()["triangles"] == expected
    assert shared.triangles(rows.where("n < 0"), by_edges).first()["triangles"] == 0
    assert shared.triangles(rows, by_edges, least_pairs=1, most=8).first()["triangles"] == expected


def test_ways_to_triangles(copart):
    for fn in (others.task_triangles, others.coloured_triangles):
        assert one(fn(copart)) == 830
    assert triangles.per_vertex(copart).agg(F.sum("triangles")).first()[0] == 3 * 830
    assert triangles.per_edge(copart).agg(F.sum("triangles")).first()[0] == 3 * 830


def test_ways_to_motifs(comin):
    expected = counted(motifs.count(comin, 4))
    assert expected["4-clique"] == 39 and expected["4-path"] == 153948
    for c in connect.STRATEGIES:
        assert counted(motifs.count(comin, 4, method="engine", connectivity=c)) == expected
    assert counted(motifs.count(comin, 4, method="engine", how="generic", materialize_candidates=True)) == expected
    assert counted(others.dfs_motifs(comin, 4)) == expected
    assert counted(others.relational_motifs(comin, 3)) == counted(motifs.count(comin, 3))
    run = blocking.run(comin, AppSpec(classify=lambda d, n: motifs.classify(d, n, "custom")), 4, blocks=3)
    assert {k: v for k, v in counted(run).items() if v} == {k: v for k, v in expected.items() if v}


def test_five_motifs_sum_to_connected_sets(comin):
    five = counted(motifs.count(comin, 5))
    assert len(five) == 21 and five[next(k for k in five if k == patterns.name_of(1023, 5))] == 1
    assert sum(five.values()) == motifs.listing(comin, 5).count()


def test_frequent_patterns(copart):
    # Patterns with support of at least sigma, by edges.
    assert counted(frequent.mine(copart, 3, 20).groupBy("n_edges").count()) == {1: 21, 2: 100, 3: 580}
    assert counted(frequent.mine(copart, 3, 10).groupBy("n_edges").count()) == {1: 21, 2: 126, 3: 1016}
    a, b = (sorted(map(tuple, frequent.mine(copart, 3, 20, plan=p).collect())) for p in ("shapes", "engine"))
    assert a == b
    assert sorted(map(tuple, others.recursive_frequent(copart, 2, 24).collect())) == sorted(map(tuple, frequent.mine(copart, 2, 24).collect()))
    supports = {(n, p): s for n, p, s in a}
    for (n, p), s in supports.items():
        if p.startswith("wedge:"):
            c, x, y = map(int, p[6:].split("-"))
            for z in (x, y):
                assert s <= supports[1, "edge:" + "-".join(map(str, sorted((c, z))))]


def test_support_modes_agree(copart):
    d = frequent.domains(frequent.named(engine.seed(copart, AppSpec(mode="edge"))))
    exact = counted(support.mni(d))
    for mode in ("set", "bitmap", "udaf"):
        assert counted(support.mni(d, mode)) == exact
    approx = counted(support.mni(d, "approx"))
    assert all(abs(approx[p] - n) <= 0.1 * n + 1 for p, n in exact.items())
    assert {r.pattern for r in support.mni_at_least(d, 30).collect()} == {p for p, n in exact.items() if n >= 30}
    generic = counted(support.mni(frequent.domains_generic(engine.seed(copart, AppSpec(mode="edge")))))
    assert sorted(generic.values()) == sorted(exact.values())


def test_edge_mode_level_sizes(copart):
    run = engine.mine(copart, AppSpec(mode="edge"), 2)
    assert run.levels[2].count() == 16259 == 13769 + 3 * 830


def test_layouts_and_stores(comin):
    app = AppSpec()
    wide = engine.grow_vertices(engine.seed(comin, app), 2, comin, app)
    rows = sorted(map(tuple, wide.select("v0", "v1", "v2", "mask").collect()))
    for layout in levels.LAYOUTS:
        level, store = engine.mine_stored(comin, app, 3, layout)
        assert sorted(map(tuple, level.select("v0", "v1", "v2", "mask").collect())) == rows
        assert store.get(2).count() == comin.edges.count() and store.bytes(3) > 0
        if layout == "tree":  # dense ids, and each row names its parent
            ids = [r.emb_id for r in store.levels[3].select("emb_id").collect()]
            assert sorted(ids) == list(range(len(rows)))
            assert {r.parent_id for r in store.levels[3].collect()} <= set(range(comin.edges.count()))
    pair = others.overapproximation(comin).first()
    assert pair["expanded"] >= pair["stored"] == len(rows)


def test_orientations_keep_every_edge(copart):
    n = copart.edges.count()
    for by in ("id", "degree", "random", "degeneracy"):
        o = copart.orient(by)
        assert o.count() == n and normalise(o).count() == n


def test_relabelling_changes_no_count(spark, comin):
    moved = normalise(comin.edges.select(F.pmod(F.col("src") * 7919, F.lit(10_007)).alias("src"), F.pmod(F.col("dst") * 7919, F.lit(10_007)).alias("dst")))
    g = PropertyGraph(moved)
    assert counted(motifs.count(g, 4)) == counted(motifs.count(comin, 4))
    ids = dense_ids(moved, "src")
    assert sorted(r["id"] for r in ids.collect()) == list(range(ids.count()))


def test_random_graphs_equal_brute_force(spark):
    import random

    for seed in range(3):
        rng = random.Random(seed)
        pairs = [p for p in complete(14) if rng.random() < 0.3]
        g = graph_of(spark, pairs)
        for k in (3, 4, 5):
            assert counted(motifs.count(g, k)) == brute_motifs(pairs, k)


def test_readers_round_trip(spark, tmp_path):
    e = graph_of(spark, complete(6)).edges
    for fmt in ("csv", "json", "orc", "parquet"):
        path = str(tmp_path / fmt)
        e.write.format(fmt).save(path)
        assert graphs.read_edge_list(spark, path, fmt).count() == 15


def test_hub_line_keeps_every_neighbour(spark, tmp_path):
    (tmp_path / "adjacency.txt").write_text("0 " + " ".join(map(str, range(1, 1_000_051))) + "\n")
    assert graphs.read_adjacency_text(spark, str(tmp_path / "adjacency.txt")).count() == 1_000_050


def test_unfinished_rounds_are_errors(spark):
    chain = PropertyGraph(spark.createDataFrame([(i, i + 1) for i in range(12)], "src long, dst long"))
    assert chain.k_core(2).count() == 0
    with pytest.raises(RuntimeError):
        chain.k_core(2, most_rounds=2)


def test_rmat_is_deterministic(spark):
    a, b = (sorted(map(tuple, graphs.rmat(spark, 7).collect())) for _ in range(2))
    assert a == b and all(x < y < 128 for x, y in a)


def brute_frequent(pairs, labels, edges, sigma):
    """Code -> support of all connected sets of that many edges."""
    domains = {}
    for own in itertools.combinations(pairs, edges):
        vids = sorted({v for e in own for v in e})
        mask = sum(1 << patterns.offset(vids.index(b)) + vids.index(a) for a, b in own)
        if patterns.connected(mask, len(vids)):
            code, orbit = patterns.canonical_labelled(mask, [labels[v] for v in vids])
            for o, v in zip(orbit, vids):
                domains.setdefault(code, {}).setdefault(o, set()).add(v)
    found = {c: min(map(len, d.values())) for c, d in domains.items()}
    return {c: n for c, n in found.items() if n >= sigma}


@pytest.fixture(scope="module")
def labelled(spark):
    import random

    rng = random.Random(4)
    pairs = sorted({tuple(sorted(rng.sample(range(12), 2))) for _ in range(22)})
    labels = {v: rng.randrange(2) for v in range(12)}
    return graph_of(spark, pairs, list(labels.items())), pairs, labels


@pytest.mark.parametrize("edges", [4, 5])
def test_larger_patterns_equal_brute_force(labelled, edges):
    g, pairs, labels = labelled
    expected = brute_frequent(pairs, labels, edges, 3)
    got = {r.pattern: r.support for r in frequent.mine(g, edges, 3).collect() if r.n_edges == edges}
    assert got == expected and expected


def test_frequent_baselines_agree(labelled):
    g, pairs, labels = labelled
    expected = {(r.n_edges, r.pattern, r.support) for r in frequent.mine(g, 3, 3).collect()}
    codes = {(n, c): s for n in (1, 2, 3) for c, s in brute_frequent(pairs, labels, n, 3).items()}
    assert sorted(s for _, _, s in expected) == sorted(codes.values())
    generic = {(r.n_edges, r.pattern): r.support for r in frequent.mine(g, 3, 3, plan="generic").collect()}
    assert generic == codes
    for fn in (frequent_others.filter_process_frequent, frequent_others.relational_frequent, frequent_others.dfs_frequent):
        assert {tuple(r) for r in fn(g, 3, 3).collect()} == expected, fn.__name__
    early = {(r.n_edges, r.pattern, r.support) for r in frequent.mine(g, 3, 3, mode="early").collect()}
    assert early == {(n, p, 3) for n, p, _ in expected}
    counted_ = {(r.n_edges, r.pattern): r.support for r in frequent.mine(g, 3, 1, kind="frequency").collect()}
    assert {(r.n_edges, r.pattern): r.support for r in frequent_others.compiled_frequency(g, 3, 1).collect()} == counted_


def test_canonical_search_names_patterns_alike():
    import random

    rng = random.Random(1)
    for _ in range(100):
        k = rng.randint(2, 5)
        bits = patterns.pairs(k)
        mask = rng.randrange(1, 1 << len(bits))
        labels = [rng.randrange(2) for _ in range(k)]
        code, orbit = patterns.canonical_labelled(mask, labels)
        perm = rng.sample(range(k), k)
        moved = sum(1 << patterns.offset(max(perm[i], perm[j])) + min(perm[i], perm[j]) for b, (i, j) in enumerate(bits) if mask >> b & 1)
        other, orbit2 = patterns.canonical_labelled(moved, [labels[perm.index(v)] for v in range(k)])
        assert code == other and [orbit[perm.index(v)] for v in range(k)] == orbit2
        assert patterns.canonical_labelled(*patterns.of_code(code))[0] == code


def test_hand_written_triangles_and_shared_joins(spark, copart):
    n = triangles.count(copart).first()["triangles"]
    assert others.hand_triangles(copart).first()["triangles"] == n
    assert others.hand_triangles(copart, chunk=100).first()["triangles"] == n
    assert others.hand_triangles(graph_of(spark, PETERSEN)).first()["triangles"] == 0
    assert others.colours_for(10**9, 50_000) > others.colours_for(10**6, 50_000) > others.colours_for(1_000, 50_000) == 3
    assert {r.pattern: r.n for r in others.compiled_motifs(copart, tuple(COPART_R)).collect()} == COPART_R


def test_rows_are_numbered_densely(spark):
    df = planning.number_rows(spark.range(1_000).where("id % 3 = 0").repartition(7), "number")
    assert sorted(r.number for r in df.collect()) == list(range(334))


def test_io_is_measured(spark, copart):
    from motifmill import measures

    found = measures.io_of(spark, lambda: triangles.count(copart))
    assert found["shuffle_write_bytes"] > 0 and found["disk_spill_bytes"] == 0


def test_checkpoints_need_a_shared_folder_on_a_cluster():
    from types import SimpleNamespace

    from motifmill import session

    class Empty:
        isEmpty = staticmethod(lambda: True)

    conf = SimpleNamespace(get=lambda *a: None)
    sc = SimpleNamespace(master="spark://somewhere:7077", _jsc=SimpleNamespace(sc=lambda: SimpleNamespace(getCheckpointDir=lambda: Empty)))
    with pytest.raises(RuntimeError):
        session.checkpoint_folder(SimpleNamespace(sparkContext=sc, conf=conf))


def test_broadcast_adjacency_takes_no_rows_to_the_driver(spark, copart, monkeypatch):
    from pyspark.sql import DataFrame

    def refused(*_):
        raise AssertionError("rows of the graph are collected on the driver")

    near = {r["id"]: r["nbrs"] for r in copart.adjacency().collect()}
    monkeypatch.setattr(DataFrame, "toPandas", refused)
    monkeypatch.setattr(DataFrame, "collect", refused)
    held = connect.broadcast_csr(copart)
    ids, first, nbrs = held.value
    assert nbrs.dtype == "int32" and {int(v): [int(ids[x]) for x in nbrs[first[i] : first[i + 1]]] for i, v in enumerate(ids)} == near
    with pytest.raises(ValueError, match="broadcast bound"):
        connect.broadcast_csr(copart, most=1000)
    labelled = graphs.load(spark, SF, "copart_r", "p_type")
    frequent_others.dfs_frequent(labelled, 2, 5)


def test_hand_triangles_on_more_vertices_than_32_bits_pair(spark):
    a = F.col("id") * 3
    ends = F.explode(F.array(F.struct(a.alias("src"), (a + 1).alias("dst")), F.struct((a + 1).alias("src"), (a + 2).alias("dst")), F.struct(a.alias("src"), (a + 2).alias("dst")))).alias("e")
    apart = PropertyGraph(spark.range(20_000).select(ends).select("e.src", "e.dst"))
    assert others.hand_triangles(apart).first()["triangles"] == 20_000


def test_nearest_vectors_are_found_in_tiles(spark, tmp_path):
    rows = [(i, [float((i * j) % 7 == 0) for j in range(64)]) for i in range(300)]  # many equal vectors
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    whole = sorted(map(tuple, graphs.knn8(spark, str(tmp_path)).collect()))
    q = {i: [int(x * 1000) for x in v] for i, v in rows}
    dot = lambda x, y: sum(a * b for a, b in zip(x, y))
    score = lambda a, b: dot(q[a], q[b]) / math.sqrt(dot(q[b], q[b]))
    near = {(min(a, b), max(a, b)) for a in q for b in sorted(set(q) - {a}, key=lambda b: (-score(a, b), b))[:8]}
    assert whole == sorted(near)
    assert sorted(map(tuple, graphs.knn8(spark, str(tmp_path), block_bytes=100 * 512, tile_bytes=8 * 700).collect())) == whole


def test_carried_neighbours_are_above_the_first_vertex(copart):
    level = motifs._carry_level(copart, 3)
    low = F.exists(F.concat("n0", "n1", "n2"), lambda u: u <= F.col("v0"))
    assert level.where(low).isEmpty() and not level.isEmpty()


@pytest.fixture(scope="module")
def copied_events(spark, tmp_path_factory):
    """Every user of events three times, and one that stands alone; rows without a user or a minute."""
    folder = tmp_path_factory.mktemp("copied")
    e = spark.read.parquet(f"{SF}/events.parquet").select("ts", "user_id")
    users = e.select("ts", F.explode(F.sequence(F.lit(0), F.lit(2))).alias("c"), "user_id").select("ts", (F.col("user_id") + F.col("c") * 10**9).alias("user_id"))
    odd = spark.sql("SELECT timestamp'2031-01-01 00:00:00' AS ts, 7L AS user_id UNION ALL SELECT timestamp'2031-01-01 00:00:00', NULL UNION ALL SELECT NULL, 8L UNION ALL SELECT NULL, 9L")
    users.unionByName(users).unionByName(odd).coalesce(1).write.parquet(f"{folder}/events.parquet")
    return str(folder)


def _by_formula(spark, folder):
    return counted(motifs.count(PropertyGraph.of(graphs.comin(spark, folder)), 4, method="formula"))


@pytest.mark.parametrize("strategy", connect.STRATEGIES)
def test_connectivity_on_copies_shuffles_no_candidates(spark, copied_events, strategy):
    want = _by_formula(spark, copied_events)
    assert min(want.values()) > 0
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        found = catalogue.QUERIES[f"abl_conn_{strategy}"](spark, copied_events)
        plan = found._jdf.queryExecution().executedPlan().toString()
        assert plan.count("SortMergeJoin") <= 1  # the names of the patterns
        assert counted(found) == want
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


@pytest.mark.parametrize("layout", levels.LAYOUTS)
def test_layouts_on_copies_store_no_last_level(spark, copied_events, layout, monkeypatch):
    kept, keep = [], levels.Store._keep
    monkeypatch.setattr(levels.Store, "_keep", lambda self, size, df: (kept.append(size), keep(self, size, df)))
    assert counted(catalogue.QUERIES[f"abl_layout4_{layout}"](spark, copied_events)) == _by_formula(spark, copied_events)
    assert kept == [2, 3]


def test_fold_of_equal_nodes(spark, copied_events):
    g = shared.fold(graphs.comin_rows(spark, copied_events))
    assert g.weights.agg(F.sum("weight")).first()[0] == spark.read.parquet(f"{copied_events}/events.parquet").where("ts is not null").select("user_id").dropna().distinct().count()
    whole = PropertyGraph.of(graphs.comin(spark, copied_events))
    assert g.n_edges * 8 < whole.n_edges
    for k in (2, 3):
        assert counted(motifs.count(g, k, how="two_step", method="engine", fused=True)) == counted(motifs.count(whole, k, how="two_step", method="engine"))
    with pytest.raises(ValueError):
        motifs.count(g, 4)


def test_linear_scans_one_part_of_a_list(spark):
    edges = [(a, b) for a in range(-20, 40) for b in range(a + 1, 40) if (a * b + a + b) % 3 == 0]
    g = PropertyGraph(spark.createDataFrame(edges, "src int, dst int"))
    near = g.adjacency().select(F.col("id").alias("u"), F.col("nbrs").alias("_n"))
    whole, parted = ({r["u"]: r["_n"] for r in df.collect()} for df in (near, connect._parted(near)))
    for u, parts in parted.items():
        assert sorted(v for p in parts for v in p) == whole[u] and all(v % connect.LIST_PARTS == i for i, p in enumerate(parts) for v in p)
    level = g.edges.select(F.col("src").alias("v0"), F.col("dst").alias("v1"))
    cand = level.join(near.select("u"), F.expr("u <> v0 and u <> v1"))
    found = connect.position_bits(cand, 2, g, "linear", fused=True)
    assert re.search(r"_n#\d+\[", found._jdf.queryExecution().optimizedPlan().toString())
    assert {tuple(r) for r in found.select("v0", "v1", "u", "bits").collect()} == {(a, b, u, (a in whole[u]) + 2 * (b in whole[u])) for a, b in edges for u in whole if u not in (a, b)}


def test_intersect_counts_the_last_level_from_its_parents(spark, copied_events, monkeypatch):
    want, grown, grow = _by_formula(spark, copied_events), [], engine.grow_vertices
    monkeypatch.setattr(engine, "grow_vertices", lambda level, size, *rest: (grown.append(size), grow(level, size, *rest))[1])
    assert counted(catalogue.QUERIES["abl_conn_intersect"](spark, copied_events)) == want
    assert grown == [2]
    g = shared.fold(graphs.comin_rows(spark, copied_events))
    g.most_weight = 1 << 32  # more than an entry of a list holds
    assert counted(motifs.count(g, 4, method="engine", connectivity="intersect", fused=True)) == want


@pytest.fixture
def small_is_dense(monkeypatch):
    monkeypatch.setattr(dense, "LEAST_EDGES", 0)
    monkeypatch.setattr(dense, "SPARSE", 1 << 20)


def test_fours_of_dense_graphs_grow_no_rows(spark, comin, small_is_dense, monkeypatch):
    want = counted(motifs.count(comin, 4, method="formula"))
    monkeypatch.setattr(motifs, "_carry_level", lambda *_: pytest.fail("a level of rows"))
    assert counted(motifs.count(comin, 4)) == want
    rng = np.random.default_rng(3)
    for n, share in ((5, 1.0), (2, 1.0), (40, 0.2), (150, 0.5)):  # 150: lists of more than one word
        pairs = [(7 * a - 50, 7 * b - 50) for a, b in complete(n) if rng.random() < share]
        g = graph_of(spark, pairs)
        want = counted(motifs.count(g, 4, method="formula"))
        assert counted(motifs.count(g, 4)) == want and counted(motifs.count(g, 4, how="memo")) == want
    monkeypatch.setattr(dense, "BITS_BYTES", 0)
    assert not dense.fits(comin)


def test_intersect_of_many_arcs_grows_no_rows(spark, copied_events, small_is_dense, monkeypatch):
    want = _by_formula(spark, copied_events)
    edges = sorted(map(tuple, graphs.comin(spark, copied_events).collect()))
    g = shared.unfold(shared.fold(graphs.comin_rows(spark, copied_events)))
    degrees = lambda pairs: sorted(sum(v in e for e in pairs) for v in {v for e in pairs for v in e})
    assert degrees(sorted(map(tuple, g.edges.collect()))) == degrees(edges) and g.validate()
    assert shared.unfolded_size(shared.fold(graphs.comin_rows(spark, copied_events))) == (len({v for e in edges for v in e}), len(edges))
    monkeypatch.setattr(engine, "grow_vertices", lambda *_: pytest.fail("a level of rows"))
    assert counted(catalogue.QUERIES["abl_conn_intersect"](spark, copied_events)) == want


def test_threes_of_stored_lists_shuffle_no_list(spark, tmp_path, monkeypatch):
    lines = [(o, (7 * o * p + p * p) % 61 - 9, p) for o in range(90) for p in range(o % 6)] + [(5, None, 9), (None, 4, 9), (None, 5, 9), (3, 10**12, 9), (3, 10**12, 8)]
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long, l_linenumber int").write.parquet(f"{tmp_path}/lineitem.parquet")
    edges = sorted(map(tuple, graphs.copart_full(spark, str(tmp_path)).collect()))
    want = counted(motifs.count(PropertyGraph.of(graphs.copart_full(spark, str(tmp_path))), 3))
    g = graphs.load_lists(spark, str(tmp_path), "copart_full")
    assert sorted(map(tuple, g.edges.collect())) == edges and min(want.values()) > 0
    monkeypatch.setattr(motifs, "_carry_level", lambda *_: pytest.fail("lists are joined to edges"))
    assert counted(catalogue.QUERIES["mc3_copart_full"](spark, str(tmp_path))) == want
    monkeypatch.setattr(listed, "BLOCK_BYTES", 400)  # many blocks
    monkeypatch.setattr(listed, "GATHER", 20)
    assert counted(motifs.count(g, 3)) == want
    none = spark.createDataFrame([], "id long, nbrs array<long>")
    assert set(counted(motifs.count(PropertyGraph(g.edges.limit(0), lists=none), 3)).values()) == {0}


def test_depth_first_completes_extension_sets_together(spark, comin, small_is_dense, monkeypatch):
    want = counted(motifs.count(comin, 4, method="formula"))
    rng = np.random.default_rng(4)
    bits = []
    for n, share in ((9, 0.6), (90, 0.3)):
        pairs = [p for p in complete(n) if rng.random() < share]
        near = [sorted({a + b - v for a, b in pairs if v in (a, b)}) for v in range(n)]
        bits.append(dense.Bits(np.append(0, np.cumsum([len(x) for x in near])), np.array(sum(near, []), np.int32)))
    for b in bits:  # both orders, for the same sets
        found = [{}, {}]
        for down in (False, True):
            for mask, c in dense.tallied(b, range(b.n), down).items():
                found[down][patterns.name_of(mask, 4)] = found[down].get(patterns.name_of(mask, 4), 0) + c
        assert found[0] == found[1]
    monkeypatch.setattr(others, "near_sets", lambda *_: pytest.fail("sets of Python numbers"))
    assert counted(others.dfs_motifs(comin, 4)) == want

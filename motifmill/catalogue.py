"""All registered graph queries with the DuckDB SQL that checks them.

The SQL takes another way than the engine wherever one exists: id-order self joins for
cliques, closed formulas for motifs, one statement a shape for frequent subgraphs.
"""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from . import measures
from .apps import cliques, frequent, motifs, triangles
from .baselines import formula_motifs, frequent_others, others
from .graph import PropertyGraph, dense_ids, label_dictionary
from .operators import blocking, connect, engine, levels, relational, shared, support
from .operators.rules import AppSpec
from .plans import planning, sqlsurface
from .sources import graphs
from .streaming import events

QUERIES: dict = {}
SQL: dict[str, str] = {}


def add(name: str, query, sql: str | None = None) -> None:
    if name in QUERIES:
        raise ValueError(f"{name} is registered twice")
    QUERIES[name] = query
    if sql:
        SQL[name] = sql


def on(graph: str, fn, label: str | None = None, lists: bool = False):
    if lists:
        return lambda spark, sf_dir: fn(graphs.load_lists(spark, sf_dir, graph))
    return lambda spark, sf_dir: fn(graphs.load(spark, sf_dir, graph, label))


# -- SQL texts ---------------------------------------------------------------


def clique_sql(graph: str, k: int, select: str | None = None) -> str:
    vs = ["e01.src", "e01.dst", *[f"e0{j}.dst" for j in range(2, k)]]
    text = "e e01"
    for j in range(2, k):
        text += f" JOIN e e0{j} ON e0{j}.src = e01.src AND e0{j}.dst > {vs[j - 1]}"
        for i in range(1, j):
            text += f" JOIN e e{i}{j} ON e{i}{j}.src = {vs[i]} AND e{i}{j}.dst = e0{j}.dst"
    return f"WITH e AS ({graphs.SQL[graph]}) SELECT " + (select or "count(*)::BIGINT AS cliques") .format(*vs) + f" FROM {text}"


def tc_sql(graph: str) -> str:
    return clique_sql(graph, 3, "count(*)::BIGINT AS triangles")


COUNTS = """
d AS (SELECT id, count(*) AS d FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY id),
t AS (SELECT x.src AS a, x.dst AS b, y.dst AS c FROM e x JOIN e y ON y.src = x.src AND y.dst > x.dst JOIN e z ON z.src = x.dst AND z.dst = y.dst),
te AS (SELECT a, b, count(*) AS t FROM (SELECT a, b FROM t UNION ALL SELECT a, c FROM t UNION ALL SELECT b, c FROM t) GROUP BY a, b),
tv AS (SELECT v, count(*) AS t FROM (SELECT a AS v FROM t UNION ALL SELECT b FROM t UNION ALL SELECT c FROM t) GROUP BY v),
k4 AS (SELECT count(*) AS n FROM t JOIN e u ON u.src = t.a AND u.dst > t.c JOIN e v ON v.src = t.b AND v.dst = u.dst JOIN e w ON w.src = t.c AND w.dst = u.dst),
r AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e),
cc AS (SELECT sum(c * (c - 1) // 2) AS n FROM (SELECT x.dst AS p, y.dst AS q, count(*) AS c FROM r x JOIN r y ON x.src = y.src AND x.dst < y.dst GROUP BY 1, 2)),
s AS (SELECT (SELECT count(*) FROM t) AS t, (SELECT n FROM k4) AS k, coalesce((SELECT sum(t * (t - 1) // 2) FROM te), 0) - 6 * (SELECT n FROM k4) AS di,
  coalesce((SELECT n FROM cc), 0) AS cc, coalesce((SELECT sum(tv.t * (d.d - 2)) FROM tv JOIN d ON tv.v = d.id), 0) AS pv, (SELECT sum(d * (d - 1) * (d - 2) // 6) FROM d) AS s3,
  (SELECT sum(d * (d - 1) // 2) FROM d) AS w, (SELECT sum((x.d - 1) * (y.d - 1)) FROM e JOIN d x ON x.id = e.src JOIN d y ON y.id = e.dst) AS pe),
q AS (SELECT *, (cc - 2 * di - 6 * k) // 2 AS cy, pv - 4 * di - 12 * k AS ta FROM s)
"""


def mc3_sql(graph: str) -> str:
    return f"WITH e AS ({graphs.SQL[graph]}), {COUNTS} SELECT 'wedge' AS pattern, (w - 3 * t)::BIGINT AS n FROM s UNION ALL SELECT 'triangle', t::BIGINT FROM s"


def mc4_sql(graph: str) -> str:
    named = {
        "4-clique": "k", "diamond": "di", "4-cycle": "cy", "tailed-triangle": "ta", "3-star": "s3 - ta - 2 * di - 4 * k",
        "4-path": "pe - 3 * t - 2 * ta - 4 * cy - 6 * di - 12 * k",
    }
    return f"WITH e AS ({graphs.SQL[graph]}), {COUNTS} " + " UNION ALL ".join(f"SELECT '{p}' AS pattern, ({x})::BIGINT AS n FROM q" for p, x in named.items())


def fsm_sql(graph: str, column: str, max_edges: int, sigma: int, measure: str = "mni") -> str:
    least = lambda *vs: "least(" + ", ".join(f"count(DISTINCT {v})" for v in vs) + ")"
    shapes = [(1, "'edge:' || x.ls || '-' || x.ld", "r x", "x.ls <= x.ld", ("x.src", "x.dst"))]
    if max_edges > 1:
        shapes.append((2, "'wedge:' || x.ls || '-' || x.ld || '-' || y.ld", "r x JOIN r y ON x.src = y.src AND x.dst <> y.dst", "x.ld <= y.ld", ("x.src", "x.dst", "y.dst")))
    if max_edges > 2:
        shapes += [
            (3, "'triangle:' || x.ls || '-' || x.ld || '-' || y.ld", "r x JOIN r y ON x.dst = y.src AND y.dst <> x.src JOIN r z ON z.src = x.src AND z.dst = y.dst", "x.ls <= x.ld AND x.ld <= y.ld", ("x.src", "x.dst", "y.dst")),
            (3, "'3-star:' || x.ls || '-' || x.ld || '-' || y.ld || '-' || z.ld", "r x JOIN r y ON x.src = y.src AND x.dst <> y.dst JOIN r z ON x.src = z.src AND z.dst <> x.dst AND z.dst <> y.dst", "x.ld <= y.ld AND y.ld <= z.ld", ("x.src", "x.dst", "y.dst", "z.dst")),
            (3, "'3-path:' || x.ls || '-' || x.ld || '-' || y.ld || '-' || z.ld", "r x JOIN r y ON x.dst = y.src AND y.dst <> x.src JOIN r z ON y.dst = z.src AND z.dst <> x.dst AND z.dst <> x.src", "(x.ls < z.ld OR (x.ls = z.ld AND x.ld <= y.ld))", ("x.src", "x.dst", "y.dst", "z.dst")),
        ]
    parts = [f"SELECT {n}::INT AS n_edges, {name} AS pattern, ({least(*vs)})::BIGINT AS support FROM {source} WHERE {cond} GROUP BY 2" for n, name, source, cond, vs in shapes]
    return (
        f"WITH e AS ({graphs.SQL[graph]}), l AS (SELECT p_partkey AS id, dense_rank() OVER (ORDER BY {column}) AS label FROM part), "
        "r AS (SELECT src, dst, a.label AS ls, b.label AS ld FROM (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e) JOIN l a ON a.id = src JOIN l b ON b.id = dst) "
        f"SELECT * FROM ({' UNION ALL '.join(parts)}) WHERE support >= {sigma}"
    )


def fsm_four_edges_sql(graph: str, column: str, sigma: int) -> str:
    """Labels, vertices and support of every frequent pattern of exactly 4 edges, shape by shape."""
    turns = [[(s + d * i) % 4 for i in range(4)] for s in range(4) for d in (1, -1)]
    cycle = "[x.ls, y.ls, z.ls, w.ls]"
    label = ["x.ls", "y.ls", "z.ls", "w.ls"]
    shapes = [
        ("r x JOIN r y ON y.src = x.src JOIN r z ON z.src = x.src JOIN r w ON w.src = x.src", ["x.src", "x.dst", "y.dst", "z.dst", "w.dst"], ["x.ls", "x.ld", "y.ld", "z.ld", "w.ld"], "x.ld <= y.ld AND y.ld <= z.ld AND z.ld <= w.ld"),
        ("r x JOIN r y ON y.src = x.dst JOIN r z ON z.src = y.dst JOIN r w ON w.src = z.dst", ["x.src", "x.dst", "y.dst", "z.dst", "w.dst"], ["x.ls", "x.ld", "y.ld", "z.ld", "w.ld"], "(x.ls < w.ld OR (x.ls = w.ld AND x.ld <= z.ld))"),
        ("r x JOIN r y ON y.src = x.src JOIN r z ON z.src = x.src JOIN r w ON w.src = z.dst", ["x.src", "x.dst", "y.dst", "z.dst", "w.dst"], ["x.ls", "x.ld", "y.ld", "z.ld", "w.ld"], "x.ld <= y.ld"),
        ("r x JOIN r y ON y.src = x.dst JOIN r z ON z.src = y.dst JOIN r w ON w.src = z.dst AND w.dst = x.src", ["x.src", "y.src", "z.src", "w.src"], label, "list_sort([" + ", ".join("[" + ", ".join(label[i] for i in t) + "]" for t in turns) + f"])[1] = {cycle}"),
        ("r x JOIN r y ON y.src = x.src JOIN r z ON z.src = x.dst AND z.dst = y.dst JOIN r w ON w.src = x.src", ["x.src", "x.dst", "y.dst", "w.dst"], ["x.ls", "x.ld", "y.ld", "w.ld"], "x.ld <= y.ld"),
    ]
    parts = []
    for source, vs, ls, cond in shapes:
        apart = " AND ".join(f"{a} <> {b}" for i, a in enumerate(vs) for b in vs[:i])
        parts.append(f"SELECT 4::INT AS n_edges, {len(vs)}::INT AS n_vertices, array_to_string(list_sort([{', '.join(ls)}]), '-') AS labels, least({', '.join(f'count(DISTINCT {v})' for v in vs)})::BIGINT AS support FROM {source} WHERE {apart} AND {cond} GROUP BY {', '.join(ls)}")
    return (
        f"WITH e AS ({graphs.SQL[graph]}), l AS (SELECT p_partkey AS id, dense_rank() OVER (ORDER BY {column}) AS label FROM part), "
        "r AS (SELECT src, dst, a.label AS ls, b.label AS ld FROM (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e) JOIN l a ON a.id = src JOIN l b ON b.id = dst) "
        f"SELECT * FROM ({' UNION ALL '.join(parts)}) WHERE support >= {sigma}"
    )


def four_edges(g: PropertyGraph, sigma: int, plan: str = "engine"):
    found = frequent.mine(g, 4, sigma, plan=plan).where("n_edges = 4")
    labels = F.split("pattern", r"\|")[0]
    return found.select("n_edges", F.size(F.split(labels, "-")).alias("n_vertices"), labels.alias("labels"), "support")


# -- methods and workloads ---------------------------------------------------

for g in ("copart_r", "knn8", "doc_line", "copart_full", "nextline", "page_href2", "supp_coorder", "tree", "custpart_top"):
    add(f"tc_{g}", on(g, triangles.count), tc_sql(g))
add("tc_comin", lambda spark, sf_dir: shared.triangles(graphs.comin_rows(spark, sf_dir), lambda e: triangles.count(PropertyGraph.of(e))), tc_sql("comin"))
for m in ("join", "engine"):
    add(f"tc_{m}_copart_r", on("copart_r", lambda g, m=m: triangles.count(g, method=m)), tc_sql("copart_r"))
for o in ("id", "random", "degeneracy", None):
    add(f"tc_order_{o}_copart_r".lower(), on("copart_r", lambda g, o=o: triangles.count(g, orient=o)), tc_sql("copart_r"))
add("tc_list_copart_r", on("copart_r", lambda g: triangles.listing(g, orient="id")), clique_sql("copart_r", 3, "{0} AS v0, {1} AS v1, {2} AS v2"))

for k, g in ((3, "copart_r"), (4, "copart_r"), (5, "copart_r"), (6, "copart_r"), (3, "knn8"), (4, "knn8"), (5, "doc_line"), (4, "comin"), (3, "page_href2"), (4, "page_href2"), (4, "copart_full")):
    add(f"cf{k}_{g}", on(g, lambda g, k=k: cliques.count(g, k)), clique_sql(g, k))
add("cf4_list_copart_r", on("copart_r", lambda g: cliques.listing(g, 4, orient="id")), clique_sql("copart_r", 4, "{0} AS v0, {1} AS v1, {2} AS v2, {3} AS v3"))
for name, how in {"both": ("degree", True), "dag": ("degree", False), "prune": (None, True), "none": (None, False)}.items():
    add(f"abl_cf4_{name}", on("copart_r", lambda g, how=how: cliques.count(g, 4, method="engine", orient=how[0], eager=how[1])), clique_sql("copart_r", 4))
for c in connect.STRATEGIES:
    add(f"abl_conn_{c}", lambda spark, sf_dir, c=c: motifs.count(shared.fold(graphs.comin_rows(spark, sf_dir)), 4, method="engine", connectivity=c, fused=True), mc4_sql("comin"))

for g in ("copart_r", "knn8", "nextline", "copart_full", "tree", "custpart_top", "comin", "page_href2"):
    add(f"mc3_{g}", on(g, lambda g: motifs.count(g, 3), lists=g in graphs.LISTS), mc3_sql(g))
for g in ("copart_r", "comin", "custpart_top", "knn8", "tree", "copart_2"):
    add(f"mc4_{g}", on(g, lambda g: motifs.count(g, 4)), mc4_sql(g))
for how in ("two_step", "memo", "spectrum"):
    add(f"abl_mc_{how}", on("copart_r", lambda g, how=how: motifs.count(g, 4, how=how)), mc4_sql("copart_r"))
add("abl_mc_generic", on("comin", lambda g: motifs.count(g, 4, how="generic", method="engine")), mc4_sql("comin"))
add("abl_mat", on("comin", lambda g: motifs.count(g, 4, method="engine", materialize_candidates=True)), mc4_sql("comin"))
for k, g, sql in ((3, "copart_full", mc3_sql), (4, "nextline", mc4_sql)):
    add(f"mc{k}_auto_{g}", on(g, lambda g, k=k: motifs.count(g, k, method="auto")), sql(g))
add("mc5_comin", on("comin", lambda g: motifs.count(g, 5)))
add("mc3_list_comin", on("comin", lambda g: motifs.listing(g, 3).select(F.array_sort(F.array("v0", "v1", "v2")).cast("string").alias("vids"), F.bit_count("mask").cast("int").alias("edges"))),
    f"WITH e AS ({graphs.SQL['comin']}), r AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e) "
    "SELECT '[' || array_to_string(s, ', ') || ']' AS vids, CASE WHEN bool_or(closed) THEN 3 ELSE 2 END::INT AS edges FROM (SELECT list_sort([x.src, x.dst, y.dst]) AS s, "
    "EXISTS (SELECT 1 FROM r z WHERE z.src = x.dst AND z.dst = y.dst) AS closed FROM r x JOIN r y ON x.src = y.src AND x.dst < y.dst) GROUP BY s")


def _layout(g: PropertyGraph, layout: str, k: int):
    """Motifs with every level that grows stored in a layout and grown from it."""
    level, store = engine.mine_stored(g, AppSpec(fused=True), k, layout)
    if g.weights is None:
        quick = level.groupBy("mask").agg(F.count("*").alias("n"))
    else:
        quick = motifs.unfolded({size: store.get(size) for size in range(2, k)} | {k: level}, g, k)
    return motifs.every_pattern(motifs.classify(quick, k, "custom").groupBy("pattern").agg(F.sum("n").alias("n")), k)


for layout in levels.LAYOUTS:
    add(f"abl_layout_{layout}", on("copart_r", lambda g, layout=layout: _layout(g, layout, 3)), mc3_sql("copart_r"))
    add(f"abl_layout4_{layout}", lambda spark, sf_dir, layout=layout: _layout(shared.fold(graphs.comin_rows(spark, sf_dir)), layout, 4), mc4_sql("comin"))


def measure_layout_bytes(spark, sf_dir):
    """Bytes that each level takes in each layout, three and four vertices."""
    g, rows = graphs.load(spark, sf_dir, "comin"), []
    for layout in levels.LAYOUTS:
        _, store = engine.mine_stored(g, AppSpec(), 4, layout)
        rows += [(layout, size, store.bytes(size)) for size in (3, 4)]
    return spark.createDataFrame(rows, "layout string, size int, bytes long")


add("measure_layout_bytes", measure_layout_bytes)
add("op_overapprox_store", on("comin", others.overapproximation))

for label, sigmas in (("type", (100, 200, 250, 300)), ("brand", (10, 20, 30))):
    for s in sigmas:
        add(f"fsm3_{label}_s{s}", on("copart_r", lambda g, s=s: frequent.mine(g, 2, s), f"p_{label}"), fsm_sql("copart_r", f"p_{label}", 2, s))
for label, sigmas in (("type", (100, 200, 250)), ("brand", (10, 20))):
    for s in sigmas:
        add(f"fsm4_{label}_s{s}", on("copart_r", lambda g, s=s: frequent.mine(g, 3, s), f"p_{label}"), fsm_sql("copart_r", f"p_{label}", 3, s))
for edges, s in ((2, 200), (3, 250)):
    add(f"fsm{edges + 1}_engine_s{s}", on("copart_r", lambda g, n=edges, s=s: frequent.mine(g, n, s, plan="engine"), "p_type"), fsm_sql("copart_r", "p_type", edges, s))
for s in (20, 25, 30):
    add(f"fsm5_type_s{s}", on("copart_2", lambda g, s=s: four_edges(g, s), "p_type"), fsm_four_edges_sql("copart_2", "p_type", s))
add("fsm5_generic_s30", on("copart_2", lambda g: four_edges(g, 30, "generic"), "p_type"), fsm_four_edges_sql("copart_2", "p_type", 30))
add("b1_fsm5_type_s30", on("copart_2", lambda g: frequent_others.filter_process_frequent(g, 4, 30).where("n_edges = 4").select("n_edges", F.size(F.split(F.split("pattern", r"\|")[0], "-")).alias("n_vertices"), F.split("pattern", r"\|")[0].alias("labels"), "support"), "p_type"),
    fsm_four_edges_sql("copart_2", "p_type", 30))
add("fsm3_early_s200", on("copart_r", lambda g: frequent.mine(g, 2, 200, mode="early"), "p_type"), f"SELECT n_edges, pattern, 200::BIGINT AS support FROM ({fsm_sql('copart_r', 'p_type', 2, 200)})")
for mode in ("set", "bitmap", "udaf"):
    add(f"fsm3_support_{mode}", on("copart_r", lambda g, m=mode: frequent.mine(g, 2, 200, mode=m), "p_type"), fsm_sql("copart_r", "p_type", 2, 200))
add("fsm3_support_approx", on("copart_r", lambda g: frequent.mine(g, 2, 200, kind="mni_approx"), "p_type"))


def _at_least(g: PropertyGraph):
    d = frequent.domains(frequent.named(engine.seed(g, AppSpec(mode="edge"))))
    return support.mni_at_least(d, 250).select("pattern")


add("fsm_support_at_least", on("copart_r", _at_least, "p_type"), f"SELECT pattern FROM ({fsm_sql('copart_r', 'p_type', 1, 250)})")
add("fsm3_frequency", on("copart_r", lambda g: frequent_others.compiled_frequency(g, 2, 100), "p_type"),
    f"WITH e AS ({graphs.SQL['copart_r']}), l AS (SELECT p_partkey AS id, dense_rank() OVER (ORDER BY p_type) AS label FROM part), "
    "r AS (SELECT src, dst, a.label AS ls, b.label AS ld FROM (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e) JOIN l a ON a.id = src JOIN l b ON b.id = dst) "
    "SELECT * FROM (SELECT 1 AS n_edges, 'edge:' || least(ls, ld) || '-' || greatest(ls, ld) AS pattern, count(*)::BIGINT AS support FROM r WHERE src < dst GROUP BY 2 UNION ALL "
    "SELECT 2, 'wedge:' || x.ls || '-' || least(x.ld, y.ld) || '-' || greatest(x.ld, y.ld), count(*)::BIGINT FROM r x JOIN r y ON x.src = y.src AND x.dst < y.dst GROUP BY 2) WHERE support >= 100")

# -- baselines ---------------------------------------------------------------

add("b1_mc3", on("comin", lambda g: others.filter_process_motifs(g, 3)), mc3_sql("comin"))
add("b1_cf4", on("comin", lambda g: others.filter_process_cliques(g, 4)), clique_sql("comin", 4))
add("b2_cf4", on("copart_r", lambda g: others.relational_cliques(g, 4)), clique_sql("copart_r", 4))
add("b2_mc3", on("copart_r", lambda g: others.relational_motifs(g, 3)), mc3_sql("copart_r"))
add("b4_cf4", on("copart_r", lambda g: others.dfs_cliques(g, 4)), clique_sql("copart_r", 4))
add("b4_mc3", on("copart_r", lambda g: others.dfs_motifs(g, 3)), mc3_sql("copart_r"))
add("b4_mc4", on("comin", lambda g: others.dfs_motifs(g, 4)), mc4_sql("comin"))
add("b5_tc", on("copart_r", others.task_triangles), tc_sql("copart_r"))
add("b6_tc", on("copart_r", lambda g: others.compiled_count(g, "triangle").select(F.col("n").alias("triangles"))), tc_sql("copart_r"))
add("b6_cf5", on("copart_r", lambda g: others.compiled_count(g, "5-clique").select(F.col("n").alias("cliques"))), clique_sql("copart_r", 5))
add("b6_mc3", on("copart_r", lambda g: others.compiled_count(g, "wedge", True).unionByName(others.compiled_count(g, "triangle", True))), mc3_sql("copart_r"))


add("b6_mc4", on("copart_r", lambda g: others.compiled_motifs(g, ("4-clique", "diamond", "4-cycle", "tailed-triangle", "3-star", "4-path"))), mc4_sql("copart_r"))
for p in (10, 20, 50, 100):
    add(f"b2_cf4_p{p}", on("copart_r", lambda g, p=p: others.relational_cliques(g, 4, p)), clique_sql("copart_r", 4))
for s in (100, 200, 250, 300):
    add(f"b1_fsm3_type_s{s}", on("copart_r", lambda g, s=s: frequent_others.filter_process_frequent(g, 2, s), "p_type"), fsm_sql("copart_r", "p_type", 2, s))
    add(f"b2_fsm3_type_s{s}", on("copart_r", lambda g, s=s: frequent_others.relational_frequent(g, 2, s), "p_type"), fsm_sql("copart_r", "p_type", 2, s))
    add(f"b4_fsm3_type_s{s}", on("copart_r", lambda g, s=s: frequent_others.dfs_frequent(g, 2, s), "p_type"), fsm_sql("copart_r", "p_type", 2, s))
add("h1_tc", on("copart_r", others.hand_triangles), tc_sql("copart_r"))
add("h2_tc", on("copart_r", others.coloured_triangles), tc_sql("copart_r"))
add("h3_cf4", on("copart_r", lambda g: others.local_graph_cliques(g, 4)), clique_sql("copart_r", 4))
add("h3_cf5", on("doc_line", lambda g: others.local_graph_cliques(g, 5)), clique_sql("doc_line", 5))
add("h4_mc3", on("nextline", formula_motifs.count3), mc3_sql("nextline"))
add("h4_mc4", on("copart_r", formula_motifs.count4), mc4_sql("copart_r"))
add("h6_fsm3", on("copart_r", lambda g: others.recursive_frequent(g, 2, 250), "p_type"), fsm_sql("copart_r", "p_type", 2, 250))
add("h6_fsm4", on("copart_r", lambda g: others.recursive_frequent(g, 3, 290), "p_type"), fsm_sql("copart_r", "p_type", 3, 290))

# -- engine parts ------------------------------------------------------------

add("blocked_mc3", on("copart_r", lambda g: blocking.run(g, AppSpec(classify=lambda d, n: motifs.classify(d, n, "custom")), 3, blocks=3).select("pattern", F.col("support").cast("long").alias("n"))), mc3_sql("copart_r"))
for name, how in {"all": ("all", None), "last": ("last", None), "dag_all": ("all", "degree"), "dag_last": ("last", "degree")}.items():
    visits = {
        "all": "(SELECT sum(d * d)::BIGINT AS visits FROM d)",
        "last": "(SELECT sum(d.d)::BIGINT AS visits FROM e JOIN d ON d.id = e.dst)",
        "dag_all": "(SELECT sum(x.o + coalesce(y.o, 0))::BIGINT AS visits FROM o e JOIN out x ON x.src = e.src LEFT JOIN out y ON y.src = e.dst)",
        "dag_last": "(SELECT sum(y.o)::BIGINT AS visits FROM o e JOIN out y ON y.src = e.dst)",
    }[name]
    add(f"search_space_{name}", on("copart_r", lambda g, how=how: engine.level_stats(g, *how)),
        f"WITH e AS ({graphs.SQL['copart_r']}), d AS (SELECT id, count(*) AS d FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY id), "
        "o AS (SELECT CASE WHEN (x.d, x.id) < (y.d, y.id) THEN src ELSE dst END AS src, CASE WHEN (x.d, x.id) < (y.d, y.id) THEN dst ELSE src END AS dst FROM e JOIN d x ON x.id = e.src JOIN d y ON y.id = e.dst), "
        f"out AS (SELECT src, count(*) AS o FROM o GROUP BY src) SELECT * FROM {visits}")
add("op_inspect_offsets", on("copart_r", lambda g: planning.prefix_sum(planning.inspect(engine.seed(g, AppSpec()).select("v0", "v1"), 2, g, [0, 1]), ["v0", "v1"], "n_children")),
    f"WITH e AS ({graphs.SQL['copart_r']}), d AS (SELECT id, count(*) AS d FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY id) "
    "SELECT src AS v0, dst AS v1, x.d + y.d AS n_children, coalesce(sum(x.d + y.d) OVER (ORDER BY src, dst ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start_offset "
    "FROM e JOIN d x ON x.id = src JOIN d y ON y.id = dst")

# -- graph building ----------------------------------------------------------

for g in graphs.BUILDERS:
    add(f"graph_{g}", lambda spark, sf_dir, g=g: graphs.BUILDERS[g](spark, sf_dir), graphs.SQL[g])
    add(f"op_graph_stats_{g}", on(g, lambda g: g.stats()),
        f"WITH e AS ({graphs.SQL[g]}), d AS (SELECT id, count(*) AS d FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY id) "
        "SELECT count(*) AS n_vertices, (sum(d) // 2)::BIGINT AS n_edges, sum(d)::BIGINT AS n_arcs, (sum(d) / count(*))::DOUBLE AS avg_degree, max(d) AS max_degree, 0::BIGINT AS n_labels FROM d")
_D = f"WITH e AS ({graphs.SQL['copart_r']}), r AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e), d AS (SELECT src AS id, count(*) AS degree FROM r GROUP BY src) "
add("op_symmetrise", on("copart_r", lambda g: g.arcs), _D + "SELECT src, dst FROM r")
add("op_degree", on("copart_r", lambda g: g.degrees), _D + "SELECT id, degree FROM d")
add("op_degree_hist", on("copart_r", lambda g: g.degrees.groupBy("degree").agg(F.count("*").alias("n"))), _D + "SELECT degree, count(*) AS n FROM d GROUP BY degree")
_O = "SELECT CASE WHEN (x.degree, x.id) < (y.degree, y.id) THEN src ELSE dst END AS src, CASE WHEN (x.degree, x.id) < (y.degree, y.id) THEN dst ELSE src END AS dst FROM e JOIN d x ON x.id = e.src JOIN d y ON y.id = e.dst"
add("op_orient_degree", on("copart_r", lambda g: g.orient("degree")), _D + _O)
add("op_orient_id", on("copart_r", lambda g: g.orient("id")), _D + "SELECT src, dst FROM e")
add("op_adjacency", on("copart_r", lambda g: g.adjacency().select("id", F.concat_ws(",", F.transform("nbrs", lambda x: x.cast("string"))).alias("nbrs"))), _D + "SELECT src AS id, string_agg(dst::VARCHAR, ',' ORDER BY dst) AS nbrs FROM r GROUP BY src")
add("op_adjacency_chunks", on("copart_r", lambda g: g.adjacency(chunk=8).select("id", "chunk", F.size("nbrs").alias("n"))),
    _D + "SELECT src AS id, ((p - 1) // 8)::INT AS chunk, count(*)::INT AS n FROM (SELECT src, row_number() OVER (PARTITION BY src ORDER BY dst) AS p FROM r) GROUP BY 1, 2")
add("op_labels", lambda spark, sf_dir: graphs.part_labels(spark, sf_dir), "SELECT p_partkey AS id, dense_rank() OVER (ORDER BY p_type)::INT AS label FROM part")
add("op_filter_label", on("copart_r", lambda g: g.induced_by_label([1, 2]).edges, "p_type"),
    f"WITH e AS ({graphs.SQL['copart_r']}), l AS (SELECT p_partkey AS id, dense_rank() OVER (ORDER BY p_type) AS label FROM part) SELECT src, dst FROM e JOIN l a ON a.id = src JOIN l b ON b.id = dst WHERE a.label <= 2 AND b.label <= 2")
CORE_ROUNDS = 40


def core_sql(graph: str, k: int) -> str:
    """The k-core by rounds written out one after another; an error if they do not suffice."""
    text = f"WITH e0 AS ({graphs.SQL[graph]})"
    for i in range(CORE_ROUNDS):
        text += (
            f", d{i} AS MATERIALIZED (SELECT id FROM (SELECT src AS id FROM e{i} UNION ALL SELECT dst FROM e{i}) GROUP BY id HAVING count(*) >= {k})"
            f", e{i + 1} AS MATERIALIZED (SELECT src, dst FROM e{i} WHERE src IN (SELECT id FROM d{i}) AND dst IN (SELECT id FROM d{i}))"
        )
    same = f"(SELECT count(*) FROM e{CORE_ROUNDS - 1}) = (SELECT count(*) FROM e{CORE_ROUNDS})"
    return text + f" SELECT CASE WHEN {same} THEN src ELSE error('not reached') END AS src, dst FROM e{CORE_ROUNDS}"


add("op_core3", on("copart_r", lambda g: g.k_core(3)), core_sql("copart_r", 3))
add("op_wedges_by_vertex", on("copart_r", lambda g: g.wedges_by_vertex()), _D + "SELECT id, (degree * (degree - 1) // 2)::BIGINT AS wedges FROM d")
add("op_common_neighbours", on("copart_r", lambda g: connect.common_neighbours(g.edges, g)), _D + "SELECT e.src, e.dst, (SELECT count(*) FROM r x JOIN r y ON x.dst = y.dst WHERE x.src = e.src AND y.src = e.dst)::BIGINT AS n_common FROM e")
_T = _D.rstrip() + ", t AS (SELECT x.src AS a, x.dst AS b, y.dst AS c FROM e x JOIN e y ON y.src = x.src AND y.dst > x.dst JOIN e z ON z.src = x.dst AND z.dst = y.dst), tv AS (SELECT v AS id, count(*) AS triangles FROM (SELECT a AS v FROM t UNION ALL SELECT b FROM t UNION ALL SELECT c FROM t) GROUP BY v) "
add("op_triangles_per_vertex", on("copart_r", triangles.per_vertex), _T + "SELECT id, triangles FROM tv")
add("op_edge_support", on("copart_r", triangles.per_edge), _T + "SELECT src, dst, count(*) AS triangles FROM (SELECT a AS src, b AS dst FROM t UNION ALL SELECT a, c FROM t UNION ALL SELECT b, c FROM t) GROUP BY src, dst")
add("op_clustering_coeff", on("copart_r", triangles.local_coefficient), _T + "SELECT d.id, (coalesce(triangles, 0) / (degree * (degree - 1) // 2))::DOUBLE AS coefficient FROM d LEFT JOIN tv ON d.id = tv.id WHERE degree > 1")
add("op_dense_ids", lambda spark, sf_dir: dense_ids(graphs.table(spark, sf_dir, "part", ["p_brand"]), "p_brand"), "SELECT p_brand, row_number() OVER (ORDER BY p_brand) - 1 AS id FROM (SELECT DISTINCT p_brand FROM part)")
add("op_is_connected", on("copart_r", lambda g: connect.is_connected(g.edges.select("src", (F.col("dst") + 1).alias("dst")), "src", "dst", g)), _D + "SELECT src, dst + 1 AS dst, EXISTS (SELECT 1 FROM r WHERE r.src = e.src AND r.dst = e.dst + 1) AS connected FROM e")


def rmat_stats(spark, sf_dir):
    """A recursive-matrix graph with an edge drawn for each order, 20 arcs a vertex."""
    keys = graphs.table(spark, sf_dir, "orders", ["o_orderkey"])
    scale = max(1, round(math.log2(max(2, keys.count() / 10))))
    return PropertyGraph.of(graphs.rmat(spark, scale, keys=keys)).stats()


add("op_rmat_stats", rmat_stats)
add("op_label_dictionary", lambda spark, sf_dir: label_dictionary(graphs.table(spark, sf_dir, "customer", ["c_custkey", "c_mktsegment"]), "c_custkey", "c_mktsegment")[1], "SELECT row_number() OVER (ORDER BY s)::INT AS label, s AS label_text FROM (SELECT DISTINCT c_mktsegment AS s FROM customer)")


# -- worked examples: as on hand-made graphs in the tests, here around the least edge of a table's graph ------


def tiny(spark, pairs, labels=None) -> PropertyGraph:
    lab = spark.createDataFrame(labels, "id long, label int") if labels else None
    return PropertyGraph(spark.createDataFrame(pairs, "src long, dst long"), lab)


def least_edge(g: PropertyGraph):
    return engine.seed(g, AppSpec()).orderBy("v0", "v1").limit(1)


def grown_once(g: PropertyGraph, seeds):
    """Children of seed edges."""
    return engine.grow_vertices(seeds, 2, g, AppSpec()).select(F.array_sort(F.array("v0", "v1", "v2")).cast("string").alias("vids"))


def kept_orders(g: PropertyGraph, seeds=None):
    """4-vertex sets, each in the one order that growth keeps."""
    return engine.mine(g, AppSpec(), 4, seeds=seeds).levels[4].select(F.array("v0", "v1", "v2", "v3").cast("string").alias("vids"))


def chain_support(g: PropertyGraph):
    return frequent.mine(g, 2, 1).where("pattern = 'wedge:2-1-3'").select("pattern", "support")


def folded(level):
    """Three-vertex embeddings folded by their pattern."""
    return engine.aggregate(level, 3, AppSpec(classify=lambda d, n: motifs.classify(d, n, "custom")))


_A = f"WITH e AS ({graphs.SQL['copart_r']}), r AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e), s AS (SELECT src AS v0, dst AS v1 FROM e ORDER BY 1, 2 LIMIT 1), "
_A += "g AS (SELECT DISTINCT v0, v1, r.dst AS v2 FROM s JOIN r ON r.src IN (v0, v1) WHERE r.dst > v0 AND r.dst <> v1 AND (r.dst > v1 OR (v0, r.dst) NOT IN (SELECT src, dst FROM r))) "
add("example_grow", on("copart_r", lambda g: grown_once(g, least_edge(g))), _A + "SELECT '[' || array_to_string(list_sort([v0, v1, v2]), ', ') || ']' AS vids FROM g")
add("example_auto", on("copart_r", lambda g: kept_orders(g, least_edge(g))),
    _A + "SELECT DISTINCT '[' || array_to_string([v0, v1, v2, u.dst], ', ') || ']' AS vids FROM g JOIN r u ON u.src IN (v0, v1, v2) WHERE u.dst > v0 AND u.dst NOT IN (v1, v2) "
    "AND CASE WHEN (v0, u.dst) IN (SELECT src, dst FROM r) THEN u.dst > v1 AND u.dst > v2 WHEN (v1, u.dst) IN (SELECT src, dst FROM r) THEN u.dst > v2 ELSE true END")
add("example_mni", on("copart_r", chain_support, "p_type"), f"SELECT pattern, support FROM ({fsm_sql('copart_r', 'p_type', 2, 1)}) WHERE pattern = 'wedge:2-1-3'")
add("example_reduce", on("copart_r", lambda g: folded(motifs.listing(g, 3))), f"SELECT pattern, n AS support FROM ({mc3_sql('copart_r')}) WHERE n > 0")


# -- more of the surroundings -----------------------------------------------------


def sink_listing(fmt: str):
    """Write a clique listing in a format and read it back."""

    def query(spark, sf_dir):
        listed = cliques.listing(graphs.load(spark, sf_dir, "copart_r"), 4, orient="id")
        path = relational.round_trip(listed, fmt)
        return spark.read.schema("v0 long, v1 long, v2 long, v3 long").format(fmt).load(path)

    return query


for fmt in ("parquet", "csv", "json"):
    add(f"op_sink_listing_{fmt}", sink_listing(fmt), clique_sql("copart_r", 4, "{0} AS v0, {1} AS v1, {2} AS v2, {3} AS v3"))


def table_catalog(spark, sf_dir):
    """Views of a registered graph with their row counts."""
    sqlsurface.register(spark, graphs.load(spark, sf_dir, "comin"), "gc")
    out = None
    for view in ("gc_edges", "gc_arcs", "gc_oriented", "gc_degrees"):
        part = spark.sql(f"SELECT '{view}' AS view, count(*) AS n FROM {view}")
        out = part if out is None else out.unionByName(part)
    return out


add("op_table_catalog", table_catalog, f"WITH e AS ({graphs.SQL['comin']}) SELECT 'gc_edges' AS view, count(*) AS n FROM e UNION ALL SELECT 'gc_arcs', 2 * count(*) FROM e UNION ALL SELECT 'gc_oriented', count(*) FROM e "
    "UNION ALL SELECT 'gc_degrees', count(*) FROM (SELECT src FROM e UNION SELECT dst FROM e)")
add("op_normalise", lambda spark, sf_dir: relational_pairs(spark, sf_dir), "SELECT DISTINCT least(l_partkey, l_suppkey) AS src, greatest(l_partkey, l_suppkey) AS dst FROM lineitem WHERE l_partkey <> l_suppkey")
add("op_map_arrow", on("comin", lambda g: connect.position_bits(g.edges.select(F.col("src").alias("v0"), F.col("dst").alias("u")), 1, g, "binary").select("v0", "u", "bits")), f"SELECT src AS v0, dst AS u, 1::INT AS bits FROM ({graphs.SQL['comin']})")
add("op_apply_group", lambda spark, sf_dir: others.local_graph_triangles(graphs.comin_rows(spark, sf_dir)), clique_sql("comin", 3))
add("op_udaf_mni", on("copart_r", lambda g: support.mni(frequent.domains(frequent.named(engine.seed(g, AppSpec(mode="edge")))), "udaf"), "p_type"), f"SELECT pattern, support FROM ({fsm_sql('copart_r', 'p_type', 1, 0)})")
add("op_topk_patterns", on("copart_r", lambda g: relational.top_k(frequent.mine(g, 2, 200), [F.desc("support"), "pattern"], 10), "p_type"), f"SELECT * FROM ({fsm_sql('copart_r', 'p_type', 2, 200)}) ORDER BY support DESC, pattern LIMIT 10")


def relational_pairs(spark, sf_dir):
    from .graph import normalise

    return normalise(graphs.table(spark, sf_dir, "lineitem", ["l_partkey", "l_suppkey"]), "l_partkey", "l_suppkey")


# -- measures ------------------------------------------------------------------


def measure_speedup(spark, sf_dir):
    """Seconds of the engine and of baselines on the same work, and baseline seconds over engine seconds; last the geometric mean."""
    pairs = [
        ("tc", "tc_copart_r", "b5_tc"), ("tc", "tc_copart_r", "h2_tc"), ("cf4", "cf4_copart_r", "b2_cf4"), ("cf4", "cf4_copart_r", "h3_cf4"), ("cf4", "cf4_copart_r", "b4_cf4"),
        ("mc3", "mc3_copart_r", "b2_mc3"), ("mc3", "mc3_copart_r", "b4_mc3"), ("fsm3", "fsm3_type_s200", "b2_fsm3_type_s200"), ("fsm3", "fsm3_type_s200", "b1_fsm3_type_s200"),
    ]
    took = {n: measures.time_app(lambda n=n: QUERIES[n](spark, sf_dir), 1).seconds for n in dict.fromkeys(x for _, a, b in pairs for x in (a, b))}
    rows = [(work, b, round(took[a], 3), round(took[b], 3), round(took[b] / took[a], 3)) for work, a, b in pairs]
    mean = measures.geo_speedup({b: took[a] for _, a, b in pairs}, {b: took[b] for _, _, b in pairs})
    return spark.createDataFrame([*rows, ("all", "geometric mean", None, None, round(mean, 3))], "work string, baseline string, engine_sec double, baseline_sec double, speedup double")


def measure_io(spark, sf_dir):
    """Bytes scanned, shuffled and spilled by an application: what stands in for the counters of a memory hierarchy."""
    rows = []
    for name in ("tc_copart_r", "cf4_copart_r", "mc3_copart_r", "mc4_copart_r", "fsm3_type_s200"):
        rows.append((name, *(int(x) for x in measures.io_of(spark, lambda n=name: QUERIES[n](spark, sf_dir)).values())))
    return spark.createDataFrame(rows, "query string, read_bytes long, shuffle_write_bytes long, shuffle_read_bytes long, memory_spill_bytes long, disk_spill_bytes long")


def measure_complexity(spark, sf_dir):
    """Worst-case work of growing the co-return graph to 3, 4 and 5 vertices."""
    row = graphs.load(spark, sf_dir, "copart_r").stats().first()
    return spark.createDataFrame([(k, round(math.log10(planning.upper_bound(row["n_vertices"], k, row["max_degree"])), 6)) for k in (3, 4, 5)], "k int, log10_work double")


def measure_level_rows(spark, sf_dir):
    """Rows of each level of the enumeration, two to four vertices."""
    g = graphs.load(spark, sf_dir, "comin")
    return spark.createDataFrame([(s["size"], s["rows"]) for s in engine.mine(g, AppSpec(), 4, collect_stats=True).stats], "size int, n long")


def measure_sketch_error(spark, sf_dir):
    """Largest relative error of sketched supports against exact ones."""
    g = graphs.load(spark, sf_dir, "copart_r", "p_type")
    d = frequent.domains(frequent.named(engine.seed(g, AppSpec(mode="edge"))))
    both = support.mni(d).join(support.mni(d, "approx").withColumnRenamed("support", "guess"), "pattern")
    return both.agg(F.max(F.abs(F.col("guess") - F.col("support")) / F.col("support")).alias("error"))


add("measure_speedup", measure_speedup)
add("measure_io", measure_io)
add("measure_complexity", measure_complexity, _D + "SELECT k::INT AS k, round(log10(n ** (k - 1) * k * k * m * greatest(1.0, log2(greatest(m, 2))) * exp(sqrt(k * ln(k)))), 6) AS log10_work FROM (SELECT count(*)::DOUBLE AS n, max(degree)::DOUBLE AS m FROM d), (SELECT unnest([3, 4, 5]) AS k)")
add("measure_level_rows", measure_level_rows, f"WITH c AS ({mc3_sql('comin')}), d AS ({mc4_sql('comin')}) SELECT 2::INT AS size, (SELECT count(*) FROM ({graphs.SQL['comin']})) AS n UNION ALL SELECT 3, (SELECT sum(n)::BIGINT FROM c) UNION ALL SELECT 4, (SELECT sum(n)::BIGINT FROM d)")
add("measure_sketch_error", measure_sketch_error)

for part in (relational, sqlsurface, events):
    for name, (query, sql) in part.queries().items():
        add(name, query, sql)

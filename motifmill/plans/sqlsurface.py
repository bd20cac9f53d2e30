"""Graphs as temporary views, methods as SQL text, and a table function for cliques."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..graph import PropertyGraph
from ..sources import graphs


def register(spark: SparkSession, graph: PropertyGraph, prefix: str = "gp") -> None:
    """Views <prefix>_edges, _arcs, _oriented, _degrees and _labelled (if labels are given)."""
    graph.edges.createOrReplaceTempView(f"{prefix}_edges")
    graph.arcs.createOrReplaceTempView(f"{prefix}_arcs")
    graph.orient("degree").createOrReplaceTempView(f"{prefix}_oriented")
    graph.degrees.createOrReplaceTempView(f"{prefix}_degrees")
    if graph.labels is not None:
        graph.labelled_edges().createOrReplaceTempView(f"{prefix}_labelled")


#: Spark SQL over the gp_* views.
TEXTS = {
    "sql_tc": "SELECT count(*) AS triangles FROM gp_oriented a JOIN gp_oriented b ON a.dst = b.src WHERE EXISTS (SELECT 1 FROM gp_oriented c WHERE c.src = a.src AND c.dst = b.dst)",
    "sql_cf4": "SELECT count(*) AS cliques FROM gp_oriented a JOIN gp_oriented b ON b.src = a.dst JOIN gp_oriented c ON c.src = a.src AND c.dst = b.dst JOIN gp_oriented d ON d.src = b.dst "
    "JOIN gp_oriented e ON e.src = a.src AND e.dst = d.dst JOIN gp_oriented f ON f.src = a.dst AND f.dst = d.dst",
    "sql_mc3": "WITH t AS (SELECT count(*) AS n FROM gp_oriented a JOIN gp_oriented b ON a.dst = b.src JOIN gp_oriented c ON c.src = a.src AND c.dst = b.dst), w AS (SELECT sum(degree * (degree - 1) div 2) AS n FROM gp_degrees) "
    "SELECT 'triangle' AS pattern, t.n AS n FROM t UNION ALL SELECT 'wedge', w.n - 3 * t.n FROM w CROSS JOIN t",
    "sql_fsm_edge": "SELECT pattern, min(n) AS support FROM (SELECT concat('edge:', least(la, lb), '-', greatest(la, lb)) AS pattern, orbit, count(DISTINCT vid) AS n FROM (SELECT la, lb, stack(2, la, src, lb, dst) AS (orbit, vid) FROM gp_labelled) GROUP BY 1, 2) GROUP BY pattern",
}


def _text(name: str, label: str | None = None):
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        register(spark, graphs.load(spark, sf_dir, "copart_r", label))
        return spark.sql(TEXTS[name])

    return query


def clique_rows(spark: SparkSession):
    """Table function: rows (v0, v1, v2) of the triangles in a partition of ego edges."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="v0 long, v1 long, v2 long")
    class CliqueRows:
        def __init__(self):
            self.seed, self.out = None, {}

        def eval(self, row):
            self.seed = row["src"]
            self.out.setdefault(row["x"], set()).add(row["y"])

        def terminate(self):
            for x, near in self.out.items():
                for y in near:
                    yield self.seed, x, y

    spark.udtf.register("clique_rows", CliqueRows)
    return CliqueRows


def udtf_triangles(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = graphs.load(spark, sf_dir, "comin")
    o = g.orient("id")
    wedge = o.select("src", F.col("dst").alias("x")).join(o.select("src", F.col("dst").alias("y")), "src")
    ego = wedge.join(o.select(F.col("src").alias("x"), F.col("dst").alias("y")), ["x", "y"], "left_semi")
    ego.createOrReplaceTempView("gp_ego")
    clique_rows(spark)
    return spark.sql("SELECT v0, v1, v2 FROM clique_rows(TABLE(SELECT src, x, y FROM gp_ego) PARTITION BY src)")


def cycles4_bipartite(spark: SparkSession, sf_dir: str) -> DataFrame:
    """4-cycles of the customer-part graph: choices of two common parts of two customers."""
    g = graphs.load(spark, sf_dir, "custpart_top")
    e = g.edges
    both = e.select(F.col("dst").alias("p"), F.col("src").alias("a")).join(e.select(F.col("dst").alias("p"), F.col("src").alias("b")), "p").where("a < b").groupBy("a", "b").agg(F.count("*").alias("c"))
    return both.agg(F.coalesce(F.sum(F.expr("c * (c - 1) div 2")), F.lit(0)).alias("cycles"))


def copart_strength(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of parts with the number of orders that hold both, the 100 strongest."""
    pairs = graphs._pairs_on(graphs.table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey"]), "l_orderkey", "l_partkey")
    return pairs.groupBy("src", "dst").agg(F.count("*").alias("n_orders")).orderBy(F.desc("n_orders"), "src", "dst").limit(100)


def queries() -> dict:
    g = graphs.SQL["copart_r"]
    e = f"WITH e AS ({g}), "
    tri = "e x JOIN e y ON y.src = x.src AND y.dst > x.dst JOIN e z ON z.src = x.dst AND z.dst = y.dst"
    oracle = {
        "sql_tc": f"WITH e AS ({g}) SELECT count(*) AS triangles FROM {tri}",
        "sql_cf4": f"WITH e AS ({g}) SELECT count(*) AS cliques FROM {tri} JOIN e u ON u.src = x.src AND u.dst > y.dst JOIN e v ON v.src = x.dst AND v.dst = u.dst JOIN e w ON w.src = y.dst AND w.dst = u.dst",
        "sql_mc3": e + f"t AS (SELECT count(*) AS n FROM {tri}), w AS (SELECT sum(d * (d - 1) // 2) AS n FROM (SELECT count(*) AS d FROM (SELECT src AS v FROM e UNION ALL SELECT dst FROM e) GROUP BY v)) "
        "SELECT 'triangle' AS pattern, n::BIGINT AS n FROM t UNION ALL SELECT 'wedge', (w.n - 3 * t.n)::BIGINT FROM w, t",
        "sql_fsm_edge": e + "l AS (SELECT p_partkey AS id, dense_rank() OVER (ORDER BY p_type) AS label FROM part), r AS (SELECT src, dst, a.label AS ls, b.label AS ld FROM (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e) "
        "JOIN l a ON a.id = src JOIN l b ON b.id = dst) SELECT 'edge:' || ls || '-' || ld AS pattern, least(count(DISTINCT src), count(DISTINCT dst)) AS support FROM r WHERE ls <= ld GROUP BY 1",
    }
    out = {name: (_text(name, "p_type" if name == "sql_fsm_edge" else None), oracle[name]) for name in TEXTS}
    c = graphs.SQL["comin"]
    out["op_udtf_cliques"] = (udtf_triangles, f"WITH e AS ({c}) SELECT x.src AS v0, x.dst AS v1, y.dst AS v2 FROM {tri}")
    out["op_cycle4_bipartite"] = (cycles4_bipartite, f"WITH e AS ({graphs.SQL['custpart_top']}) SELECT coalesce(sum(n * (n - 1) // 2), 0)::BIGINT AS cycles FROM (SELECT count(*) AS n FROM e x JOIN e y ON x.dst = y.dst AND x.src < y.src GROUP BY x.src, y.src)")
    pair = "(SELECT DISTINCT l_orderkey AS k, l_partkey AS n FROM lineitem)"
    out["op_copart_strength"] = (copart_strength, f"SELECT x.n AS src, y.n AS dst, count(*) AS n_orders FROM {pair} x JOIN {pair} y ON x.k = y.k AND x.n < y.n GROUP BY 1, 2 ORDER BY 3 DESC, 1, 2 LIMIT 100")
    return out

"""Headline timings: python bench.py prints one JSON line.

Graphs are built and materialised first; then each query is timed on its own, best
comparable to the published mining times, which exclude preprocessing.  BENCH_SF_DIR and
BENCH_CPUS choose the data and the cores; BENCH_REPEATS the runs that are averaged.
"""

from __future__ import annotations

import json
import os
import sys
import time

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
REPEATS = int(os.environ.get("BENCH_REPEATS", "2"))


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    from motifmill.apps import cliques, frequent, motifs, triangles
    from motifmill.baselines import formula_motifs, frequent_others, others
    from motifmill.sources import graphs

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("motifmill-bench").config("spark.driver.memory", "16g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.shuffle.partitions", CPUS).config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    began = time.perf_counter()
    g = graphs.load(spark, SF_DIR, "copart_r", "p_type")
    full = graphs.load(spark, SF_DIR, "copart_full")
    line = graphs.load(spark, SF_DIR, "nextline")
    docs = graphs.load(spark, SF_DIR, "doc_line")
    for x in (g, full, line, docs):
        x.edges.count()
    build = time.perf_counter() - began
    sigma = [int(s) for s in os.environ.get("BENCH_SIGMAS", "1000,2000,2500").split(",")]
    work = {
        "tc_copart_r": lambda: triangles.count(g), "tc_copart_full": lambda: triangles.count(full), "tc_nextline": lambda: triangles.count(line), "tc_doc_line": lambda: triangles.count(docs),
        "cf3_copart_r": lambda: cliques.count(g, 3), "cf4_copart_r": lambda: cliques.count(g, 4), "cf5_copart_r": lambda: cliques.count(g, 5),
        "cf4_copart_full": lambda: cliques.count(full, 4), "cf5_doc_line": lambda: cliques.count(docs, 5),
        "mc3_copart_r": lambda: motifs.count(g, 3), "mc3_copart_full": lambda: motifs.count(full, 3), "mc3_nextline": lambda: motifs.count(line, 3), "mc4_copart_r": lambda: motifs.count(g, 4),
        "h4_formula_mc3_copart_full": lambda: formula_motifs.count(full, 3), "h4_formula_mc4_copart_r": lambda: formula_motifs.count(g, 4),
        **{f"fsm3_type_s{s}": (lambda s=s: frequent.mine(g, 2, s)) for s in sigma}, "fsm4_type_s2000": lambda: frequent.mine(g, 3, 2000),
        "b4_dfs_cf4_copart_r": lambda: others.dfs_cliques(g, 4), "h3_local_cf4_copart_r": lambda: others.local_graph_cliques(g, 4), "h2_coloured_tc_copart_r": lambda: others.coloured_triangles(g),
        "h1_hand_tc_copart_r": lambda: others.hand_triangles(g), "b2_relational_fsm3_type_s2000": lambda: frequent_others.relational_frequent(g, 2, 2000), "b6_compiled_tc_copart_r": lambda: others.compiled_count(g, "triangle"),
    }
    only = set(sys.argv[1:])
    seconds = {}
    for name, fn in work.items():
        if only and name not in only:
            continue
        fn().agg(F.count("*")).collect()  # warm
        runs = []
        for _ in range(REPEATS):
            t = time.perf_counter()
            fn().collect()
            runs.append(time.perf_counter() - t)
        seconds[name] = round(sum(runs) / len(runs), 3)
        print(name, seconds[name], file=sys.stderr, flush=True)
    print(json.dumps({"metric": "total seconds of the headline mining queries", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "graph_build_sec": round(build, 3), "sf": SF_DIR.rstrip("/").rsplit("sf", 1)[-1], "cpus": int(CPUS)}))


if __name__ == "__main__":
    main()

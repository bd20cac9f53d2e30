"""Weak scaling: recursive-matrix graphs of growing size, times relative to the smallest.
python benchmarks/weak.py [scales...]"""

import json
import os
import sys

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def main() -> None:
    from pyspark.sql import SparkSession

    from motifmill.apps import cliques, motifs, triangles
    from motifmill.graph import PropertyGraph
    from motifmill.measures import time_app
    from motifmill.sources import graphs

    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", cpus).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    out = {}
    for scale in map(int, sys.argv[1:] or ["10", "11", "12", "13", "14", "15"]):
        g = PropertyGraph.of(graphs.rmat(spark, scale))
        row = {"edges": g.edges.count(), "tc": time_app(lambda: triangles.count(g), 2).seconds, "cf4": time_app(lambda: cliques.count(g, 4), 2).seconds, "mc3": time_app(lambda: motifs.count(g, 3, method="auto"), 2).seconds}
        out[scale] = {k: round(v, 3) for k, v in row.items()}
        print(scale, out[scale], file=sys.stderr, flush=True)
    first = next(iter(out.values()))
    relative = {s: {k: round(v / first[k], 2) for k, v in row.items()} for s, row in out.items()}
    print(json.dumps({"metric": "weak scaling on recursive-matrix graphs", "unit": "sec", "scales": out, "relative": relative}))


if __name__ == "__main__":
    main()

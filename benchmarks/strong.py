"""Strong scaling: the same work on 1, 2, 4, ... cores.  python benchmarks/strong.py [cores...]

Each core count runs in a process of its own, since a session keeps its master."""

import json
import os
import subprocess
import sys

CODE = """
import json, sys, time
sys.path.insert(0, {root!r})
from pyspark.sql import SparkSession
n = int(sys.argv[1])
spark = SparkSession.builder.master(f"local[{{n}}]").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", str(max(4, n))).getOrCreate()
spark.sparkContext.setLogLevel("ERROR")
from motifmill.apps import cliques, frequent, motifs, triangles
from motifmill.measures import time_app
from motifmill.sources import graphs
g = graphs.load(spark, {sf!r}, "copart_r", "p_type")
work = {{"tc": lambda: triangles.count(g), "cf4": lambda: cliques.count(g, 4), "mc3": lambda: motifs.count(g, 3), "fsm3": lambda: frequent.mine(g, 2, 2500)}}
print(json.dumps({{k: round(time_app(f, 2).seconds, 3) for k, f in work.items()}}))
"""


def main() -> None:
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    out = {}
    for n in map(int, sys.argv[1:] or ["1", "2", "4", "8"]):
        done = subprocess.run([sys.executable, "-c", CODE.format(root=root, sf=sf), str(n)], capture_output=True, text=True, timeout=1800)
        out[n] = json.loads(done.stdout.strip().splitlines()[-1])
        print(n, out[n], file=sys.stderr, flush=True)
    print(json.dumps({"metric": "strong scaling", "unit": "sec", "cores": out}))


if __name__ == "__main__":
    main()

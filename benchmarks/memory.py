"""Peak resident memory of each application, in a process of its own."""

import json
import os
import subprocess
import sys

CODE = """
import json, sys
sys.path.insert(0, {root!r})
from pyspark.sql import SparkSession
spark = SparkSession.builder.master("local[4]").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", "8").getOrCreate()
spark.sparkContext.setLogLevel("ERROR")
from motifmill.apps import cliques, frequent, motifs, triangles
from motifmill.measures import peak_resident_mb
from motifmill.sources import graphs
g = graphs.load(spark, {sf!r}, "copart_r", "p_type")
work = {{"build": lambda: g.edges, "tc": lambda: triangles.count(g), "cf4": lambda: cliques.count(g, 4), "mc3": lambda: motifs.count(g, 3), "fsm3": lambda: frequent.mine(g, 2, 2500)}}
work[sys.argv[1]]().count()
print(round(peak_resident_mb()))
"""


def main() -> None:
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    out = {}
    for name in sys.argv[1:] or ["build", "tc", "cf4", "mc3", "fsm3"]:
        done = subprocess.run([sys.executable, "-c", CODE.format(root=root, sf=sf), name], capture_output=True, text=True, timeout=900)
        out[name] = int(done.stdout.strip().splitlines()[-1])
    print(json.dumps({"metric": "peak resident memory", "unit": "MB", "apps": out}))


if __name__ == "__main__":
    main()

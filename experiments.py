"""The measured experiments: methods x representations x cores, steps, sorting, sampling and CPU time, as printed tables.

python experiments.py [SF_DIR [GRAPH [CORES ...]]]. Each number of cores has a session of its own (local[n]), one after
the other; on a cluster run the part of one() there with that many cores. Figures go to standard output as JSON lines.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys


def one(sf_dir: str, graph: str, cores: int, repeats: int) -> None:
    """All runs with this number of cores, a JSON line for each."""
    from pyspark.sql import SparkSession

    from turnwise.plans import runs
    from turnwise.sources import workloads

    spark = (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", max(8, cores))
        .config("spark.ui.enabled", "false")
        .config("spark.driver.memory", "12g")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    g = runs.settled(workloads.GRAPHS[graph](spark, sf_dir))
    whole = runs.run_table(spark, graph, g, repeats=repeats)
    steps = runs.run_table(spark, graph, g, repeats=repeats, forms=("row", "column"), steps=True)
    for r in whole.unionByName(steps).collect():
        print(json.dumps(r.asDict()), flush=True)


def main() -> None:
    sf_dir = sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.1"
    graph = sys.argv[2] if len(sys.argv) > 2 else "word_successor"
    cores = [int(x) for x in sys.argv[3:]] or [1, 2, 4, 8]
    rows = []
    for n in cores:
        out = subprocess.run([sys.executable, __file__, "--one", sf_dir, graph, str(n)], capture_output=True, text=True, check=True).stdout
        rows += [json.loads(x) for x in out.splitlines() if x.startswith("{")]
    for r in rows:
        print(json.dumps(r))

    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    from turnwise.plans import measures, runs

    spark = SparkSession.builder.master("local[2]").config("spark.ui.enabled", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    table = spark.createDataFrame(rows, runs.RUN_SCHEMA).cache()
    most = table.where((F.col("cores") == max(cores)) & (F.col("step") == "all"))
    steps = table.where((F.col("cores") == max(cores)) & (F.col("step") != "all"))
    speedups = measures.speedup_table(most)
    tables = {
        "speedup": speedups,
        "summary": measures.speedup_summary(speedups),
        "losses": measures.loss_summary(speedups),
        "edges_per_second": measures.edges_per_second(most),
        "cpu": runs.cpu_reduction(most),
        "efficiency": measures.parallel_efficiency(table.where("step = 'all' AND representation = 'row'"), min(cores)),
        "steps": runs.step_shares(steps),
        "sorting": runs.sort_times(steps),
        "sampling": steps.where("step = 'sample'").select("graph", "representation", "seconds"),
    }
    for name, df in tables.items():
        for r in df.collect():
            print(json.dumps({"table": name} | r.asDict()))


if __name__ == "__main__":
    if sys.argv[1:2] == ["--one"]:
        one(sys.argv[2], sys.argv[3], int(sys.argv[4]), int(os.environ.get("REPEATS", "3")))
    else:
        main()

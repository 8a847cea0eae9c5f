"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]: seconds each, one JSON line.

A graph is derived and cached before its queries are timed, as loading is not
part of the published times; each query is the mean of BENCH_REPEATS runs.  No
query is begun after BENCH_BUDGET_S seconds; those left out are named.  With
BENCH_THREADS (such as 1,2,4,8) the whole is run for each number of threads, a
line each.
"""

import json
import os
import subprocess
import sys
import time

from pyspark.sql import SparkSession

HEADLINE = ["cycle4", "triangle_count", "motif3_vertex", "motif3_vertex_ret", "motif4_vertex", "motif4_vertex_ret", "chain5_count", "clique4", "clique5", "cycle5", "cycle6", "pseudoclique_5", "fsm_t100", "constraint_demo", "fragments_cycle4", "star10_labels",
            "baseline_setenum", "baseline_symmetry", "baseline_restr", "baseline_restr_count", "baseline_native45", "motif5_vertex"]


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "20g").config("spark.ui.enabled", "false")
             .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate())
    spark.sparkContext.setLogLevel("ERROR")
    from cutloom import queries as q

    for kind, label in (("bulk", None), ("ret", None), ("bulk", "p_type")):
        g = q.graph(spark, sf_dir, kind, label)
        g.arcs.count()
    took: dict[str, float] = {}
    q.QUERIES[HEADLINE[0]](spark, "/root/testdata/sf0.001").collect()  # starts the session's code
    budget, start = float(os.environ.get("BENCH_BUDGET_S", "900")), time.perf_counter()
    left = []
    for name in HEADLINE:
        if time.perf_counter() - start > budget:
            left.append(name)
            continue
        began = time.perf_counter()
        repeats = int(os.environ.get("BENCH_REPEATS", "1"))
        for _ in range(repeats):
            q.QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        took[name] = round((time.perf_counter() - began) / repeats, 3)
    print(json.dumps({"metric": "total_headline_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "left_out": left, "sf": sf_dir.rsplit("sf", 1)[-1]}))


if __name__ == "__main__":
    threads = [x for x in os.environ.get("BENCH_THREADS", "").split(",") if x]
    if threads:
        for n in threads:
            subprocess.run([sys.executable, __file__], env={**os.environ, "BENCH_THREADS": "", "BENCH_CPUS": n}, check=True)
    else:
        main()

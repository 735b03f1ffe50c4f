"""Experiments on census methods: seconds (median of runs), CPU utilisation and, for a trace, utilisation by interval; one JSON line a case.

python bench_sweep.py cores [graph:method,..]           strong scaling, cores as 1,2,4,8; one process a core count
python bench_sweep.py 8 trace:graph:method              utilisation in intervals of a second (ten seconds are one or two points at these sizes)
Methods: scalable, join, set, merge, outer, weighted, shared (one census vector), matrix, static, dynamic, guided (hand-out of task units).
$BENCH_SF_DIR is the data, $BENCH_RUNS the timed runs after one warm-up at sf0.01."""

import glob
import json
import os
import statistics
import subprocess
import sys
import tempfile
import time

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
RUNS = int(os.environ.get("BENCH_RUNS", "3"))
CASES = "social:scalable,social:merge,social:outer,citation:scalable,citation:merge,web:scalable,web:merge,traffic:scalable,traffic:merge"


def methods() -> dict:
    from triadspark.operators import census as C

    edge = lambda **k: lambda g: C.census_edge_driven(g, **k)
    units = lambda n: lambda g: C.census_edge_driven(g, "merge", parts=n * int(g.dyads.sparkSession.sparkContext.defaultParallelism))
    return {"scalable": C.census_scalable, "matrix": C.census_matrix, "join": edge(union="join"), "set": edge(union="set"), "merge": edge(union="merge"), "outer": edge(union="merge", balance="outer", slots=1),
            "weighted": edge(union="merge", balance="weighted"), "shared": edge(union="merge", slots=1), "static": units(1), "dynamic": units(16), "guided": edge(union="merge", balance="weighted", slots=64)}


def cpu_between(log: str, a: float, b: float) -> float:
    cpu = 0.0
    with open(log) as f:
        for line in f:
            e = json.loads(line) if '"SparkListenerTaskEnd"' in line else None
            if e and e.get("Task Metrics") and a * 1000 <= e["Task Info"]["Launch Time"] <= b * 1000:
                cpu += e["Task Metrics"]["Executor CPU Time"] / 1e9
    return cpu


def one(cores: int, cases: list[str]) -> None:
    from pyspark.sql import SparkSession

    from triadspark.plans.registry import GRAPHS
    from triadspark.sources.store import event_log_utilisation
    from triadspark.sources.workloads import word_graph

    log = tempfile.mkdtemp()
    conf = {"spark.sql.shuffle.partitions": str(2 * cores), "spark.driver.memory": "8g", "spark.ui.enabled": "false", "spark.eventLog.enabled": "true", "spark.eventLog.dir": log, "spark.eventLog.compress": "false",
            "spark.eventLog.rolling.enabled": "false", "spark.checkpoint.dir": tempfile.mkdtemp(prefix="sweep-shared-")}
    b = SparkSession.builder.master(f"local[{cores}]")
    for k, v in conf.items():
        b = b.config(k, v)
    spark = b.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    run, graphs = methods(), GRAPHS | {"words": word_graph}
    small = os.path.join(os.path.dirname(SF.rstrip("/")), "sf0.01")
    path = lambda: max(glob.glob(log + "/local*"), key=os.path.getmtime)
    for case in cases:
        *kind, graph, method = case.split(":")
        run[method](graphs[graph](spark, small)).collect()
        times, cpu, start = [], 0.0, time.time()
        for _ in range(1 if kind else RUNS):
            at = time.time()
            run[method](graphs[graph](spark, SF)).collect()
            times.append(time.time() - at)
        end = time.time()
        cpu = cpu_between(path(), start, end)
        line = {"graph": graph, "method": method, "cores": cores, "seconds": round(statistics.median(times), 2), "jvm_cpu_util": round(cpu / (cores * (end - start)), 3)}
        if kind:
            shown = event_log_utilisation(spark, path(), cores, every=1).where(f"at between {int(start)} and {int(end)}").orderBy("at").collect()
            line["trace"] = [round(r.utilisation, 2) for r in shown]
        print(json.dumps(line), flush=True)
    spark.stop()


if __name__ == "__main__":
    cores = sys.argv[1] if len(sys.argv) > 1 else "1,2,4,8"
    cases = sys.argv[2] if len(sys.argv) > 2 else CASES
    if "," in cores:
        for c in cores.split(","):
            subprocess.run([sys.executable, __file__, c, cases], check=True)
    else:
        one(int(cores), cases.split(","))

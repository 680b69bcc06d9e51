"""Phase times and speedups of the scalability runs: one session for each number of workers, the mean of several repeats.

python sweep.py [workload ...]; $SWEEP_SF_DIR (default sf0.01), $SWEEP_WORKERS (1,2,4), $SWEEP_REPEATS (3).  Each number of workers runs
in its own process on local[workers] with as many partitions; entities and links are written before the clock starts.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
from statistics import mean

HERE = os.path.dirname(os.path.abspath(__file__))
PHASES = ("pre", "components", "decomposition", "merge")


def one(names: list[str], workers: int, repeats: int, sf: str) -> dict:
    sys.path.insert(0, HERE)
    from pyspark.sql import SparkSession

    from linkcluster import queries
    from linkcluster.plans.iterate import written
    from linkcluster.plans.workflow import cluster

    spark = SparkSession.builder.master(f"local[{workers}]").config("spark.sql.shuffle.partitions", workers).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    out = {}
    for name in names:
        v, links, cfg = queries.WORKLOADS[name](spark, sf)
        v, links = written(v), written(links)
        runs = [cluster(v, links, cfg).seconds for _ in range(repeats)]
        out[name] = {p: round(mean(r[p] for r in runs), 2) for p in PHASES} | {"entities": v.count(), "links": links.count(), "total": round(mean(sum(r.values()) for r in runs), 2)}
    return out


def main() -> None:
    names = sys.argv[1:] or ["workflow_geo_large", "workflow_music_star"]
    sf, repeats = os.environ.get("SWEEP_SF_DIR", "/root/testdata/sf0.01"), int(os.environ.get("SWEEP_REPEATS", "3"))
    if os.environ.get("SWEEP_ONE"):
        print("RESULT " + json.dumps(one(names, int(os.environ["SWEEP_ONE"]), repeats, sf)))
        return
    first: dict[str, float] = {}
    for workers in os.environ.get("SWEEP_WORKERS", "1,2,4").split(","):
        env = os.environ | {"SWEEP_ONE": workers, "PYTHONPATH": HERE + os.pathsep + os.environ.get("PYTHONPATH", "")}
        said = subprocess.run([sys.executable, os.path.abspath(__file__), *names], env=env, capture_output=True, text=True)
        got = [x for x in said.stdout.splitlines() if x.startswith("RESULT ")]
        if not got:
            sys.exit(said.stderr[-2000:])
        for name, row in json.loads(got[-1][7:]).items():
            print(json.dumps({"workload": name, "workers": int(workers), "repeats": repeats} | row | {"entities_per_second": round(row["entities"] / row["total"], 1), "speedup": round(first.setdefault(name, row["total"]) / row["total"], 2)}), flush=True)


if __name__ == "__main__":
    main()

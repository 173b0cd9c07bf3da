"""Headline timings: prints one JSON line. BENCH_SF_DIR and BENCH_CPUS name the input and the cores.

``queries`` holds seconds; ``measures`` holds RSS, RSS loss and time gain of the two proposals over the baseline of 8
rounds at each published setting of k (P) and at k scaled with n (R). ``python bench.py --report`` also runs the
engine ablation (W11), link rules and linkages over five seeds (W13, W16), other weights, the enlarged collection (W4,
W8) and speed-up over cores (W10).
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = int(os.environ.get("BENCH_CPUS", "8"))


def session(cpus: int):
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("textgroups-bench").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.shuffle.partitions", str(max(2, cpus))).config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def timed(f):
    began = time.time()
    out = f()
    return out, time.time() - began


def main() -> None:
    from textgroups.plans.storage import clear
    from textgroups.workloads import SETTINGS, prepared, run_setting

    spark = session(CPUS)
    seconds, measures = {}, []
    vecs, seconds["vectors"] = timed(lambda: prepared(spark, SF_DIR))
    run_setting(vecs, "warm-up", 5, 15)
    for name, k, m in SETTINGS:
        for r in run_setting(vecs, name, k, m):
            seconds[f"{name}_{r['method']}"] = round(r["seconds"], 2)
            measures.append({x: round(y, 4) if isinstance(y, float) else y for x, y in r.items()})
    out = {"metric": "seconds of all runs", "value": round(sum(seconds.values()), 2), "unit": "sec", "queries": {k: round(v, 2) for k, v in seconds.items()}, "sf": SF_DIR.rsplit("sf", 1)[-1], "cores": CPUS, "measures": measures}
    if "--report" in sys.argv:
        from textgroups.workloads import ablations, forms, run_workload

        out["ablations"] = ablations(spark, SF_DIR, vecs)
        out["forms"] = forms(spark, SF_DIR)
        for scale in ("R", "P"):
            out["enlarged_" + scale] = [{k: v for k, v in r.items()} for r in run_workload("W8", spark, SF_DIR, scale) + run_workload("W4", spark, SF_DIR, scale)[1:]]
        out["speed_up"] = speed_up()
    print(json.dumps(out))
    clear(spark)
    spark.stop()


def speed_up() -> list[dict]:
    """The k = 50 setting on 1, 2 and 4 cores, each in its own process."""
    code = "import bench, json, os; from textgroups.workloads import prepared, run_setting; s = bench.session(int(os.environ['BENCH_CPUS'])); v = prepared(s, bench.SF_DIR); run_setting(v, 'w', 5, 15); print('RUNS' + json.dumps([(r['method'], r['seconds']) for r in run_setting(v, 'P50', 50, 250)]))"
    rows = {}
    for cores in (1, 2, 4):
        got = subprocess.run([sys.executable, "-c", code], env=os.environ | {"BENCH_CPUS": str(cores)}, capture_output=True, text=True, timeout=1800)
        rows[cores] = dict(json.loads(next(x for x in got.stdout.splitlines() if x.startswith("RUNS"))[4:]))
    return [{"method": m, "cores": c, "seconds": round(rows[c][m], 2), "speed_up": round(rows[1][m] / rows[c][m], 2)} for c in rows for m in rows[c]]


if __name__ == "__main__":
    main()

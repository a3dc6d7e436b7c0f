"""Headline runs: prints one JSON line. BENCH_SF_DIR names the tables, BENCH_CPUS the cores."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import SparkSession  # noqa: E402

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", str(max(4, 2 * int(CPUS))))
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from eqmat import workloads as W
    from eqmat.catalog import queries
    from eqmat.operators.materialise import Options
    from eqmat.operators.measures import measures

    seconds, report = {}, {}

    def timed(name, run):
        began = time.time()
        out = run()
        seconds[name] = round(time.time() - began, 2)
        return out

    small = str(Path(SF_DIR).parent / "sf0.001")
    timed("warm_up", lambda: W.run_named(spark, "", "example"))
    for name in ("w1", "w2", "w3", "w4", "w5"):
        r = timed(f"{name}_rew", lambda name=name: W.run_named(spark, SF_DIR, name))
        report[f"{name}_rew"] = measures(r.mat)
    for name in ("w1", "w4", "w5"):  # both modes at a size where the axioms can be run
        # Every match of a rule counts on both sides: equalities by key are off.
        pair = {m: timed(f"{name}_small_{m}", lambda name=name, m=m: W.run(W.WORKLOADS[name](spark, small), m, Options(by_key=False))) for m in ("rew", "ax")}
        a, b = (measures(pair[m].mat) for m in ("ax", "rew"))
        report[f"{name}_factors"] = {k: round(a[k] / max(b[k], 1e-9), 2) for k in ("triples_total", "rule_applications", "derivations", "wall_seconds")}
    for name in ("w1_q1", "w1_q3", "w1_q3_on_expansion", "w1_q6", "w3_q3", "w4_q3"):
        timed(name, lambda name=name: queries()[name](spark, SF_DIR).count())
    timed("components_star", lambda: queries()["components_star"](spark, SF_DIR).count())
    seconds.pop("warm_up")
    print(json.dumps({"metric": "total_seconds", "value": round(sum(seconds.values()), 2), "unit": "sec", "queries": seconds, "sf": Path(SF_DIR).name.removeprefix("sf"), "cpus": CPUS, "measures": report}))


if __name__ == "__main__":
    main()

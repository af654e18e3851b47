"""The studies at their full settings: python studies.py [name ...]; the tables' folder is $BENCH_SF_DIR.

Names: the workloads w01 to w06 (budgets), controls, leaves, bins, precursor, open. Prints a table of means and standard
deviations over the trials of each, as JSON lines.
"""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
os.environ["PYTHONPATH"] = os.pathsep.join([sys.path[0], os.environ.get("PYTHONPATH", "")])
os.environ.setdefault("OMP_NUM_THREADS", "1")

from pyspark.sql import SparkSession

from privgrove.plans import experiments

STUDIES = {
    **{name: (lambda spark, d, name=name: experiments.sweep(spark, d, name)) for name in ("w01", "w02", "w03", "w04", "w05", "w06")},
    "controls": lambda spark, d: experiments.sweep(spark, d, "w11a").unionByName(experiments.sweep(spark, d, "w12")),
    "leaves": experiments.leaf_study,
    "bins": experiments.bin_study,
    "precursor": lambda spark, d: experiments.against_precursor(spark, d, "w01", experiments.EPSILONS, experiments.TRIALS),
    "open": lambda spark, d: experiments.open_models(spark, d, "w01", ways=("even", "sketch")),
}


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("studies").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g")
        .config("spark.sql.shuffle.partitions", cpus).config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    for name in sys.argv[1:] or STUDIES:
        began = time.time()
        rows = experiments.means(STUDIES[name](spark, sf_dir)).orderBy("workload", "variant", "epsilon").collect()
        for r in rows:
            print(json.dumps({"study": name, "workload": r["workload"], "variant": r["variant"], "epsilon": str(r["epsilon"]), r["measure"]: round(r["mean"], 3), "stddev": round(r["stddev"], 3), "trials": r["trials"]}), flush=True)
        print(json.dumps({"study": name, "seconds": round(time.time() - began, 1)}), flush=True)


if __name__ == "__main__":
    main()

"""Runs workloads by name at any parameters, the long ones included, and writes their rows as CSV.

    python experiments.py /root/testdata/sf0.01 out_folder full_private_against_uniform full_sweep_p
"""

from __future__ import annotations

import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))


def main(sf_dir: str, out: str, names: list[str]) -> None:
    from pyspark.sql import SparkSession

    from veilwalk.plans import queries

    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(os.environ.get("SPARK_MASTER", f"local[{cpus}]"))
        .config("spark.sql.shuffle.partitions", str(2 * int(cpus)))
        .config("spark.driver.memory", "6g")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    for name in names or queries.LONG:
        began = time.time()
        queries.queries()[name](spark, sf_dir).write.mode("overwrite").option("header", True).csv(f"{out}/{name}")
        print(name, round(time.time() - began, 1), "s", flush=True)


if __name__ == "__main__":
    main(sys.argv[1], sys.argv[2], sys.argv[3:])

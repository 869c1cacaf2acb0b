"""Headline queries on local[$BENCH_CPUS] over $BENCH_SF_DIR; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
#: Workload and strategy; each workload is run by the operator and by what it is compared with.
HEADLINE = (
    ("syn_s2", "shared_arms"), ("syn_s3", "shared_arms"), ("syn_s3", "traditional"), ("syn_c1", "shared_arms"), ("syn_c2", "shared_arms"), ("syn_c2", "preagg_every"), ("syn_c2", "traditional"), ("syn_c3", "shared_arms"), ("syn_c3", "traditional"),
    ("syn_b1", "shared_arms"), ("syn_b2", "shared_arms"), ("syn_b2", "preagg_every"), ("syn_b3", "shared_arms"), ("syn_b3", "traditional"), ("tpch_zip", "shared_arms"), ("tpch_zip", "traditional"),
    ("pairs_suppliers", "shared_arms"), ("pairs_suppliers", "traditional"), ("twohop", "shared_arms"), ("pairs_users", "shared_arms"), ("chain4_groups4", "shared_arms"), ("branch5_groups4", "shared_arms"), ("triple_events", "shared_arms"),
)


def main() -> None:
    from pyspark.sql import SparkSession

    from multiagg.queries import RUNS
    from multiagg.sources.tables import force
    from multiagg.workloads import workload

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "6g"))
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    force(RUNS["shared_arms"](workload("syn_c3", spark, SF_DIR)))
    took: dict[str, float] = {}
    for name, how in HEADLINE:
        at = time.perf_counter()
        force(RUNS[how](workload(name, spark, SF_DIR)))
        took[f"{name}__{how}"] = round(time.perf_counter() - at, 3)
    print(json.dumps({"metric": "headline queries, total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": SF_DIR.rstrip("/").rsplit("sf", 1)[-1]}))
    spark.stop()


if __name__ == "__main__":
    main()

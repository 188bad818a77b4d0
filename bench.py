"""Times headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Each workload runs in several ways; seconds are the median of $BENCH_RUNS runs (default 2)
into a sink that keeps nothing. Loading both indexes is timed on its own.
"""

from __future__ import annotations

import json
import os
import time
from statistics import median

from pyspark.sql import SparkSession

from probejoin import queries as core
from probejoin.operators import costs

HEADLINE = [f"w_{w}_{v}" for w in ("l1", "l3", "l5", "l7", "l8", "l11", "l13", "s3a", "x2") for v in ("cascade", "shuffle")]
HEADLINE += [f"w_{w}_{v}" for w in ("l4", "s1", "x1") for v in ("cascade", "multiway", "row", "shuffle", "shuffle_star")]
HEADLINE += [f"w_s2_{v}" for v in ("multiway", "row", "shuffle_star")] + [f"w_{w}_{v}" for w in ("l6", "l14", "s10") for v in ("distributed", "local", "base_scan")]


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus, runs = os.environ.get("BENCH_CPUS", "8"), int(os.environ.get("BENCH_RUNS", "2"))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.driver.memory", "8g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    began = time.time()
    idx = core.catalog(spark, sf_dir)
    idx.table("OI")
    idx.stats()
    load = time.time() - began
    seconds, moved = {}, {}
    for name in HEADLINE:
        taken = []
        for _ in range(runs):
            began = time.time()
            df = core.QUERIES[name](spark, sf_dir)
            df.write.format("noop").mode("overwrite").save()
            taken.append(time.time() - began)
        seconds[name] = round(median(taken), 3)
        moved[name] = costs.exchanges(df)
    ratio = {w: round(seconds[f"w_{w}_shuffle"] / seconds[f"w_{w}_cascade"], 2) for w in ("l1", "l3", "l4", "l5", "l7", "l8", "l11", "l13", "s1", "s3a", "x1", "x2")}
    stars = {w: round(seconds[f"w_{w}_shuffle_star"] / seconds[f"w_{w}_row"], 2) for w in ("l4", "s1", "s2", "x1")}
    gain = {w: round(seconds[f"w_{w}_cascade"] / seconds[f"w_{w}_row"], 2) for w in ("l4", "s1", "x1")}
    print(json.dumps({
        "metric": "graph-pattern workloads, sum of medians", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": {"load_both_indexes": round(load, 3), **seconds}, "sf": os.path.basename(sf_dir.rstrip("/")),
        "shuffle_over_probe": ratio, "star_shuffle_over_row": stars, "cascade_over_row": gain, "exchanges": moved,
    }))


if __name__ == "__main__":
    main()

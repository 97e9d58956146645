"""Headline workloads at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from driftrank.operators import push
from driftrank.plans import workloads
from driftrank.sources import graph as G


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    took, seen = {}, {}

    def timed(name, work):
        t = time.perf_counter()
        seen[name] = [r.asDict() for r in work().collect()]
        took[name] = round(time.perf_counter() - t, 3)

    def static(kind, rmax):
        arcs = push.cut_lineage(G.undirect(G.build(spark, sf, "g_dense")))
        return push.push(arcs, push.start_state(G.sample_roots(arcs, 10)), 0.2, rmax, kind).selectExpr("count(*) as rows", "sum(est) as mass")

    for g in ("g_sparse", "g_mid", "g_dense"):
        timed(f"table2_{g}", lambda g=g: workloads.table2(spark, sf, g, roots=16, updates=300, seconds=True, rmax_lazy=7e-6, rmax_eager=1e-5))
    timed("table3_g_dense", lambda: workloads.table3_4(spark, sf, "g_dense", 50, 5e-5, 16000, roots=8, updates=200, seconds=True))
    timed("figure1_g_mid", lambda: workloads.figure1(spark, sf, roots=8, updates=300, first_rebuilds=3, seconds=True))
    timed("forward_rounds_g_dense", lambda: static("forward", 5e-5))
    timed("reverse_rounds_g_dense", lambda: static("reverse", 1e-3))
    print(json.dumps({"metric": "headline workloads", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": sf, "measures": {k: v for k, v in seen.items() if not k.endswith("rounds_g_dense")}}))


if __name__ == "__main__":
    main()

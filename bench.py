"""Times the headline queries on $BENCH_SF_DIR with local[$BENCH_CPUS] and prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))
os.environ.setdefault("PYSPARK_PYTHON", sys.executable)

#: Samplers, their structures, the baselines' builds and queries, and the operators that they rest on.
HEADLINE = (
    "flagship_monthly", "keyed_pairs", "ipps_tau_pairs", "poisson_pairs_total", "varopt_hash_docs", "order_shipday_bucketed", "hier_region_nation_customer", "disjoint_priority",
    "two_pass_pairs", "two_pass_events", "two_pass_flows", "est_boxes", "exact_boxes", "join_range_binned", "subnet_traffic",
)


def main() -> None:
    from pyspark.sql import SparkSession

    d, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "16g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from rangekeep import registry
    from rangekeep.operators import estimate as E
    from rangekeep.operators import structures as S
    from rangekeep.operators import twopass as T
    from rangekeep.plans import experiments as X
    from rangekeep.plans import workloads as W
    from rangekeep.plans.sampling_queries import key_set
    from rangekeep.sources.shared import keep

    full = lambda df: df.write.format("noop").mode("overwrite").save()
    queries, times = registry.queries(), {}

    def timed(name, f):
        t = time.perf_counter()
        f()
        times[name] = round(time.perf_counter() - t, 3)

    full(queries["flagship_monthly"](spark, d))  # starts the engine, not timed
    for name in HEADLINE:
        timed(name, lambda n=name: full(queries[n](spark, d)))
    k = keep(key_set(spark, d, "pairs"))
    pair = ["l_partkey", "l_suppkey"]
    timed("build_oblivious_2700", lambda: full(S.varopt(k, 2700).rows))
    timed("build_aware_2700", lambda: full(T.two_pass(k, 2700, T.Product(pair)).rows))
    made = S.varopt(k, 2700)
    sample = S.Summary(keep(made.rows), made.th, 1, "varopt")
    wide, high = (r + 1 for r in k.agg({"l_partkey": "max", "l_suppkey": "max"}).first())
    boxes = keep(W.frame(spark, W.uniform_area(int(wide), int(high), 100, 25, 0.05)))
    timed("boxes_2500_sample", lambda: full(E.estimate_boxes(sample, boxes, *pair)))
    timed("boxes_2500_data", lambda: full(W.exact_boxes(k, boxes, *pair, "units", max(1, int(wide) // 64), max(1, int(high) // 64))))
    # builders side by side on the same kept plane of parts by suppliers, with the work that each does; beside the headline, not in it
    builds = {f"{r['method']} {r['s']}": {k: r[k] for k in ("sec", "keys_per_sec", "touched", "made", "bytes")} for r in X.build_times(spark, d, (2700,), "pairs")}
    print(json.dumps({"metric": "headline_total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": Path(d).name, "cpus": int(cpus), "builds": builds}))
    spark.stop()


if __name__ == "__main__":
    main()

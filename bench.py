"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

HEADLINE = (
    "profile_sum",
    "kmeans_central",
    "kmeans_masked",
    "fuzzy_classical_central",
    "fuzzy_classical_masked",
    "gmm_full_central",
    "gmm_full_masked",
    "consensus_masked_boosted_total",
    "consensus_error_race",
    "silhouette_squared",
    "topology_sweep",
    "profile_month_supplier",
    "join_broadcast",
    "join_asof",
    "stream_tumbling",
)


def main() -> None:
    from meshprofile.session import local_session

    sf, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = local_session(cpus)
    spark.sparkContext.setLogLevel("ERROR")
    from meshprofile.plans import methods, registry

    queries, took = registry.queries(), {}
    queries["profile_sum"](spark, sf).write.format("noop").mode("overwrite").save()  # warm up
    for name in HEADLINE:
        began = time.perf_counter()
        queries[name](spark, sf).write.format("noop").mode("overwrite").save()
        took[name] = round(time.perf_counter() - began, 3)
        print(name, took[name], file=sys.stderr, flush=True)
    # a fit over ten times as many consumers as there are customers (150 thousand at sf0.1)
    began = time.perf_counter()
    rows = sum(r["n"] for r in methods.q_kmeans_wide(spark, sf).collect())
    took["kmeans_masked_wide"], took["kmeans_masked_wide_rows"] = round(time.perf_counter() - began, 3), rows
    # the two sides of the reported comparison: seconds of local work, without Spark's overhead
    for r in methods.q_times(spark, sf, ("events",)).collect():
        took[f"local_{r['family']}_{r['kind']}"] = round(r["local_seconds"] + r["consensus_seconds"], 5)
        took[f"iterations_{r['family']}_{r['kind']}"] = r["iterations"]
    print(json.dumps({"metric": "headline_total", "value": round(sum(took[n] for n in HEADLINE), 3), "unit": "sec", "queries": took, "sf": sf}))


if __name__ == "__main__":
    main()

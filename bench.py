"""Headline queries on $BENCH_SF_DIR with local[$BENCH_CPUS]; prints one JSON line.

With --workloads [names]: runs the long experiment workloads instead and prints their rows."""

from __future__ import annotations

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

HEADLINE = ["corpus_lines", "bounded_scan", "postings", "index_range_search", "relax_batch", "relax_gallop", "relax_rank", "relax_align", "cluster_walk", "swap_baseline", "multipass_greedy", "word2vec_clusters", "lambda_sweep"]


def main() -> None:
    from simsearch.queries import QUERIES
    from simsearch.session import local_session, ship_package

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = local_session(os.environ.get("BENCH_CPUS", "8"), 8)
    spark.sparkContext.setLogLevel("ERROR")
    ship_package(spark)
    QUERIES["corpus_names"](spark, sf_dir).count()  # starts the JVM's work
    if "--workloads" in sys.argv:
        from simsearch.experiments import WORKLOADS

        for name in [a for a in sys.argv[1:] if a in WORKLOADS] or WORKLOADS:
            print(json.dumps({"workload": name, "rows": [r.asDict() for r in WORKLOADS[name](spark, sf_dir).collect()]}), flush=True)
        return
    took = {}
    for name in HEADLINE:
        began = time.time()
        QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        took[name] = round(time.time() - began, 3)
        spark.catalog.clearCache()
    print(json.dumps({"metric": "headline_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": Path(sf_dir).name.removeprefix("sf")}))


if __name__ == "__main__":
    main()

"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from graphpart.queries import QUERIES  # noqa: E402
from graphpart.session import make_session  # noqa: E402

NAMES = ["graph_cust_supp", "sym_weighted_events", "hist", "best_label", "blp_t1", "blp_t5", "blp_t5_directed_events", "plain_lpa_t3", "adapt_t3_all", "elastic_add_t3", "hash_quality", "pagerank_20", "wcc"]


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = make_session(cores=os.environ.get("BENCH_CPUS", "8"), shuffle_partitions=8)
    spark.sparkContext.setLogLevel("ERROR")
    spark.range(1000).groupBy().sum().collect()
    took = {}
    for name in NAMES:
        began = time.time()
        QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        took[name] = round(time.time() - began, 3)
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf")}))


if __name__ == "__main__":
    main()

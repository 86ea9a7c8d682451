"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = int(os.environ.get("BENCH_CPUS", "8"))
ROOT = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, ROOT)
os.environ["PYTHONPATH"] = ROOT + os.pathsep + os.environ.get("PYTHONPATH", "")

HEADLINES = ["vectors_baskets", "vectors_docs", "weighted_signature", "minwise_signature", "sign_bits", "mode_split_baskets", "sorted_blocks_weighted", "recall_of_split", "retrieve_campaigns", "full_split_baskets", "sorted_blocks_hundred"]


def main() -> None:
    from cohort_engine import catalog
    from cohort_engine.session import local_session, ship

    spark = local_session(CPUS)
    spark.sparkContext.setLogLevel("ERROR")
    ship(spark)
    all_queries, took = catalog.queries(), {}
    for name in HEADLINES[:3:2]:  # start the workers
        all_queries[name](spark, SF).write.format("noop").mode("overwrite").save()
    for name in HEADLINES:
        began = time.time()
        all_queries[name](spark, SF).write.format("noop").mode("overwrite").save()
        took[name] = round(time.time() - began, 3)
    users = spark.read.parquet(f"{SF}/customer.parquet").count()
    rates = {f"{q}_users_per_second": round(users / took[q]) for q in ("weighted_signature", "mode_split_baskets", "full_split_baskets")}
    print(json.dumps({"metric": "total of the headline queries", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "rates": rates, "sf": float(os.path.basename(SF.rstrip("/")).removeprefix("sf") or 0)}))


if __name__ == "__main__":
    main()

"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import time

from pyspark.sql import SparkSession

from rotahash import registry

HEADLINE = (
    "std_minhash_sig",
    "rot_minhash_sig",
    "bin_minhash_sig",
    "copy_uniform_sig",
    "fresh_sig",
    "rotbin_sig",
    "rotbin_2u_sig",
    "rotbin_baskets_sig",
    "rotbin_suppliers_sig",
    "udf_rotbin",
    "estimate_word_pairs_rotbin_2u",
    "exact_jaccard_all_pairs",
    "mse_word_pairs_fig4",
    "mse_word_pairs_fig5",
    "mse_synthetic_fig3_m_2k",
    "near_dup_docs",
    "dup_clusters",
    "benchmark_contamination",
    "topk_search",
    "stream_bin_minima",
)


def main() -> None:
    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", str(2 * int(cpus)))
        .config("spark.driver.memory", "6g")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    queries, took = registry.queries(), {}
    queries["word_postings"](spark, sf_dir).count()  # starts the workers and compiles
    for name in HEADLINE:
        began = time.perf_counter()
        queries[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        took[name] = round(time.perf_counter() - began, 3)
    print(json.dumps({"metric": "headline_total", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": float(os.path.basename(sf_dir.rstrip("/")).removeprefix("sf") or 0)}))


if __name__ == "__main__":
    main()

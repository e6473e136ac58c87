"""Times headline queries; prints one JSON line.

Environment: BENCH_SF_DIR (default /root/testdata/sf0.1), BENCH_CPUS (default 8).
"""

from __future__ import annotations

import json
import os
import statistics
import time

from pyspark.sql import SparkSession

HEADLINE = [
    "frs_registers_by_priority",
    "frs_registers_bulk_hash",
    "frs_registers_contiguous",
    "frs_cube_sketch",
    "frs_packed_roundtrip",
    "card_auto",
    "jaccard_corrected_approx_priorities",
    "jaccard_corrected_approx",
    "intersection_segment_priority",
    "cnf_three_clause",
    "minhash_kpart_16",
    "minhash_khash",
    "kmv_jaccard",
    "f2_jaccard",
    "incl_excl_jaccard",
    "exact_jaccard_all_pairs",
    "fig6_register_sim",
    "headline_sim",
    "doc_source_matrix",
    "benchmark_containment",
    "stream_equals_batch",
]
REPEATS = 3


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    conf = {"spark.sql.shuffle.partitions": cpus, "spark.driver.memory": "8g", "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.sql.session.timeZone": "UTC"}
    spark = SparkSession.builder.master(f"local[{cpus}]").config(map=conf).getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    from frsketch.operators.build import sketch
    from frsketch.params import FrsParams
    from frsketch.plans.registry import QUERIES
    from frsketch.sources.tables import table

    def timed(run) -> float:
        run()  # compiles
        got = []
        for _ in range(REPEATS):
            t = time.perf_counter()
            run()
            got.append(time.perf_counter() - t)
        return statistics.median(got)

    queries = {}
    for name in HEADLINE:
        queries[name] = round(timed(lambda f=QUERIES[name]: f(spark, sf_dir).write.format("noop").mode("overwrite").save()), 3)
    li = table(spark, sf_dir, "lineitem")
    rows = li.count()
    rates = {}
    for p, q, r, h, mode in ((6, 4, 4, "md5", "independent"), (10, 4, 8, "md5", "independent"), (10, 6, 8, "sha1", "contiguous"), (15, 6, 10, "xx", "independent")):
        params = FrsParams(p, q, r, hash=h, mantissa=mode)
        s = timed(lambda x=params: sketch(li, ["l_orderkey", "l_partkey"], ["l_returnflag"], x).write.format("noop").mode("overwrite").save())
        rates[f"rows_per_s_{h}_{mode}_p{p}"] = round(rows / s)
    out = {"metric": "total of headline queries", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "build": rates, "sf": os.path.basename(sf_dir.rstrip("/"))}
    print(json.dumps(out))
    spark.stop()


if __name__ == "__main__":
    main()

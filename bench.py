"""Times headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

``--scaling`` also runs the sort at equal rows for each partition (weak) and the k-mer count at equal input (strong).
"""

import json
import os
import sys
import time

from pyspark.sql import SparkSession

from distds import queries as core
from distds.plans import micro

QUERIES = ("kt_insert_merge", "sw_flush", "kt_find_only", "kt_find_atomic", "amo_fetch_add", "pq_push", "rq_many_pushpop", "bb_insert", "isort_bucketed", "isort_bulk_sync", "isort_pipelined", "isort_global", "km_count", "km_two_level", "cg_specialised", "rel_join5")
WARM = "/root/testdata/sf0.001"


def main() -> None:
    sf, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    found, times = core.queries(), {}
    for name in QUERIES:
        if name != "cg_specialised":
            found[name](spark, WARM).write.format("noop").mode("overwrite").save()
        t = time.time()
        found[name](spark, sf).write.format("noop").mode("overwrite").save()
        times[name] = round(time.time() - t, 3)
    ops = {name: round(micro.seconds(make), 3) for name, make in micro.operations(spark, sf).items()}
    ratios = {name: round(ops[a] / ops[b], 2) for name, (a, b) in micro.RATIOS.items()}
    out = {"metric": "headline_seconds", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "micro": ops, "ratios": ratios, "lines": micro.program_lengths(), "sf": sf}
    if "--scaling" in sys.argv:
        from distds.plans import kmers, sorting
        from distds.queries.kmers import K, reads
        from distds.sources.io import table

        weak = {}
        for d, p in (("sf0.001", 1), ("sf0.01", 10), ("sf0.1", 100)):
            keys = sorting.sort_keys(table(spark, f"/root/testdata/{d}", "lineitem"))
            weak[p] = round(micro.seconds(lambda k=keys, p=p: sorting.sort_bucketed(k, p)), 3)
        strong = {}
        for p in (1, 2, 4, 8, 16):
            r = reads(spark, sf)
            strong[p] = round(micro.seconds(lambda r=r, p=p: kmers.count_plain(kmers.extract(r.repartition(p), K, edges=False)), 1), 3)
        out |= {"weak_sort": weak, "strong_kmers": strong}
    print(json.dumps(out))


if __name__ == "__main__":
    main()

"""Headline queries, timed to a sink that writes nothing; prints one JSON line."""

import json
import os
import time

from pyspark.sql import SparkSession

from sparsetier import queries

#: The two-level product beside its competitors, on co-purchase and on the square of part to next part.
HEADLINE = ["m7_two_level", "m1b_relational", "m2_expand_sort_compress", "m9_segmented_b", "m10_hash", "m14_portable_sql", "m15_outer", "m4_fine_level",
            "m7_square", "m1b_square", "m3_symbolic", "s15_census"]


def main():
    sf, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "8g").config("spark.sql.shuffle.partitions", "16").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    found, times = queries.queries(), {}
    for name in HEADLINE:
        found[name](spark, sf).write.format("noop").mode("overwrite").save()  # one warm-up, as in the published protocol
        at = time.perf_counter()
        found[name](spark, sf).write.format("noop").mode("overwrite").save()
        times[name] = round(time.perf_counter() - at, 3)
    print(json.dumps({"metric": "headline_total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": sf}))


if __name__ == "__main__":
    main()

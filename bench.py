"""Headline timings: one JSON line.

Phases of an archive of lineitem and of the star view (structure, parameters, coding with writing, decompression), and a
few statistics. BENCH_SF_DIR names the tables, BENCH_CPUS the threads.
"""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))


def main() -> None:
    from pyspark.sql import SparkSession

    sf_dir, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", cpus)
             .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate())
    spark.sparkContext.setLogLevel("ERROR")
    from relcodec import measures
    from relcodec.queries import QUERIES
    from relcodec.sources.tables import star, table

    seconds: dict[str, float] = {}
    table(spark, sf_dir, "region").count()
    lineitem = table(spark, sf_dir, "lineitem")
    for name, df in (("lineitem", lineitem.repartition(int(cpus))), ("star", star(spark, sf_dir).repartition(int(cpus)))):
        for phase, s in measures.timed_phases(spark, df).items():
            seconds[f"{name}_{phase}"] = round(s, 3)
    for name in ("lossless_ratio_star", "objective_pairs", "cumulative_masses", "lineitem_codes", "delta_bits_lineitem", "pairwise_copy_bits", "contingency_grouping_sets"):
        t = time.time()
        QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.time() - t, 3)
    mb = measures.raw_bytes(lineitem) / 1e6
    from relcodec import archive, baselines
    from relcodec.plans.studies import written
    from relcodec.sources.tables import scratch

    sizes = {}
    for name, df in (("lineitem", lineitem), ("star", written(star(spark, sf_dir)))):
        path = scratch(spark)
        made = archive.compress(df, path)
        # A place in the middle of the first block, until its row is here.
        block, t = made.blocks(spark).agg({"block_id": "min"}).first()[0], time.time()
        archive.lookup(spark, path, [(block, 1000)]).collect()
        look = time.time() - t
        size = measures.compression_ratio(spark, made, df)
        sizes[name] = {"ratio": round(size["ratio"], 4), "code_bits_per_row": round(size["code_bits"] / size["rows"], 2), "model_bytes": size["model"],
                       "gzip_ratio": round(baselines.universal_size(df) / size["raw"], 4), "lookup_sec": round(look, 3)}
    print(json.dumps({"metric": "archive_and_statistics_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(sf_dir).removeprefix("sf"),
                      "sizes": sizes, "raw_mb": round(mb, 2), "compress_mb_per_s": round(mb / seconds["lineitem_compression"], 2), "decompress_mb_per_s": round(mb / seconds["lineitem_decompression"], 2)}))


if __name__ == "__main__":
    main()

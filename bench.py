"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]: one JSON line. Times are of full evaluation into a sink that discards the rows."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))


def main() -> None:
    from pyspark.sql import SparkSession

    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "12g")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from viewsize.functions.hashing import HashSpec
    from viewsize.operators import exact, multi, multifractal
    from viewsize.plans.views import CATALOGUE, CENSUS, SYNTHETIC, facts

    took: dict[str, float] = {}
    more: dict[str, float] = {}

    def run(name: str, make) -> None:
        began = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        took[name] = round(time.perf_counter() - began, 3)

    spec = HashSpec()
    one, three, four = CATALOGUE["D4"], CATALOGUE["D9"], CATALOGUE["D7"]
    many = lambda v, m, M: multi.estimate_many(facts(spark, sf_dir, *v), v, [m], M, spec)
    run("warm_up", lambda: many([one], "ac", 256))
    took.pop("warm_up")
    for m in ("pc", "ll", "ac", "gc", "lps"):
        run(f"census_20_views_{m}", lambda m=m: many(CENSUS, m, 2048 if m not in ("gc", "lps") else 256))
        run(f"synthetic_8_views_{m}", lambda m=m: many(SYNTHETIC, m, 256))
        for label, view in (("1dim", one), ("3dim", three)):
            for M in (256, 2**20):
                run(f"{label}_{m}_M{M}", lambda m=m, view=view, M=M: many([view], m, M))
    for m in ("pc", "ll", "ac", "gc", "lps"):
        for M in (16, 2**12, 2**16):
            run(f"time_vs_M_{m}_{M}", lambda m=m, M=M: many([four], m, M))
    run("exact_census_grouping_sets", lambda: exact.view_sizes(facts(spark, sf_dir, *CENSUS), CENSUS))
    key = ["l_orderkey", "l_linenumber"]
    run("mf_all_views_half_percent", lambda: multifractal.mf_from_stats(multifractal.mf_many(facts(spark, sf_dir, *CENSUS, extra=tuple(key)), CENSUS, [0.005], 1, key)))
    run("mf_sample_half_percent", lambda: multifractal.mf_estimate(facts(spark, sf_dir, CATALOGUE["C08"]), CATALOGUE["C08"], 0.005))
    n = facts(spark, sf_dir, one).count()
    more["facts"] = n
    more["facts_per_s_3dim_ac"] = round(n / took["3dim_ac_M256"])
    more["facts_times_views_per_s_census_ac"] = round(20 * n / took["census_20_views_ac"])
    more["published_facts_per_s_3dim"] = round(5 / 2 * 13_977_981 / 237)
    print(json.dumps({"metric": "view-size headline queries", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": sf_dir.rstrip("/").rsplit("sf", 1)[-1], "rates": more}), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()

"""Times the headline queries on $BENCH_SF_DIR with local[$BENCH_CPUS] and prints one JSON line."""

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parent))

from pyspark.sql import SparkSession  # noqa: E402


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from tallygrid.functions.hashing import GridSpec
    from tallygrid.operators import estimates, grid, likelihood
    from tallygrid.plans import base, experiments, registry, workloads
    from tallygrid.sources import tables

    def run(df) -> None:
        df.write.format("noop").mode("overwrite").save()

    def timing_workload() -> float:
        """Milliseconds per likelihood estimate: 2,000 items of 2-grams, 8 x 10^6 cells, grid and density given."""
        return experiments.timed(spark, tables.ngrams(spark, sf, 2), GridSpec(8, 1_000_000))[2]

    def kept_grid_answers() -> None:
        """Estimates with intervals from a grid that is there already, as a user asks them again and again."""
        run(estimates.debiased_min(grid.probe(asked.items, asked.grid), estimates.grid_law(asked.grid), 4, mode="exact"))

    headline = {
        "build_grid_parts_r8": lambda: run(grid.build_grid(tables.parts(spark, sf), GridSpec(8, 10_000)).df),
        "build_grid_dense_parts_r8": lambda: run(grid.build_grid_dense(tables.parts(spark, sf), GridSpec(8, 10_000)).df),
        "debiased_min": lambda: run(registry.QUERIES["deb_min"](spark, sf)),
        "debiased_mle": lambda: run(registry.QUERIES["mle_debiased_fitted"](spark, sf)),
        "density_fit": lambda: likelihood.density(estimates.grid_law(grid.build_grid(tables.parts(spark, sf), GridSpec(4, 250)))),
        "tune_depth": lambda: run(registry.QUERIES["tune_depth"](spark, sf)),
        "joint_mle": lambda: run(registry.QUERIES["joint_mle"](spark, sf)),
        "answers_from_kept_grid": kept_grid_answers,
        "power_law_1e6_items": lambda: run(workloads.power_law_sweep(spark, 1_000_000, (2.0,), (0.0,), [GridSpec(4, 100_000)])),
        "w03_bigrams": lambda: run(workloads.compare(tables.ngrams(spark, sf, 2, "th"), [GridSpec(4, 10_000)])),
    }
    asked = base.Setting(spark, sf)
    run(registry.QUERIES["deb_min"](spark, sf))  # the first query pays for starting up
    seconds = {}
    for name, f in headline.items():
        began = time.perf_counter()
        f()
        seconds[name] = round(time.perf_counter() - began, 3)
    per_count = timing_workload()
    print(json.dumps({"metric": "headline_queries_total", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": sf, "ms_per_count": round(per_count, 5), "published_ms_per_count": 4.0}))
    spark.stop()


if __name__ == "__main__":
    main()

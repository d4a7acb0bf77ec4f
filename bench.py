"""Time the headline queries and print one JSON line: medians of several runs, speedups of methods, and the range query's share."""

from __future__ import annotations

import json
import os
import statistics
import time

from pyspark.sql import SparkSession

from vistapoint import workloads as W
from vistapoint.operators import matrix, sampler, sampling
from vistapoint.session import ship

RUNS = 3


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "8")
    spark = SparkSession.builder.master(f"local[{cpus}]").config("spark.driver.memory", "12g").config("spark.sql.shuffle.partitions", cpus).config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    ship(spark)
    # The given table is one file of one row group, which only one task reads; a store of fields of view has many files.
    fovs = {v: W.kept(W.events(spark, sf_dir, v).repartition(int(cpus), "fov_id")) for v in ("pie60", "mix30", "mix70")}
    regions = {"t1": W.T1, "t2": W.T2, "t3": W.T3, "t4": W.T4}
    top = lambda m, k=5: matrix.top_cells(m, k)

    runs = {f"q_range_query_{t}": lambda q=q: matrix.candidates(fovs["pie60"], q) for t, q in regions.items()}
    for v in fovs:
        for t, q in regions.items():
            runs[f"q_optimized_{t}_{v}"] = lambda q=q, v=v: top(matrix.optimized(fovs[v], q))
            runs[f"q_tiled_{t}_{v}"] = lambda q=q, v=v: top(matrix.tiled(fovs[v], q))
    # Naive against optimized on the smallest region: on the others it would take hours at this scale.
    runs["q_naive_t0_pie60"] = lambda: top(matrix.naive(fovs["pie60"], W.T0))
    runs["q_optimized_t0_pie60"] = lambda: top(matrix.optimized(fovs["pie60"], W.T0))
    for v, some in (("pie60", ("t1", "t2", "t3", "t4")), ("mix30", ("t3", "t4"))):
        for t in some:
            runs[f"q_clustered_{t}_{v}"] = lambda q=regions[t], v=v: sampler.run(fovs[v], q, W.OPT)[0]
            runs[f"q_single_{t}_{v}"] = lambda q=regions[t], v=v: top(matrix.tiled(sampling.by_fraction(fovs[v], 0.3), q))
    for k in (1, 10):
        runs[f"q_optimized_t2_k{k}"] = lambda k=k: top(matrix.optimized(fovs["pie60"], W.T2), k)
    for warm in (matrix.tiled, matrix.optimized):
        top(warm(fovs["pie60"], W.T1)).write.format("noop").mode("overwrite").save()
    out = {}
    for name, run in runs.items():
        took = []
        for _ in range(RUNS):
            began = time.time()
            run().write.format("noop").mode("overwrite").save()
            took.append(time.time() - began)
        out[name] = round(statistics.median(took), 3)
    exact = {f"{t}_{v}": min(out[f"q_optimized_{t}_{v}"], out[f"q_tiled_{t}_{v}"]) for t in regions for v in fovs}
    ratio = lambda a, b: round(a / b, 2) if b else None
    speedups = {"naive_over_optimized_t0": ratio(out["q_naive_t0_pie60"], out["q_optimized_t0_pie60"])}
    for name in out:
        for method in ("clustered", "single"):
            if name.startswith(f"q_{method}_"):
                speedups[f"exact_over_{name[2:]}"] = ratio(exact[name.removeprefix(f"q_{method}_")], out[name])
    share = {t: ratio(out[f"q_range_query_{t}"], exact[f"{t}_pie60"]) for t in regions}
    print(json.dumps({"metric": "total_seconds_of_headline_queries", "value": round(sum(out.values()), 3), "unit": "sec", "queries": out, "speedups": speedups, "query_share": share, "runs": RUNS, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf")}))
    spark.stop()


if __name__ == "__main__":
    main()

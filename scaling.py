"""The dense square product by every method at a side where arithmetic shows.

    SCALING_N=4704 SCALING_TILE=588 python scaling.py [method ...]

Prints a JSON line per run: seconds, effective GFLOPS, shuffle bytes, and
whether the sum of all cells equals the one that the factors' column and row
sums give. The matrices are the fold of ``lineitem`` at another side.
"""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from sevenfold.operators import grids
from sevenfold.operators.hybrid import hybrid, wide
from sevenfold.operators.leaf import LeafSpec
from sevenfold.operators.tiles import cells_to_tiles, durable
from sevenfold.plans.report import moved
from sevenfold.sources.matrices import fold_pair

METHODS = {
    "grid2d": lambda a, b: grids.grid2d(a, b, 4),
    "grid2d_shift": lambda a, b: grids.grid2d_shift(a, b, 4),
    "grid3d": lambda a, b: grids.grid3d(a, b, 2),
    "grid25d": lambda a, b: grids.grid25d(a, b, 32, 2),
    "grid2d_fast": lambda a, b: grids.grid2d_fast(a, b, 4, 2),
    "grid25d_fast": lambda a, b: grids.grid25d_fast(a, b, 32, 2, 2),
    "fast_grid2d": lambda a, b: grids.fast_grid2d(a, b, 1, 2, pack=True),
    "hybrid_7": lambda a, b: wide(a, b, 7, leaf=LeafSpec(levels=2, cutoff=256)),
    "hybrid_49": lambda a, b: wide(a, b, 49),
    "hybrid_49_fused": lambda a, b: wide(a, b, 49, fuse=2),
    "hybrid_SW": lambda a, b: hybrid(a, b, "SW"),
    "classical_8": lambda a, b: hybrid(a, b, "W", scheme="c8"),
}


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", str(os.cpu_count()))
    n, tile = int(os.environ.get("SCALING_N", "4704")), int(os.environ.get("SCALING_TILE", "588"))
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g"))
        .config("spark.sql.execution.arrow.maxRecordsPerBatch", "16")  # a row is a tile
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    x, y, _ = fold_pair(spark, sf_dir, n)
    x, y = durable(x), durable(y)
    sums = x.groupBy(F.col("j").alias("k")).agg(F.sum("v").alias("s")).join(y.groupBy(F.col("i").alias("k")).agg(F.sum("v").alias("t")), "k")
    want = sums.agg(F.sum(F.col("s") * F.col("t"))).first()[0]
    a, b = (cells_to_tiles(m, n, n, tile) for m in (x, y))
    a, b = a.with_df(durable(a.df)), b.with_df(durable(b.df))
    got = {}
    for name in sys.argv[1:] or METHODS:
        def run(f=METHODS[name]):
            cells = F.aggregate("vals", F.lit(0).cast("long"), lambda s, v: s + v)
            got["sum"] = f(a, b).df.agg(F.sum(cells)).first()[0]

        began = time.perf_counter()
        cost = moved(spark, run)
        seconds = time.perf_counter() - began
        print(json.dumps({"method": name, "n": n, "seconds": round(seconds, 2), "effective_gflops": round(2 * n**3 / seconds / 1e9, 2), "right": got["sum"] == want} | cost), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()

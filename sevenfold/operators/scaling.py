"""Strong scaling: one product over growing numbers of logical workers, every point tuned by time."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sevenfold.operators import grids
from sevenfold.operators.hybrid import hybrid
from sevenfold.operators.leaf import LeafSpec
from sevenfold.operators.tiles import TileMatrix, durable
from sevenfold.plans.costs import effective_gflops, method_cost, traffic
from sevenfold.plans.planner import interleavings, tune
from sevenfold.plans.report import moved, speedup_report

COLUMNS = "method string, p int, setting string, runs int, seconds double, gflops double, gflops_per_worker double, words double, shuffle_bytes long, spilled_bytes long, stages int, equal boolean"


def points(most_levels: int = 2, copies: tuple[int, ...] = (1, 2, 3, 6), depths: tuple[int, ...] = (1, 2), squares: tuple[int, ...] = (4, 16), replicated=((8, 2), (32, 2)), leaf_levels=(0, 1, 2)) -> list[tuple[str, int, str]]:
    """(method, p, setting): the traversal on c * 7**k workers by schedule, the grids by fast levels."""
    out = []
    for k in depths:
        for schedule in interleavings(k, max(k, most_levels)):
            for c in copies if "S" not in schedule else (1,):
                out += [("hybrid", c * 7**k, f"{schedule} c={c} leaf={x}") for x in (leaf_levels[:2] if c == 1 and "S" not in schedule else (0,))]
    for p in squares:
        out += [("grid2d", p, "")] + [("grid2d_fast", p, f"leaf={x}") for x in leaf_levels] + [("fast_grid2d", p, f"top={x}") for x in (0, 1)]
    for p, c in replicated:
        out += [("grid25d", p, f"c={c}")] + [("grid25d_fast", p, f"c={c} leaf={x}") for x in leaf_levels]
    return out


def _run(a: TileMatrix, b: TileMatrix, method: str, p: int, setting: str) -> TileMatrix:
    named = dict(x.split("=") for x in setting.split() if "=" in x)
    leaf, g = int(named.get("leaf", 0)), round(p**0.5)
    if method == "hybrid":
        return hybrid(a, b, setting.split()[0], c=int(named["c"]), leaf=LeafSpec(levels=leaf, cutoff=8))
    if method == "fast_grid2d":
        return grids.fast_grid2d(a, b, int(named["top"]), g, pack=True)
    if method in ("grid2d", "grid2d_fast"):
        return grids.grid2d(a, b, g, LeafSpec(levels=leaf, cutoff=8))
    return grids.grid25d(a, b, p, int(named["c"]), LeafSpec(levels=leaf, cutoff=8))


def _words(method: str, n: int, p: int, setting: str) -> float:
    """Words a worker by the exact recurrence of the traversal, or by the formula of a grid."""
    if method == "hybrid":
        schedule, c = setting.split()[0], int(setting.split("c=")[1].split()[0])
        return float(traffic(n, p // c, schedule)[0]) / c
    top = int(setting.split("top=")[1]) if "top=" in setting else 0
    return method_cost(method, n, p, 3 * n * n * (int(setting.split("c=")[1].split()[0]) if "c=" in setting else 1) / p, top).words


def strong_scaling(spark: SparkSession, a: TileMatrix, b: TileMatrix, chosen: list[tuple[str, int, str]] | None = None) -> DataFrame:
    """The tuned points with seconds, effective rates, words, what Spark moved, and whether all results were equal.

    Each setting runs once after a warm-up; of a method's settings at one p the
    fastest is the point, ``runs`` says out of how many. ``equal``: the sum of all
    cells is that of the classical product. The logical workers share this cluster.
    """
    a, b = a.with_df(durable(a.df)), b.with_df(durable(b.df))
    n = a.n_rows
    cells = F.aggregate("vals", F.lit(0).cast("long"), lambda s, v: s + v)
    found: dict = {}

    def total(m: TileMatrix):
        return m.df.select(F.sum(cells)).first()[0]

    want = total(grids.grid2d(a, b, 2))  # and the warm-up
    for method, p, setting in chosen or points():
        def run(p, setting, method=method):
            kept = {}
            began = time.perf_counter()
            cost = moved(spark, lambda: kept.update(sum=total(_run(a, b, method, p, setting))))
            seconds = time.perf_counter() - began
            found[method, p, setting] = (seconds, cost, kept["sum"] == want)
            return seconds

        found.setdefault((method, p), []).append((p, setting, run))
    rows = []
    for key, settings in list(found.items()):
        if len(key) != 2:
            continue
        method, p = key
        seconds, setting = tune([(p, (s, f)) for _, s, f in settings], lambda p, x: x[1](p, x[0]))[p]
        _, cost, equal = found[method, p, setting[0]]
        total_rate, own_rate = effective_gflops(n, seconds, p)
        rows.append((method, p, setting[0], len(settings), seconds, total_rate, own_rate, _words(method, n, p, setting[0]), cost["shuffle_bytes"], cost["spilled_bytes"], cost["stages"], equal))
    return spark.createDataFrame(rows, COLUMNS)


def speedups(runs: DataFrame) -> DataFrame:
    """By worker count of the traversal, percent over the best other points with at most as many workers."""
    ours = runs.where("method = 'hybrid'").groupBy("p").agg(F.min("seconds").alias("seconds"))
    others = runs.where("method <> 'hybrid'").select(F.col("p").alias("q"), "method", F.col("seconds").alias("s"))
    reach = ours.join(F.broadcast(others), F.col("q") <= F.col("p")).select("method", "p", F.col("s").alias("seconds"))
    return speedup_report(reach.unionByName(ours.select(F.lit("hybrid").alias("method"), "p", "seconds")))

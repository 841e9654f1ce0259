"""One product for the user: reads the factors once, then chooses cells, schedule and method."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sevenfold.operators import grids
from sevenfold.operators.hybrid import hybrid, sql_multiply
from sevenfold.operators.tiles import DOUBLE, INTEGER, TileMatrix, cells_to_tiles, durable, exact_twin, tiles_to_cells
from sevenfold.plans.costs import Machine
from sevenfold.plans.layout import usable_workers
from sevenfold.plans.planner import choose_multiplier, plan_greedy, valid_25d
from sevenfold.plans.schemes import scheme_of


@dataclass(frozen=True)
class Factor:
    """What one pass over a factor's tiles tells: cells that aren't zero, the largest magnitude, cells that aren't finite."""

    nonzero: int
    largest: float
    not_finite: int


def look_at(m: TileMatrix) -> Factor:
    """One aggregate over the tiles, with partial sums; nothing but three numbers leaves the tasks."""
    fits = F.filter("vals", lambda v: F.abs(v.cast("double")) < float("inf"))
    row = m.df.agg(
        F.sum(F.size(F.filter("vals", lambda v: v != 0))),
        F.max(F.greatest(F.abs(F.array_max(fits).cast("double")), F.abs(F.array_min(fits).cast("double")))),
        F.sum(F.size("vals") - F.size(fits)),
    ).first()
    return Factor(int(row[0] or 0), float(row[1] or 0), int(row[2] or 0))


def choose(a: TileMatrix, b: TileMatrix, x: Factor, y: Factor, workers: int, memory: float, machine: Machine = Machine(), scheme="s7a15") -> dict:
    """(method, schedule, dtype): the cheapest method by model, the levels by memory, decimals where 64 bits may not do."""
    n = max(a.n_rows, a.n_cols, b.n_cols)
    usable, _, k = usable_workers(workers, (1,))
    finite = not (x.not_finite or y.not_finite)
    method = choose_multiplier(n, max(usable, 2), memory, machine, (x.nonzero, y.nonzero), finite)
    schedule = plan_greedy(n, usable, memory) if method == "hybrid" else ""
    growth = scheme_of(scheme).growth() ** len(schedule) if "fast" in method or method == "hybrid" else 1
    wide = a.dtype == INTEGER and x.largest * y.largest * a.n_cols * growth >= 2.0**62
    return {"method": method, "schedule": schedule, "dtype": "decimal(38,0)" if wide else a.dtype, "levels": k}


def multiply(a: TileMatrix, b: TileMatrix, workers: int = 49, memory: float = 1e9, machine: Machine = Machine(), scheme="s7a15") -> tuple[TileMatrix, dict]:
    """The product and the choice that led to it.

    ``workers`` and ``memory`` words each are the logical machine of the model.
    Factors with NaN or infinite cells get a classical method; integers whose
    product or whose sums on the way may not fit 64 bits are multiplied as decimals.
    """
    x, y = look_at(a), look_at(b)
    plan = choose(a, b, x, y, workers, memory, machine, scheme)
    if plan["dtype"] != a.dtype:
        a, b = exact_twin(a), exact_twin(b)
    method, side = plan["method"], max(1, int(workers**0.5))
    if method == "sql" and a.dtype == DOUBLE and (x.not_finite or y.not_finite):
        method = plan["method"] = "grid2d"  # a join skips zeros, and zero times infinity isn't zero
    if method == "sql":
        cells: DataFrame = sql_multiply(tiles_to_cells(a), tiles_to_cells(b))
        return cells_to_tiles(cells, a.n_rows, b.n_cols, a.tile, a.dtype), plan
    if method == "hybrid":
        return hybrid(a, b, plan["schedule"], scheme=scheme), plan
    if method in ("grid25d", "grid25d_fast"):
        p = max(v for v in range(1, workers + 1) if valid_25d(v))
        f = grids.grid25d if method == "grid25d" else grids.grid25d_fast
        return f(a, b, p), plan
    return (grids.grid2d if method == "grid2d" else grids.grid2d_fast)(a, b, side), plan


#: Dense products that cost as much as one pair of cells in a join.
PAIR_COST = 16


def multiply_cells(x: DataFrame, y: DataFrame, sides: tuple[int, int, int], tile: int, schedule: str = "W") -> DataFrame:
    """Integer cells times cells: tiles along the schedule, or a join where the cells are so few that tiles would hold mostly zeros.

    The pairs that the join makes are counted by inner key before, and compared to the dense products.
    """
    x, y = durable(x), durable(y)
    m, k, n = sides
    rows = x.groupBy("j").agg(F.count("*").alias("p")).join(y.groupBy(F.col("i").alias("j")).agg(F.count("*").alias("q")), "j")
    pairs = rows.agg(F.sum(F.col("p") * F.col("q"))).first()[0] or 0
    if PAIR_COST * pairs < m * k * n:
        return sql_multiply(x, y)
    return tiles_to_cells(hybrid(cells_to_tiles(x, m, k, tile), cells_to_tiles(y, k, n, tile), schedule))

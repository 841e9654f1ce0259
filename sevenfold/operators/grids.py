"""Classical processor-grid products, alone and with fast levels inside or outside.

Every method is the same declarative step under another key: a tile of A goes to
all owners that need it, so does a tile of B, the owners multiply what they get,
and products that share a place are summed.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sevenfold.operators.hybrid import hybrid
from sevenfold.operators.leaf import LeafSpec, dense_products
from sevenfold.operators.tiles import TileMatrix, durable, refuse_not_finite, release, sum_tiles, tiles_to_cells
from sevenfold.plans.planner import levels_opt_25d, valid_25d


def _grid_step(a: DataFrame, b: DataFrame, shape, g: int, layer: Callable[[Column, Column, Column], Column], layers: int, inner: int, tile: int, dtype: str, leaf: LeafSpec, only: int | None = None) -> DataFrame:
    """(path, bi, bj, vals) of the products; ``layer`` places an inner block on one of the layers, of which ``only`` takes one."""
    m, k, n = shape
    span = lambda tiles, parts: max(1, -(-tiles // parts))
    everyone = F.explode(F.sequence(F.lit(0), F.lit(g - 1)))
    block = lambda column, tiles, parts: F.floor(F.col(column) / span(tiles, parts)).cast("int")
    x = a.withColumn("gi", block("bi", m, g)).withColumn("kb", block("bj", k, inner)).withColumn("gj", everyone)
    y = b.withColumn("gj", block("bj", n, g)).withColumn("kb", block("bi", k, inner)).withColumn("gi", everyone)
    x, y = (f.withColumn("z", layer(F.col("gi"), F.col("gj"), F.col("kb")).cast("int")) for f in (x, y))
    if only is not None:
        x, y = x.where(F.col("z") == only), y.where(F.col("z") == only)
    number = ((F.col("path") * layers + F.col("z")) * g + F.col("gi")) * g + F.col("gj")
    out = dense_products(x, y, ["path", "gi", "gj", "z"], tile, dtype, leaf, (span(m, g), span(k, inner), span(n, g)), number)
    return out.select("path", "bi", "bj", "vals") if layers == 1 or only is not None else sum_tiles(out, ["path", "bi", "bj"])


def _run(a: TileMatrix, b: TileMatrix, g, layer, layers, inner, leaf) -> TileMatrix:
    if leaf.levels:
        a, b = refuse_not_finite(a), refuse_not_finite(b)
    shape = (*a.grid, b.grid[1])
    x, y = (m.df.withColumn("path", F.lit(0).cast("long")) for m in (a, b))
    out = _grid_step(x, y, shape, g, layer, layers, inner, a.tile, a.dtype, leaf)
    return replace(a, df=out.select("bi", "bj", "vals"), n_cols=b.n_cols)


CLASSICAL = LeafSpec()


def _in_rounds(a: TileMatrix, b: TileMatrix, rounds: int, part: Callable[[DataFrame, DataFrame, int], DataFrame]) -> TileMatrix:
    """Partial products one after another, each added to a durable sum; what was added is deleted."""
    total = None
    for t in range(rounds):
        step = part(a.df, b.df, t)
        before, total = total, durable(step if total is None else sum_tiles(total.unionByName(step), ["bi", "bj"]))
        release(before)
    return replace(a, df=total, n_cols=b.n_cols)


def grid2d(a: TileMatrix, b: TileMatrix, g: int = 4, leaf: LeafSpec = CLASSICAL, panel: int | None = None) -> TileMatrix:
    """g x g owners; rows of A and columns of B go to their owners as panels.

    With ``panel`` inner tiles a panel, the panels go one after another, and an
    owner holds one panel of each factor and its block of the sum. Without, all
    panels go at once.
    """
    if not panel:
        return _run(a, b, g, lambda i, j, k: F.lit(0), 1, 1, leaf)

    def part(x, y, t):
        own = lambda column: (F.col(column) >= t * panel) & (F.col(column) < (t + 1) * panel)
        return grid2d(a.with_df(x.where(own("bj"))), b.with_df(y.where(own("bi"))), g, leaf).df

    return _in_rounds(a, b, -(-a.grid[1] // panel), part)


def grid2d_shift(a: TileMatrix, b: TileMatrix, g: int = 4, leaf: LeafSpec = CLASSICAL, rounds: bool = False) -> TileMatrix:
    """g x g owners; in round t owner (i, j) has the skewed inner block (i + j + t) mod g.

    ``rounds`` runs the g rounds one after another, so that an owner holds one
    block of each factor at a time; otherwise all rounds are layers of one step.
    """
    turn = lambda i, j, k: F.pmod(k - i - j, F.lit(g))
    if not rounds:
        return _run(a, b, g, turn, g, g, leaf)
    shape = (*a.grid, b.grid[1])

    def part(x, y, t):
        x, y = (f.withColumn("path", F.lit(0).cast("long")) for f in (x, y))
        return _grid_step(x, y, shape, g, turn, g, g, a.tile, a.dtype, leaf, only=t).select("bi", "bj", "vals")

    return _in_rounds(a, b, g, part)


def grid3d(a: TileMatrix, b: TileMatrix, g: int = 2, leaf: LeafSpec = CLASSICAL) -> TileMatrix:
    """g x g x g owners, each with one inner block; the products are summed along it."""
    return _run(a, b, g, lambda i, j, k: k, g, g, leaf)


def copies_that_fit(n: int, workers: int, memory: float | None = None) -> int:
    """Most copies c of a valid grid whose share of the three matrices fits ``memory`` words a worker."""
    fits = [c for _, c in valid_25d(workers) if memory is None or 3 * n * n * c / workers <= memory]
    if not fits:
        raise ValueError(f"no 2.5D grid of {workers} workers fits {memory} words")
    return max(fits)


def grid25d(a: TileMatrix, b: TileMatrix, workers: int = 8, c: int | str = "auto", leaf: LeafSpec = CLASSICAL, memory: float | None = None) -> TileMatrix:
    """c layers of a sqrt(P/c) grid; a layer takes every c-th inner panel. With c = 1 this is 2D.

    ``auto`` takes as many copies as the grid allows and ``memory`` words a worker hold.
    """
    c = copies_that_fit(max(a.n_rows, a.n_cols, b.n_cols), workers, memory) if c == "auto" else c
    if (workers, c) not in valid_25d(workers):
        raise ValueError(f"no 2.5D grid of {workers} workers with {c} copies; valid are {valid_25d(workers)}")
    g = round((workers / c) ** 0.5)
    return _run(a, b, g, lambda i, j, k: F.pmod(k, F.lit(c)), c, g, leaf)


def grid2d_fast(a: TileMatrix, b: TileMatrix, g: int = 4, levels: int = 1) -> TileMatrix:
    """2D between the owners, fast inside."""
    return grid2d(a, b, g, LeafSpec(levels=levels, cutoff=1))


def grid25d_fast(a: TileMatrix, b: TileMatrix, workers: int = 8, c: int | str = "auto", levels: int = 1) -> TileMatrix:
    """2.5D between the owners, fast inside."""
    return grid25d(a, b, workers, c, LeafSpec(levels=levels, cutoff=1))


def fast_grid2d(a: TileMatrix, b: TileMatrix, levels: int = 1, g: int = 4, pack: bool = False) -> TileMatrix:
    """Fast levels outside, 2D inside. ``pack`` runs all subproducts in one job."""
    rule = lambda x, y, shape: _grid_step(x, y, shape, g, lambda i, j, k: F.lit(0), 1, 1, a.tile, a.dtype, CLASSICAL)
    return hybrid(a, b, ("W" if pack else "S") * levels, leaf_rule=rule)


def fast_grid25d(a: TileMatrix, b: TileMatrix, workers: int = 8, c: int = 2, levels: int | str = "opt", memory: float | None = None, pack: bool = True) -> TileMatrix:
    """Fast levels outside, 2.5D inside; ``opt`` takes the levels beyond which words grow."""
    if levels == "opt":
        levels = levels_opt_25d(a.n_rows, workers, memory or 3 * a.n_rows**2 * c / workers)
    if not levels:
        return grid25d(a, b, workers, c)
    g = round((workers / c) ** 0.5)
    rule = lambda x, y, shape: _grid_step(x, y, shape, g, lambda i, j, k: F.pmod(k, F.lit(c)), c, g, a.tile, a.dtype, CLASSICAL)
    return hybrid(a, b, ("W" if pack else "S") * levels, leaf_rule=rule)


def lib_block(a: TileMatrix, b: TileMatrix) -> DataFrame:
    """The block matrix of the machine-learning library, cells out. Doubles inside."""
    from pyspark.mllib.linalg import DenseMatrix
    from pyspark.mllib.linalg.distributed import BlockMatrix

    def blocks(m: TileMatrix):
        t = m.tile
        rows = m.df.select("bi", "bj", "vals").rdd.map(lambda r: ((r[0], r[1]), DenseMatrix(t, t, [float(x) for x in r[2]], True)))
        return BlockMatrix(rows, t, t, m.grid[0] * t, m.grid[1] * t)

    entries = blocks(a).multiply(blocks(b)).toCoordinateMatrix().entries
    cells = a.df.sparkSession.createDataFrame(entries.map(lambda e: (e.i, e.j, e.value)), "i long, j long, v double")
    return cells.where("v <> 0").select("i", "j", F.round("v").cast("long").alias("v") if a.dtype == "bigint" else "v")


__all__ = ["fast_grid25d", "fast_grid2d", "grid25d", "grid25d_fast", "grid2d", "grid2d_fast", "grid2d_shift", "grid3d", "lib_block", "tiles_to_cells"]

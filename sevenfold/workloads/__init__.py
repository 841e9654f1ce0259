"""Named queries over the given tables, with SQL for each that SQL can express."""

from __future__ import annotations

from sevenfold.operators.hybrid import wide
from sevenfold.operators.tiles import tiles_to_cells
from sevenfold.workloads import accuracy, costs, products, streams, surrounding  # noqa: F401  they register their queries
from sevenfold.workloads.registry import ORACLES, QUERIES, as_cells, fold_tiles

__all__ = ["ORACLES", "QUERIES", "entry"]


def entry(spark, sf_dir: str):
    """The flagship: the fold product by wide levels on seven logical workers."""
    a, b = fold_tiles(spark, sf_dir)
    return as_cells(tiles_to_cells(wide(a, b, 7)))

"""Where queries and their SQL are put, and what they share."""

from __future__ import annotations

from pyspark.sql import functions as F

from sevenfold.operators.tiles import cells_to_tiles
from sevenfold.sources.matrices import FOLD_SQL, PRODUCT_SQL, fold_pair

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
#: Side of a tile by the side of the fold matrices.
TILES = {56: 7, 224: 28, 672: 84}
FOLD_PRODUCT = f"WITH {FOLD_SQL} {PRODUCT_SQL}"


def query(name: str, sql: str | None = None):
    """Register a function of (spark, sf_dir), and SQL that gives the same rows."""

    def put(f):
        if name in QUERIES:
            raise ValueError(f"{name} is there already")
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


def as_cells(df):
    return df.select(F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), F.col("v").cast("long").alias("v"))


def fold_tiles(spark, d):
    a, b, n = fold_pair(spark, d)
    return tuple(cells_to_tiles(x, n, n, TILES[n]) for x in (a, b))

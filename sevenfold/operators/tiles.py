"""Matrices as DataFrames: keyed tiles for dense ones, (i, j, v) cells for the rest."""

from __future__ import annotations

import tempfile
from dataclasses import dataclass, replace
from decimal import Decimal

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


#: Cell types: 64-bit integers and decimals are exact, doubles round.
INTEGER, EXACT, DOUBLE = "bigint", "decimal(38,0)", "double"


def shared_folder(spark: SparkSession) -> str:
    """The folder that ``spark.checkpoint.dir`` names; in local mode a fresh one if none is set.

    On a cluster a folder of one machine would not do, so there it must be named.
    """
    sc = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not named:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        named = tempfile.mkdtemp(prefix="sevenfold-checkpoint-")
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(named)
    return named.rstrip("/")


def durable(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in the shared folder; keeps the partitioning."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def release(df: DataFrame | None) -> None:
    """Delete the files of a checkpoint that nothing will read again."""
    if df is None:
        return
    plan = df._jdf.queryExecution().logical()
    if plan.getClass().getSimpleName() != "LogicalRDD" or not plan.rdd().getCheckpointFile().isDefined():
        raise ValueError("not a checkpoint")
    spark = df.sparkSession
    path = spark._jvm.org.apache.hadoop.fs.Path(plan.rdd().getCheckpointFile().get())
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def numpy_kind(dtype: str):
    """numpy's type for cells: Python integers hold decimals, as these don't overflow."""
    return {INTEGER: np.int64, EXACT: object, DOUBLE: np.float64}[dtype]


def as_numpy(values, dtype: str) -> np.ndarray:
    """A tile's values (Arrow, numpy or a list) as numpy."""
    if dtype == EXACT:
        return np.array([int(v) for v in (values.to_pylist() if hasattr(values, "to_pylist") else values)], dtype=object)
    return values.to_numpy(zero_copy_only=False) if hasattr(values, "to_pylist") else np.asarray(values)


def as_cells(values: np.ndarray, dtype: str):
    """What goes back to Spark: decimals for Python integers; raises beyond 38 digits."""
    if dtype != EXACT:
        return values
    if len(values) and max(abs(int(v)) for v in values) >= 10**38:
        raise OverflowError("a cell has more than 38 digits")
    return np.array([Decimal(int(v)) for v in values], dtype=object)


def not_a_number_kept(df: DataFrame, dtype: str) -> DataFrame:
    """Doubles that come from pandas: it hands NaN within a tile over as null, and here it is NaN again."""
    return df.withColumn("vals", F.expr("transform(vals, v -> coalesce(v, double('NaN')))")) if dtype == DOUBLE else df


def largest(x: np.ndarray) -> int:
    """Largest magnitude, as a Python integer so that bounds don't wrap."""
    return max(abs(int(x.max())), abs(int(x.min()))) if x.size else 0


@dataclass(frozen=True)
class TileMatrix:
    """Square tiles (bi, bj, vals row by row); an absent tile is zero, edge tiles are zero-padded."""

    df: DataFrame
    n_rows: int
    n_cols: int
    tile: int
    dtype: str = "bigint"

    @property
    def grid(self) -> tuple[int, int]:
        return -(-self.n_rows // self.tile), -(-self.n_cols // self.tile)

    def with_df(self, df: DataFrame) -> TileMatrix:
        return replace(self, df=df)


def cells_to_tiles(cells: DataFrame, n_rows: int, n_cols: int, tile: int, dtype: str = "bigint") -> TileMatrix:
    """From (i, j, v), at most one row a cell. Null values are refused; a NaN is a value."""
    size = tile * tile
    kind = numpy_kind(dtype)

    def fill(rows: pd.DataFrame) -> pd.DataFrame:
        vals = np.zeros(size, dtype=kind)
        np.add.at(vals, rows["pos"].to_numpy(), as_numpy(rows["v"].to_numpy(), dtype).astype(kind))
        return pd.DataFrame({"bi": rows["bi"].iloc[:1], "bj": rows["bj"].iloc[:1], "vals": [as_cells(vals, dtype)]})

    value = F.col("v").cast(dtype)
    keyed = cells.select(
        F.floor(F.col("i") / tile).cast("int").alias("bi"),
        F.floor(F.col("j") / tile).cast("int").alias("bj"),
        (F.pmod("i", F.lit(tile)) * tile + F.pmod("j", F.lit(tile))).cast("int").alias("pos"),
        F.when(value.isNotNull(), value).otherwise(F.raise_error(F.lit("a cell is null")).cast(dtype)).alias("v"),
    )
    df = keyed.groupBy("bi", "bj").applyInPandas(fill, f"bi int, bj int, vals array<{dtype}>")
    return TileMatrix(not_a_number_kept(df, dtype), n_rows, n_cols, tile, dtype)


def refuse_not_finite(m: TileMatrix) -> TileMatrix:
    """Raises, when run, at a NaN or an infinity: sums of a fast scheme would spread it over whole quadrants."""
    if m.dtype != DOUBLE:
        return m
    fine = (F.array_max("vals") < float("inf")) & (F.array_min("vals") > float("-inf"))  # NaN is above all
    spread = F.raise_error(F.lit("a cell is not finite; use a classical method")).cast("array<double>")
    return m.with_df(m.df.withColumn("vals", F.when(fine, F.col("vals")).otherwise(spread)))


def exact_twin(m: TileMatrix) -> TileMatrix:
    """The same integers as decimals of 38 digits."""
    return replace(m, df=m.df.withColumn("vals", F.col("vals").cast(f"array<{EXACT}>")), dtype=EXACT)


def tiles_to_cells(m: TileMatrix, keep_zero: bool = False) -> DataFrame:
    t = m.tile
    out = m.df.select("bi", "bj", F.posexplode("vals").alias("pos", "v")).select(
        (F.col("bi").cast("long") * t + F.floor(F.col("pos") / t)).alias("i"), (F.col("bj").cast("long") * t + F.col("pos") % t).alias("j"), "v"
    )
    out = out.where((F.col("i") < m.n_rows) & (F.col("j") < m.n_cols))
    return out if keep_zero else out.where("v <> 0")


def slice_tiles(m: TileMatrix, rows: tuple[int, int], cols: tuple[int, int]) -> TileMatrix:
    """The cells of half-open ranges; others are zero.

    Tiles off the ranges go by their keys, which a scan can prune; only tiles
    across an edge are opened, and lose the cells beyond it.
    """
    t = m.tile
    near = m.df.where((F.col("bi") >= rows[0] // t) & (F.col("bi") < -(-rows[1] // t)) & (F.col("bj") >= cols[0] // t) & (F.col("bj") < -(-cols[1] // t)))
    whole = (F.col("bi") * t >= rows[0]) & ((F.col("bi") + 1) * t <= rows[1]) & (F.col("bj") * t >= cols[0]) & ((F.col("bj") + 1) * t <= cols[1])
    i, j = f"bi * {t} + p div {t}", f"bj * {t} + p % {t}"
    cut = F.expr(f"transform(vals, (v, p) -> IF({i} >= {rows[0]} AND {i} < {rows[1]} AND {j} >= {cols[0]} AND {j} < {cols[1]}, v, CAST(0 AS {m.dtype})))")
    return m.with_df(near.withColumn("vals", F.when(whole, F.col("vals")).otherwise(cut)))


def scaled(x: Column, c: int) -> Column:
    return x if c == 1 else F.transform(x, lambda a: a * F.lit(c))


def relayout(m: TileMatrix, spec, tasks: int | None = None) -> TileMatrix:
    """Rearranged to a layout: every tile goes to the task of its owner, the matrix moves once.

    ``spec`` is a layout over logical workers, whose blocks are whole tiles;
    worker w is task w modulo ``tasks``, by default one task each.
    """
    rows, cols = spec.block
    if rows % m.tile or cols % m.tile:
        raise ValueError(f"blocks of {rows} x {cols} aren't made of whole tiles of {m.tile}")
    owner = spec.owner(F.floor(F.col("bi") * m.tile / rows), F.floor(F.col("bj") * m.tile / cols))
    n = tasks or spec.workers
    return m.with_df(m.df.withColumn("owner", owner).repartitionById(n, F.pmod(F.col("owner"), F.lit(n)).cast("int")))


def sum_of(terms: list[tuple[int, str]]) -> str:
    """SQL for the sum of coefficient times tile; null operands are zero tiles, all null gives null.

    Additions of 64-bit integers that don't fit raise.
    """
    times = lambda c, x: x if c == 1 else f"transform({x}, t -> {c} * t)"
    total = times(*terms[0])
    for c, x in terms[1:]:
        joint = "u + t" if c == 1 else "u - t" if c == -1 else f"u + {c} * t"
        total = f"coalesce(zip_with({total}, {x}, (u, t) -> {joint}), {total}, {times(c, x)})"
    return total


def sum_tiles(df: DataFrame, keys: list[str]) -> DataFrame:
    """Elementwise sum of the tiles of a key."""
    parts = F.collect_list("vals")
    total = F.aggregate(F.slice(parts, 2, F.greatest(F.size(parts) - 1, F.lit(0))), F.element_at(parts, 1), lambda a, x: F.zip_with(a, x, lambda p, q: p + q))
    return df.groupBy(*keys).agg(total.alias("vals"))


def transpose(m: TileMatrix) -> TileMatrix:
    t = m.tile
    turned = F.transform(F.sequence(F.lit(0), F.lit(t * t - 1)), lambda k: F.element_at("vals", ((k % t) * t + F.floor(k / t) + 1).cast("int")))
    return replace(m, df=m.df.select(F.col("bj").alias("bi"), F.col("bi").alias("bj"), turned.alias("vals")), n_rows=m.n_cols, n_cols=m.n_rows)


def axpy(a: int, x: TileMatrix, b: int, y: TileMatrix) -> TileMatrix:
    """a * x + b * y."""
    both = x.df.select("bi", "bj", scaled(F.col("vals"), a).alias("vals")).unionByName(y.df.select("bi", "bj", scaled(F.col("vals"), b).alias("vals")))
    return x.with_df(sum_tiles(both, ["bi", "bj"]))


def write_tiles(m: TileMatrix, path: str, band: int = 8) -> None:
    """Parquet by bands of tile rows, so that a row range reads few files."""
    m.df.withColumn("band", F.floor(F.col("bi") / band).cast("int")).write.mode("overwrite").partitionBy("band").parquet(path)


def read_tiles(spark: SparkSession, path: str, like: TileMatrix, rows: tuple[int, int] | None = None, band: int = 8) -> TileMatrix:
    """Tiles of the tile rows in the half-open range ``rows``, or all."""
    df = spark.read.parquet(path)
    if rows:
        df = df.where(F.col("band").between(rows[0] // band, (rows[1] - 1) // band) & (F.col("bi") >= rows[0]) & (F.col("bi") < rows[1]))
    return like.with_df(df.select("bi", "bj", "vals"))

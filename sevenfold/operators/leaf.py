"""Local products: dense kernels on what one task holds, or tile products by a join."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sevenfold.operators.tiles import as_cells, as_numpy, largest, not_a_number_kept, numpy_kind, sum_tiles
from sevenfold.plans.schemes import Scheme, Stages, scheme_of


@dataclass(frozen=True)
class LeafSpec:
    """``kind``: dense (one task per leaf) or tiles (a join, for leaves beyond a task's memory).

    ``levels`` fast levels inside the dense kernel, none below ``cutoff``.
    """

    kind: str = "dense"
    levels: int = 0
    cutoff: int = 64
    scheme: str = "s7a15"
    most_bytes: int = 2 << 30


def _combine(stages: Stages, inputs: list[np.ndarray]) -> list[np.ndarray]:
    known = {str(k): x for k, x in enumerate(inputs)}
    for name, terms in stages.steps:
        known[name] = sum((c * known[x] for c, x in terms[1:]), terms[0][0] * known[terms[0][1]])
    return [known[x] for x in stages.outputs]


def classical_product(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact for integers: by floating point where every sum is below 2**53. Raises where 64 bits may not do."""
    if a.dtype != np.int64:
        return a @ b
    bound = largest(a) * largest(b) * a.shape[1]
    if bound < 1 << 53:
        return (a.astype(np.float64) @ b.astype(np.float64)).astype(np.int64)
    if bound >= 1 << 63:
        raise OverflowError(f"the product may not fit 64 bits; use cells of {'decimal(38,0)'}")
    return a @ b


def seq_fast(a: np.ndarray, b: np.ndarray, levels: int, scheme: Scheme | str = "s7a15", cutoff: int = 1) -> np.ndarray:
    """Recursive fast product; classical at the cutoff or where a side doesn't split.

    Integers are classical too where the sums of the levels might not fit 64 bits.
    """
    s = scheme_of(scheme)
    n0 = s.n0
    if not levels or min(*a.shape, b.shape[1]) <= cutoff or any(x % n0 for x in (*a.shape, b.shape[1])):
        return classical_product(a, b)
    if a.dtype == np.int64 and s.growth() ** levels * largest(a) * largest(b) * a.shape[1] >= 1 << 63:
        return classical_product(a, b)

    def blocks(x):
        r, c = x.shape[0] // n0, x.shape[1] // n0
        return [x[i * r : (i + 1) * r, j * c : (j + 1) * c] for i in range(n0) for j in range(n0)]

    left, right = _combine(s.left, blocks(a)), _combine(s.right, blocks(b))
    out = _combine(s.out, [seq_fast(x, y, levels - 1, s, cutoff) for x, y in zip(left, right, strict=True)])
    return np.block([out[i * n0 : (i + 1) * n0] for i in range(n0)])


def _dense(rows: pd.DataFrame, row: str, col: str, row_ids: np.ndarray, col_ids: np.ndarray, t: int, dtype: str) -> np.ndarray:
    out = np.zeros((len(row_ids), t, len(col_ids), t), dtype=numpy_kind(dtype))
    r, c = np.searchsorted(row_ids, rows[row].to_numpy()), np.searchsorted(col_ids, rows[col].to_numpy())
    for x, y, v in zip(r, c, rows["vals"], strict=True):
        out[x, :, y, :] = as_numpy(v, dtype).reshape(t, t)
    return out.reshape(len(row_ids) * t, len(col_ids) * t)


def dense_products(a: DataFrame, b: DataFrame, keys: list[str], tile: int, dtype: str, leaf: LeafSpec, per: tuple[int, int, int] | None = None, number: Column | None = None) -> DataFrame:
    """One product per key: tiles (keys, bi, bj, vals) of a and b to those of the product.

    ``number`` counts the keys from 0. Keys are then dealt to the tasks in turn:
    they are few and equal in size, so hashing would leave some tasks with two
    or three times the work of others. ``per`` gives the tile rows, inner tiles and tile columns that a full key
    has, so that absent tiles keep the fast levels even.
    """
    kind = numpy_kind(dtype)

    def product(x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        if not len(x) or not len(y):
            return pd.DataFrame({c: pd.Series([], dtype="object" if c == "vals" else "int64") for c in (*keys, "bi", "bj", "vals")})
        inner = np.union1d(x["bj"].unique(), y["bi"].unique())
        rows, cols = np.unique(x["bi"]), np.unique(y["bj"])
        if per and leaf.levels:
            fill = lambda ids, n: ids if len(ids) >= n else np.union1d(ids, np.setdiff1d(np.arange(ids.min() // n * n, ids.min() // n * n + n), ids)[: n - len(ids)])
            rows, inner, cols = (fill(i, n) for i, n in zip((rows, inner, cols), per, strict=True))
        held = 8 * tile * tile * (len(rows) * len(inner) + len(inner) * len(cols) + len(rows) * len(cols))
        if held > leaf.most_bytes:
            raise MemoryError(f"a leaf takes {held} bytes; use more levels or LeafSpec(kind='tiles')")
        p = _dense(x, "bi", "bj", rows, inner, tile, dtype)
        q = _dense(y, "bi", "bj", inner, cols, tile, dtype)
        c = seq_fast(p, q, leaf.levels, leaf.scheme, leaf.cutoff).astype(kind)
        cut = c.reshape(len(rows), tile, len(cols), tile)
        out = [(i, j, as_cells(cut[a, :, b, :].ravel(), dtype)) for a, i in enumerate(rows) for b, j in enumerate(cols)]
        frame = pd.DataFrame(out, columns=["bi", "bj", "vals"])
        for name in keys:
            frame[name] = x[name].iloc[0]
        return frame[[*keys, "bi", "bj", "vals"]]

    kinds = dict(a.dtypes)
    schema = ", ".join(f"{k} {kinds[k]}" for k in keys) + f", bi int, bj int, vals array<{dtype}>"
    cols = [*keys, "bi", "bj", "vals"]
    if number is None:
        made = a.select(*cols).groupBy(*keys).cogroup(b.select(*cols).groupBy(*keys)).applyInPandas(product, schema)
        return not_a_number_kept(made, dtype)
    tasks = max(int(a.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    task = F.pmod(number, F.lit(tasks)).cast("int").alias("task")
    x, y = (f.select(task, *cols).repartitionById(tasks, F.col("task")).groupBy("task", *keys) for f in (a, b))
    return not_a_number_kept(x.cogroup(y).applyInPandas(product, schema), dtype)


def tile_gemm(tile: int, dtype: str):
    """Vectorised UDF: product of two square tiles."""
    kind = numpy_kind(dtype)

    @F.pandas_udf(f"array<{dtype}>")
    def gemm(a: pd.Series, b: pd.Series) -> pd.Series:
        x, y = (np.stack([as_numpy(v, dtype) for v in s]).reshape(-1, tile, tile) for s in (a, b))
        return pd.Series([as_cells(classical_product(p, q).astype(kind).ravel(), dtype) for p, q in zip(x, y, strict=True)])

    return gemm


def tile_products(a: DataFrame, b: DataFrame, keys: list[str], tile: int, dtype: str) -> DataFrame:
    """Products of any size: join on the inner tile index, multiply tiles, sum."""
    x = a.select(*keys, "bi", F.col("bj").alias("k"), F.col("vals").alias("x"))
    y = b.select(*keys, F.col("bi").alias("k"), "bj", F.col("vals").alias("y"))
    parts = x.join(y, [*keys, "k"]).select(*keys, "bi", "bj", tile_gemm(tile, dtype)("x", "y").alias("vals"))
    return sum_tiles(not_a_number_kept(parts, dtype), [*keys, "bi", "bj"])

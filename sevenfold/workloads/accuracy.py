"""Accuracy: every bound against an exact reference, scaling that repairs, growth by level, exactness."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sevenfold.operators import accuracy as acc
from sevenfold.operators import grids
from sevenfold.operators import relational as rel
from sevenfold.operators.hybrid import hybrid
from sevenfold.operators.leaf import LeafSpec
from sevenfold.operators.tiles import cells_to_tiles, durable, exact_twin, tiles_to_cells
from sevenfold.sources.matrices import FOLD_SQL, PRODUCT_SQL, fold_pair
from sevenfold.workloads.registry import TILES, query

#: Bits by which the cells are shifted to be integers.
SHIFT = 12
#: Exponents of the factors' grades by case, in i and j.
GRADES = {"both": ("3 * i - 5 * j", "3 * i - 5 * j"), "outer": ("3 * i", "5 * j"), "inner": ("5 * j", "5 * i"), "none": ("12", "12")}

#: The grades repeat after this many rows or columns.
PERIOD = 24
#: Tiles by which no half or quarter of the padded sides is a multiple of the period. Else blocks that are
#: added up have the same grades, scaling commutes with the sums, and the product is scaled without being asked to be.
GRADED_TILES = TILES | {672: 25}


def _sign(case: str, side: int) -> int:
    return -1 if case == "inner" and side else 1


def _integers(case: str) -> str:
    """SQL for the graded factors as integers x and y: 2**SHIFT times their cells."""
    grade = lambda text, sign: f"{SHIFT} {'+' if sign > 0 else '-'} (((({text}) % 24) + 24) % 24 - 12)"
    mantissa = "(v * 1048576 + (i * {p} + j * {q}) % 1048576)"
    parts = []
    for name, table, side, p, q in (("x", "a", 0, 7919, 104729), ("y", "b", 1, 15485863, 32452843)):
        parts.append(f"{name} AS (SELECT i, j, CAST({mantissa.format(p=p, q=q)} * CAST(pow(2, {grade(GRADES[case][side], _sign(case, side))}) AS BIGINT) AS BIGINT) AS v FROM {table})")
    return ", ".join(parts)


def graded(spark, d, case: str) -> tuple[DataFrame, DataFrame, int]:
    """The fold matrices with long mantissas and magnitudes over 24 powers of two, as doubles without rounding.

    both: graded along and across, as no scaling can level. outer: rows of the
    left, columns of the right factor. inner: the inner index, in opposite ways.
    """
    out = []
    a, b, n = fold_pair(spark, d)
    for x, side, p, q in ((a, 0, 7919, 104729), (b, 1, 15485863, 32452843)):
        mantissa = F.col("v") * 1048576 + F.pmod(F.col("i") * p + F.col("j") * q, F.lit(1048576))
        power = (F.pmod(F.expr(GRADES[case][side]), F.lit(24)) - 12) * _sign(case, side)
        out.append(durable(x.select("i", "j", (mantissa.cast("double") * F.pow(F.lit(2.0), power)).alias("v"))))
    return out[0], out[1], n


def _product(kind: str, n: int):
    """A product of double cells: classical, or with that many fast levels over classical leaves."""
    tile = GRADED_TILES[n]

    def run(a: DataFrame, b: DataFrame) -> DataFrame:
        x, y = (cells_to_tiles(m, n, n, tile, "double") for m in (a, b))
        return durable(tiles_to_cells(grids.grid2d(x, y, 2) if kind == "classical" else hybrid(x, y, "W", leaf=LeafSpec(levels=int(kind) - 1, cutoff=1))))

    return run


def measured(spark, d, case: str, runs: list[tuple[str, str, str | None, str]]) -> DataFrame:
    """(product, measure, n, cells, checksum, value, holds) of ``runs`` (product, kind, scaling, measure) on one graded pair."""
    a, b, n = graded(spark, d, case)
    x, y = (durable(acc.to_integers(m, SHIFT)) for m in (a, b))
    exact = durable(acc.exact_product(x, y))
    rows = []
    for name, kind, scaling, measure in runs:
        run = _product(kind, n)
        got = run(a, b) if scaling is None else durable(acc.scaled_multiply(a, b, scaling, lambda p, q, f=run: f(durable(p), durable(q))))
        rows.append(acc.judge(measure, exact, acc.to_integers(got, 2 * SHIFT), x, y, n).withColumn("product", F.lit(name)))
    total = exact.agg(F.sum("v").cast("string").alias("checksum"), F.count("*").alias("cells"))
    checksum, cells = total.first()
    return reduce(DataFrame.unionByName, rows).withColumn("checksum", F.lit(checksum)).withColumn("cells", F.lit(cells))


CASES = {
    "a_componentwise": ("both", [("classical", "classical", None, "componentwise"), ("fast", "2", None, "componentwise")], [True, False]),
    "a_normwise": ("both", [("classical", "classical", None, "normwise"), ("fast", "2", None, "normwise")], [True, True]),
    "a_scaled_outer": ("outer", [("fast", "2", None, "outer"), ("fast, scaled", "2", "outer", "outer")], [False, True]),
    "a_scaled_inner": ("inner", [("fast", "2", None, "inner"), ("fast, scaled", "2", "inner", "inner")], [False, True]),
}
VERDICT = ["product", "measure", "n", "cells", "checksum", "holds"]


def _verdict_sql(case: str, runs, holds) -> str:
    """The exact product in integers by SQL, and what the theory says of each bound."""
    values = ", ".join(f"('{name}', '{measure}', {str(h).lower()})" for (name, _, _, measure), h in zip(runs, holds, strict=True))
    return f"""WITH {FOLD_SQL}, {_integers(case)},
c AS (SELECT x.i AS i, y.j AS j, sum(CAST(x.v AS HUGEINT) * CAST(y.v AS HUGEINT)) AS v FROM x JOIN y ON x.j = y.i GROUP BY 1, 2),
t AS (SELECT count(*) AS cells, CAST(CAST(sum(v) AS HUGEINT) AS VARCHAR) AS checksum FROM c WHERE v <> 0)
SELECT product, measure, CAST(n AS INTEGER) AS n, cells, checksum, holds FROM (VALUES {values}) AS q(product, measure, holds), n, t"""


def _verdict(case, runs):
    return lambda spark, d: measured(spark, d, case, runs).select(*VERDICT)


for _name, (_case, _runs, _holds) in CASES.items():
    query(_name, _verdict_sql(_case, _runs, _holds))(_verdict(_case, _runs))


@query("a_growth", f"WITH {FOLD_SQL} SELECT CAST(l AS VARCHAR) AS product, 'normwise' AS measure, CAST(n AS INTEGER) AS n, true AS holds FROM n, (SELECT unnest(range(1, 4)) AS l)")
def a_growth(spark, d):
    """The normwise bound with one to three fast levels."""
    return a_growth_values(spark, d).select("product", "measure", "n", "holds")


@query("a_growth_values")
def a_growth_values(spark, d):
    """How the error over eps times the norms grows with the levels; depends on the machine's order of summation."""
    return measured(spark, d, "none", [(str(k), str(k), None, "normwise") for k in (1, 2, 3)]).select("product", "measure", "n", "value", "holds")


@query("a_values")
def a_values(spark, d):
    """The measured size of every error over its bound's unit; depends on the machine's order of summation."""
    parts = [measured(spark, d, case, runs).withColumn("query", F.lit(name)) for name, (case, runs, _) in CASES.items()]
    return reduce(DataFrame.unionByName, parts).select("query", "product", "measure", "n", "value", "holds")


@query("a_norms", f"""WITH {FOLD_SQL} SELECT 'one' AS kind, CAST(max(s) AS BIGINT) AS v FROM (SELECT j, sum(abs(v)) AS s FROM a GROUP BY j)
UNION ALL SELECT 'inf', CAST(max(s) AS BIGINT) FROM (SELECT i, sum(abs(v)) AS s FROM a GROUP BY i)
UNION ALL SELECT 'squares', CAST(sum(v * v) AS BIGINT) FROM a UNION ALL SELECT 'max', CAST(max(abs(v)) AS BIGINT) FROM a""")
def a_norms(spark, d):
    return rel.norms(fold_pair(spark, d)[0])


@query("a_overflow", f"""WITH {FOLD_SQL} SELECT CAST((SELECT max(abs(v)) FROM a) AS DOUBLE) * (SELECT max(abs(v)) FROM b) * n * 324 AS bound, true AS exact FROM n
UNION ALL SELECT CAST((SELECT max(abs(v)) FROM a) AS DOUBLE) * 1073741824 * (SELECT max(abs(v)) FROM b) * 1073741824 * n * 324, false FROM n""")
def a_overflow(spark, d):
    """The bound on all sums on the way, for the fold matrices and for these times 2**30 each, which 64 bits don't hold."""
    a, b, n = fold_pair(spark, d)
    grown = lambda x: x.withColumn("v", F.col("v") * (1 << 30))
    return acc.overflow_bound(a, b, n, levels=2).unionByName(acc.overflow_bound(grown(a), grown(b), n, levels=2))


@query("a_beyond_64_bits", f"WITH {FOLD_SQL}, p AS ({PRODUCT_SQL}) SELECT i, j, CAST(CAST(v AS HUGEINT) * 1152921504606846976 AS VARCHAR) AS v FROM p")
def a_beyond_64_bits(spark, d):
    """The product of the fold matrices times 2**30 each: decimals give it whole where 64-bit integers raise."""
    a, b, n = fold_pair(spark, d)
    x, y = (exact_twin(cells_to_tiles(m.withColumn("v", F.col("v") * (1 << 30)), n, n, TILES[n])) for m in (a, b))
    return tiles_to_cells(hybrid(x, y, "W")).select("i", "j", F.col("v").cast("string").alias("v"))


@query("a_random_check", "SELECT CAST(0 AS BIGINT) AS mismatches")
def a_random_check(spark, d):
    a, b, n = fold_pair(spark, d)
    a, b = durable(a), durable(b)
    c = durable(tiles_to_cells(hybrid(*(cells_to_tiles(x, n, n, TILES[n]) for x in (a, b)), "W")))
    return acc.random_check(a, b, c)

"""Fast multiplication along a schedule of wide and serial levels.

Tiles carry a ``path``: the subproblem that they belong to, its digits in base q.
A tile's place, the residues of its row and column, stays the same on every
level, so with tiles dealt by it every level's sums are local: matching
quadrants lie in one partition. A wide level fans out all q subproblems in one
plan; a serial level runs them one after another, adding each product to a
durable accumulator. Its operands are durable too, so they are made once and
not once for each subproblem, and what a level has used up is deleted.
"""

from __future__ import annotations

import math
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sevenfold.operators.leaf import LeafSpec, dense_products, tile_products
from sevenfold.operators.tiles import EXACT, TileMatrix, as_cells, as_numpy, cells_to_tiles, durable, largest, refuse_not_finite, release, sum_of, sum_tiles, tiles_to_cells
from sevenfold.plans.planner import plan_budgeted, plan_greedy
from sevenfold.plans.layout import digits_of
from sevenfold.plans.schemes import Scheme, Stages, scheme_of


def _residues(tiles: int, tasks: int) -> tuple[int, int]:
    """Side of the cyclic grid for a leaf of ``tiles`` a side, and the leaf's side once padded to a multiple of it.

    The places are what the tasks are dealt, so they grow with them, up to 16 a
    task. Absent tiles pad at no cost, so any number of tiles will do: the side
    is the largest that pads by a sixteenth at most.
    """
    most = max(14, math.isqrt(16 * tasks))
    up = lambda d: -(-tiles // d) * d
    side = max(d for d in range(1, min(tiles, most) + 1) if 16 * (up(d) - tiles) <= tiles)
    return side, up(side)


#: Beyond this many operands, or values a tile, sums run on Arrow batches instead of native functions.
NATIVE_SLOTS, NATIVE_VALUES = 8, 4096


def _added(terms: list[tuple[int, np.ndarray]]) -> np.ndarray | None:
    """Signed sum of the tiles that are there. Raises where 64-bit integers might wrap."""
    if not terms:
        return None
    c, total = terms[0]
    if total.dtype == np.int64 and sum(abs(c) * largest(x) for c, x in terms) >= 1 << 63:
        whole = sum(c * x.astype(object) for c, x in terms)
        if largest(whole) >= 1 << 63:
            raise OverflowError(f"a sum of tiles doesn't fit 64 bits; use cells of {EXACT}")
        return whole.astype(np.int64)
    total = total if c == 1 else c * total
    for c, x in terms[1:]:
        total = total + x if c == 1 else total - x if c == -1 else total + c * x
    return total


def combine(df: DataFrame, keys: list[str], slot: Column, slots: int, stages: Stages, tile: int, dtype: str, only: int | None = None) -> DataFrame:
    """Gather the tiles of a key by slot, and emit (keys, r, vals) for each output of the stages.

    The shared steps are evaluated once per key. A key without any operand of an
    output emits no tile for it.
    """
    gathered = df.groupBy(*keys).agg(*(F.first(F.when(slot == k, F.col("vals")), ignorenulls=True).alias(f"s{k}") for k in range(slots)))
    wanted = stages.outputs if only is None else (stages.outputs[only],)
    numbered = [(k if only is None else only, x) for k, x in enumerate(wanted)]
    needed, todo = set(), list(wanted)
    terms_of = dict(stages.steps)
    while todo:
        x = todo.pop()
        if x in terms_of and x not in needed:
            needed.add(x)
            todo += [y for _, y in terms_of[x]]
    steps = [(name, terms) for name, terms in stages.steps if name in needed]
    if slots > NATIVE_SLOTS or len(stages.outputs) > NATIVE_SLOTS or tile * tile > NATIVE_VALUES or dtype == EXACT:

        def sums(batches):
            for batch in batches:
                tiles = [batch.column(f"s{k}") for k in range(slots)]
                for row in range(batch.num_rows):
                    known = {str(k): as_numpy(x[row].values, dtype) if x[row].is_valid else None for k, x in enumerate(tiles)}
                    for name, terms in steps:
                        known[name] = _added([(c, known[x]) for c, x in terms if known[x] is not None])
                    out = [(k, known[x]) for k, x in numbered if known[x] is not None]
                    if out:
                        flat = pa.array(np.concatenate([as_cells(v, dtype) for _, v in out]), pa.decimal128(38, 0) if dtype == EXACT else None)
                        vals = pa.ListArray.from_arrays(np.arange(len(out) + 1, dtype=np.int32) * len(out[0][1]), flat)
                        same = [pa.repeat(batch.column(name)[row], len(out)) for name in keys]
                        yield pa.RecordBatch.from_arrays([*same, pa.array([k for k, _ in out], pa.int32()), vals], [*keys, "r", "vals"])

        kinds = dict(gathered.dtypes)
        return gathered.mapInArrow(sums, ", ".join(f"{k} {kinds[k]}" for k in keys) + f", r int, vals array<{dtype}>")
    # steps whose operands are there go into one projection, so that the plan stays small
    at, depth = {str(k): f"s{k}" for k in range(slots)}, {str(k): 0 for k in range(slots)}
    for name, terms in steps:
        depth[name], at[name] = 1 + max(depth[x] for _, x in terms), f"v_{name}"
    for level in sorted({depth[name] for name, _ in steps}):
        gathered = gathered.select("*", *(F.expr(sum_of([(c, at[x]) for c, x in terms])).alias(at[name]) for name, terms in steps if depth[name] == level))
    made = ", ".join(f"named_struct('r', {k}, 'vals', {at[x]})" for k, x in numbered)
    return gathered.select(*keys, F.expr(f"inline(array({made}))")).where("vals is not null")


class _Run:
    def __init__(self, a: TileMatrix, b: TileMatrix, depth: int, scheme: Scheme, leaf: LeafSpec, c: int, exchange: str, leaf_rule=None):
        self.s, self.leaf, self.c, self.exchange, self.tile, self.dtype = scheme, leaf, c, exchange, a.tile, a.dtype
        unit = scheme.n0**depth
        self.leaf_rule = leaf_rule
        self.tasks = max(int(a.df.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
        sides = [_residues(-(-x // unit), self.tasks) for x in (a.grid[0], a.grid[1], b.grid[1])]
        self.res = tuple(side for side, _ in sides)
        self.shape = tuple(padded * unit for _, padded in sides)

    def lay(self, df: DataFrame, rows: int, cols: int) -> DataFrame:
        """Deal the tiles by their residues, places to tasks in turn."""
        df = df.withColumn("place", (F.col("bi") % rows * cols + F.col("bj") % cols).cast("int"))
        return df.repartitionById(self.tasks, F.col("place"))

    def down(self, df, stages, rows, cols, only=None):
        """Combinations of quadrants: subproblems of a level, r in the path."""
        n0 = self.s.n0
        hr, hc = rows // n0, cols // n0
        slot = F.floor(F.col("bi") / hr).cast("int") * n0 + F.floor(F.col("bj") / hc).cast("int")
        df = df.withColumn("slot", slot).withColumn("bi", F.col("bi") % hr).withColumn("bj", F.col("bj") % hc)
        out = combine(df, ["path", "bi", "bj", "place"], F.col("slot"), n0 * n0, stages, self.tile, self.dtype, only)
        out = out.withColumn("path", F.col("path") * self.s.q + F.col("r")).drop("r")
        return out.repartition(self.tasks, "path", "place") if self.exchange == "stepwise" else out

    def up(self, q, rows, cols):
        """Products of a level to their parents' quadrants."""
        n0, s = self.s.n0, self.s
        hr, hc = rows // n0, cols // n0
        q = q.withColumn("slot", (F.col("path") % s.q).cast("int")).withColumn("path", F.floor(F.col("path") / s.q))
        if self.exchange == "stepwise":
            q = q.repartition(self.tasks, "path", "place")
        out = combine(q, ["path", "bi", "bj", "place"], F.col("slot"), s.q, s.out, self.tile, self.dtype)
        return out.withColumn("bi", (F.col("bi") + hr * F.floor(F.col("r") / n0)).cast("int")).withColumn("bj", (F.col("bj") + hc * (F.col("r") % n0)).cast("int")).drop("r")

    def product(self, a, b, shape):
        if self.leaf_rule:
            out = self.leaf_rule(a, b, shape)
        elif self.leaf.kind == "tiles":
            out = tile_products(a, b, ["path"], self.tile, self.dtype)
        else:
            keys, number = ["path"], F.col("path")
            if self.c > 1:  # the base product on c workers: slices of its rows
                a = a.withColumn("part", F.col("bi") % self.c)
                b = b.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(self.c - 1))))
                keys, number = ["path", "part"], F.col("path") * self.c + F.col("part")
            out = dense_products(a, b, keys, self.tile, self.dtype, self.leaf, None if self.c > 1 else shape, number)
        return self.lay(out.select("path", "bi", "bj", "vals"), self.res[0], self.res[2])

    def multiply(self, a, b, schedule, shape):
        if not schedule:
            return self.product(a, b, shape)
        m, k, n = shape
        inner = tuple(x // self.s.n0 for x in shape)
        if schedule[0] == "W":
            q = self.multiply(self.down(a, self.s.left, m, k), self.down(b, self.s.right, k, n), schedule[1:], inner)
            return self.up(q, m, n)
        total = None
        n0, w = self.s.n0, self.s.tables[2]
        a, b = durable(a), durable(b)  # else each subproblem would make them again
        for r in range(self.s.q):
            q = self.multiply(self.down(a, self.s.left, m, k, r), self.down(b, self.s.right, k, n, r), schedule[1:], inner)
            parts = F.array(*(F.struct(F.lit(x).alias("x"), F.lit(int(w[x, r])).alias("c")) for x in range(n0 * n0) if w[x, r]))
            added = q.withColumn("path", F.floor(F.col("path") / self.s.q)).withColumn("p", F.explode(parts))
            added = added.select(
                "path",
                (F.col("bi") + inner[0] * F.floor(F.col("p.x") / n0)).cast("int").alias("bi"),
                (F.col("bj") + inner[2] * (F.col("p.x") % n0)).cast("int").alias("bj"),
                "place",
                F.transform("vals", lambda v: (v * F.col("p.c")).cast(self.dtype)).alias("vals"),
            )
            before, total = total, durable(added if total is None else sum_tiles(total.unionByName(added), ["path", "bi", "bj", "place"]))
            release(before)
            if schedule[1:2] == "S":
                release(q)
        release(a)
        release(b)
        return total


def hybrid(a: TileMatrix, b: TileMatrix, schedule: str = "W", scheme="s7a15", leaf: LeafSpec = LeafSpec(), c: int = 1, exchange: str = "fused", leaf_rule=None) -> TileMatrix:
    """a times b along a schedule of W and S levels, e.g. ``SWW``.

    Any shapes: sides are padded with absent tiles. ``exchange`` fused moves the
    subproblems once, after all wide levels; stepwise once per level, as on
    machines where memory grows with the levels. ``c`` workers share a leaf.
    Integers are exact or the run raises, also where only a sum on the way
    doesn't fit; decimals then do. Doubles must be finite for a fast scheme.
    """
    if a.tile != b.tile or a.n_cols != b.n_rows or a.dtype != b.dtype:
        raise ValueError("the matrices don't match")
    if set(schedule) - {"W", "S"}:
        raise ValueError(f"a schedule has letters W and S, not {schedule!r}")
    kind = scheme_of(scheme)
    if (schedule and kind.q < kind.n0**3) or leaf.levels:
        a, b = refuse_not_finite(a), refuse_not_finite(b)
    run = _Run(a, b, len(schedule), kind, leaf, c, exchange, leaf_rule)
    m, k, n = run.res
    x = run.lay(a.df.withColumn("path", F.lit(0).cast("long")), m, k)
    y = run.lay(b.df.withColumn("path", F.lit(0).cast("long")), k, n)
    out = run.multiply(x, y, schedule, run.shape)
    # tiles beyond the edge are zero
    kept = out.where((F.col("bi") < a.grid[0]) & (F.col("bj") < b.grid[1])).select("bi", "bj", "vals")
    return replace(a, df=kept, n_cols=b.n_cols)


def wide(a: TileMatrix, b: TileMatrix, workers: int = 7, fuse: int = 1, **options) -> TileMatrix:
    """All levels wide on 7**k logical workers; ``fuse`` levels in one step of a composed scheme."""
    from sevenfold.plans.schemes import compose

    k = digits_of(workers)
    if fuse > 1 and k % fuse == 0:
        s = base = scheme_of(options.pop("scheme", "s7a15"))
        for _ in range(fuse - 1):
            s = compose(s, base)
        return hybrid(a, b, "W" * (k // fuse), scheme=s, **options)
    return hybrid(a, b, "W" * k, **options)


def budgeted(a: TileMatrix, b: TileMatrix, workers: int, memory: float, depth: str = "closed", **options) -> TileMatrix:
    """Serial levels until the wide ones fit ``memory`` words per logical worker."""
    n = max(a.n_rows, a.n_cols, b.n_cols)
    return hybrid(a, b, plan_budgeted(n, workers, memory, depth)["schedule"], **options)


def greedy(a: TileMatrix, b: TileMatrix, workers: int, memory: float, **options) -> TileMatrix:
    """Level by level: wide where ``memory`` words per logical worker allow it, else serial."""
    n = max(a.n_rows, a.n_cols, b.n_cols)
    return hybrid(a, b, plan_greedy(n, workers, memory), **options)


def sql_multiply(x: DataFrame, y: DataFrame, hint: str | None = None) -> DataFrame:
    """Cells times cells: join on the inner key, sum. The plain relational product."""
    right = y.select(F.col("i").alias("k"), "j", F.col("v").alias("w"))
    right = right.hint(hint) if hint else right
    out = x.select("i", F.col("j").alias("k"), "v").join(right, "k")
    return out.groupBy("i", "j").agg(F.sum(F.col("v") * F.col("w")).alias("v")).where("v <> 0")


def peel(x: DataFrame, y: DataFrame, n: tuple[int, int, int], tile: int, schedule: str = "W", dtype: str = "bigint", **options) -> DataFrame:
    """Cells times cells by peeling: an even core by the fast scheme, the borders by joins.

    What is left of a side beyond a multiple of tile * n0**levels is multiplied
    relationally: border columns of x with border rows of y for the core, then
    the last rows and the last columns of the product.
    """
    unit = tile * scheme_of(options.get("scheme", "s7a15")).n0 ** len(schedule)
    m, k, p = (v // unit * unit for v in n)
    if not (m and k and p):
        return sql_multiply(x, y)
    core = hybrid(
        cells_to_tiles(x.where((F.col("i") < m) & (F.col("j") < k)), m, k, tile, dtype),
        cells_to_tiles(y.where((F.col("i") < k) & (F.col("j") < p)), k, p, tile, dtype),
        schedule, **options,
    )
    parts = [
        tiles_to_cells(core),
        sql_multiply(x.where((F.col("i") < m) & (F.col("j") >= k)), y.where((F.col("i") >= k) & (F.col("j") < p))),
        sql_multiply(x.where(F.col("i") >= m), y),
        sql_multiply(x.where(F.col("i") < m), y.where(F.col("j") >= p)),
    ]
    total = parts[0]
    for part in parts[1:]:
        total = total.unionByName(part)
    return total.groupBy("i", "j").agg(F.sum("v").alias("v")).where("v <> 0")


def peel_levels(a: TileMatrix, b: TileMatrix, levels: int = 1, scheme="s7a15") -> TileMatrix:
    """Wide levels on any sides: each level peels what doesn't split off the remainder of its own sides.

    A side that isn't even in tiles loses its last ones on that level; the even core
    goes on, and the peeled rows and columns are multiplied by joins over tiles,
    for all subproblems of the level at once. Nothing is padded but edge tiles.
    """
    s = scheme_of(scheme)
    run = _Run(a, b, 0, s, LeafSpec(), 1, "fused")
    a, b = refuse_not_finite(a), refuse_not_finite(b)
    keyed = lambda m: m.df.select(F.lit(0).cast("long").alias("path"), "bi", "bj", F.lit(0).alias("place"), "vals")
    border = lambda x, y: tile_products(x, y, ["path"], a.tile, a.dtype)

    def level(x, y, shape, left):
        m, k, n = shape
        if not left or min(shape) < s.n0:
            return border(x, y)
        em, ek, en = (v // s.n0 * s.n0 for v in shape)
        top, low = x.where(F.col("bi") < em), x.where(F.col("bi") >= em)
        near, far = y.where(F.col("bj") < en), y.where(F.col("bj") >= en)
        core = tuple(v // s.n0 for v in (em, ek, en))
        q = level(run.down(top.where(F.col("bj") < ek), s.left, em, ek), run.down(near.where(F.col("bi") < ek), s.right, ek, en), core, left - 1)
        parts = [run.up(q.withColumn("place", F.lit(0)), em, en).select("path", "bi", "bj", "vals")]
        if ek < k:
            parts.append(border(top.where(F.col("bj") >= ek), near.where(F.col("bi") >= ek)))
        if em < m:
            parts.append(border(low, y))
        if en < n:
            parts.append(border(top, far))
        total = parts[0]
        for part in parts[1:]:
            total = total.unionByName(part)
        return total if len(parts) == 1 else sum_tiles(total, ["path", "bi", "bj"])

    out = level(keyed(a), keyed(b), (a.grid[0], a.grid[1], b.grid[1]), levels)
    return replace(a, df=out.select("bi", "bj", "vals"), n_cols=b.n_cols)


def exact_multiply(x: DataFrame, y: DataFrame) -> DataFrame:
    """``sql_multiply`` of integer cells, durable; in decimals of 38 digits where the sums may not fit 64 bits."""
    top = lambda m: int(m.agg(F.max(F.abs(F.col("v").cast(EXACT)))).first()[0] or 0)
    inner = x.agg(F.count_distinct("j")).first()[0]
    if {dict(m.dtypes)["v"] for m in (x, y)} != {"bigint"} or top(x) * top(y) * inner >= 1 << 63:
        x, y = (m.withColumn("v", F.col("v").cast(EXACT)) for m in (x, y))
    return durable(sql_multiply(x, y))


def power(x: DataFrame, exponent: int) -> DataFrame:
    """Cells of a square matrix's power by repeated squaring, durable at each step.

    Integers come back in 64 bits if all of them fit, else as decimals of 38 digits.
    """
    multiply = exact_multiply if dict(x.dtypes)["v"] in ("bigint", EXACT) else lambda a, b: durable(sql_multiply(a, b))
    base, out = durable(x), None
    while exponent:
        if exponent & 1:
            out = base if out is None else multiply(out, base)
        exponent >>= 1
        if exponent:
            base = multiply(base, base)
    if dict(x.dtypes)["v"] == "bigint" and dict(out.dtypes)["v"] == EXACT and not out.where(f"abs(v) >= {1 << 63}").limit(1).count():
        out = out.withColumn("v", F.col("v").cast("bigint"))
    return out


def chain_order(sizes: list[int]) -> tuple[int, object]:
    """Cheapest bracketing of a product of matrices sizes[0] x sizes[1], sizes[1] x sizes[2], ..."""
    n = len(sizes) - 1
    best = {(i, i): (0, i) for i in range(n)}
    for span in range(1, n):
        for i in range(n - span):
            j = i + span
            best[i, j] = min(((best[i, s][0] + best[s + 1, j][0] + sizes[i] * sizes[s + 1] * sizes[j + 1], (best[i, s][1], best[s + 1, j][1])) for s in range(i, j)), key=lambda t: t[0])
    return best[0, n - 1]


def chain_multiply(cells: list[DataFrame], sizes: list[int]) -> DataFrame:
    def build(tree):
        return cells[tree] if isinstance(tree, int) else sql_multiply(build(tree[0]), build(tree[1]))

    return build(chain_order(sizes)[1])


def expected_levels(n: int, tile: int, leaf: int) -> int:
    """Levels that bring a leaf to ``leaf`` or below."""
    return max(0, math.ceil(math.log2(max(1, n) / max(leaf, tile))))

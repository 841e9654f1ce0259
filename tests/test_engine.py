"""Products against numpy, plans, ledger, accuracy and streams."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from sevenfold.operators import accuracy, grids, ledger, scaling
from sevenfold.operators.hybrid import _residues, chain_order, hybrid, peel, peel_levels, power, sql_multiply, wide
from sevenfold.operators.leaf import LeafSpec
from sevenfold.operators.multiply import look_at, multiply
from sevenfold.operators.tiles import axpy, cells_to_tiles, durable, exact_twin, relayout, tiles_to_cells, transpose
from sevenfold.plans import costs
from sevenfold.plans.explain import spark_costs
from sevenfold.plans.layout import LayoutSpec
from sevenfold.plans.report import moved, speedup_report


def cells(spark, x):
    rows = [(int(i), int(j), x[i, j].item()) for i, j in zip(*np.nonzero(x), strict=True)]
    return spark.createDataFrame(rows, "i long, j long, v long" if x.dtype.kind == "i" else "i long, j long, v double")


def dense(df, shape):
    out = np.zeros(shape, dtype=np.int64)
    for r in df.collect():
        out[r.i, r.j] += r.v
    return out


def pair(spark, m, k, n, tile, seed=0):
    rng = np.random.default_rng(seed)
    x, y = rng.integers(-9, 10, (m, k)), rng.integers(-9, 10, (k, n))
    return x, y, cells_to_tiles(cells(spark, x), m, k, tile), cells_to_tiles(cells(spark, y), k, n, tile)


@pytest.mark.parametrize("schedule", ["", "W", "SW", "WS"])
@pytest.mark.parametrize("shape", [(16, 16, 16), (7, 5, 3)])
def test_schedules_agree(spark, schedule, shape):
    x, y, a, b = pair(spark, *shape, 2)
    assert (dense(tiles_to_cells(hybrid(a, b, schedule)), (shape[0], shape[2])) == x @ y).all()


@pytest.mark.parametrize("options", [{"exchange": "stepwise"}, {"c": 3}, {"scheme": "s7a18"}, {"scheme": "tensor4"}, {"leaf": LeafSpec(kind="tiles")}, {"leaf": LeafSpec(levels=1, cutoff=1)}])
def test_variants(spark, options):
    x, y, a, b = pair(spark, 16, 12, 20, 2, 1)
    assert (dense(tiles_to_cells(hybrid(a, b, "W", **options)), (16, 20)) == x @ y).all()


def test_zero_quadrant_empty_and_one(spark):
    x, y, a, b = pair(spark, 8, 8, 8, 2, 2)
    x[:4, :4] = 0
    a = cells_to_tiles(cells(spark, x), 8, 8, 2)
    assert (dense(tiles_to_cells(hybrid(a, b, "W")), (8, 8)) == x @ y).all()
    none = a.with_df(a.df.where("false"))
    assert tiles_to_cells(hybrid(none, b, "W")).count() == 0
    x, y, a, b = pair(spark, 1, 1, 1, 2, 3)
    assert (dense(tiles_to_cells(hybrid(a, b, "W")), (1, 1)) == x @ y).all()
    with pytest.raises(ValueError):
        hybrid(a, b, "WX")


def test_grids_and_degenerate_cases(spark):
    x, y, a, b = pair(spark, 16, 16, 16, 2, 4)
    for c in (grids.grid2d(a, b, 2), grids.grid2d_shift(a, b, 2), grids.grid3d(a, b, 2), grids.grid25d(a, b, 4, 1), grids.grid25d(a, b, 32, 2), grids.grid2d_fast(a, b, 2), grids.fast_grid2d(a, b, 1, 2, pack=True), grids.fast_grid2d(a, b, 0, 2), grids.fast_grid25d(a, b, 8, 2, 0)):
        assert (dense(tiles_to_cells(c), (16, 16)) == x @ y).all()


def test_metamorphic(spark):
    x, y, a, b = pair(spark, 8, 8, 8, 2, 5)
    c = hybrid(a, b, "W")
    assert (dense(tiles_to_cells(transpose(c)), (8, 8)) == dense(tiles_to_cells(hybrid(transpose(b), transpose(a), "W")), (8, 8))).all()
    assert (dense(tiles_to_cells(axpy(2, a, -1, b)), (8, 8)) == 2 * x - y).all()
    ac, bc = cells(spark, x), cells(spark, y)
    assert accuracy.random_check(ac, bc, tiles_to_cells(c)).first()[0] == 0
    assert accuracy.random_check(ac, bc, tiles_to_cells(c).withColumn("v", F.col("v") + F.when((F.col("i") == 0) & (F.col("j") == 0), 1).otherwise(0))).first()[0] == 1
    assert (dense(power(ac, 3), (8, 8)) == x @ x @ x).all()
    assert (dense(sql_multiply(ac, bc), (8, 8)) == x @ y).all()


def test_peel_odd_sizes(spark):
    for n in (9, 3):
        x, y, _, _ = pair(spark, n, n, n, 2, n)
        assert (dense(peel(cells(spark, x), cells(spark, y), (n, n, n), 2), (n, n)) == x @ y).all()


def test_null_cell_is_refused(spark):
    bad = spark.createDataFrame([(0, 0, None)], "i long, j long, v long")
    with pytest.raises(Exception, match="null"):
        cells_to_tiles(bad, 1, 1, 2).df.collect()


def test_chain_order():
    assert chain_order([10, 1, 10, 1]) == (20, (0, (1, 2)))


def test_combinations_need_no_exchange(spark):
    """After the layout, all wide levels sum in place: one exchange a side, one to the leaves, one back."""
    _, _, a, b = pair(spark, 16, 16, 16, 2, 6)
    a, b = a.with_df(durable(a.df)), b.with_df(durable(b.df))
    fused, stepwise = (spark_costs(wide(a, b, 49, exchange=e).df)["exchanges"] for e in ("fused", "stepwise"))
    assert fused < stepwise
    assert fused <= 5


def test_ledger_equals_formula(spark):
    for n, p, words, messages in ((56, 7, 4032, 36), (224, 49, 25344, 72)):
        book = ledger.traffic_ledger(spark, n, p)
        row = ledger.critical_path(book).first()
        assert (row["words"], row["messages"]) == (words, messages)
        spread = ledger.per_worker(book).groupBy("step").agg(F.min("words").alias("a"), F.max("words").alias("b"), F.count("*").alias("n")).collect()
        assert all(r["a"] == r["b"] and r["n"] == p for r in spread)


def test_error_measures(spark):
    rng = np.random.default_rng(7)
    grade = 2 ** ((np.arange(14)[:, None] * 3 - np.arange(14)[None, :] * 5) % 24)
    x, y = (rng.integers(1, 2**26, (14, 14)) * grade for _ in range(2))  # integers, so exact as doubles too
    want = x.astype(object) @ y.astype(object)
    a, b = (durable(cells(spark, m.astype(float))) for m in (x, y))
    ints = [durable(accuracy.to_integers(m, 0)) for m in (a, b)]
    exact = durable(accuracy.exact_product(*ints))
    assert {(r.i, r.j): int(r.v) for r in exact.collect()} == {(i, j): want[i, j] for i in range(14) for j in range(14)}
    judged = lambda measure, got: accuracy.judge(measure, exact, accuracy.to_integers(got, 0), *ints, 14).first()
    fast = durable(tiles_to_cells(hybrid(cells_to_tiles(a, 14, 14, 1, "double"), cells_to_tiles(b, 14, 14, 1, "double"), "W", leaf=LeafSpec(levels=2, cutoff=1))))
    classical = durable(tiles_to_cells(grids.grid2d(cells_to_tiles(a, 14, 14, 7, "double"), cells_to_tiles(b, 14, 14, 7, "double"), 2)))
    assert judged("componentwise", classical).holds and not judged("componentwise", fast).holds
    assert judged("normwise", classical).holds and judged("normwise", fast).holds
    # the value is that of exact integers
    got = np.array([[int(v) for v in row] for row in (x.astype(float) @ y.astype(float))], dtype=object)
    own = spark.createDataFrame([(i, j, float(got[i, j])) for i in range(14) for j in range(14)], "i long, j long, v double")
    top = max(abs(int(g) - w) for g, w in zip(got.ravel(), want.ravel(), strict=True))
    assert abs(judged("normwise", own).value - top * 2**53 / (int(x.max()) * int(y.max()))) < 1e-9
    for mode in ("outer", "inner", "both"):
        assert judged("normwise", accuracy.scaled_multiply(a, b, mode, sql_multiply)).holds
    with pytest.raises(Exception, match="not a multiple"):
        accuracy.to_integers(spark.createDataFrame([(0, 0, 0.5)], "i long, j long, v double"), 0).collect()


BIG, ONE = np.array([[2**62, 2**62], [0, 0]]), np.array([[1, 0], [1, 0]])


@pytest.mark.parametrize("tile,schedule,leaf", [(1, "", LeafSpec()), (1, "W", LeafSpec()), (2, "", LeafSpec(levels=1, cutoff=1)), (1, "W", LeafSpec(kind="tiles")), (70, "W", LeafSpec())])
def test_no_integer_wraps(spark, tile, schedule, leaf):
    """2**62 + 2**62 doesn't fit: 64-bit integers raise on every path, decimals give it."""
    size = 2 * max(1, tile // 35) if tile > 2 else 2
    x, y = np.zeros((size, size), dtype=np.int64), np.zeros((size, size), dtype=np.int64)
    x[:2, :2], y[:2, :2] = BIG, ONE
    a, b = (cells_to_tiles(cells(spark, m), size, size, tile) for m in (x, y))
    with pytest.raises(Exception, match="64 bits|OVERFLOW"):
        hybrid(a, b, schedule, leaf=leaf).df.collect()
    got = tiles_to_cells(hybrid(exact_twin(a), exact_twin(b), schedule, leaf=leaf)).collect()
    assert [(r.i, r.j, int(r.v)) for r in got] == [(0, 0, 2**63)]


def test_decimals_along_serial_levels(spark):
    x, y, a, b = pair(spark, 8, 8, 8, 2, 11)
    got = tiles_to_cells(hybrid(exact_twin(a), exact_twin(b), "S", scheme="s7a18")).collect()
    assert (np.array([[next((int(r.v) for r in got if (r.i, r.j) == (i, j)), 0) for j in range(8)] for i in range(8)]) == x @ y).all()


def test_not_finite(spark):
    x = spark.createDataFrame([(0, 0, float("nan")), (1, 1, 2.0), (2, 3, float("inf"))], "i long, j long, v double")
    y = spark.createDataFrame([(k, k, 1.0) for k in range(4)], "i long, j long, v double")
    a, b = (cells_to_tiles(m, 4, 4, 2, "double") for m in (x, y))
    for run in (lambda: hybrid(a, b, "W"), lambda: grids.grid2d_fast(a, b, 1)):
        with pytest.raises(Exception, match="not finite"):
            run().df.collect()
    got = {(r.i, r.j): r.v for r in tiles_to_cells(multiply(a, b)[0], keep_zero=True).collect()}
    assert np.isnan(got[0, 0]) and got[1, 1] == 2.0 and got[2, 3] == float("inf")
    assert look_at(a).not_finite == 2 and look_at(a).nonzero == 3 and look_at(a).largest == 2.0


def test_multiply_chooses(spark):
    x, y, a, b = pair(spark, 12, 12, 12, 3, 8)
    out, plan = multiply(a, b)
    assert plan["dtype"] == "bigint" and (dense(tiles_to_cells(out), (12, 12)) == x @ y).all()
    big = cells_to_tiles(cells(spark, x * 2**40), 12, 12, 3)
    out, plan = multiply(big, cells_to_tiles(cells(spark, y * 2**40), 12, 12, 3))
    assert plan["dtype"] == "decimal(38,0)"
    assert {(r.i, r.j): int(r.v) for r in tiles_to_cells(out).collect()} == {(i, j): int(v) * 2**80 for (i, j), v in np.ndenumerate(x @ y) if v}


@pytest.mark.parametrize("shape", [(7, 5, 3), (9, 14, 6), (3, 3, 3)])
def test_peel_levels(spark, shape):
    x, y, a, b = pair(spark, *shape, 1, 9)
    assert (dense(tiles_to_cells(peel_levels(a, b, 2)), (shape[0], shape[2])) == x @ y).all()


def test_grid_rounds_and_copies(spark):
    x, y, a, b = pair(spark, 12, 12, 12, 2, 10)
    for c in (grids.grid2d(a, b, 2, panel=2), grids.grid2d_shift(a, b, 3, rounds=True), grids.fast_grid25d(a, b, 8, 2, "opt", memory=14.4)):
        assert (dense(tiles_to_cells(c), (12, 12)) == x @ y).all()
    assert grids.copies_that_fit(100, 64) == 4 and grids.copies_that_fit(100, 64, 3 * 100**2 / 64) == 1
    with pytest.raises(ValueError, match="fits"):
        grids.copies_that_fit(100, 64, 100)


def test_serial_levels_read_their_operands_once(spark):
    """The source is read once for each factor, and every accumulator but the last is deleted."""
    _, _, a, b = pair(spark, 8, 8, 8, 2, 12)
    seen = spark.sparkContext.accumulator(0)

    def count(batches):
        for batch in batches:
            seen.add(len(batch))
            yield batch

    a, b = (m.with_df(durable(m.df).mapInPandas(count, m.df.schema)) for m in (a, b))
    root = spark.sparkContext.getCheckpointDir()
    path = spark._jvm.org.apache.hadoop.fs.Path(root)
    files = lambda: sum(f.isDirectory() for f in path.getFileSystem(spark._jsc.hadoopConfiguration()).listStatus(path))
    before = files()
    hybrid(a, b, "S")
    assert seen.value == 32 and files() == before + 1


def test_places_of_any_number_of_tiles():
    for tiles in (1, 2, 13, 97, 101, 1009, 1024, 2018, 3539):
        for tasks in (1, 8, 64, 4096):
            side, padded = _residues(tiles, tasks)
            assert padded % side == 0 and 0 <= 16 * (padded - tiles) <= tiles
            assert side * side >= min(tasks, tiles * tiles // 4) or side == tiles
    assert _residues(1009, 64) == (32, 1024)


def test_relayout_moves_tiles_to_their_owners(spark):
    x, _, a, _ = pair(spark, 28, 28, 28, 2, 13)
    spec = LayoutSpec(28, 49, 1)
    moved_tiles = relayout(a, spec)
    got = moved_tiles.df.select("owner", F.spark_partition_id().alias("p"), "bi", "bj").collect()
    assert all(r.p == r.owner == (r.bi % 7) * 7 + r.bj % 7 for r in got) and (dense(tiles_to_cells(moved_tiles), (28, 28)) == x).all()


def test_ledgers_of_any_scheme_and_schedule(spark):
    from sevenfold.plans.schemes import scheme_of

    for n, p, schedule, scheme in ((64, 64, "WW", "c8"), (56, 7, "SW", "s7a15"), (56, 7, "WS", "s7a18")):
        got = ledger.critical_path(ledger.traffic_ledger(spark, n, p, schedule, scheme=scheme)).first()
        assert (got["words"], got["messages"]) == costs.traffic(n, p, schedule, scheme)
        own = ledger.flop_ledger(spark, n, p, schedule, scheme).groupBy("worker").agg(F.sum("flops").alias("f")).collect()
        assert len(own) == p and {r.f for r in own} == {float(costs.flops(n, p, schedule, scheme))}
    assert costs.generic_costs(scheme_of("c8"), 64, 2)["words"] == costs.traffic(64, 64, "WW", "c8")[0]


def test_strong_scaling_points(spark):
    _, _, a, b = pair(spark, 16, 16, 16, 4, 14)
    some = [("hybrid", 7, "W c=1 leaf=0"), ("hybrid", 7, "W c=1 leaf=1"), ("hybrid", 14, "W c=2 leaf=0"), ("grid2d", 4, ""), ("grid2d_fast", 4, "leaf=1"), ("grid25d", 8, "c=2")]
    rows = scaling.strong_scaling(spark, a, b, some).collect()
    assert all(r.equal and r.seconds > 0 for r in rows) and {(r.method, r.p): r.runs for r in rows}["hybrid", 7] == 2 and len(rows) == 5
    by_p = {r.p: r for r in scaling.speedups(spark.createDataFrame(rows)).collect()}
    assert set(by_p) == {7, 14} and by_p[7].over_fast_pct is not None
    assert {p for _, p, _ in scaling.points()} >= {7, 14, 21, 42, 49, 98, 147, 294, 4, 16, 8, 32}


def test_two_sided_product_over_batches(spark):
    from sevenfold.streaming import windows as st

    rng = np.random.default_rng(15)
    rows = [(int(k % 3), int(i), int(j), int(v)) for k, (i, j, v) in enumerate(rng.integers(0, 5, (60, 3)))]
    frame = spark.createDataFrame(rows, "part int, i long, j long, v long")
    split = lambda want: lambda e: e.where(F.pmod(F.col("i") + F.col("v"), F.lit(2)) == want).groupBy("i", "j").agg(F.sum("v").alias("v")).where("v <> 0")
    got = st.two_sided_product(st.stream_of_slices([frame.where(F.col("part") == k) for k in range(3)]), split(0), split(1))
    a, b = (dense(split(k)(frame), (5, 5)) for k in (0, 1))
    assert (dense(got, (5, 5)) == a @ b).all()


def test_late_rows_are_dropped(spark):
    from sevenfold.streaming import windows as st

    d = "/root/testdata/sf0.001"
    build = lambda e: st.windowed_cells(e, "tumbling")
    slices = st.late_replay(spark, d)
    alone, none = st.run_in_slices(slices[:1], build)
    both, late = st.run_in_slices(slices, build)
    assert none == 0 and late > 0
    assert alone.count() == both.count() > 0 and both.exceptAll(alone).count() == 0


def test_speedup_report(spark):
    runs = [("hybrid", 49, 2.0), ("grid2d", 49, 3.0), ("grid25d", 49, 5.0), ("grid2d_fast", 49, 2.5), ("hybrid", 343, 1.0), ("grid2d", 343, 1.5), ("grid2d", 7, 1.0)]
    got = {r.p: (r.over_classical_pct, r.over_fast_pct) for r in speedup_report(spark.createDataFrame(runs, "method string, p int, seconds double")).collect()}
    assert got == {49: (50.0, 25.0), 343: (50.0, None)}


def test_moved_counts_shuffles(spark):
    wide = spark.range(0, 10_000, 1, 4).repartition(5, "id")
    got = moved(spark, lambda: wide.write.format("noop").mode("overwrite").save())
    assert got["shuffle_records"] == 10_000 and got["shuffle_bytes"] > 0 and got["stages"] == 2
    assert moved(spark, lambda: spark.range(5).write.format("noop").mode("overwrite").save())["shuffle_bytes"] == 0


def test_entry_points(spark):
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    assert e.entry(spark).count() > 0


def test_whole_tables(spark):
    from sevenfold.workloads import QUERIES

    d = "/root/testdata/sf0.001"
    ranks = QUERIES["o_rank_forms"](spark, d)
    assert ranks.count() == QUERIES["o_fold"](spark, d).count() and ranks.select("i").distinct().count() == 56
    wide, events = QUERIES["o_pivot"](spark, d), spark.read.parquet(f"{d}/events.parquet")
    assert sum(wide.groupBy().sum(*wide.columns[1:]).first()) == events.count()
    assert set(wide.columns[1:]) == {r[0] for r in events.select("event_type").distinct().collect()}
    for name, table in (("o_semi", "orders"), ("o_anti", "orders"), ("o_sparsify", None)):
        some = QUERIES[name](spark, d).count()
        assert some > 0 and (table is None or some < spark.read.parquet(f"{d}/{table}.parquet").count())


def test_power_beyond_64_bits(spark):
    x = np.array([[3, 0, 24_000], [24_000, 5, 1], [24_000, 24_000, 24_000]])
    for factor, kind in ((1, "bigint"), (10, "decimal(38,0)")):
        got = power(cells(spark, factor * x), 4)
        assert dict(got.dtypes)["v"] == kind
        whole = np.linalg.matrix_power((factor * x).astype(object), 4)
        assert {(r.i, r.j): int(r.v) for r in got.collect()} == {(i, j): whole[i, j] for i, j in np.ndindex(3, 3)}


def test_few_cells_go_by_a_join(spark):
    from sevenfold.operators.multiply import multiply_cells

    rng = np.random.default_rng(5)
    for share, udf in ((1.0, True), (0.03, False)):
        x, y = (rng.integers(1, 9, s) * (rng.random(s) <= share) for s in ((7, 60), (60, 40)))
        got = multiply_cells(cells(spark, x), cells(spark, y), (7, 60, 40), 4)
        assert (dense(got, (7, 40)) == x @ y).all()
        assert ("FlatMapCoGroupsInPandas" in got._jdf.queryExecution().toString()) == udf


def test_gram_of_gaps_in_ids(spark, tmp_path):
    from sevenfold.workloads.products import w_gram_embed

    rng = np.random.default_rng(3)
    ids = np.array([0, 50, 51, 149, 150, 1000])
    x = np.round(rng.normal(size=(len(ids), 64)), 3)
    rows = [(int(k), v.tolist(), 0) for k, v in zip(ids, x, strict=True)]
    spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    w = np.rint(x * 1000).astype(int)
    want = {(int(p), int(q)): int(w[a] @ w[b]) for a, p in enumerate(ids) for b, q in enumerate(ids) if p % 50 == 0 and w[a] @ w[b]}
    got = w_gram_embed(spark, str(tmp_path))
    assert {(r.i, r.j): r.v for r in got.collect()} == want
    assert "FlatMapCoGroupsInPandas" not in got._jdf.queryExecution().toString()  # no task holds a leaf whole


def test_graded_products_are_not_scaled_by_their_blocks():
    from sevenfold.operators.leaf import seq_fast
    from sevenfold.workloads.accuracy import GRADED_TILES, PERIOD

    for n, tile in GRADED_TILES.items():
        side = -(-n // (2 * tile)) * 2 * tile
        assert side // 2 % PERIOD and side // 4 % PERIOD
    n, rng = 672, np.random.default_rng(0)
    i, j = np.indices((n, n))
    for case, left, right in (("both", 3 * i - 5 * j, 3 * i - 5 * j), ("outer", 3 * i, 5 * j), ("inner", 5 * j, -5 * i)):
        x, y = np.zeros((side, side)), np.zeros((side, side))
        x[:n, :n], y[:n, :n] = (rng.integers(1 << 20, 1 << 25, (n, n)) * 2.0 ** (g % PERIOD - 12) for g in (left, right))
        error = np.abs(seq_fast(x, y, 2) - x.astype(np.longdouble) @ y.astype(np.longdouble))[:n, :n] * 2.0**53
        sums = (np.abs(x) @ np.abs(y))[:n, :n]
        unit = {"both": n * sums, "outer": 8 * n * np.outer(x.max(1), y.max(0))[:n, :n], "inner": 8 * n * sums.max()}[case]
        assert (error / unit).max() > 1


#: Cost queries over the order lines; ``c_`` queries that are not here keep points of their own.
OVER_LINES = ["c_cost_table", "c_excess", "c_ledger_wide", "c_ledger_budgeted", "c_ledger_interleaved", "c_ledger_classical", "c_ledger_c3", "c_ledger_balance", "c_flop_ledger", "c_intensity", "c_levels_beyond", "c_optimality_gap"]


def test_costs_follow_the_order_lines(spark, tmp_path):
    import __spark_entry__ as e
    import duckdb

    rows = [(float(q),) for q, times in ((1, 900), (2, 40), (7, 40), (50, 3000)) for _ in range(times)]
    spark.createDataFrame(rows, "l_quantity double").coalesce(1).write.parquet(f"{tmp_path}/lineitem.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW lineitem AS SELECT * FROM '{tmp_path}/lineitem.parquet/*.parquet'")
    for name in OVER_LINES:
        got = e.queries()[name](spark, str(tmp_path))
        want = con.execute(e.oracle_sql()[name])
        assert got.columns == [c[0] for c in want.description], name
        want = sorted(want.fetchall(), key=repr)
        assert want and sorted(map(tuple, got.collect()), key=repr) == want, name
        assert {r.quantity for r in got.collect()} == {1.0, 2.0, 7.0, 50.0}, name

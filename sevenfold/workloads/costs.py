"""Cost measures: formulas, recurrences, ledgers, rankings."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from sevenfold.operators import ledger
from sevenfold.plans.costs import METHODS, OMEGA, Cost, classical_over_fast, footprint_wide, intensity, optimality_gap, relayout_cost, traffic
from sevenfold.plans.layout import LayoutSpec, exchange_peers
from sevenfold.plans.planner import compute_bound, levels_opt_25d, plan_search
from sevenfold.plans.report import CLASSICAL, EARLIER_FAST, speedup_report
from sevenfold.sources.matrices import table
from sevenfold.workloads.registry import query

_POINTS = [(n, 7**k, n * n * c / 7**k) for n in (1000, 94080) for k in (2, 3, 4) for c in (3.0, 12.0, 48.0)]

#: What the order lines ask for: (quantity, lines), a group for each quantity.
_ASKED = "asked AS (SELECT l_quantity AS quantity, count(*) AS lines FROM lineitem GROUP BY 1)"


def _asked(spark, d):
    return table(spark, d, "lineitem", F.col("l_quantity").alias("quantity")).groupBy("quantity").agg(F.count("*").alias("lines"))


def _doubles(values) -> str:
    return "(VALUES " + ", ".join(f"(CAST({v} AS DOUBLE))" for v in values) + ")"


def _sides_sql(ks, shares, also: str = "") -> str:
    """SQL for points of a square product with a side for each quantity: as many rows as it has lines, 7**k workers, shares of its size as memory."""
    kp = ", ".join(f"({k}, CAST({7**k} AS DOUBLE))" for k in ks)
    return f"SELECT quantity, n, k, p, n * n * c / p AS m{also} FROM (SELECT quantity, CAST(lines AS DOUBLE) AS n FROM asked), (VALUES {kp}) AS w(k, p), {_doubles(shares)} AS u(c)"


def _sides(spark, d, ks, shares):
    """(quantity, n, k, p, m): the same points by Spark."""
    n = _asked(spark, d).select("quantity", F.col("lines").cast("double").alias("n"))
    kp = F.explode(F.array(*(F.struct(F.lit(k).alias("k"), F.lit(float(7**k)).alias("p")) for k in ks))).alias("w")
    points = n.select("*", kp).select("*", F.explode(F.array(*map(F.lit, map(float, shares)))).alias("c"))
    return points.select("quantity", "n", "w.k", "w.p", (F.col("n") * F.col("n") * F.col("c") / F.col("w.p")).alias("m"))


_TABLE_POINTS = ((2, 3, 4), (3, 12, 48))


def _methods_sql(columns: str) -> str:
    rows = []
    for name, (f, w, m) in METHODS.items():
        rows.append(f"SELECT '{name}' AS method, {columns}, round(ln({f}), 6) AS ln_flops, round(ln({w}), 6) AS ln_words, round(ln(greatest({m}, 1.0)), 6) AS ln_messages FROM points")
    return " UNION ALL ".join(rows)


def _method_rows(levels: int) -> str:
    values = ", ".join(f"(CAST({n} AS DOUBLE), CAST({p} AS DOUBLE), CAST({m!r} AS DOUBLE), CAST({levels} AS DOUBLE))" for n, p, m in _POINTS)
    return f"WITH points AS (SELECT * FROM (VALUES {values}) AS q(n, p, m, l)) {_methods_sql('n, p, m')}"


def _costs(points, *columns: str):
    """Costs of all methods at points (n, p, m, l); the same formulas feed the planner."""
    one = lambda f, w, m: F.array(*(F.expr(f"round(ln({x}), 6)") for x in (f, w, f"greatest({m}, 1.0)")))
    rows = F.explode(F.array(*(F.struct(F.lit(k).alias("method"), one(*x).alias("x")) for k, x in METHODS.items()))).alias("r")
    return points.select(*columns, rows).select("r.method", *columns, *(F.col("r.x")[k].alias(f"ln_{c}") for k, c in enumerate(("flops", "words", "messages"))))


def _fixed_costs(spark):
    points = spark.createDataFrame([(float(n), float(p), float(m), 1.0) for n, p, m in _POINTS], "n double, p double, m double, l double")
    return _costs(points, "n", "p", "m")


_TABLE_SQL = f"{_ASKED}, points AS ({_sides_sql(*_TABLE_POINTS, ', CAST(1 AS DOUBLE) AS l')})"


@query("c_cost_table", f"WITH {_TABLE_SQL} {_methods_sql('quantity, n, p, m')}")
def c_cost_table(spark, d):
    """Costs of all methods at a grid of points, with a side for each quantity of the order lines."""
    return _costs(_sides(spark, d, *_TABLE_POINTS).withColumn("l", F.lit(1.0)), "quantity", "n", "p", "m")


@query("c_excess", f"WITH {_TABLE_SQL}, c AS ({_methods_sql('quantity, n, p, m')}) SELECT x.method AS method, x.quantity AS quantity, x.n AS n, x.p AS p, x.m AS m, round(x.ln_words - y.ln_words, 5) AS words_over, round(x.ln_flops - y.ln_flops, 5) AS flops_over FROM c x JOIN c y ON y.method = 'hybrid' AND x.quantity = y.quantity AND x.p = y.p AND x.m = y.m")
def c_excess(spark, d):
    c = c_cost_table(spark, d)
    best = c.where("method = 'hybrid'").select("quantity", "p", "m", F.col("ln_words").alias("w"), F.col("ln_flops").alias("f"))
    return c.join(best, ["quantity", "p", "m"]).select("method", "quantity", "n", "p", "m", F.round(F.col("ln_words") - F.col("w"), 5).alias("words_over"), F.round(F.col("ln_flops") - F.col("f"), 5).alias("flops_over"))


@query("c_recurrence", "WITH r AS (SELECT unnest(range(1, 9)) AS k) SELECT k, CAST(round(3 * pow(2, 20) / pow(7.0, k) * list_sum([pow(1.75, x) for x in range(0, k + 1)]), 3) AS DOUBLE) AS footprint, CAST(round(9 * pow(2, 20) / pow(7.0, k) * list_sum([pow(1.75, x) for x in range(0, k)]), 3) AS DOUBLE) AS words, 36 * k AS messages FROM r")
def c_recurrence(spark, d):
    """Footprint, words and messages of k wide levels of a 1024-square product, from the closed forms."""
    r = spark.range(1, 9).withColumnRenamed("id", "k")
    p, n2 = F.pow(F.lit(7.0), F.col("k")), 2.0**20
    return r.select("k", F.round(7 * n2 / F.pow(F.lit(4.0), F.col("k")) - 4 * n2 / p, 3).alias("footprint"), F.round(12 * n2 * (F.pow(F.lit(4.0), -F.col("k")) - 1 / p), 3).alias("words"), (36 * F.col("k")).alias("messages"))


@query("c_scaling", "WITH r AS (SELECT unnest(range(1, 7)) AS k), x AS (SELECT k, greatest(pow(94080.0, 2.807354922057604) / pow(1e9, 0.403677461028802), pow(94080.0, 2) * pow(7.0, k) / pow(4.0, k)) AS words_p FROM r) SELECT k, round(words_p / 1e6, 3) AS words_p, round(words_p / lag(words_p) OVER (ORDER BY k), 6) AS step FROM x")
def c_scaling(spark, d):
    """Words times workers along the workers: flat while memory binds, rising beyond."""
    omega = 2.807354922057604
    x = spark.range(1, 7).withColumnRenamed("id", "k").withColumn("words_p", F.greatest(F.lit(94080.0**omega / 1e9 ** (omega / 2 - 1)), F.lit(94080.0**2) * F.pow(F.lit(7.0), "k") / F.pow(F.lit(4.0), "k")))
    return x.select("k", F.round(F.col("words_p") / 1e6, 3).alias("words_p"), F.round(F.col("words_p") / F.lag("words_p").over(Window.orderBy("k")), 6).alias("step"))


@query("c_regimes", f"WITH c AS ({_method_rows(1)}) SELECT n, p, m, CASE WHEN m < n * n / pow(4.0, round(ln(p) / ln(7.0))) THEN 'memory-dependent' ELSE 'memory-independent' END AS regime FROM c WHERE method = 'hybrid'")
def c_regimes(spark, d):
    c = _fixed_costs(spark).where("method = 'hybrid'")
    free = F.col("n") * F.col("n") / F.pow(F.lit(4.0), F.round(F.log("p") / F.log(F.lit(7.0))))
    return c.select("n", "p", "m", F.when(F.col("m") < free, "memory-dependent").otherwise("memory-independent").alias("regime"))


def _products(spark, d):
    """(quantity, scale, times): one product for every order line, of a side that grows with its quantity."""
    return _asked(spark, d).select("quantity", F.col("quantity").alias("scale"), F.col("lines").alias("times"))


@query("c_ledger_wide", f"WITH {_ASKED}, w AS (SELECT unnest(range(0, 49)) AS worker) SELECT quantity, 1 AS step, worker, CAST(9 * 224 * 224 / 49 * quantity * quantity * lines AS BIGINT) AS words, 36 * lines AS messages FROM w, asked UNION ALL SELECT quantity, 2, worker, CAST(9 * 112 * 112 / 7 * quantity * quantity * lines AS BIGINT), 36 * lines FROM w, asked")
def c_ledger_wide(spark, d):
    """Words and messages of every worker in every step, from the layout: all equal, and equal to the formula."""
    out = ledger.of_products(ledger.per_worker(ledger.traffic_ledger(spark, 224, 49)), _products(spark, d), ["words"], ["messages"])
    return out.select("quantity", "step", F.col("worker").cast("long").alias("worker"), F.col("words").cast("long").alias("words"), F.col("messages").cast("long").alias("messages"))


def _path_cost(spark, d, book):
    """(quantity, words, messages) of the critical path, one product after another for every order line."""
    path = ledger.critical_path(book)
    return ledger.of_products(path, _products(spark, d), ["words"], ["messages"]).select("quantity", F.col("words").cast("long").alias("words"), F.col("messages").cast("long").alias("messages"))


@query("c_ledger_budgeted", f"WITH {_ASKED} SELECT quantity, CAST(44352 * quantity * quantity * lines AS BIGINT) AS words, 504 * lines AS messages FROM asked")
def c_ledger_budgeted(spark, d):
    """One serial, two wide levels: the seven runs below the serial level, one after another."""
    return _path_cost(spark, d, ledger.traffic_ledger(spark, 224, 49, "SWW"))


@query("c_ledger_interleaved", f"WITH {_ASKED} SELECT quantity, CAST(9 * 56 * 56 / 7 * quantity * quantity * lines AS BIGINT) AS words, 36 * lines AS messages FROM asked")
def c_ledger_interleaved(spark, d):
    """A serial level below a wide one sends nothing more."""
    return _path_cost(spark, d, ledger.traffic_ledger(spark, 56, 7, "WS"))


@query("c_ledger_classical", f"WITH {_ASKED} SELECT quantity, CAST(42 / 4.0 * 64 * 64 / 64 * 3 * quantity * quantity * lines AS BIGINT) AS words, 6 * 7 * 2 * lines AS messages FROM asked")
def c_ledger_classical(spark, d):
    """Two wide levels of the recursive classical scheme on 64 workers: the general form with 8 products."""
    return _path_cost(spark, d, ledger.traffic_ledger(spark, 64, 64, scheme="c8"))


@query("c_ledger_c3", f"WITH {_ASKED} SELECT quantity, CAST((9 * 42 * 42 / 21 + 2 * 2 * 21 * 21 / 3) * quantity * quantity * lines AS BIGINT) AS words, (36 + 4) * lines AS messages FROM asked")
def c_ledger_c3(spark, d):
    """Seven groups of three workers: the wide level, then each member gets the others' shares of the right factor."""
    return _path_cost(spark, d, ledger.traffic_ledger(spark, 42, 7, c=3))


@query("c_flop_ledger", f"WITH {_ASKED} SELECT quantity, worker, CAST(lines * (15 * 56 * 56 / 4 + 7 * (15 * 28 * 28 / 4 + 15 * 14 * 14 * 7 / 4 + 7 * 49 * (2 * 343 - 49) / 7)) / 7 AS BIGINT) AS flops FROM asked, (SELECT unnest(range(0, 7)) AS worker)")
def c_flop_ledger(spark, d):
    """Additions and multiplications of every worker along SW with leaves of side 7, from the blocks that it holds, in one product of side 56 for every order line."""
    out = ledger.flop_ledger(spark, 56, 7, "SW", cutoff=7).groupBy("worker").agg(F.sum("flops").alias("flops"))
    out = ledger.of_products(out, _asked(spark, d).select("quantity", F.lit(1).alias("scale"), F.col("lines").alias("times")), [], ["flops"])
    return out.select("quantity", F.col("worker").cast("long").alias("worker"), F.col("flops").cast("long").alias("flops"))


@query("c_ledger_balance", f"WITH {_ASKED} SELECT quantity, step, workers, CAST(words * quantity * quantity * lines AS BIGINT) AS least, CAST(words * quantity * quantity * lines AS BIGINT) AS most FROM asked, (VALUES (1, CAST(49 AS BIGINT), 9216), (2, 49, 16128)) AS q(step, workers, words)")
def c_ledger_balance(spark, d):
    """Every worker sends and receives the same in every step."""
    out = ledger.of_products(ledger.per_worker(ledger.traffic_ledger(spark, 224, 49)), _products(spark, d), ["words"], ["messages"])
    out = out.groupBy("quantity", "step").agg(F.count("*").alias("workers"), F.min("words").alias("least"), F.max("words").alias("most"))
    return out.select("quantity", "step", "workers", F.col("least").cast("long").alias("least"), F.col("most").cast("long").alias("most"))


@query("c_owner_map", "SELECT CAST((bi % 7) * 7 + bj % 7 AS INTEGER) AS owner, count(*) AS blocks FROM (SELECT unnest(range(0, 28)) AS bi), (SELECT unnest(range(0, 28)) AS bj) GROUP BY 1")
def c_owner_map(spark, d):
    """Blocks of each of 49 workers at n = 224 with two levels: all equal."""
    spec = LayoutSpec(224, 49, 2).check()
    side = 224 // spec.block[0]
    blocks = spark.range(side * side).select(F.floor(F.col("id") / side).alias("bi"), F.pmod("id", F.lit(side)).alias("bj"))
    return blocks.select(spec.owner(F.col("bi"), F.col("bj")).alias("owner")).groupBy("owner").agg(F.count("*").alias("blocks"))


_RANK = """WITH RECURSIVE s AS (
  SELECT '' AS schedule, 672::DOUBLE AS n, 49::DOUBLE AS p, 1::DOUBLE AS times, 0::DOUBLE AS flops, 0::DOUBLE AS words, 0::DOUBLE AS messages, 0::DOUBLE AS held
  UNION ALL
  SELECT schedule || x, n / 2, CASE WHEN x = 'W' THEN p / 7 ELSE p END, CASE WHEN x = 'S' THEN times * 7 ELSE times END,
         flops + times * 15 * n * n / (4 * p), words + CASE WHEN x = 'W' THEN times * 9 * n * n / p ELSE 0 END,
         messages + CASE WHEN x = 'W' THEN times * 36 ELSE 0 END, held + 3 * n * n / p
  FROM s, (VALUES ('W'), ('S')) AS q(x)
  WHERE length(schedule) < 4 AND (x = 'S' OR p > 1.5) AND length(schedule || x) - length(replace(schedule || x, 'S', '')) <= 2),
e AS (SELECT *, CAST(5 - length(schedule) AS INTEGER) AS a FROM s WHERE p < 1.5 AND held + 3 * n * n / p <= 160000),
f AS (SELECT schedule, words, messages,
             flops + times * (pow(7.0, a) * (2 * 9261 - 441) + 15 * 441 * (pow(7.0, a) - pow(4.0, a)) / 3) / p AS flops FROM e),
t AS (SELECT schedule, 0.0001 * messages + 0.00000001 * words + 0.000000001 * flops AS seconds FROM f)
SELECT CAST(row_number() OVER (ORDER BY seconds, schedule) AS INTEGER) AS rank, schedule, round(seconds, 9) AS seconds FROM t"""


@query("c_schedule_rank", _RANK)
def c_schedule_rank(spark, d):
    """All interleavings of two wide levels with up to two serial ones that fit, by model time."""
    found = plan_search(672, 49, 160_000.0, 4)
    return spark.createDataFrame([(k + 1, s, round(t, 9)) for k, (t, s) in enumerate(found)], "rank int, schedule string, seconds double")


_SECONDS = "(0.0001 * exp(ln_messages) + 0.00000001 * exp(ln_words) + 0.000000001 * exp(ln_flops))"
_BEST = lambda names: f"min(CASE WHEN method IN ({', '.join(repr(x) for x in names)}) THEN seconds END)"


@query("c_speedup", f"WITH c AS ({_method_rows(1)}), t AS (SELECT method, p, {_SECONDS} AS seconds FROM c WHERE n = 94080 AND m = n * n * 12 / p), b AS (SELECT p, {_BEST(('hybrid',))} AS s, {_BEST(CLASSICAL)} AS k, {_BEST(EARLIER_FAST)} AS f FROM t GROUP BY p) SELECT p, round((k / s - 1) * 100, 4) AS over_classical_pct, round((f / s - 1) * 100, 4) AS over_fast_pct FROM b")
def c_speedup(spark, d):
    """Modelled speedup of the traversal over the best classical and the best earlier fast method, by workers."""
    c = _fixed_costs(spark).where("n = 94080 AND m = n * n * 12 / p")
    return speedup_report(c.selectExpr("method", "p", f"{_SECONDS} AS seconds"))


# --------------------------------------------------- regimes, gaps, rates, machines
_OMEGA = repr(OMEGA)
_GRID = [(float(n), k, float(n) * n * c / 7**k) for n in (1000, 94080) for k in (2, 3, 4) for c in (3, 6, 12, 24, 48, 96)]
_GRID_SQL = "(SELECT * FROM (VALUES " + ", ".join(f"(CAST({n} AS DOUBLE), {k}, CAST({m!r} AS DOUBLE))" for n, k, m in _GRID) + ") AS q(n, k, m))"


def _grid(spark):
    return spark.createDataFrame(_GRID, "n double, k int, m double")


@query("c_three_regimes", f"""SELECT n, k, m,
CASE WHEN m <= n * n / pow(4.0, k) THEN 'both memory-dependent' WHEN m <= n * n / pow(pow(7.0, k), 2 / 3.0) THEN 'classical memory-dependent'
     ELSE 'neither memory-dependent' END AS regime,
round(CASE WHEN m <= n * n / pow(4.0, k) THEN pow(n / sqrt(m), 3 - {_OMEGA}) WHEN m <= n * n / pow(pow(7.0, k), 2 / 3.0) THEN n * pow(pow(7.0, k), 2 / {_OMEGA} - 1) / sqrt(m)
     ELSE pow(pow(7.0, k), 2 / {_OMEGA} - 2 / 3.0) END, 6) AS classical_over_fast FROM {_GRID_SQL}""")
def c_three_regimes(spark, d):
    """By how much the classical bound on words exceeds the fast one, in the three regimes of memory."""
    rows = [(n, k, m, *classical_over_fast(n, 7**k, m)) for n, k, m in _GRID]
    out = spark.createDataFrame(rows, "n double, k int, m double, regime string, classical_over_fast double")
    return out.withColumn("classical_over_fast", F.round("classical_over_fast", 6))


_GAP_POINTS = ((2, 3, 4), (3, 6, 12, 24, 48, 96))


@query("c_optimality_gap", f"""WITH {_ASKED}, points AS ({_sides_sql(*_GAP_POINTS)}) SELECT quantity, n, k, m, round((12 * n * n / pow(4.0, k) - 12 * n * n / pow(7.0, k)) / greatest(pow(n / sqrt(m), {_OMEGA}) * m / pow(7.0, k), n * n / pow(4.0, k)), 6) AS words_gap,
round(36 * k / greatest(pow(n / sqrt(m), {_OMEGA}) / pow(7.0, k), 1.0), 6) AS messages_gap FROM points
WHERE m >= 7 * n * n / pow(4.0, k) - 4 * n * n / pow(7.0, k)""")
def c_optimality_gap(spark, d):
    """Words and messages of the wide-only scheme over their lower bounds, where its footprint fits: a constant, and a logarithm."""


    def gaps(batches):
        for x in batches:
            rows = []
            for quantity, n, k, p, m in x[["quantity", "n", "k", "p", "m"]].itertuples(index=False):
                if m >= footprint_wide(int(n), int(p)):
                    words, messages = traffic(int(n), int(p), "W" * int(k))
                    gap = optimality_gap(Cost(0, float(words), messages), n, int(p), m)
                    rows.append((quantity, n, k, m, gap["words"], gap["messages"]))
            yield pd.DataFrame(rows, columns=["quantity", "n", "k", "m", "words_gap", "messages_gap"])

    out = _sides(spark, d, *_GAP_POINTS).mapInPandas(gaps, "quantity double, n double, k int, m double, words_gap double, messages_gap double")
    return out.withColumns({c: F.round(c, 6) for c in ("words_gap", "messages_gap")})


@query("c_peak_share", f"""SELECT p, round(2 * pow(94080.0, 3) / s / 1e9, 3) AS gflops, round(2 * pow(94080.0, 3) / s / 1e9 / p / 36.8, 6) AS classical_share,
round((6 * pow(94080.0, {_OMEGA}) - 5 * pow(94080.0, 2)) / s / 1e9 / p / 36.8, 6) AS fast_share FROM (VALUES (49, 692.0), (343, 105.0), (2401, 16.0)) AS q(p, s)""")
def c_peak_share(spark, d):
    """Effective rates at given seconds, as shares of the classical peak and of the peak on the scheme's own arithmetic."""
    runs, n = spark.createDataFrame([(49, 692.0), (343, 105.0), (2401, 16.0)], "p int, s double"), 94080.0
    rate = F.lit(2 * n**3) / F.col("s") / 1e9
    own = F.lit(6 * n**OMEGA - 5 * n**2) / F.col("s") / 1e9
    return runs.select("p", F.round(rate, 3).alias("gflops"), F.round(rate / F.col("p") / 36.8, 6).alias("classical_share"), F.round(own / F.col("p") / 36.8, 6).alias("fast_share"))


@query("c_intensity", f"""WITH {_ASKED} SELECT quantity, m, round(sqrt(m), 4) AS classical, round(pow(m, {_OMEGA} / 2 - 1), 4) AS fast,
1e-9 * sqrt(m) >= 1e-8 AS classical_bound, 1e-9 * pow(m, {_OMEGA} / 2 - 1) >= 1e-8 AS fast_bound FROM (SELECT quantity, CAST(lines AS DOUBLE) * t / 100000 AS m FROM asked, {_doubles(10**k for k in range(1, 10))} AS q(t))""")
def c_intensity(spark, d):
    """Flops a word by memory, of a hundred-thousandth up to ten thousand times the lines of each quantity, and whether a machine with ten times dearer words is bound by arithmetic."""
    kinds = ("classical", "fast")
    steps = F.explode(F.array(*(F.lit(10.0**k) for k in range(1, 10)))).alias("t")
    m = _asked(spark, d).select("quantity", F.col("lines").cast("double").alias("lines"), steps).select("quantity", (F.col("lines") * F.col("t") / 100000).alias("m"))

    def rates(batches):
        for x in batches:
            x = x.assign(**{k: [intensity(m, k) for m in x["m"]] for k in kinds}, **{f"{k}_bound": [compute_bound(m, 1e-8, 1e-9, k) for m in x["m"]] for k in kinds})
            yield x[["quantity", "m", *kinds, *(f"{k}_bound" for k in kinds)]]

    out = m.mapInPandas(rates, "quantity double, m double, classical double, fast double, classical_bound boolean, fast_bound boolean")
    return out.withColumns({k: F.round(k, 4) for k in kinds})


@query("c_levels_beyond", f"""WITH {_ASKED}, x AS (SELECT extra, quantity, CAST(lines AS DOUBLE) AS n, CAST(64 AS DOUBLE) AS p, CAST(lines AS DOUBLE) * lines / 64 AS m FROM asked, (SELECT unnest(range(0, 4)) AS extra)),
y AS (SELECT *, greatest(0, ceil(log2(n / (sqrt(m) * pow(p, 1 / 3.0))) - 1e-12)) + extra AS l FROM x)
SELECT quantity, extra, l AS levels, round(ln(pow(0.875, l) * pow(n, 3) / p), 6) AS ln_flops, round(ln(pow(1.75, l) * pow(n, 2) / pow(p, 2 / 3.0)), 6) AS ln_words, round(pow(7.0, l) * log2(p), 3) AS messages FROM y""")
def c_levels_beyond(spark, d):
    """Fast levels beyond the best number above a 2.5D grid: each multiplies words by 7/4, messages by 7 and flops by 7/8."""
    p, n, level = 64.0, F.col("n"), F.col("levels")

    def best(batches):
        for x in batches:
            yield x.assign(best=[levels_opt_25d(n, p, n * n / p) for n in x["n"]])

    sides = _asked(spark, d).select("quantity", F.col("lines").cast("double").alias("n")).mapInPandas(best, "quantity double, n double, best long")
    beyond = sides.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(3).cast("long"))).alias("extra")).withColumn("levels", (F.col("best") + F.col("extra")).cast("double"))
    return beyond.select(
        "quantity", "extra", "levels", F.round(F.log(F.pow(F.lit(0.875), level) * F.pow(n, F.lit(3)) / p), 6).alias("ln_flops"),
        F.round(F.log(F.pow(F.lit(1.75), level) * F.pow(n, F.lit(2)) / p ** (2 / 3)), 6).alias("ln_words"), F.round(F.pow(F.lit(7.0), level) * math.log2(p), 3).alias("messages"),
    )


@query("c_relayout", """WITH c AS (SELECT i, j FROM (SELECT unnest(range(0, 196)) AS i), (SELECT unnest(range(0, 196)) AS j)),
o AS (SELECT (i // 7 % 7) * 7 + j // 7 % 7 AS src, (i // 14 % 7) * 7 + j // 14 % 7 AS dst FROM c),
m AS (SELECT src, dst, count(*) AS words FROM o WHERE src <> dst GROUP BY 1, 2)
SELECT CAST(src AS INTEGER) AS src, CAST(sum(words) AS BIGINT) AS words, count(*) AS messages, sum(words) <= 2 * 196 * 196 / 49 AS within FROM m GROUP BY 1""")
def c_relayout(spark, d):
    """Words and messages that every worker sends when a matrix changes its layout, against the bound on words."""
    moved = ledger.relayout_ledger(spark, 196, LayoutSpec(196, 49, 2), LayoutSpec(196, 49, 1))
    bound = relayout_cost(196, 49).words
    return moved.groupBy("src").agg(F.sum("words").alias("words"), F.count("*").alias("messages"), (F.sum("words") <= bound).alias("within"))


@query("c_peers", "SELECT CAST(w AS INTEGER) AS worker, CAST(d AS INTEGER) AS place, CAST(CASE WHEN d = 0 THEN w - w % 7 + x ELSE x * 7 + w % 7 END AS INTEGER) AS peer FROM (SELECT unnest(range(0, 49)) AS w), (SELECT unnest(range(0, 2)) AS d), (SELECT unnest(range(0, 7)) AS x)")
def c_peers(spark, d):
    """The groups of seven that exchange on each wide level: workers that agree in all digits but one."""
    own = spark.range(49).select(F.col("id").cast("int").alias("worker"))
    at = lambda k: own.select("worker", F.lit(k).alias("place"), F.explode(exchange_peers(F.col("worker"), k)).alias("peer"))
    return at(0).unionByName(at(1))

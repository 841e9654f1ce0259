"""Traffic ledger: who sends how many words to whom, and who adds how much, from the layout itself."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sevenfold.plans.costs import sequential_flops
from sevenfold.plans.layout import LayoutSpec, digits_of, with_digit
from sevenfold.plans.schemes import Scheme, scheme_of


def _levels(spark: SparkSession, n: int, workers: int, schedule: str | None, fine: int, s: Scheme) -> Iterator[tuple[int, str, int, int, DataFrame]]:
    """Of every level: number, letter, words of a block, serial runs, and the blocks of one quadrant with their holders.

    Every block of every combination is dealt by the layout of the input; the
    holder of a subproblem's block is its first owner with the digits of the
    wide levels above put in. A serial level runs its subproblems one after
    another on the same workers.
    """
    schedule = "W" * digits_of(workers, s.q) if schedule is None else schedule
    spec = LayoutSpec(n, workers, len(schedule), fine, s.q, s.n0).check()
    if schedule.count("W") != spec.k:
        raise ValueError(f"{workers} workers need {spec.k} wide levels, {schedule!r} has {schedule.count('W')}")
    rows, cols = spec.block
    for m, letter in enumerate(schedule):
        wide, runs = schedule[:m].count("W"), s.q ** schedule[:m].count("S")
        side_r, side_c = n // s.n0 ** (m + 1) // rows, n // s.n0 ** (m + 1) // cols
        blocks = spark.range(s.q**wide * side_r * side_c).select(
            F.floor(F.col("id") / (side_r * side_c)).alias("path"), F.pmod(F.floor(F.col("id") / side_c), F.lit(side_r)).alias("bi"), F.pmod("id", F.lit(side_c)).alias("bj")
        )
        holder = spec.owner(F.col("bi"), F.col("bj"))
        for place in range(wide):  # digits that earlier wide levels have set
            holder = with_digit(holder, place, F.pmod(F.floor(F.col("path") / s.q ** (wide - 1 - place)), F.lit(s.q)), s.q)
        yield m, letter, rows * cols, runs, blocks.select("path", holder.alias("holder"))


def traffic_ledger(spark: SparkSession, n: int, workers: int, schedule: str | None = None, fine: int = 1, scheme="s7a15", c: int = 1) -> DataFrame:
    """(run, step, family, src, dst, words) of a run along a schedule, wide-only by default.

    On a wide level a block of subproblem r goes to the worker whose digit of
    that level is r, and the products come back the same way. Serial levels send
    nothing, but repeat what is below them: ``run`` numbers the repeats.

    With ``c`` > 1 every one of the ``workers`` is c workers: each holds a c-th of
    the blocks' words, and for the base product of a group each of its members,
    who has its rows of the left factor, gets the others' shares of the right one.
    """
    s = scheme_of(scheme)
    schedule = "W" * digits_of(workers, s.q) if schedule is None else schedule
    steps = []
    for m, letter, words, runs, blocks in _levels(spark, n, workers, schedule, fine, s):
        if letter == "S":
            continue
        place = schedule[:m].count("W")
        sent = blocks.withColumn("r", F.explode(F.sequence(F.lit(0), F.lit(s.q - 1)))).withColumn("dst", with_digit(F.col("holder"), place, F.col("r"), s.q))
        sent = sent.where("holder <> dst").groupBy("holder", "dst").agg((F.count("*") * words).alias("words"))
        back = F.col("family") == "Q"
        sent = sent.withColumn("family", F.explode(F.array(F.lit("L"), F.lit("R"), F.lit("Q")))).withColumn("member", F.explode(F.sequence(F.lit(0), F.lit(c - 1))))
        number = lambda x: F.col(x) * c + F.col("member")
        steps.append(sent.select(
            F.explode(F.sequence(F.lit(0), F.lit(runs - 1))).alias("run"), F.lit(m + 1).alias("step"), "family",
            F.when(back, number("dst")).otherwise(number("holder")).alias("src"), F.when(back, number("holder")).otherwise(number("dst")).alias("dst"), (F.col("words") / c).alias("words"),
        ))
    if c > 1:
        leaf, members = n // s.n0 ** len(schedule), F.sequence(F.lit(0), F.lit(c - 1))
        pairs = spark.range(workers).select(F.col("id").cast("int").alias("group"), F.explode(members).alias("a")).withColumn("b", F.explode(members)).where("a <> b")
        steps.append(pairs.select(
            F.explode(F.sequence(F.lit(0), F.lit(s.q ** schedule.count("S") - 1))).alias("run"), F.lit(len(schedule) + 1).alias("step"), F.lit("R").alias("family"),
            (F.col("group") * c + F.col("a")).alias("src"), (F.col("group") * c + F.col("b")).alias("dst"), F.lit(leaf * leaf / c).alias("words"),
        ))
    return reduce(DataFrame.unionByName, steps)


def flop_ledger(spark: SparkSession, n: int, workers: int, schedule: str | None = None, scheme="s7a15", cutoff: int = 1) -> DataFrame:
    """(level, worker, flops): the additions that every worker does on every level on the blocks it holds, and its leaves."""
    s = scheme_of(scheme)
    schedule = "W" * digits_of(workers, s.q) if schedule is None else schedule
    parts = [
        blocks.groupBy(F.col("holder").alias("worker")).agg((F.count("*") * (words * s.additions * runs)).cast("double").alias("flops")).select(F.lit(m + 1).alias("level"), "worker", "flops")
        for m, _, words, runs, blocks in _levels(spark, n, workers, schedule, 1, s)
    ]
    leaf = float(sequential_flops(n // s.n0 ** len(schedule), s, cutoff)) * s.q ** schedule.count("S")
    parts.append(spark.range(workers).select(F.lit(len(schedule) + 1).alias("level"), F.col("id").cast("int").alias("worker"), F.lit(leaf).alias("flops")))
    return reduce(DataFrame.unionByName, parts)


def per_worker(ledger: DataFrame) -> DataFrame:
    """(run, step, worker, words, messages), sends and receives both counted."""
    ends = F.explode(F.array("src", "dst")).alias("worker")
    return ledger.select("run", "step", ends, "words").groupBy("run", "step", "worker").agg(F.sum("words").alias("words"), F.count("*").alias("messages"))


def critical_path(ledger: DataFrame) -> DataFrame:
    """(words, messages): the busiest worker of each step of each run, summed."""
    worst = per_worker(ledger).groupBy("run", "step").agg(F.max("words").alias("words"), F.max("messages").alias("messages"))
    return worst.agg(F.sum("words").alias("words"), F.sum("messages").alias("messages"))


def of_products(book: DataFrame, products: DataFrame, areas: list[str], counts: list[str]) -> DataFrame:
    """A ledger's rows for every row of ``products`` (scale, times, ...): so many products with ``scale`` times its side.

    Blocks of the same layout grow with the square of the scale, and so do ``areas``; ``counts`` don't depend on it.
    """
    area = F.col("scale") * F.col("scale") * F.col("times")
    return products.crossJoin(F.broadcast(book)).withColumns({c: F.col(c) * area for c in areas} | {c: F.col(c) * F.col("times") for c in counts})


def relayout_ledger(spark: SparkSession, n: int, before: LayoutSpec, after: LayoutSpec) -> DataFrame:
    """(src, dst, words) of moving a matrix between two layouts, at the cells' level."""
    r1, c1 = before.block
    r2, c2 = after.block
    cells = spark.range(n * n).select(F.floor(F.col("id") / n).alias("i"), F.pmod("id", F.lit(n)).alias("j"))
    src = before.owner(F.floor(F.col("i") / r1), F.floor(F.col("j") / c1))
    dst = after.owner(F.floor(F.col("i") / r2), F.floor(F.col("j") / c2))
    return cells.select(src.alias("src"), dst.alias("dst")).where("src <> dst").groupBy("src", "dst").agg(F.count("*").alias("words"))

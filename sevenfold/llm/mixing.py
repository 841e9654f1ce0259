"""Mixing sources to target weights by weighted fair queueing.

Every source serves its documents in a shuffled order. A document's virtual
finish time is its source's cumulative size, itself included, over the source's
target; a source that repeats its documents goes on in further rounds. All
copies are sorted by range of virtual finish time and taken in that order until
the total budget is used up. That is at virtual time one, when every source has
been served just its target; so the copy that a source then has in service
gives the words up to its source's target, and what a document gives is the sum
over its copies.
"""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from sevenfold.llm.common import durable

#: A source's words may be taken this many times.
MOST_REPEATS = 3
#: Fixed pattern of a word.
WORD = r"[^\x20\x09-\x0D]+"
#: Rows aimed at for one block of a source's shuffled order.
BLOCK_ROWS = 100_000


def cycle_weights(sources: list[str | None]) -> dict[str | None, int]:
    """1, 2, 3, repeating, over the sources by code point, null last."""
    ordered = sorted(s for s in sources if s is not None) + [None] * (None in sources)
    return {s: 1 + k % 3 for k, s in enumerate(ordered)}


def shares(sizes: dict, weights: dict, budget: int, most_repeats: int = MOST_REPEATS) -> dict:
    """Target of each source as an exact fraction.

    By weight, but at most ``most_repeats`` times a source's size; what exceeds
    that goes to the others by weight until none is above.
    """
    target, open_, left = {}, set(sizes), Fraction(budget)
    while open_:
        total = sum(weights[s] for s in open_)
        share = {s: left * weights[s] / total for s in open_}
        full = {s for s in open_ if share[s] > most_repeats * sizes[s]}
        if not full:
            return target | share
        for s in full:
            target[s] = Fraction(most_repeats * sizes[s])
            left -= target[s]
        open_ -= full
    return target


def place_copies(docs: DataFrame, weights=cycle_weights, key: str = "doc_id", text: str = "text", source: str = "source", carry: tuple = ()) -> tuple[DataFrame, int]:
    """Every document with its source's target and the words that its source serves before it; and the total budget.

    Checkpointed; ``rid`` numbers the rows, as ids may repeat. The order within a
    source is that of the ids' MD5, so reruns agree. Prefix sums go over blocks
    of that order first and within a block then, so a hot source spreads over
    many tasks. The sources are collected to the driver; one row each.
    """
    spark = docs.sparkSession
    ident = F.coalesce(F.col(key).cast("string"), F.lit(""))
    light = docs.select(
        F.col(key).alias("id"),
        F.col(source).alias("src"),
        F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long").alias("size"),
        F.md5(ident.cast("binary")).alias("u"),
        F.monotonically_increasing_id().alias("rid"),
        *carry,
    )
    light = durable(light)
    rows = light.groupBy("src").agg(F.sum("size").alias("size"), F.count("*").alias("n")).collect()
    sizes = {r["src"]: int(r["size"]) for r in rows}
    goals = shares(sizes, weights(list(sizes)), sum(sizes.values()))
    table = spark.createDataFrame(
        [(s, size, float(goals[s]), int(goals[s])) for s, size in sizes.items()], "src string, source_size long, target double, serve long"
    )
    digits, most = 1, max([r["n"] for r in rows], default=0)
    while most > BLOCK_ROWS * 16**digits and digits < 7:
        digits += 1
    light = light.withColumn("block", F.substring("u", 1, digits + 1))
    blocks = light.groupBy("src", "block").agg(F.sum("size").alias("served"))
    earlier = Window.partitionBy("src").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    blocks = blocks.select("src", "block", F.coalesce(F.sum("served").over(earlier), F.lit(0)).alias("offset"))
    within = Window.partitionBy("src", "block").orderBy("u", "id", "size").rowsBetween(Window.unboundedPreceding, -1)
    placed = light.withColumn("inner", F.coalesce(F.sum("size").over(within), F.lit(0)))
    right = blocks.withColumnsRenamed({"src": "b_src", "block": "b_block"})
    placed = placed.join(right, placed["src"].eqNullSafe(right["b_src"]) & (placed["block"] == right["b_block"]))
    right = F.broadcast(table.withColumnRenamed("src", "t_src")) if len(sizes) <= 100_000 else table.withColumnRenamed("src", "t_src")
    placed = placed.join(right, placed["src"].eqNullSafe(right["t_src"])).withColumn("before", F.col("offset") + F.col("inner"))
    placed = durable(placed.drop("offset", "inner", "block", "b_src", "b_block", "t_src"))
    return placed, sum(int(goals[s]) for s in sizes)


def plan_mix(docs: DataFrame, weights=cycle_weights, key: str = "doc_id", text: str = "text", source: str = "source", carry: tuple = ()) -> DataFrame:
    """One row per document: id, source, size, source_size, target, taken, before, virtual_finish, and ``carry``.

    ``weights`` maps the list of sources to their weights. ``taken`` is the sum
    over the document's copies in the sorted and truncated mix.
    """
    placed, budget = place_copies(docs, weights, key, text, source, carry)
    partitions = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    taken = truncated(sorted_copies(placed, partitions), budget).groupBy("rid").agg(F.sum("words").alias("taken"))
    finish = F.when(F.col("target") > 0, (F.col("before") + F.col("size")) / F.col("target"))
    extra = [c for c in placed.columns if c not in ("rid", "id", "src", "size", "u", "source_size", "target", "serve", "before")]
    whole = placed.join(taken, "rid", "left")
    return whole.select("id", "src", "size", "source_size", "target", F.coalesce("taken", F.lit(0)).cast("long").alias("taken"), "before", finish.alias("virtual_finish"), *extra)


def sorted_copies(placed: DataFrame, partitions: int) -> DataFrame:
    """A row for each copy of a document that its source begins to serve, sorted by range of virtual finish time.

    ``words`` are those up to the source's target, so only a copy in service at
    virtual time one has fewer than its size. Ties go by source, id, order and round.
    """
    rounds = F.explode(F.transform(F.sequence(F.lit(0), F.lit(MOST_REPEATS - 1)), lambda k: F.struct(k.alias("copy"), (F.col("before") + k * F.col("source_size")).alias("at"))))
    copies = placed.where("size > 0").select("rid", "id", "src", "size", "target", "serve", rounds.alias("c")).select("*", "c.copy", "c.at").drop("c")
    copies = copies.withColumn("words", F.least("size", F.col("serve") - F.col("at"))).where("words > 0")
    copies = copies.withColumn("finish", (F.col("at") + F.col("size")) / F.col("target"))
    order = ["finish", "src", "id", "at", "rid"]
    return copies.repartitionByRange(partitions, *order).sortWithinPartitions(*order)


def truncated(copies: DataFrame, budget: int) -> DataFrame:
    """The sorted copies until their running total reaches the budget; the last one is cut to fit.

    Totals go over the ranges first, then within each; a range is a partition of
    the sort, so its own running total needs no further shuffle than its number.
    """
    copies = durable(copies.withColumn("range", F.spark_partition_id()))
    ranges = copies.groupBy("range").agg(F.sum("words").alias("range_words"))
    earlier = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)  # one row a range
    ranges = ranges.select(F.col("range").alias("r"), F.coalesce(F.sum("range_words").over(earlier), F.lit(0)).alias("earlier"))
    within = Window.partitionBy("range").orderBy("finish", "src", "id", "at", "rid").rowsBetween(Window.unboundedPreceding, -1)
    running = copies.withColumn("inner", F.coalesce(F.sum("words").over(within), F.lit(0))).join(F.broadcast(ranges), F.col("range") == F.col("r"))
    left = F.lit(budget) - F.col("earlier") - F.col("inner")
    return running.withColumn("words", F.least("words", left)).where("words > 0").drop("r", "earlier", "inner")


def mixed_order(docs: DataFrame, partitions: int, **options) -> DataFrame:
    """The mix itself: (id, src, copy, words, finish) of each copy taken, in order of virtual finish time.

    The partitions in order are the mix in order.
    """
    placed, budget = place_copies(docs, **options)
    return truncated(sorted_copies(placed, partitions), budget).select("id", "src", "copy", "words", "finish", "range").repartitionByRange(partitions, "finish", "src", "id").sortWithinPartitions("finish", "src", "id").drop("range")


def op7_mixing(spark, sf_dir: str) -> DataFrame:
    """The mix of all documents by source weights 1, 2, 3; one row per document.

    Null text has size 0; null is a source of its own, the last. What a document
    gives is the sum over its copies in the mix, the last copy of a source being
    cut where the source's target ends. Repeated rows are documents of their own,
    and so are rows with a null id; an empty table gives no rows.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source")
    return plan_mix(docs).select(F.col("id").alias("doc_id"), "size", "source_size", "target", "taken", "virtual_finish")


SQL_OP7 = r"""
WITH d AS (
  SELECT doc_id, source, md5(coalesce(CAST(doc_id AS VARCHAR), '')) AS u,
         coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size
  FROM documents),
s AS (
  SELECT source, sum(size)::BIGINT AS source_size,
         1 + ((row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3) AS w
  FROM d GROUP BY source),
r AS (
  SELECT *, sum(source_size) OVER () - coalesce(sum(3 * source_size) OVER p, 0) AS left_size,
         sum(w) OVER () - coalesce(sum(w) OVER p, 0) AS left_w
  FROM s WINDOW p AS (ORDER BY source_size::DOUBLE / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
f AS (SELECT *, left_size * w > 3 * source_size * left_w AS full_up FROM r),
o AS (SELECT min(left_size) FILTER (NOT full_up) AS x, any_value(1) AS one FROM f),
q AS (SELECT max(left_size) FILTER (NOT full_up) AS rest, max(left_w) FILTER (NOT full_up) AS rest_w FROM f),
g AS (
  SELECT source, source_size,
         CASE WHEN full_up THEN (3 * source_size)::DOUBLE ELSE (rest * w)::DOUBLE / rest_w::DOUBLE END AS target,
         CASE WHEN full_up THEN (3 * source_size)::BIGINT ELSE ((rest * w) // rest_w)::BIGINT END AS serve
  FROM f, q),
c AS (
  SELECT d.*, coalesce(sum(size) OVER (PARTITION BY source ORDER BY u, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS before
  FROM d)
SELECT doc_id, size, source_size, target,
       (greatest(0, least(size, serve - before)) + greatest(0, least(size, serve - source_size - before))
        + greatest(0, least(size, serve - 2 * source_size - before)))::BIGINT AS taken,
       CASE WHEN target > 0 THEN (before + size)::DOUBLE / target END AS virtual_finish
FROM c JOIN g ON c.source IS NOT DISTINCT FROM g.source
"""


def take_mix(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: the documents in the mix, with ``taken`` words and ``copies`` begun.

    Columns of those two names that the documents bring are replaced. Null and
    empty texts have no words and so no place in the mix. Rows that repeat id, source and text are told apart by a row number, so each
    takes what the plan gives to one of them.
    """
    mark = F.xxhash64(F.coalesce("text", F.lit(""))).alias("h")
    plan = durable(plan_mix(docs, carry=(mark,)).select("id", "src", "h", F.col("taken").alias("mix_taken"), F.col("size").alias("mix_size")))
    packed = docs.select(F.struct("*").alias("row"), F.col("doc_id").alias("d_id"), F.col("source").alias("d_src"), F.xxhash64(F.coalesce("text", F.lit(""))).alias("d_h"))
    repeats = plan.groupBy("id", "src", "h").count().where("count > 1").limit(1).count()
    if repeats:
        plan = plan.withColumn("turn", F.row_number().over(Window.partitionBy("id", "src", "h").orderBy(F.desc("mix_taken"))))
        packed = packed.withColumn("d_turn", F.row_number().over(Window.partitionBy("d_id", "d_src", "d_h").orderBy(F.xxhash64("row"))))
    plan = plan.where("mix_taken > 0")
    same = packed["d_id"].eqNullSafe(plan["id"]) & packed["d_src"].eqNullSafe(plan["src"]) & (packed["d_h"] == plan["h"])
    found = packed.join(plan, same & (packed["d_turn"] == plan["turn"]) if repeats else same)
    named = [c for c in docs.columns if c not in ("taken", "copies")]
    return found.select(*(F.col("row")[c].alias(c) for c in named), F.col("mix_taken").alias("taken"), F.ceil(F.col("mix_taken") / F.col("mix_size")).cast("int").alias("copies"))

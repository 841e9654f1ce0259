"""Operators around the product: slices, norms, joins, windows and sets over cells."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sevenfold.operators.tiles import durable


def checked_broadcast(df: DataFrame, rows: int = 100_000) -> DataFrame:
    """Marked for broadcast only if it is counted to hold at most ``rows`` rows; beyond, Spark joins by shuffle."""
    return F.broadcast(df) if df.count() <= rows else df


def slice_cells(x: DataFrame, rows: tuple[int, int], cols: tuple[int, int]) -> DataFrame:
    """Cells of half-open ranges; both reach the scan as filters."""
    return x.where((F.col("i") >= rows[0]) & (F.col("i") < rows[1]) & (F.col("j") >= cols[0]) & (F.col("j") < cols[1]))


def band(x: DataFrame, low: int, high: int) -> DataFrame:
    """Cells with low <= j - i <= high: (0, n) is the upper triangle, (0, 0) the diagonal."""
    return x.where((F.col("j") - F.col("i")).between(low, high))


def sparsify(x: DataFrame, eps) -> DataFrame:
    return x.where(F.abs("v") > eps)


def transpose(x: DataFrame) -> DataFrame:
    return x.select(F.col("j").alias("i"), F.col("i").alias("j"), "v")


def axpy(a, x: DataFrame, b, y: DataFrame) -> DataFrame:
    """a x + b y."""
    both = x.select("i", "j", (F.col("v") * a).alias("v")).unionByName(y.select("i", "j", (F.col("v") * b).alias("v")))
    return both.groupBy("i", "j").agg(F.sum("v").alias("v")).where("v <> 0")


def hadamard(x: DataFrame, y: DataFrame) -> DataFrame:
    return x.join(y.withColumnRenamed("v", "w"), ["i", "j"]).select("i", "j", (F.col("v") * F.col("w")).alias("v"))


def matvec(x: DataFrame, vector: DataFrame) -> DataFrame:
    """(i, v) from cells and a vector (j, x)."""
    return x.join(vector, "j").groupBy("i").agg(F.sum(F.col("v") * F.col("x")).alias("v"))


def diff(x: DataFrame, y: DataFrame) -> DataFrame:
    """x - y by a full outer join; equal cells vanish."""
    joined = x.join(y.withColumnRenamed("v", "w"), ["i", "j"], "full_outer")
    return joined.select("i", "j", (F.coalesce("v", F.lit(0)) - F.coalesce("w", F.lit(0))).alias("v")).where("v <> 0")


def norms(x: DataFrame) -> DataFrame:
    """(kind, v): largest column sum, largest row sum, sum of squares, largest cell."""
    size = F.abs("v")
    one = x.groupBy("j").agg(F.sum(size).alias("s")).agg(F.max("s").alias("v")).select(F.lit("one").alias("kind"), "v")
    inf = x.groupBy("i").agg(F.sum(size).alias("s")).agg(F.max("s").alias("v")).select(F.lit("inf").alias("kind"), "v")
    rest = x.agg(F.sum(F.col("v") * F.col("v")).alias("squares"), F.max(size).alias("max"))
    rest = rest.select(F.explode(F.create_map(F.lit("squares"), "squares", F.lit("max"), "max")).alias("kind", "v"))
    return one.unionByName(inf).unionByName(rest)


def topk_per_row(x: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("i").orderBy(F.desc("v"), "j")
    return x.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k)


def index_keys(df: DataFrame, column: str) -> DataFrame:
    """(key, idx): dense numbers in key order, without a global window.

    Ranges of keys are numbered each for itself; the counts before a range are
    joined in. There is one count per partition.
    """
    keys = df.select(F.col(column).alias("key")).where("key is not null").distinct()
    spread = keys.repartitionByRange(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), "key").withColumn("p", F.spark_partition_id())
    spread = durable(spread)
    counts = spread.groupBy("p").agg(F.count("*").alias("n"))
    before = counts.select("p", F.coalesce(F.sum("n").over(Window.orderBy("p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("offset"))
    numbered = spread.withColumn("r", F.row_number().over(Window.partitionBy("p").orderBy("key")))
    return numbered.join(F.broadcast(before), "p").select("key", (F.col("offset") + F.col("r") - 1).alias("idx"))


def band_join(x: DataFrame, y: DataFrame, on: str, width: float) -> DataFrame:
    """Pairs with |x.on - y.on| <= width: equi-join on buckets of that width, then the exact test."""
    bucket = lambda c: F.floor(c / width)
    left = x.withColumn("bucket", F.explode(F.sequence(bucket(F.col(on)) - 1, bucket(F.col(on)) + 1)))
    right = y.select(*(F.col(c).alias(f"{c}_r") for c in y.columns)).withColumn("bucket", bucket(F.col(f"{on}_r")))
    return left.join(right, "bucket").where(F.abs(F.col(on) - F.col(f"{on}_r")) <= width).drop("bucket")


def asof_last(events: DataFrame, probes: DataFrame, by: str, time: str, value: str) -> DataFrame:
    """Last value up to each probe's time: union, then the last non-null within the key."""
    e = events.select(by, time, F.col(value).alias("seen"), F.lit(0).alias("probe"))
    p = probes.select(by, time, F.lit(None).cast(dict(events.dtypes)[value]).alias("seen"), F.lit(1).alias("probe"))
    w = Window.partitionBy(by).orderBy(time, "probe", "seen").rowsBetween(Window.unboundedPreceding, 0)
    return e.unionByName(p).withColumn("last_seen", F.last("seen", ignorenulls=True).over(w)).where("probe = 1").select(by, time, "last_seen")


def block_totals(df: DataFrame, keys: list[str], value: Column, kind: str = "rollup") -> DataFrame:
    """Totals of all levels of a hierarchy (rollup) or of all subsets (cube)."""
    return getattr(df, kind)(*keys).agg(F.sum(value).alias("v"), F.grouping_id().cast("long").alias("level"))

"""The given tables as matrices: cells (i, j, v) with exact integer values."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table with only the columns asked for."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def fold_size(spark: SparkSession, sf_dir: str) -> int:
    """Side of the fold matrices by the size of the order lines."""
    rows = table(spark, sf_dir, "lineitem").count()
    return 56 if rows < 20_000 else 224 if rows < 200_000 else 672


def cells_from(df: DataFrame, row, col, val) -> DataFrame:
    """Sum of ``val`` by row and column key; zero cells are absent."""
    return df.select(row.cast("long").alias("i"), col.cast("long").alias("j"), val.cast("long").alias("v")).groupBy("i", "j").agg(F.sum("v").alias("v")).where("v <> 0")


def fold_pair(spark: SparkSession, sf_dir: str, n: int | None = None) -> tuple[DataFrame, DataFrame, int]:
    """The two dense fold matrices of the order lines, and their side."""
    n = n or fold_size(spark, sf_dir)
    lines = table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_linenumber", "l_quantity")
    side = F.lit(n)
    a = cells_from(lines, F.pmod("l_orderkey", side), F.pmod("l_partkey", side), F.col("l_quantity"))
    b = cells_from(lines, F.pmod("l_partkey", side), F.pmod(3 * F.col("l_orderkey") + F.col("l_linenumber"), side), F.col("l_linenumber"))
    return a, b, n


FOLD_SQL = """
n AS (SELECT CASE WHEN count(*) < 20000 THEN 56 WHEN count(*) < 200000 THEN 224 ELSE 672 END AS n FROM lineitem),
a AS (SELECT l_orderkey % n AS i, l_partkey % n AS j, CAST(sum(l_quantity) AS BIGINT) AS v FROM lineitem, n GROUP BY 1, 2 HAVING sum(l_quantity) <> 0),
b AS (SELECT l_partkey % n AS i, (3 * l_orderkey + l_linenumber) % n AS j, CAST(sum(l_linenumber) AS BIGINT) AS v FROM lineitem, n GROUP BY 1, 2 HAVING sum(l_linenumber) <> 0)
"""
PRODUCT_SQL = "SELECT a.i AS i, b.j AS j, CAST(sum(a.v * b.v) AS BIGINT) AS v FROM a JOIN b ON a.j = b.i GROUP BY 1, 2 HAVING sum(a.v * b.v) <> 0"


def trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nation by nation: quantity that customers of one ordered from suppliers of the other."""
    c = table(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    o = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    li = table(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey", "l_quantity")
    s = table(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey")
    joined = li.join(o, li["l_orderkey"] == o["o_orderkey"]).join(c, F.col("o_custkey") == F.col("c_custkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
    return cells_from(joined, F.col("c_nationkey"), F.col("s_nationkey"), F.col("l_quantity"))


TRADE_SQL = """
t AS (SELECT CAST(c_nationkey AS BIGINT) AS i, CAST(s_nationkey AS BIGINT) AS j, CAST(sum(l_quantity) AS BIGINT) AS v
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1, 2)
"""


def embedding_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors by position, in thousandths."""
    e = table(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", F.posexplode("embedding").alias("j", "x"))
    return e.select(F.col("vec_id").alias("i"), F.col("j").cast("long").alias("j"), F.round(F.col("x").cast("double") * 1000).cast("long").alias("v")).where("v <> 0")


EMBED_SQL = """
e AS (SELECT vec_id AS i, CAST(k - 1 AS BIGINT) AS j, CAST(round(CAST(embedding[k] AS DOUBLE) * 1000) AS BIGINT) AS v
  FROM (SELECT vec_id, embedding, unnest(range(1, len(embedding) + 1)) AS k FROM embeddings)),
m AS (SELECT * FROM e WHERE v <> 0)
"""

"""Connected components by alternating star contractions, with durable rounds."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sevenfold.llm.common import durable


def local_components(n: int, a: np.ndarray, b: np.ndarray, label: np.ndarray | None = None) -> np.ndarray:
    """Smallest member of each component over vertices 0..n-1, from edges a-b on top of ``label``."""
    label = np.arange(n) if label is None else label.copy()
    while True:
        x, y = label[a], label[b]
        low, high = np.minimum(x, y), np.maximum(x, y)
        open_ = low != high
        if not open_.any():
            return label
        np.minimum.at(label, high[open_], low[open_])
        while True:
            jumped = label[label]
            if np.array_equal(jumped, label):
                break
            label = jumped


def connected_components(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(v, root) for every vertex with an edge; root is the component's smallest vertex.

    ``edges`` has long columns a, b. Minima are aggregated before they shuffle and
    the edges meet them by a join, so a vertex of very high degree is no single task.
    """
    tied = F.col("a") != F.col("b")
    e = durable(edges.where(tied).select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    before = None
    for _ in range(most_rounds):
        both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where(tied).distinct()
        large = durable(large)
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a").select(F.explode(F.array(F.struct("a", F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("x"))
        e = durable(small.select("x.a", "x.b").where(tied).distinct())
        now = e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == before:
            break
        before = now
    else:
        raise RuntimeError(f"components are not stable after {most_rounds} rounds")
    return e.select(F.col("a").alias("v"), F.col("b").alias("root"))

"""Reports on runs: speedups over the baselines, and what Spark moved."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

CLASSICAL = ("grid2d", "grid2d_shift", "grid3d", "grid25d", "lib_block", "sql")
EARLIER_FAST = ("grid2d_fast", "fast_grid2d", "grid25d_fast", "fast_grid25d")


def speedup_report(runs: DataFrame, ours: str = "hybrid") -> DataFrame:
    """Per worker count, how much faster in percent ``ours`` is than the best run of either class.

    ``runs`` has (method, p, seconds); a class without runs at p gives null. One
    conditional aggregate, so the baselines need not be pivoted or joined.
    """
    best = lambda names: F.min(F.when(F.col("method").isin(*names), F.col("seconds")))
    over = lambda column: F.round((F.col(column) / F.col("seconds") - 1) * 100, 4)
    at = runs.groupBy("p").agg(best((ours,)).alias("seconds"), best(CLASSICAL).alias("classical"), best(EARLIER_FAST).alias("fast"))
    return at.where("seconds is not null").select("p", over("classical").alias("over_classical_pct"), over("fast").alias("over_fast_pct"))


def moved(spark: SparkSession, action: Callable[[], object]) -> dict[str, int]:
    """Run ``action``; shuffle bytes and records written, bytes spilled and stages run by it.

    Read from the status store of the session, so it counts the stages that are
    new since the call; runs of other threads count too.
    """
    jvm, sc = spark.sparkContext._jvm, spark.sparkContext._jsc.sc()

    def stages():
        none = jvm.java.util.ArrayList()
        found = sc.statusStore().stageList(none, False, False, spark.sparkContext._gateway.new_array(jvm.double, 0), none)
        return [found.apply(k) for k in range(found.size())]

    before = {(s.stageId(), s.attemptId()) for s in stages()}
    action()
    sc.listenerBus().waitUntilEmpty(60_000)
    new = [s for s in stages() if (s.stageId(), s.attemptId()) not in before and s.numCompleteTasks()]
    return {
        "shuffle_bytes": sum(s.shuffleWriteBytes() for s in new),
        "shuffle_records": sum(s.shuffleWriteRecords() for s in new),
        "spilled_bytes": sum(s.diskBytesSpilled() for s in new),
        "stages": len(new),
    }

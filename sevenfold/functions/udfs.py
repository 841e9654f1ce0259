"""UDF surface: grouped aggregates and table functions, registered for SQL."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from sevenfold.plans.costs import traffic


def frobenius_udaf():
    """Grouped aggregate: square root of the sum of squares, rounded to six digits."""

    @F.pandas_udf("double")
    def frobenius(v: pd.Series) -> float:
        return round(float(np.sqrt(np.square(v.astype(float)).sum())), 6)

    return frobenius


def schedule_steps():
    """Table function: the levels of a schedule with workers, side, words and messages of each."""

    @F.udtf(returnType="step int, letter string, n long, workers long, words double, messages long")
    class ScheduleSteps:
        def eval(self, schedule: str, n: int, workers: int):
            for k, letter in enumerate(schedule):
                here = traffic(n, workers, schedule[k:])
                below = traffic(n // 2, workers // 7 if letter == "W" else workers, schedule[k + 1 :])
                own = (here[0] - below[0], here[1] - below[1]) if letter == "W" else (0, 0)
                yield k + 1, letter, n, workers, float(own[0]), int(own[1])
                n, workers = n // 2, workers // 7 if letter == "W" else workers

    return ScheduleSteps


def quadrant_of():
    """Table function: the quadrant of a tile in a grid of ``side`` tiles, and its place there."""

    @F.udtf(returnType="quadrant int, row int, col int")
    class QuadrantOf:
        def eval(self, bi: int, bj: int, side: int):
            half = side // 2
            yield 2 * (bi // half) + bj // half, bi % half, bj % half

    return QuadrantOf


def register(spark: SparkSession) -> None:
    """Make the functions known to SQL."""
    spark.udtf.register("schedule_steps", schedule_steps())
    spark.udtf.register("quadrant_of", quadrant_of())
    spark.udf.register("frobenius", frobenius_udaf())

"""What a plan does physically: exchanges, broadcasts, Python nodes."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame

PATTERNS = {"exchanges": r"(?<!Broadcast)(?<!Reused)Exchange (?:hash|range|Single|Round|REB|shuffle)", "broadcasts": r"BroadcastExchange", "python": r"(?:ArrowEvalPython|MapInPandas|MapInArrow|FlatMap(?:Co)?GroupsInPandas|BatchEvalPython)", "sorts": r"\bSort \["}


def spark_costs(df: DataFrame) -> dict[str, int]:
    """Counts in the physical plan, from its text."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return {k: len(re.findall(p, plan)) for k, p in PATTERNS.items()}

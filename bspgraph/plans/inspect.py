"""What a plan does, as counts of its operators."""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import DataFrame

_NODE = re.compile(r"^[\s:+*|-]*(?:\(\d+\) )?([A-Z]\w+)", re.M)


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def operators(df: DataFrame) -> Counter:
    """Operator names of the physical plan and how often each occurs."""
    return Counter(_NODE.findall(plan_text(df)))


def exchanges(df: DataFrame) -> int:
    """Shuffles of the plan."""
    return len(re.findall(r"(?:^|[\s+-])Exchange (?:hash|range|single|round|Hash|Range|Single|Round)", plan_text(df)))

"""Counts of operators in a DataFrame's physical plan, for tests that pin a plan's shape."""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import DataFrame


def operators(df: DataFrame) -> Counter:
    """How often each physical operator occurs (the initial plan under adaptive execution)."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return Counter(re.findall(r"^[\s:+\-|]*(?:\*\(\d+\) )?([A-Z]\w+)", text, re.M))


def shuffles(df: DataFrame) -> int:
    return operators(df)["Exchange"]

"""What a plan costs: operators of its final form, rows and time."""

from __future__ import annotations

import re
import time
from collections import Counter

from pyspark.sql import DataFrame, Row

KINDS = ("Exchange", "BroadcastExchange", "SortMergeJoin", "BroadcastHashJoin", "ShuffledHashJoin", "BroadcastNestedLoopJoin", "HashAggregate", "Window", "Sort", "Scan")


def measure(df: DataFrame, name: str) -> Row:
    """(name, rows, ms, and how often each of KINDS stands in the executed plan); runs df once."""
    began = time.time()
    rows = df.count()
    seen = Counter(re.findall(r"[A-Z]\w+", df._jdf.queryExecution().executedPlan().toString()))
    return Row(name=name, rows=rows, ms=int(1000 * (time.time() - began)), **{k: int(seen[k]) for k in KINDS})

"""What a physical plan holds: exchanges, joins, Python."""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import DataFrame


def operators(df: DataFrame) -> Counter:
    """Names of physical operators and how often they stand in the plan (before adaptive changes)."""
    plan = df._jdf.queryExecution().executedPlan()
    if plan.getClass().getSimpleName() == "AdaptiveSparkPlanExec":
        plan = plan.initialPlan()
    text = plan.toString()
    # what a cached relation was made from has run already
    kept, depth = [], None
    for line in text.split("\n"):
        indent = len(line) - len(line.lstrip(" :+-|"))
        if depth is not None and indent > depth:
            continue
        depth = indent if "InMemoryRelation" in line else None
        kept.append(line)
    names = re.findall(r"(?m)^[\s:+\-|*()\d]*([A-Z][A-Za-z]+)", "\n".join(kept))
    return Counter(names)


def exchanges(df: DataFrame) -> int:
    return operators(df)["Exchange"]


def python_operators(df: DataFrame) -> int:
    return sum(n for k, n in operators(df).items() if re.search("Python|Pandas|Arrow", k))


def scanned_columns(df: DataFrame) -> list[str]:
    """ReadSchema of each file scan."""
    return re.findall(r"ReadSchema: struct<([^\n]*)>", df._jdf.queryExecution().executedPlan().toString())

"""What a physical plan does: exchanges, broadcasts, products of all pairs."""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import DataFrame


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def nodes(df: DataFrame) -> Counter:
    """Operator names of the physical plan, counted."""
    names = re.findall(r"^[\s:+|*()\d-]*([A-Z][A-Za-z]+)", plan_text(df), flags=re.M)
    return Counter(names)


def exchanges(df: DataFrame) -> int:
    """Shuffles in the plan; broadcasts are not counted."""
    return nodes(df)["Exchange"]


def assert_exchanges(df: DataFrame, most: int) -> None:
    found = exchanges(df)
    if found > most:
        raise AssertionError(f"{found} exchanges, {most} expected:\n{plan_text(df)}")


def assert_no_cross(df: DataFrame) -> None:
    found = nodes(df)
    if found["CartesianProduct"]:
        raise AssertionError(plan_text(df))

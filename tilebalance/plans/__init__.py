"""Reading of physical plans, for tests and tuning."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def text(df: DataFrame) -> str:
    return df._jdf.queryExecution().toString()


def exchanges(df: DataFrame) -> int:
    """Shuffles in the plan as first compiled."""
    return len(re.findall(r"(?m)^[\s:+\-*()\d]*Exchange ", df._jdf.queryExecution().executedPlan().toString()))


def uses_python(df: DataFrame) -> bool:
    return bool(re.search("Python|Pandas|ArrowEval|MapInArrow", text(df)))


def read_schemas(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: (struct<[^\n]*>)", text(df))

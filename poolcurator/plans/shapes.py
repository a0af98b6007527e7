"""What a physical plan contains: for plan tests and for `explain` in notebooks."""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import DataFrame


def physical(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def operators(df: DataFrame) -> Counter:
    """How often each physical operator occurs."""
    return Counter(re.findall(r"^[\s:+\-*()0-9]*([A-Z][A-Za-z]+)", physical(df), re.MULTILINE))


def pushed_filters(df: DataFrame) -> list[str]:
    return [f for m in re.findall(r"PushedFilters: \[([^\]]*)\]", physical(df)) for f in m.split(", ") if f]


def read_columns(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: (struct<[^\n]*>)", physical(df))


def uses_python(df: DataFrame) -> bool:
    return bool(re.search(r"Python|Pandas|Arrow", physical(df)))

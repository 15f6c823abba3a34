"""What plans must not have, and must have."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def text_of(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def to_one_partition(df: DataFrame) -> list[str]:
    """Exchanges of rows to a single task, but for sums that are partial already and the ends of top lists."""
    lines = text_of(df).splitlines()
    found = []
    for i, line in enumerate(lines):
        if "Exchange SinglePartition" in line:
            below = lines[i + 1] if i + 1 < len(lines) else ""
            if not re.search(r"partial_|functions=\[\]", below):
                found.append(line.strip())
    return found


def windows_over_all(df: DataFrame) -> bool:
    """Whether some window has no partition: all rows would go through one task."""
    return bool(re.search(r"Window \[[^\n]*windowspecdefinition\((?![^)]*\bpartition)[^\n]*\], \[[^\]]*ASC", text_of(df))) and "SinglePartition" in text_of(df)


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[([^\]]+)\]", text_of(df))


def read_columns(df: DataFrame) -> list[str]:
    return re.findall(r"ReadSchema: struct<([^>]*)>", text_of(df))


def row_functions(df: DataFrame) -> bool:
    """Whether plain Python functions run row by row."""
    return "BatchEvalPython" in text_of(df)

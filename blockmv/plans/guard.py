"""Checks on executed plans: the matrix must not be exchanged after it was laid out."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def executed_plan(df: DataFrame) -> list[tuple[int, str]]:
    """(depth, operator) of the physical plan, outermost first."""
    text = df._jdf.queryExecution().executedPlan().toString()
    rows = []
    for line in text.split("\n"):
        m = re.match(r"^([\s:|+\-*()\d]*)(.*)$", line)
        if m and m[2]:
            rows.append((len(re.match(r"^[\s:|+\-*]*", line)[0]), m[2]))
    return rows


def matrix_exchanges(df: DataFrame, marker: str = "rb#") -> list[str]:
    """Exchanges that stand between the cached cells and the rest of one iteration's plan. Cells are recognised by the
    column ``marker`` in their scan; partial results of an aggregate do not count."""
    rows = executed_plan(df)
    found = []
    for k, (depth, op) in enumerate(rows):
        if not op.startswith("InMemoryTableScan") or marker not in op:
            continue
        level = depth
        for d, o in reversed(rows[:k]):
            if d < level:
                level = d
                if "Aggregate" in o or "Join" in o:
                    break
                if o.startswith("Exchange"):
                    found.append(o)
    return found

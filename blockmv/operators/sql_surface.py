"""One step of a product in SQL over temporary views, for users who prefer it. Aggregation over a recursive reference
is refused by Spark, so rounds are driven from outside."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

FOLDS = {"sum", "min", "max", "bool_or"}


def product_sql(combine: str, fold: str, assign: str, identity: str, edges: str = "edges", state: str = "state") -> str:
    """combine: an expression over w and val; assign: one over val and acc. edges (src, dst, w), state (node, val)."""
    if fold not in FOLDS:
        raise ValueError(f"fold must be one of {', '.join(sorted(FOLDS))}")
    return f"""
        WITH acc AS (
          SELECT e.dst AS node, {fold}({combine}) AS acc
          FROM {edges} e JOIN {state} v ON e.src = v.node GROUP BY e.dst)
        SELECT node, {assign} AS val
        FROM (SELECT v.node, v.val, coalesce(a.acc, {identity}) AS acc FROM {state} v LEFT JOIN acc a ON v.node = a.node)
    """


def multiply_sql(spark: SparkSession, edges: DataFrame, state: DataFrame, combine: str, fold: str, assign: str, identity: str) -> DataFrame:
    edges.createOrReplaceTempView("blockmv_edges")
    state.createOrReplaceTempView("blockmv_state")
    return spark.sql(product_sql(combine, fold, assign, identity, "blockmv_edges", "blockmv_state"))

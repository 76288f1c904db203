"""User code where columns do not suffice: vectorised combine functions, a fold of any shape, neighbours as a table."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .algebra import Algebra


def vectorised(name: str, combine: Callable[[pd.Series, pd.Series], pd.Series], fold, merge, identity, assign) -> Algebra:
    """An algebra over doubles whose combine is a function of two pandas Series; all else stays columns."""
    f = F.pandas_udf(combine, "double")
    return Algebra(name, "double", lambda w, v: f(w.cast("double"), v.cast("double")), fold, merge, identity, assign)


def folded(values: DataFrame, fold: Callable[[pd.Series], float]) -> DataFrame:
    """values (key, x) -> key, acc by a grouped pandas aggregate. A key's values are held in one task's memory."""
    f = F.pandas_udf(fold, "double", F.PandasUDFType.GROUPED_AGG)
    return values.groupBy("key").agg(f(F.col("x")).alias("acc"))


@F.udtf(returnType="src bigint, dst bigint")
class Neighbours:
    """neighbours(src, 'a b c'): one row per neighbour in a text adjacency list."""

    def eval(self, src: int, line: str):
        for x in (line or "").split():
            yield src, int(x)


def register(spark: SparkSession) -> None:
    spark.udtf.register("neighbours", Neighbours)

"""User-defined products: how a cell meets a vector element, how a row folds, how a vertex takes its new value.

All parts are functions over Spark columns, so a whole iteration stays inside generated code. ``fold`` must be a
commutative and associative aggregate: it is applied to partial results before and after the exchange.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

INF = float("inf")


@dataclass(frozen=True)
class Algebra:
    """combine(w, value) on a cell; fold over a row; merge of two folds; assign(old, folded) on a vertex.

    ``identity`` stands for a row without contribution. ``monotone`` says that assign never takes a value back, so
    "no change" is a fixed point.
    """

    name: str
    dtype: str
    combine: Callable[[Column, Column], Column]
    fold: Callable[[Column], Column]
    merge: Callable[[Column, Column], Column]
    identity: object
    assign: Callable[[Column, Column], Column]
    monotone: bool = False

    def zero(self) -> Column:
        return F.lit(self.identity).cast(self.dtype)


def plus(a: Column, b: Column) -> Column:
    return a + b


def rank_algebra(damping: float, vertices: int) -> Algebra:
    """Damped ranks; the weight of a cell is the share of its source's rank."""
    base = (1.0 - damping) / vertices
    return Algebra("rank", "double", lambda w, v: w * v, F.sum, plus, 0.0, lambda old, acc: F.lit(base) + F.lit(damping) * acc)


def restart_algebra(restart: float, seeds: Column, share: float) -> Algebra:
    """Random walk that returns to the seeds: ``seeds`` is a condition over the column node."""
    back = F.when(seeds, F.lit(restart * share)).otherwise(F.lit(0.0))
    return Algebra("walk", "double", lambda w, v: w * v, F.sum, plus, 0.0, lambda old, acc: F.lit(1.0 - restart) * acc + back)


def distance_algebra() -> Algebra:
    return Algebra("distance", "double", lambda w, v: w + v, F.min, F.least, INF, F.least, monotone=True)


def hop_algebra() -> Algebra:
    return Algebra("hops", "double", lambda w, v: v + F.lit(1.0), F.min, F.least, INF, F.least, monotone=True)


def label_algebra(largest: bool = False) -> Algebra:
    """Spread of the smallest (largest) label; labels are longs."""
    if largest:
        return Algebra("max_label", "bigint", lambda w, v: v, F.max, F.greatest, -(1 << 63), F.greatest, monotone=True)
    return Algebra("min_label", "bigint", lambda w, v: v, F.min, F.least, (1 << 63) - 1, F.least, monotone=True)


def reach_algebra() -> Algebra:
    return Algebra("reach", "boolean", lambda w, v: v, F.bool_or, lambda a, b: a | b, False, lambda old, acc: old | acc, monotone=True)


def widest_algebra() -> Algebra:
    """Largest bottleneck of a path: the maximum over paths of the least weight."""
    return Algebra("widest", "double", F.least, F.max, F.greatest, -INF, F.greatest, monotone=True)


def count_algebra() -> Algebra:
    """Number of walks, exact in longs: repeated product with the adjacency matrix."""
    return Algebra("walks", "bigint", lambda w, v: v, F.sum, plus, 0, lambda old, acc: acc)


def product_algebra() -> Algebra:
    """The ordinary product."""
    return Algebra("product", "double", lambda w, v: w * v, F.sum, plus, 0.0, lambda old, acc: acc)

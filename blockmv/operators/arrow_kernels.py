"""The same product with Arrow kernels in Python workers: the second engine of the engine comparison.

Cells and vector meet in a cogroup on the block; each group is one block column (or row), whose size psi bounds.
Numeric algebras of the kinds sum, min and max over w*v, w+v or v.
"""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..functions.algebra import Algebra
from ..plans.blocks import BlockedGraph
from ..plans.session import Traffic, forget, loop_settings, reliable
from .loop import Result, Round

_COMBINE = {
    "times": lambda w, v: w * v,
    "plus": lambda w, v: w + v,
    "value": lambda w, v: v,
}
_FOLD = {"sum": (np.add, 0.0), "min": (np.minimum, np.inf), "max": (np.maximum, -np.inf)}


def _kernel(combine: str, fold: str, keys: list[str]):
    f, (ufunc, zero) = _COMBINE[combine], _FOLD[fold]

    def run(cells: pa.Table, vector: pa.Table) -> pa.Table:
        node = vector.column("node").to_numpy()
        order = np.argsort(node, kind="stable")
        node, val = node[order], vector.column("val").to_numpy()[order]
        src = cells.column("src").to_numpy()
        at = np.searchsorted(node, src)
        at_safe = np.minimum(at, max(len(node) - 1, 0))
        known = (at < len(node)) & (node[at_safe] == src) if len(node) else np.zeros(len(src), dtype=bool)
        dst = cells.column("dst").to_numpy()[known]
        x = f(cells.column("w").to_numpy()[known], val[at_safe[known]]) if known.any() else np.zeros(0)
        rows, back = np.unique(dst, return_inverse=True)
        acc = np.full(len(rows), zero)
        ufunc.at(acc, back, x)
        block = {k: cells.column(k).to_numpy()[known] for k in keys}
        first = np.zeros(len(rows), dtype=np.int64)
        first[back] = np.arange(len(back))
        return pa.table({**{k: block[k][first].astype(np.int32) for k in keys}, "dst": rows, "acc": acc})

    return run


def multiply_arrow(bg: BlockedGraph, state: DataFrame, algebra: Algebra, combine: str = "times", fold: str = "sum") -> DataFrame:
    """state (node, blk, heavy, val) -> node, blk, heavy, val; values are doubles."""
    v = state.select("blk", "node", F.col("val").cast("double").alias("val"))
    now, have = state.select("node", "blk", "heavy", "val"), []
    if bg.light is not None:
        part = bg.light.groupBy("cb").cogroup(v.groupBy("blk")).applyInArrow(_kernel(combine, fold, ["rb"]), "rb int, dst bigint, acc double")
        light = part.groupBy("dst").agg(algebra.fold(F.col("acc")).alias("light_acc")).withColumnRenamed("dst", "l_dst")
        now = now.join(light, now["node"] == light["l_dst"], "left")
        have.append("light_acc")
    if bg.heavy is not None:
        copies = state.filter("heavy").select("node", F.col("val").cast("double").alias("val"), F.explode(F.sequence(F.lit(0), F.lit(bg.b - 1))).alias("blk"))
        part = bg.heavy.groupBy("rb").cogroup(copies.groupBy("blk")).applyInArrow(_kernel(combine, fold, ["rb"]), "rb int, dst bigint, acc double")
        heavy = part.select(F.col("dst").alias("h_dst"), F.col("acc").alias("heavy_acc"))
        now = now.join(heavy, now["node"] == heavy["h_dst"], "left")
        have.append("heavy_acc")
    accs = [F.coalesce(F.col(c), algebra.zero()) for c in have] or [algebra.zero()]
    acc = accs[0] if len(accs) == 1 else algebra.merge(*accs)
    return now.select("node", "blk", "heavy", algebra.assign(F.col("val"), acc).cast("double").alias("val"))


def iterate_arrow(bg: BlockedGraph, start: DataFrame, algebra: Algebra, max_iter: int, combine: str = "times", fold: str = "sum") -> Result:
    """start (node, val) -> the state after ``max_iter`` products by Arrow kernels; one reliable checkpoint a round."""
    spark = start.sparkSession
    out = Result(start, "arrow", bg.b, bg.theta)
    with loop_settings(spark, bg.tasks):
        first = start.select(F.col("node").alias("s_node"), "val")
        now = bg.nodes.join(first, bg.nodes["node"] == first["s_node"], "left")
        now = reliable(now.select("node", "blk", "heavy", F.coalesce(F.col("val").cast("double"), algebra.zero()).alias("val")))
        traffic = Traffic(spark)
        for k in range(1, max_iter + 1):
            tick, seen = time.time(), Observation()
            made = multiply_arrow(bg, now, algebra, combine, fold).observe(seen, F.count(F.lit(1)).alias("n"))
            last, now = now, reliable(made)
            forget(last)
            out.history.append(Round(k, float("nan"), bg.light_nodes + bg.b * bg.heavy_nodes, seen.get["n"], 0, 0, time.time() - tick, traffic.taken()))
    out.state = now.select("node", "val")
    return out

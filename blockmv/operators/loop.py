"""Iteration to a fixed number of rounds or to convergence, with a ledger of the vector elements that moved."""

from __future__ import annotations

import math
import time
import uuid
from collections.abc import Callable
from contextlib import contextmanager
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..functions.algebra import Algebra
from ..functions.psi import Psi
from ..plans import cost
from ..plans.blocks import BlockedGraph, prepartition
from ..plans.session import Traffic, drop_folder, forget, held, loop_settings, reliable, shared_folder
from .multiply import multiply

#: Cells that a task goes through in one step, where it has several blocks.
CELLS_A_TASK = 500_000


@dataclass(frozen=True)
class Workers:
    """What the number of blocks follows from: workers, bytes of memory of one, and whether the engine holds the old
    and the new sub-vector at once."""

    number: int
    memory_bytes: int
    expansion: float = 2.0

    def blocks(self, vertices: int) -> int:
        return cost.block_count(vertices, self.number, max(1, self.memory_bytes // cost.ELEMENT_BYTES), self.expansion)

    def tasks(self, blocks: int, cells: int, cores: int) -> int:
        """Tasks that go through the blocks of a step: one for each block while there are no more than workers or cores, else
        as many as CELLS_A_TASK asks for. A task merges its blocks one after the other, so it needs no more memory."""
        return tasks_for(blocks, cells, max(self.number, cores))


def tasks_for(blocks: int, cells: int, cores: int) -> int:
    """One for each block, or as many as keep the cores busy and hold CELLS_A_TASK cells (or copies, where they are more)."""
    return min(blocks, max(cores, math.ceil(cells / CELLS_A_TASK)))


PLACEMENTS = ("horizontal", "vertical", "selected", "hybrid")


@dataclass(frozen=True)
class Round:
    """Vector elements of one iteration, counted while it ran. read: elements that tasks took in, each copy counted;
    written: elements of the new state; exchanged: partial results stored for other blocks and loaded there (for rivals
    whatever else moves); diagonal: partial results of own blocks, which stay where they are. moved_bytes: what Spark
    wrote for exchanges."""

    iteration: int
    delta: float
    read: int
    written: int
    exchanged: int
    diagonal: int
    seconds: float
    moved_bytes: int = 0

    @property
    def total(self) -> int:
        return self.read + self.written + self.exchanged


@dataclass
class Result:
    """state: node, val. status: done (rounds used up), converged, or o.o.t. (time budget)."""

    state: DataFrame
    placement: str
    b: int
    theta: int | None
    history: list[Round] = field(default_factory=list)
    status: str = "done"

    def history_frame(self) -> DataFrame:
        rows = [(r.iteration, r.delta, r.read, r.written, r.exchanged, r.diagonal, r.total, r.moved_bytes, r.seconds, self.status) for r in self.history]
        ddl = "iter int, delta double, read bigint, written bigint, exchanged bigint, diagonal bigint, total bigint, moved_bytes bigint, seconds double, status string"
        return self.state.sparkSession.createDataFrame(rows, ddl)


def select_placement(shape: cost.GraphShape, b: int, model: str = "published", in_degrees: list[tuple[int, float]] | None = None) -> str:
    """published: the density rule. degree_aware: against a vertical cost that knows the in-degrees."""
    if model == "published":
        return "horizontal" if cost.prefers_horizontal(shape, b) else "vertical"
    vertical = cost.cost_degree_aware(shape.vertices, b, in_degrees or [])
    return "horizontal" if cost.cost_horizontal(shape, b) < vertical else "vertical"


def threshold_for(placement: str, edges: DataFrame, vertices: DataFrame, b: int, theta: int | str | None, model: str) -> tuple[str, int | None]:
    """The placement after selection, and its degree threshold."""
    if placement == "selected":
        placement = select_placement(cost.shape_of(edges, vertices), b)
    if placement == "horizontal":
        return placement, 0
    if placement == "vertical":
        return placement, None
    if placement != "hybrid":
        raise ValueError(f"unknown placement: {placement}; one of {', '.join(PLACEMENTS)}")
    return placement, cost.choose_threshold(edges, vertices, b, model)[0] if theta == "auto" else theta


def _account(bg: BlockedGraph, made, written: int, copy: str, k: int, delta: float, seconds: float, moved: int) -> Round:
    """A broadcast element is read by the tasks of all row blocks; other copies were counted one by one."""
    partials = made.partials.get if made.partials else {}
    copied = sum(seen.get.get("copies") or 0 for seen in made.copies)
    off, all_ = partials.get("off_block") or 0, partials.get("all") or 0
    read = bg.light_nodes + (bg.b * copied if copy == "broadcast" else copied)
    return Round(k, delta, read, written, 2 * off, all_ - off, seconds, moved)


def iterate(
    bg: BlockedGraph,
    start: DataFrame,
    algebra: Algebra,
    max_iter: int,
    tol: float | None = None,
    norm: str = "max",
    copy: str = "replicate",
    state: str = "memory",
    path: str | None = None,
    budget_seconds: float | None = None,
    shared: Callable[[DataFrame, int], Algebra] | None = None,
) -> Result:
    """start (node, val) -> the state after the last round.

    state='memory' keeps the vector's partitioning through a reliable checkpoint of each round; state='storage' writes
    it as Parquet, one folder per round, from which ``resume`` can go on. tol: stop when the change (``max`` or ``sum``
    of absolute differences; for other than numbers, the count of changed vertices) is at most tol. ``shared`` may make
    the algebra of a round from the state ahead of it, so numbers of the whole vector (dangling rank, its length) can
    enter each product while blocks and vector stay where they are.
    """
    spark = start.sparkSession
    folder = path or f"{shared_folder(spark)}/vector-{uuid.uuid4().hex}"
    out = Result(start, "", bg.b, bg.theta)
    began = time.time()
    numeric = algebra.dtype != "boolean"
    with loop_settings(spark, bg.tasks):
        # nodes come from the cache with their partitioning; only the start values move
        first = start.select(F.col("node").alias("s_node"), "val").repartitionById(bg.tasks, _block(bg, "s_node"))
        nodes = bg.nodes
        now = nodes.join(first.withColumn("s_blk", _block(bg, "s_node")).hint("merge"), (nodes["blk"] == F.col("s_blk")) & (nodes["node"] == F.col("s_node")), "left")
        now = now.select("node", "blk", "heavy", F.coalesce(F.col("val").cast(algebra.dtype), algebra.zero()).alias("val"))
        now = _kept(now, bg, state, folder, 0)
        traffic = Traffic(spark)
        for k in range(1, max_iter + 1):
            tick = time.time()
            made = multiply(bg, now, shared(now, k) if shared else algebra, copy)
            count = Observation()
            last, now = now, _kept(made.state.observe(count, F.count(F.lit(1)).alias("n")), bg, state, folder, k)
            forget(last)
            if state == "storage" and path is None and k > 1:
                drop_folder(spark, f"{folder}/round={k - 2:05d}")  # nobody knows the folder, so nobody resumes from it
            delta = _change(now, numeric, norm) if tol is not None else float("nan")
            out.history.append(_account(bg, made, count.get["n"], copy, k, delta, time.time() - tick, traffic.taken()))
            if tol is not None and delta <= tol:
                out.status = "converged"
                break
            if budget_seconds is not None and time.time() - began > budget_seconds:
                out.status = "o.o.t."
                break
    out.state = now.select("node", "val")
    return out


def _block(bg: BlockedGraph, name: str) -> Column:
    return bg.psi(F.col(name), bg.b)


def _kept(df: DataFrame, bg: BlockedGraph, state: str, folder: str, k: int) -> DataFrame:
    if state == "memory":
        return reliable(df)
    if state != "storage":
        raise ValueError(f"unknown state store: {state}")
    df.write.mode("overwrite").parquet(f"{folder}/round={k:05d}")
    return stored_round(df.sparkSession, bg, folder, k)


def stored_round(spark: SparkSession, bg: BlockedGraph, folder: str, k: int) -> DataFrame:
    """A stored vector, next to its blocks again: the vector moves, cells do not."""
    back = spark.read.parquet(f"{folder}/round={k:05d}")
    return back.repartitionById(bg.tasks, "blk").sortWithinPartitions("blk", "node")


def resume(bg: BlockedGraph, spark: SparkSession, folder: str, k: int, algebra: Algebra, max_iter: int, **how) -> Result:
    """Go on from the stored round k, in a new folder."""
    return iterate(bg, stored_round(spark, bg, folder, k).select("node", "val"), algebra, max_iter, **how)


def _change(now: DataFrame, numeric: bool, norm: str) -> float:
    changed = ~F.col("val").eqNullSafe(F.col("prev"))
    if not numeric:
        how = F.count_if(changed)
    else:
        gap = F.when(changed, F.abs(F.col("val").cast("double") - F.col("prev").cast("double"))).otherwise(F.lit(0.0))
        how = F.max(gap) if norm == "max" else F.sum(gap)
    got = now.agg(how).first()[0]
    return float(got or 0)


@contextmanager
def laid_out(edges: DataFrame, vertices: DataFrame, placement: str = "hybrid", b: int | Workers = 4, psi: str | Psi = "hash", theta: int | str | None = "auto", model: str = "row_conditional", tasks: int | None = None):
    """The blocks of a graph for as long as they are needed: (blocks, placement after selection, threshold).

    The edges are read from their source once and held on executors' disks until they are laid out. b: a number, or the
    workers and their memory, from which the number of blocks follows. tasks: see ``prepartition``.
    """
    with held(edges, vertices):
        workers = b if isinstance(b, Workers) else None
        b = workers.blocks(vertices.count()) if workers else b
        chosen, t = threshold_for(placement, edges, vertices, b, theta, model)
        tasks = workers.tasks(b, edges.count(), edges.sparkSession.sparkContext.defaultParallelism) if workers and b > workers.number else tasks
        bg = prepartition(edges, vertices, b, psi, t, tasks=tasks)
        if workers:
            bg.hashed = 0
            bg.hashed = max(0, workers.memory_bytes // cost.ELEMENT_BYTES - bg.held_elements())
    try:
        yield bg, chosen, t
    finally:
        bg.release()


def run(
    edges: DataFrame,
    vertices: DataFrame,
    start: DataFrame,
    algebra: Algebra,
    placement: str = "hybrid",
    b: int | Workers = 4,
    psi: str | Psi = "hash",
    theta: int | str | None = "auto",
    model: str = "row_conditional",
    max_iter: int = 8,
    **how,
) -> Result:
    """Partition once, then iterate. See ``iterate`` for the other settings."""
    with laid_out(edges, vertices, placement, b, psi, theta, model) as (bg, chosen, t):
        out = iterate(bg, start, algebra, max_iter, **how)
    out.placement, out.theta = chosen, t
    return out

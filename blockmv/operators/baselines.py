"""The rivals' ways to the same product, with the same algebra and result, and what each of them moves or must hold.

They are readings of why such systems stop: moving the whole matrix each round, or needing it in memory. Elements are
counted while a round runs, as in the block methods: whatever is sent is stored once and loaded once.
"""

from __future__ import annotations

import time
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..functions.algebra import Algebra
from ..functions.psi import Psi, named
from ..plans.cost import CELL_BYTES, ELEMENT_BYTES
from ..plans.session import Traffic, drop_folder, forget, loop_settings, reliable, shared_folder
from .loop import Result, Round

def _finish(state: DataFrame, acc: DataFrame, algebra: Algebra) -> DataFrame:
    a = acc.select(F.col("dst").alias("a_dst"), "acc")
    met = state.join(a.hint("merge"), state["node"] == a["a_dst"], "left")
    return met.select("node", algebra.assign(F.col("val"), F.coalesce("acc", algebra.zero())).cast(algebra.dtype).alias("val"))


def _counted(df: DataFrame, *more) -> tuple[DataFrame, Observation]:
    seen = Observation()
    return df.observe(seen, F.count(F.lit(1)).alias("n"), *more), seen


def reshuffle(
    edges: DataFrame,
    start: DataFrame,
    algebra: Algebra,
    iters: int = 8,
    partitions: int = 4,
    budget_seconds: float | None = None,
    budget_bytes: int | None = None,
    psi: str | Psi = "hash",
) -> Result:
    """Disk-based product: each round reads the edges from storage and shuffles them and the vector again. A task holds
    the values of one vertex at a time, so memory does not stop it."""
    spark = start.sparkSession
    folder, f = f"{shared_folder(spark)}/reshuffle-{uuid.uuid4().hex}", named(psi)
    edges.select("src", "dst", "w").write.parquet(f"{folder}/edges")
    began, out = time.time(), Result(start, "reshuffle", partitions, None)
    state = start
    with loop_settings(spark, partitions):
        traffic = Traffic(spark)
        for k in range(1, iters + 1):
            tick = time.time()
            cells, read = _counted(spark.read.parquet(f"{folder}/edges"))
            cells = cells.withColumn("cb", f(F.col("src"), partitions)).repartitionById(partitions, "cb")
            old, sent = _counted(state)
            v = old.select(F.col("node"), "val", f(F.col("node"), partitions).alias("blk")).repartitionById(partitions, "blk")
            met = cells.join(v.hint("merge"), (cells["cb"] == v["blk"]) & (cells["src"] == v["node"]))
            part = met.groupBy("cb", "dst").agg(algebra.fold(algebra.combine(F.col("w"), F.col("val"))).alias("acc"))
            part, partials = _counted(part, F.count_if(F.col("cb") != f(F.col("dst"), partitions)).alias("off"))
            acc = part.groupBy("dst").agg(algebra.fold(F.col("acc")).alias("acc"))
            _finish(state, acc, algebra).write.parquet(f"{folder}/round={k:05d}")
            if k > 1:
                drop_folder(spark, f"{folder}/round={k - 1:05d}")
            state = spark.read.parquet(f"{folder}/round={k:05d}")
            m, n, off = read.get["n"], sent.get["n"], partials.get["off"] or 0
            out.history.append(Round(k, float("nan"), m + n, n, 2 * (m + n + off), (partials.get["n"] or 0) - off, time.time() - tick, traffic.taken()))
            if budget_seconds is not None and time.time() - began > budget_seconds:
                out.status = "o.o.t."
                break
    drop_folder(spark, f"{folder}/edges")
    out.state = state
    return out


@contextmanager
def _kept(df: DataFrame, level: StorageLevel) -> Iterator[DataFrame]:
    held = df.persist(level)
    try:
        yield held
    finally:
        held.unpersist()


def vertex_cut(
    edges: DataFrame,
    start: DataFrame,
    algebra: Algebra,
    iters: int = 8,
    grid: int = 2,
    storage: str = "MEMORY_AND_DISK",
    budget_bytes: int | None = None,
    psi: str | Psi = "hash",
) -> Result:
    """Edges dealt over grid x grid parts by both ends; a vertex is mirrored in each part that has an edge of it.

    Each round sends a value to every mirror of a source and brings a partial result back from every mirror of a
    destination. With a memory-only store, edges and mirrors of a part must fit: ``o.o.m.`` if not.
    """
    spark, f = start.sparkSession, named(psi)
    parts = grid * grid
    part = f(F.col("src"), grid) * grid + f(F.col("dst"), grid)
    out = Result(start, "vertex_cut", parts, None)
    level = getattr(StorageLevel, storage)
    with loop_settings(spark, parts):
        dealt = edges.select("src", "dst", "w", part.cast("int").alias("part")).repartitionById(parts, "part").sortWithinPartitions("part", "src")
        with _kept(dealt, level) as cells, _kept(cells.select("part", "src").distinct(), level) as mirrors:
            if storage.startswith("MEMORY_ONLY") and budget_bytes is not None and vertex_cut_bytes(cells) > budget_bytes:
                out.status = "o.o.m."
                return out
            state, traffic = start, Traffic(spark)
            for k in range(1, iters + 1):
                tick = time.time()
                old, read = _counted(state)
                sent = mirrors.join(old.hint("merge"), mirrors["src"] == old["node"]).select("part", "src", "val")
                sent, copies = _counted(sent)
                s = sent.repartitionById(parts, "part").select(F.col("part").alias("s_part"), F.col("src").alias("s_src"), "val")
                met = cells.join(s.hint("merge"), (cells["part"] == s["s_part"]) & (cells["src"] == s["s_src"]))
                local = met.groupBy("part", "dst").agg(algebra.fold(algebra.combine(F.col("w"), F.col("val"))).alias("acc"))
                local, back = _counted(local)
                acc = local.groupBy("dst").agg(algebra.fold(F.col("acc")).alias("acc"))
                last, state = state, reliable(_finish(state, acc, algebra))
                if last is not start:
                    forget(last)
                n = read.get["n"]
                out.history.append(Round(k, float("nan"), n, n, 2 * ((copies.get["n"] or 0) + (back.get["n"] or 0)), 0, time.time() - tick, traffic.taken()))
    out.state = state
    return out


def vertex_cut_bytes(cells: DataFrame) -> int:
    """Of the largest part: its cells and the mirrors of their ends. cells: part, src, dst."""
    sizes = cells.groupBy("part").agg((F.count("*") * CELL_BYTES + (F.count_distinct("src") + F.count_distinct("dst")) * ELEMENT_BYTES).alias("held"))
    return sizes.agg(F.max("held")).first()[0] or 0


def replication(edges: DataFrame, grid: int = 2) -> DataFrame:
    """parts, mirrors, vertices, factor: how many copies of a vertex a vertex-cut keeps on average (psi: mod)."""
    part = F.pmod(F.col("src"), F.lit(grid)) * grid + F.pmod(F.col("dst"), F.lit(grid))
    ends = edges.select(part.alias("part"), F.explode(F.array("src", "dst")).alias("node")).groupBy("node").agg(F.count_distinct("part").alias("k"))
    return ends.agg(
        F.lit(grid * grid).alias("parts"), F.sum("k").alias("mirrors"), F.count("*").alias("vertices"), (F.sum("k") / F.count("*")).alias("factor")
    )


def vertex_centric(
    edges: DataFrame, start: DataFrame, algebra: Algebra, iters: int = 8, parts: int = 4, budget_bytes: int | None = None, psi: str | Psi = "hash"
) -> Result:
    """Message passing: a vertex holds all its out-edges and sends along them; messages to one vertex are combined in the
    worker before they leave it. Vertices, their edges and the combined messages must fit: ``o.o.m.`` if not."""
    spark, f = start.sparkSession, named(psi)
    out = Result(start, "vertex_centric", parts, None)
    with loop_settings(spark, parts):
        held_edges = edges.groupBy(F.col("src").alias("v")).agg(F.collect_list(F.struct("dst", "w")).alias("out")).withColumn("part", f(F.col("v"), parts))
        with _kept(held_edges.repartitionById(parts, "part"), StorageLevel.MEMORY_AND_DISK) as held:
            if budget_bytes is not None and vertex_centric_bytes(held, start, f, parts) > budget_bytes:
                out.status = "o.o.m."
                return out
            state, traffic = start, Traffic(spark)
            for k in range(1, iters + 1):
                tick = time.time()
                old, read = _counted(state)
                s = old.select(F.col("node"), "val", f(F.col("node"), parts).alias("blk")).repartitionById(parts, "blk")
                met = held.join(s.hint("merge"), (held["part"] == s["blk"]) & (held["v"] == s["node"]))
                messages = met.select("part", F.explode("out").alias("e"), "val").select("part", "e.dst", algebra.combine(F.col("e.w"), F.col("val")).alias("x"))
                combined = messages.groupBy("part", "dst").agg(algebra.fold(F.col("x")).alias("x"))
                combined, sent = _counted(combined, F.count_if(F.col("part") != f(F.col("dst"), parts)).alias("off"))
                acc = combined.groupBy("dst").agg(algebra.fold(F.col("x")).alias("acc"))
                last, state = state, reliable(_finish(state, acc, algebra))
                if last is not start:
                    forget(last)
                n, off = read.get["n"], sent.get["off"] or 0
                out.history.append(Round(k, float("nan"), n, n, 2 * off, (sent.get["n"] or 0) - off, time.time() - tick, traffic.taken()))
    out.state = state
    return out


def vertex_centric_bytes(held: DataFrame, vertices: DataFrame, f: Psi, parts: int) -> int:
    """Of the largest worker: its vertices, their out-edges, and one combined message per vertex it sends to."""
    own = vertices.groupBy(f(F.col("node"), parts).alias("p")).agg((F.count("*") * 2 * ELEMENT_BYTES).alias("x"))
    edges = held.groupBy(F.col("part").alias("p")).agg((F.sum(F.size("out")) * CELL_BYTES).alias("x"))
    sent = held.select("part", F.explode("out.dst").alias("dst")).distinct().groupBy(F.col("part").alias("p")).agg((F.count("*") * ELEMENT_BYTES).alias("x"))
    return own.union(edges).union(sent).groupBy("p").agg(F.sum("x").alias("x")).agg(F.max("x")).first()[0] or 0


def compare_states(a: DataFrame, b: DataFrame) -> float:
    """Largest absolute difference of two states; infinity if a vertex is missing on one side."""
    x, y = a.select("node", F.col("val").cast("double").alias("x")), b.select(F.col("node").alias("n2"), F.col("val").cast("double").alias("y"))
    gap = F.when(F.col("x").isNull() | F.col("y").isNull(), F.lit(float("inf"))).when(F.col("x") == F.col("y"), 0.0).otherwise(F.abs(F.col("x") - F.col("y")))
    return float(x.join(y, x["node"] == y["n2"], "full_outer").agg(F.max(gap)).first()[0] or 0.0)


def max_processed(results: dict[str, dict[int, str]]) -> dict[str, int]:
    """method -> largest edge count with status done or converged. results: method -> edge count -> status."""
    return {m: max((n for n, s in by.items() if s in ("done", "converged")), default=0) for m, by in results.items()}

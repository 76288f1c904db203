"""One generalised product of the blocked matrix with the state, in any placement.

There is one code path: light cells vertically, heavy cells horizontally, one assign. theta = None leaves the vertical
placement alone, theta = 0 the horizontal one. Joins of cells with the vector are on block and vertex, both sides
partitioned by the block, so cells stay where they are.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from ..functions.algebra import Algebra
from ..plans.blocks import BlockedGraph

#: Heavy vertices up to which ``copy='broadcast'`` is allowed: about 100 MB of (id, value) pairs.
MAX_BROADCAST = 4_000_000


@dataclass
class Product:
    """The next state (node, blk, heavy, val, prev), not yet run, and what will tell the counts of partial results
    and of copies."""

    state: DataFrame
    partials: Observation | None
    copies: list[Observation]


def reference(edges: DataFrame, state: DataFrame, algebra: Algebra) -> DataFrame:
    """The product without any partitioning: edges (src, dst, w), state (node, val) -> node, val."""
    acc = (
        edges.join(state, edges["src"] == state["node"])
        .groupBy("dst")
        .agg(algebra.fold(algebra.combine(F.col("w"), F.col("val"))).alias("acc"))
    )
    joined = state.join(acc, state["node"] == acc["dst"], "left")
    return joined.select("node", algebra.assign(F.col("val"), F.coalesce("acc", algebra.zero())).cast(algebra.dtype).alias("val"))


def _way(bg: BlockedGraph, elements: float) -> str:
    """How a task meets so many vector elements a block: psi bounds them, so a hash table is the rule, over all blocks of
    the task. A merge goes block by block."""
    return "shuffle_hash" if elements * bg.blocks_a_task <= bg.hashed else "merge"


def _folded(cells: DataFrame, vector: DataFrame, on: Column, keys: list[str], algebra: Algebra, way: str) -> DataFrame:
    met = cells.join(vector.hint(way), on)
    return met.groupBy(*keys).agg(algebra.fold(algebra.combine(F.col("w"), F.col("val"))).alias("acc"))


def block_partials(bg: BlockedGraph, state: DataFrame, algebra: Algebra) -> DataFrame:
    """cb, rb, dst, acc: the partial result of each block of light cells. No exchange: cells and vector lie together."""
    v = state.select("blk", "node", "val")
    on = (bg.light["cb"] == v["blk"]) & (bg.light["src"] == v["node"])
    return _folded(bg.light, v, on, ["cb", "rb", "dst"], algebra, _way(bg, bg.vertices / bg.b))


def light_rows(bg: BlockedGraph, state: DataFrame, algebra: Algebra) -> tuple[DataFrame, Observation]:
    """Vertical: partials, one exchange to the row blocks, fold. Own blocks' partials are counted apart."""
    seen = Observation()
    off = F.count_if(F.col("cb") != F.col("rb"))
    partials = block_partials(bg, state, algebra).observe(seen, off.alias("off_block"), F.count(F.lit(1)).alias("all"))
    moved = partials.select("rb", "dst", "acc").repartitionById(bg.tasks, "rb")
    return moved.groupBy("rb", "dst").agg(algebra.fold(F.col("acc")).alias("light_acc")), seen


def heavy_rows(bg: BlockedGraph, state: DataFrame, algebra: Algebra, copy: str = "replicate", chunks: int = 4) -> tuple[DataFrame, list[Observation]]:
    """Horizontal: the vector's heavy part goes to every row block; results never leave their task.

    copy: replicate (an exchange of b copies), broadcast (one copy per executor; refused beyond MAX_BROADCAST), needed
    (an element goes to those row blocks that have a cell of it, by a static routing table), chunked (replicate, or
    needed where that is less, but the sub-vectors of ``chunks`` groups of column blocks come one after the other, so a
    task holds a share of the vector at a time).
    """
    if copy == "chunked":
        return _chunked(bg, state, algebra, min(chunks, bg.b))
    seen = Observation()
    v = state.filter("heavy").select("node", "val")
    cells = bg.heavy
    if copy == "broadcast":
        if bg.heavy_nodes > MAX_BROADCAST:
            raise ValueError(f"{bg.heavy_nodes} heavy vertices are too many to broadcast; use copy='replicate'")
        met = cells.join(F.broadcast(v.observe(seen, F.count(F.lit(1)).alias("copies"))), cells["src"] == v["node"])
        return met.groupBy("rb", "dst").agg(algebra.fold(algebra.combine(F.col("w"), F.col("val"))).alias("heavy_acc")), [seen]
    if copy == "needed":
        routes = bg.heavy_routes()
        copies = state.filter("heavy").join(routes.hint("merge"), (state["blk"] == routes["r_blk"]) & (state["node"] == routes["r_src"])).select("node", "val", "to")
    elif copy == "replicate":
        copies = v.withColumn("to", F.explode(F.sequence(F.lit(0), F.lit(bg.b - 1))))
    else:
        raise ValueError(f"unknown way to copy: {copy}")
    copies = copies.observe(seen, F.count(F.lit(1)).alias("copies")).repartitionById(bg.tasks, "to")
    on = (cells["rb"] == copies["to"]) & (cells["src"] == copies["node"])
    return _folded(cells, copies, on, ["rb", "dst"], algebra, _way(bg, bg.heavy_nodes)).withColumnRenamed("acc", "heavy_acc"), [seen]


def _chunked(bg: BlockedGraph, state: DataFrame, algebra: Algebra, chunks: int) -> tuple[DataFrame, list[Observation]]:
    """Row blocks take the sub-vectors chunk by chunk; each chunk's fold is merged into what the task has so far. With so
    many blocks that copies for all of them outnumber a routing table and its copies (at most a row per cell each), an
    element goes only where a cell waits for it. Each chunk joins its own share of vector and table."""
    all_ = state.filter("heavy").select("node", "blk", "val")
    routed = bg.b * bg.heavy_nodes > 2 * bg.heavy_cells
    routes = bg.heavy_routes() if routed else None
    seen, out = [], None
    for k in range(chunks):
        part = all_.filter(F.col("blk") % chunks == k)
        if routed:
            some = routes.filter(F.col("r_blk") % chunks == k)
            part = part.join(some.hint("merge"), (part["blk"] == some["r_blk"]) & (part["node"] == some["r_src"])).select("node", "val", "to")
        else:
            part = part.select("node", "val", F.explode(F.sequence(F.lit(0), F.lit(bg.b - 1))).alias("to"))
        seen.append(Observation())
        part = part.observe(seen[-1], F.count(F.lit(1)).alias("copies")).repartitionById(bg.tasks, "to")
        cells = bg.heavy.filter(F.col("cb") % chunks == k)
        on = (cells["rb"] == part["to"]) & (cells["src"] == part["node"])
        acc = _folded(cells, part, on, ["rb", "dst"], algebra, _way(bg, bg.heavy_nodes / chunks))
        if out is None:
            out = acc.withColumnRenamed("acc", "heavy_acc")
            continue
        more = acc.select(F.col("rb").alias("m_rb"), F.col("dst").alias("m_dst"), "acc")
        met = out.join(more.hint("merge"), (out["rb"] == more["m_rb"]) & (out["dst"] == more["m_dst"]), "full_outer")
        both = algebra.merge(F.coalesce("heavy_acc", algebra.zero()), F.coalesce("acc", algebra.zero()))
        out = met.select(F.coalesce("rb", "m_rb").alias("rb"), F.coalesce("dst", "m_dst").alias("dst"), both.alias("heavy_acc"))
    return out, seen


def multiply(bg: BlockedGraph, state: DataFrame, algebra: Algebra, copy: str = "replicate") -> Product:
    """state (node, blk, heavy, val), partitioned by blk -> the next one. Every vertex is assigned, with or without
    in-edges. Two left joins bring the accumulators together: a union would add an exchange."""
    old = state.select("node", "blk", "heavy", "val")
    now, seen, copied, have = old, None, [], []
    way = _way(bg, bg.vertices / bg.b)
    if bg.light is not None:
        light, seen = light_rows(bg, old, algebra)
        l = light.select(F.col("rb").alias("l_rb"), F.col("dst").alias("l_dst"), "light_acc")  # noqa: E741
        now = now.join(l.hint(way), (now["blk"] == l["l_rb"]) & (now["node"] == l["l_dst"]), "left")
        have.append("light_acc")
    if bg.heavy is not None:
        heavy, copied = heavy_rows(bg, old, algebra, copy)
        h = heavy.select(F.col("rb").alias("h_rb"), F.col("dst").alias("h_dst"), "heavy_acc")
        now = now.join(h.hint(way), (now["blk"] == h["h_rb"]) & (now["node"] == h["h_dst"]), "left")
        have.append("heavy_acc")
    accs = [F.coalesce(F.col(c), algebra.zero()) for c in have] or [algebra.zero()]
    acc = accs[0] if len(accs) == 1 else algebra.merge(*accs)
    value = algebra.assign(F.col("val"), acc).cast(algebra.dtype)
    return Product(now.select("node", "blk", "heavy", value.alias("val"), F.col("val").alias("prev")), seen, copied)

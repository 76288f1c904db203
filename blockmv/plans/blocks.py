"""The matrix cut once into b x b blocks, and kept where it is used.

Light cells (source out-degree below theta) lie by column block next to their sub-vector; heavy cells lie by row block
next to their result. theta = 0 makes every cell heavy (the horizontal placement), theta = None none (the vertical one).
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.psi import Psi, named
from .session import loop_settings


#: Heavy vertices (8 bytes each) that are broadcast while cells are laid out.
MAX_BROADCAST = 4_000_000
#: Vector elements of a task up to which they are hashed.
MAX_HASHED = 4_000_000


@dataclass
class BlockedGraph:
    """light: cells by column block; heavy: cells by row block; nodes: node, blk, heavy. Any frame may be empty."""

    b: int
    theta: int | None
    psi: Psi
    nodes: DataFrame
    light: DataFrame | None
    heavy: DataFrame | None
    light_nodes: int
    heavy_nodes: int
    light_cells: int = 0
    heavy_cells: int = 0
    #: Vector elements that a task may hash; beyond, cells and vector are merged, which spills.
    hashed: int = MAX_HASHED
    held: list[DataFrame] = field(default_factory=list)
    #: Partitions of every frame: block k lies in partition k mod tasks, sorted by block, so a task goes through its blocks
    #: one after the other. 0: one for each block.
    tasks: int = 0
    _routes: DataFrame | None = None

    def heavy_routes(self) -> DataFrame:
        """r_src, r_blk, to: the row blocks that have a cell of a heavy vertex; made once, without an exchange to find them
        and with one to the vertices' own blocks, where a join with the vector moves neither."""
        if self._routes is None:
            made = self.heavy.groupBy("rb", "src").agg(F.first("cb").alias("r_blk")).select(F.col("src").alias("r_src"), "r_blk", F.col("rb").alias("to"))
            made = made.repartitionById(self.tasks, "r_blk").sortWithinPartitions("r_blk", "r_src")
            self._routes = made.persist(StorageLevel.MEMORY_AND_DISK)
            self.held.append(self._routes)
        return self._routes

    def __post_init__(self) -> None:
        self.tasks = self.tasks or self.b

    @property
    def blocks_a_task(self) -> int:
        return -(-self.b // self.tasks)

    @property
    def vertices(self) -> int:
        return self.light_nodes + self.heavy_nodes

    def held_elements(self) -> int:
        """Vector elements of the largest task, as they lie: the old and the new sub-vector, and the copies of heavy
        vertices where they are hashed."""
        block = self.nodes.groupBy("blk").count().agg(F.max("count")).first()[0] or 0
        return 2 * block + (self.heavy_nodes if self.heavy is not None and self.heavy_nodes <= self.hashed else 0)

    def release(self) -> None:
        for df in self.held:
            df.unpersist()


def with_blocks(edges: DataFrame, b: int, psi: str | Psi = "hash") -> DataFrame:
    f = named(psi)
    return edges.withColumn("cb", f(F.col("src"), b)).withColumn("rb", f(F.col("dst"), b))


def out_degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("src").alias("node")).agg(F.count("*").alias("deg"))


def prepartition(
    edges: DataFrame,
    vertices: DataFrame,
    b: int,
    psi: str | Psi = "hash",
    theta: int | None = None,
    level: StorageLevel = StorageLevel.MEMORY_AND_DISK,
    tasks: int | None = None,
) -> BlockedGraph:
    """edges (src, dst, w), vertices (node) -> blocks, laid out when this returns. The only time that cells are shuffled.

    Each cell goes to exactly one of the two layouts, sorted by block and source, so the join of an iteration reads it
    in order. Cells that know their blocks (cb, rb: see ``with_blocks``) keep them. The frames are persisted; a lost executor
    recomputes its blocks from the source. ``tasks``: partitions that the blocks are dealt over, by default one for each
    block. Up to MAX_BROADCAST heavy vertices are broadcast to tell the cells apart; with more, cells are joined with the
    degrees, one more shuffle.
    """
    f = named(psi)
    spark = edges.sparkSession
    tasks = min(b, tasks or b)
    with loop_settings(spark, tasks):
        cells = edges if {"cb", "rb"} <= set(edges.columns) else with_blocks(edges.select("src", "dst", "w"), b, f)
        nodes = vertices.select("node").withColumn("blk", f(F.col("node"), b))
        if theta is None or theta <= 0:
            nodes = nodes.withColumn("heavy", F.lit(theta is not None))
            parts = {"light": cells if theta is None else None, "heavy": None if theta is None else cells}
        else:
            large = out_degrees(edges).filter(F.col("deg") >= theta).select(F.col("node").alias("large")).persist(level)
            known = F.broadcast(large) if large.count() <= MAX_BROADCAST else large
            parts = {k: cells.join(known, cells["src"] == known["large"], f"left_{how}") for k, how in (("light", "anti"), ("heavy", "semi"))}
            nodes = nodes.join(known, nodes["node"] == known["large"], "left").withColumn("heavy", F.col("large").isNotNull())
        nodes = nodes.select("node", "blk", "heavy").repartitionById(tasks, "blk").sortWithinPartitions("blk", "node").persist(level)
        counts = {r["heavy"]: r["count"] for r in nodes.groupBy("heavy").count().collect()}
        held, made, cells_of = [nodes], {}, {"light": 0, "heavy": 0}
        for k, by in (("light", "cb"), ("heavy", "rb")):
            made[k] = None
            if parts[k] is not None and not (k == "heavy" and theta and not counts.get(True)):
                made[k] = parts[k].select("src", "dst", "w", "cb", "rb").repartitionById(tasks, by).sortWithinPartitions(by, "src").persist(level)
                held.append(made[k])
                cells_of[k] = made[k].count()
        if theta is not None and theta > 0:
            large.unpersist()
    return BlockedGraph(b, theta, f, nodes, made["light"], made["heavy"], counts.get(False, 0), counts.get(True, 0), *cells_of.values(), held=held, tasks=tasks)


def block_statistics(edges: DataFrame, b: int, psi: str | Psi = "hash", theta: int | None = None) -> DataFrame:
    """rb, cb, edges, rows (distinct destinations), light, heavy per block: what a skewed psi or hub looks like."""
    deg = out_degrees(edges)
    cells = with_blocks(edges, b, psi).join(deg, F.col("src") == F.col("node"))
    heavy = F.lit(False) if theta is None else F.col("deg") >= theta
    per_row = cells.groupBy("rb", "cb", "dst").agg(F.count("*").alias("n"), F.count_if(heavy).alias("h"))
    return per_row.groupBy("rb", "cb").agg(
        F.sum("n").alias("edges"), F.count("*").alias("rows"), F.sum(F.col("n") - F.col("h")).alias("light"), F.sum("h").alias("heavy")
    )


# ---- blocks that outlive a session ----------------------------------------------------------------------------------


def save_blocks(edges: DataFrame, table: str, b: int, by: str = "src") -> None:
    """Cells as a table bucketed by source (vertical) or destination (horizontal): psi is Spark's own hash, so later
    sessions join a vector hash-partitioned into b parts without moving a cell."""
    rows = edges.select("src", "dst", "w").repartition(b, by)
    rows.write.bucketBy(b, by).sortBy("src").mode("overwrite").saveAsTable(table)


def multiply_saved(table: str, state: DataFrame, b: int, algebra) -> DataFrame:
    """One vertical product with a table of ``save_blocks(by='src')``: state (node, val) -> node, val."""
    spark = state.sparkSession
    cells = spark.table(table)
    v = state.repartition(b, "node").hint("merge")
    part = cells.join(v, cells["src"] == v["node"]).groupBy("dst").agg(algebra.fold(algebra.combine(F.col("w"), F.col("val"))).alias("acc"))
    old = state.select(F.col("node"), F.col("val"))
    joined = old.join(part, old["node"] == part["dst"], "left")
    return joined.select("node", algebra.assign(F.col("val"), F.coalesce("acc", algebra.zero())).alias("val"))

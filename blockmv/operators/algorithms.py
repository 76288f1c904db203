"""Graph analyses as repeated generalised products. edges (src, dst, w), vertices (node)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import algebra as A
from ..plans.cost import degrees
from ..plans.session import held, loop_settings
from .loop import Result, iterate, laid_out, run


def stochastic(edges: DataFrame, weighted: bool = False) -> DataFrame:
    """Weights by source: equal shares, or in proportion to w."""
    total = F.sum("w") if weighted else F.count("*")
    sums = edges.groupBy(F.col("src").alias("s")).agg(total.cast("double").alias("t"))
    share = (F.col("w") if weighted else F.lit(1.0)) / F.col("t")
    return edges.join(sums, F.col("src") == F.col("s")).select("src", "dst", share.alias("w"))


def pagerank(edges: DataFrame, vertices: DataFrame, damping: float = 0.85, iters: int = 8, dangling: str = "leak", weighted: bool = False, **how) -> Result:
    """Damped ranks from 1/n. dangling='uniform' spreads the rank of vertices without out-edges over all vertices: their
    mass is a single number, which enters the base of the next round."""
    if dangling not in ("leak", "uniform"):
        raise ValueError(f"unknown treatment of dangling vertices: {dangling}")
    with held(edges, vertices):
        n = vertices.count()
        if dangling == "uniform":
            return _uniform(stochastic(edges, weighted), vertices, damping, n, iters, **how)
        start = vertices.select("node", F.lit(1.0 / max(n, 1)).alias("val"))
        return run(stochastic(edges, weighted), vertices, start, A.rank_algebra(damping, max(n, 1)), max_iter=iters, **how)


def _uniform(cells: DataFrame, vertices: DataFrame, damping: float, n: int, iters: int, **how) -> Result:
    layout = {k: how.pop(k) for k in ("placement", "b", "psi", "theta", "model") if k in how}
    start = vertices.select("node", F.lit(1.0 / max(n, 1)).alias("val"))
    with laid_out(cells, vertices, **layout) as (bg, placement, theta):
        with loop_settings(cells.sparkSession, bg.tasks):
            # out of which vertices an edge goes, next to the vector: a join of the two moves neither
            f = bg.psi
            sources = cells.select(F.col("src").alias("s_node")).distinct().withColumn("s_blk", f(F.col("s_node"), bg.b))
            sources = sources.repartitionById(bg.tasks, "s_blk").sortWithinPartitions("s_blk", "s_node").persist()

        def shared(state: DataFrame, k: int) -> A.Algebra:
            on = (state["blk"] == sources["s_blk"]) & (state["node"] == sources["s_node"])
            lost = state.join(sources.hint("merge"), on, "left_anti").agg(F.sum("val")).first()[0] or 0.0
            base = (1.0 - damping) / n + damping * lost / n
            return A.Algebra("rank", "double", lambda w, v: w * v, F.sum, A.plus, 0.0, lambda old, acc: F.lit(base) + F.lit(damping) * acc)

        try:
            out = iterate(bg, start, A.rank_algebra(damping, max(n, 1)), iters, shared=shared, **how)
        finally:
            sources.unpersist()
    out.placement, out.theta = placement, theta
    return out


def random_walk_with_restart(edges: DataFrame, vertices: DataFrame, seeds: Column | DataFrame, n_seeds: int, restart: float = 0.15, iters: int = 8, weighted: bool = True, **how) -> Result:
    """seeds: a condition over node, true for n_seeds vertices; or their ids (node), distinct, which are joined and
    never collected: seeds hold their restart share in a state of their own scale."""
    share = 1.0 / max(n_seeds, 1)
    if isinstance(seeds, DataFrame):
        return _walk_from(edges, vertices, seeds, share, restart, iters, weighted, **how)
    start = vertices.select("node", F.when(seeds, F.lit(share)).otherwise(F.lit(0.0)).alias("val"))
    return run(stochastic(edges, weighted), vertices, start, A.restart_algebra(restart, seeds, share), max_iter=iters, **how)


def _walk_from(edges: DataFrame, vertices: DataFrame, seeds: DataFrame, share: float, restart: float, iters: int, weighted: bool, **how) -> Result:
    """The restart is a cell as well: a source outside the graph holds the constant 1 and has an edge to each seed, so
    no table of seeds is joined in the loop."""
    cells = stochastic(edges, weighted).withColumn("w", F.col("w") * F.lit(1.0 - restart))
    home = vertices.agg(F.min("node")).first()[0]
    source = (home or 0) - 1
    spark = edges.sparkSession
    outside = spark.createDataFrame([(source,)], "node bigint")
    mine = seeds.select(F.lit(source).alias("src"), F.col("node").alias("dst"), F.lit(restart * share).alias("w"))
    loop_ = spark.createDataFrame([(source, source, 1.0)], "src bigint, dst bigint, w double")
    all_ = vertices.select("node").union(outside)
    known = seeds.select(F.col("node").alias("s_node"))
    start = all_.join(known, all_["node"] == known["s_node"], "left").select(
        "node", F.when(F.col("node") == source, 1.0).when(F.col("s_node").isNotNull(), share).otherwise(0.0).alias("val")
    )
    out = run(cells.union(mine).union(loop_), all_, start, A.product_algebra(), max_iter=iters, **how)
    out.state = out.state.filter(F.col("node") != source)
    return out


def _fixpoint(edges: DataFrame, vertices: DataFrame, start: DataFrame, algebra: A.Algebra, max_iter: int | None, **how) -> Result:
    """Rounds until nothing changes: no path without a cycle is longer than the number of vertices. Raises if
    ``max_iter`` rounds do not suffice; only a budget of seconds may end earlier, with its status."""
    rounds = vertices.count() + 1 if max_iter is None else max_iter
    out = run(edges, vertices, start, algebra, max_iter=rounds, tol=0.0, **how)
    if out.status == "done":
        raise RuntimeError(f"values did not settle in {rounds} rounds")
    return out


def _from_source(vertices: DataFrame, source: int) -> DataFrame:
    return vertices.select("node", F.when(F.col("node") == source, F.lit(0.0)).otherwise(F.lit(A.INF)).alias("val"))


def shortest_paths(edges: DataFrame, vertices: DataFrame, source: int, max_iter: int | None = None, check: bool = True, **how) -> Result:
    """Distances from one vertex; infinity where there is no path. Negative weights are refused."""
    if check and edges.filter("w < 0").limit(1).count():
        raise ValueError("negative weights")
    return _fixpoint(edges, vertices, _from_source(vertices, source), A.distance_algebra(), max_iter, **how)


def hop_levels(edges: DataFrame, vertices: DataFrame, source: int, max_iter: int | None = None, **how) -> Result:
    return _fixpoint(edges, vertices, _from_source(vertices, source), A.hop_algebra(), max_iter, **how)


def reachable(edges: DataFrame, vertices: DataFrame, source: int, max_iter: int | None = None, **how) -> Result:
    start = vertices.select("node", (F.col("node") == source).alias("val"))
    return _fixpoint(edges, vertices, start, A.reach_algebra(), max_iter, **how)


def widest_paths(edges: DataFrame, vertices: DataFrame, source: int, max_iter: int | None = None, **how) -> Result:
    start = vertices.select("node", F.when(F.col("node") == source, F.lit(A.INF)).otherwise(F.lit(-A.INF)).alias("val"))
    return _fixpoint(edges, vertices, start, A.widest_algebra(), max_iter, **how)


def components(edges: DataFrame, vertices: DataFrame, max_iter: int | None = None, symmetric: bool = False, **how) -> Result:
    """The smallest id of each vertex's component. Edges are taken both ways unless they already come so."""
    both = edges if symmetric else symmetrise(edges)
    start = vertices.select("node", F.col("node").alias("val"))
    return _fixpoint(both, vertices, start, A.label_algebra(), max_iter, **how)


def largest_labels(edges: DataFrame, vertices: DataFrame, max_iter: int | None = None, **how) -> Result:
    start = vertices.select("node", F.col("node").alias("val"))
    return _fixpoint(edges, vertices, start, A.label_algebra(largest=True), max_iter, **how)


def walk_counts(edges: DataFrame, vertices: DataFrame, length: int, **how) -> Result:
    """Number of walks of ``length`` edges that end in each vertex, exact."""
    start = vertices.select("node", F.lit(1).cast("bigint").alias("val"))
    return run(edges, vertices, start, A.count_algebra(), max_iter=length, **how)


def spmv(edges: DataFrame, vertices: DataFrame, start: DataFrame, **how) -> Result:
    """One ordinary product."""
    return run(edges, vertices, start, A.product_algebra(), max_iter=1, **how)


def power_iteration(edges: DataFrame, vertices: DataFrame, iters: int = 20, **how) -> tuple[float, Result]:
    """The dominant eigenvalue (absolute) and vector of length one. Blocks are laid out once; each round scales by the
    length of the vector before it, which is one number."""
    layout = {k: how.pop(k) for k in ("placement", "b", "psi", "theta", "model") if k in how}
    sizes: list[float] = []

    def length(state: DataFrame) -> float:
        return (state.agg(F.sum(F.col("val") * F.col("val"))).first()[0] or 0.0) ** 0.5

    def shared(state: DataFrame, k: int) -> A.Algebra:
        sizes.append(length(state))
        scale = 1.0 / sizes[-1] if sizes[-1] else 0.0
        return A.Algebra("power", "double", lambda w, v: w * v * F.lit(scale), F.sum, A.plus, 0.0, lambda old, acc: acc)

    ones = vertices.select("node", F.lit(1.0).alias("val"))
    with laid_out(edges, vertices, **layout) as (bg, placement, theta):
        out = iterate(bg, ones, A.product_algebra(), iters, shared=shared, **how)
    size = length(out.state)
    out.state = out.state.select("node", (F.col("val") / F.lit(size or 1.0)).alias("val"))
    out.placement, out.theta = placement, theta
    return size, out


def degrees_by_product(edges: DataFrame, vertices: DataFrame, direction: str = "in", **how) -> Result:
    ones = vertices.select("node", F.lit(1.0).alias("val"))
    cells = edges if direction == "in" else edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")
    return spmv(cells.withColumn("w", F.lit(1.0)), vertices, ones, **how)


# ---- graph preparation -----------------------------------------------------------------------------------------------


def prepare(edges: DataFrame, repeated: str = "distinct", drop_loops: bool = False, weight: float = 1.0) -> DataFrame:
    """src, dst, w without null ends. repeated: distinct (w = weight), sum, min (of w), or keep."""
    some = edges.filter("src is not null and dst is not null")
    if drop_loops:
        some = some.filter("src <> dst")
    if repeated == "keep":
        return some.select("src", "dst", "w" if "w" in edges.columns else F.lit(weight).alias("w"))
    if repeated == "distinct":
        return some.select("src", "dst").distinct().withColumn("w", F.lit(weight))
    if repeated not in ("sum", "min"):
        raise ValueError(f"unknown treatment of repeated edges: {repeated}")
    return some.groupBy("src", "dst").agg((F.sum if repeated == "sum" else F.min)("w").alias("w"))


def symmetrise(edges: DataFrame) -> DataFrame:
    turned = edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")
    return edges.select("src", "dst", "w").union(turned).groupBy("src", "dst").agg(F.min("w").alias("w"))


def transpose(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")


def vertices_of(edges: DataFrame) -> DataFrame:
    """Distinct ends. Vertices without edges must be added by whoever knows them."""
    return edges.select(F.explode(F.array("src", "dst")).alias("node")).distinct()


def sampled(node: Column, fraction: float) -> Column:
    """A vertex sample that does not depend on partitions: the first 8 hex digits of md5 as a fraction."""
    return F.conv(F.substring(F.md5(node.cast("string").cast("binary")), 1, 8), 16, 10).cast("bigint") < F.lit(int(fraction * (1 << 32)))


def induced_subgraph(edges: DataFrame, fraction: float) -> DataFrame:
    """Edges with both ends in a vertex sample; about fraction**2 of the edges stay."""
    return edges.filter(sampled(F.col("src"), fraction) & sampled(F.col("dst"), fraction))


def subgraph_of(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Edges with both ends among the vertices, by two semi joins."""
    ids = vertices.select("node")
    left = edges.join(ids, edges["src"] == ids["node"], "left_semi")
    return left.join(ids, left["dst"] == ids["node"], "left_semi")


def relabel(edges: DataFrame, names: DataFrame) -> DataFrame:
    """Replace ends by names (node, id)."""
    a = names.select(F.col("node").alias("a"), F.col("id").alias("a_id"))
    b = names.select(F.col("node").alias("b"), F.col("id").alias("b_id"))
    met = edges.join(a, edges["src"] == F.col("a")).join(b, F.col("dst") == F.col("b"))
    return met.select(F.col("a_id").alias("src"), F.col("b_id").alias("dst"), "w")


def graph_summary(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """n, m, density, average degree, extremes, vertices without out- or in-edges: one row, one pass after degrees."""
    d = degrees(edges, vertices)
    return d.agg(
        F.count("*").alias("n"),
        F.sum("out_degree").alias("m"),
        (F.sum("out_degree") / (F.count("*").cast("double") * F.count("*"))).alias("density"),
        (F.sum("out_degree") / F.count("*")).alias("average"),
        F.max("out_degree").alias("max_out"),
        F.max("in_degree").alias("max_in"),
        F.count_if(F.col("out_degree") == 0).alias("dangling"),
        F.count_if(F.col("in_degree") == 0).alias("no_in"),
    )

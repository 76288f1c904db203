"""The experiment workloads on the given tables. Each function returns a table of figures.

    python -m blockmv.experiments growing --tables /root/testdata/sf0.1 --cores 8

Elements and statuses are counted and can be had in SQL as well; seconds and bytes depend on the machine.
"""

from __future__ import annotations

import argparse
import statistics
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import algebra as A
from .functions.psi import named
from .operators import algorithms as al
from .operators import baselines, loop
from .operators.arrow_kernels import iterate_arrow
from .plans import blocks, cost
from .plans.session import held
from .sources import graphs as G

FRACTIONS = (0.25, 0.35, 0.5, 0.71, 1.0)
GRAPHS = ("conv_chain", "fk_forest", "word_bigram", "weblink_sym", "part_chain", "user_trans", "trade")
METHODS = (*loop.PLACEMENTS, "reshuffle", "vertex_cut", "vertex_cut_memory", "vertex_centric")
#: Workers of the growing study and bytes of memory that each of them may hold.
WORKERS, BUDGET_BYTES = 4, 128 * 1024
THETA = 24


def _run(edges: DataFrame, vertices: DataFrame, method: str, b: int | loop.Workers, iters: int, theta=THETA, psi: str = "md5", budget: int | None = None, cells: DataFrame | None = None, tasks: int | None = None) -> tuple[loop.Result, int]:
    """PageRank by one method, and the bytes that its largest task holds. The same budget stops any method that does not
    fit it, the block methods included. ``cells``: the edges with their shares, where several runs read the same."""
    n = vertices.count()
    start = vertices.select("node", F.lit(1.0 / max(n, 1)).alias("val"))
    cells, alg = al.stochastic(edges) if cells is None else cells, A.rank_algebra(0.85, max(n, 1))
    if method in loop.PLACEMENTS:
        with loop.laid_out(cells, vertices, method, b, psi, theta, tasks=tasks) as (bg, _, _):
            need = bg.held_elements() * cost.ELEMENT_BYTES
            if budget is not None and need > budget:
                return loop.Result(start, method, bg.b, bg.theta, status="o.o.m."), need
            return loop.iterate(bg, start, alg, iters), need
    parts, f = b.number if isinstance(b, loop.Workers) else b, named(psi)
    grid = max(2, round(parts**0.5))
    part = f(F.col("src"), grid) * grid + f(F.col("dst"), grid)
    if method == "reshuffle":
        return baselines.reshuffle(cells, start, alg, iters, parts, psi=psi), cost.CELL_BYTES
    if method == "vertex_cut":
        return baselines.vertex_cut(cells, start, alg, iters, grid, psi=psi), cost.CELL_BYTES
    if method == "vertex_cut_memory":
        need = baselines.vertex_cut_bytes(edges.select("src", "dst", part.alias("part")))
        return baselines.vertex_cut(cells, start, alg, iters, grid, "MEMORY_ONLY", budget, psi), need
    out = edges.groupBy(F.col("src").alias("v")).agg(F.collect_list(F.struct("dst", "w")).alias("out")).withColumn("part", f(F.col("v"), parts))
    need = baselines.vertex_centric_bytes(out, vertices, f, parts)
    return baselines.vertex_centric(cells, start, alg, iters, parts, budget, psi), need


def _selected(edges: DataFrame, vertices: DataFrame, b: int) -> str:
    """The basic placement that the rule picks; where that one has run already, its run is the selected one's."""
    return loop.select_placement(cost.shape_of(edges, vertices), b)


def growing(
    spark: SparkSession, d: str, graph: str = "part_chain", iters: int = 8, workers: int = WORKERS, budget: int = BUDGET_BYTES, fractions=FRACTIONS, methods=METHODS
) -> DataFrame:
    """Induced subgraphs of growing size, all methods: who still finishes, in which time, with how many elements.

    Shares and blocks of the cells are found once for each subgraph. Every worker may hold ``budget`` bytes. Block methods take as many blocks as that needs; what each method's largest
    task holds is measured and decides its status."""
    edges, _ = G.BUILDERS[graph](spark, d)
    out = []
    with held(edges):
        for fraction in fractions:
            e = al.induced_subgraph(edges, fraction)
            v = al.vertices_of(e)
            with held(e, v):
                m, runs, asked = e.count(), {}, loop.Workers(workers, budget)
                b = asked.blocks(v.count())
                cells = al.stochastic(e)
                blocked = blocks.with_blocks(cells, b, "md5")
                with held(cells, blocked):
                    for method in sorted(methods, key=lambda x: x == "selected"):
                        method_ = _selected(e, v, b) if method == "selected" else method
                        runs[method] = runs.get(method_) or _run(e, v, method_, asked, iters, budget=budget, cells=blocked if method_ in loop.PLACEMENTS else cells)
                for method in methods:
                    r, need = runs[method]
                    last = r.history[-1] if r.history else None
                    out.append((graph, fraction, m, method, r.status, need, last.total if last else 0, last.moved_bytes if last else 0, round(float(sum(h.seconds for h in r.history)), 3)))
    ddl = "graph string, fraction double, edges bigint, method string, status string, held_bytes bigint, elements bigint, moved_bytes bigint, seconds double"
    return spark.createDataFrame(out, ddl)


def largest(figures: DataFrame) -> DataFrame:
    """method, edges of the largest graph it did, and how many times as many the best of all methods did."""
    per = figures.groupBy("method").agg(F.coalesce(F.max(F.when(F.col("status") == "done", F.col("edges"))), F.lit(0)).alias("edges"))
    most = per.agg(F.max("edges").alias("most"))
    return per.join(F.broadcast(most), F.lit(True)).select("method", "edges", F.round(F.col("most") / F.nullif("edges", F.lit(0)), 6).alias("ratio"))


def density(spark: SparkSession, d: str, graphs=GRAPHS, bs=(4, 16, 64), iters: int = 2) -> DataFrame:
    """Four placements on graphs from sparse to dense: time and elements per iteration. The hybrid's threshold is the one
    of least expected cost; where it parts no vertex from the others, a basic placement's run is the hybrid's. Shares,
    degrees and blocks of the cells are found once for all runs that need the same."""
    out = []
    for g in graphs:
        edges, vertices = G.BUILDERS[g](spark, d)
        cells = al.stochastic(edges)
        with held(edges, vertices, cells):
            shape = cost.shape_of(edges, vertices)
            best = cost.choose_thresholds(edges, vertices, tuple(bs))
            for b in bs:
                blocked, cores = blocks.with_blocks(cells, b, "md5"), spark.sparkContext.defaultParallelism
                tasks = loop.tasks_for(b, shape.edges, cores)
                copied = loop.tasks_for(b, max(shape.edges, b * shape.vertices), cores)
                with held(blocked):
                    runs = {p: _run(edges, vertices, p, b, iters, cells=blocked, tasks=t)[0] for p, t in (("horizontal", copied), ("vertical", tasks))}
                    alike = {0: "horizontal", None: "vertical"}.get(best[b])
                    runs["hybrid"] = runs[alike] if alike else _run(edges, vertices, "hybrid", b, iters, best[b], cells=blocked, tasks=tasks)[0]
                runs["selected"] = runs[loop.select_placement(shape, b)]
                for p in loop.PLACEMENTS:
                    r = runs[p]
                    last = r.history[-1]
                    out.append((g, round(shape.density, 12), b, p, last.total, last.moved_bytes, round(statistics.mean(h.seconds for h in r.history), 3)))
    return spark.createDataFrame(out, "graph string, density double, b int, method string, elements bigint, moved_bytes bigint, seconds double")


def threshold(spark: SparkSession, d: str, graph: str = "supply_sym", b: int = 16, iters: int = 30, thetas=cost.THETAS) -> DataFrame:
    """Time, elements and bytes of the hybrid over the degree threshold, beside the three models' expectations; which
    threshold moves least and which is fastest. Thresholds that part the vertices alike share a run."""
    edges, vertices = G.BUILDERS[graph](spark, d)
    out, runs = [], {}
    with held(edges, vertices):
        models = {m: dict(cost.choose_threshold(edges, vertices, b, m, tuple(thetas))[1]) for m in ("vertex_share", "edge_share", "row_conditional")}
        shares = {r["theta"]: r["p_vertex"] for r in cost.light_shares(cost.degree_histogram(edges, vertices), tuple(thetas)).collect()}
        for t in thetas:
            if shares[t] not in runs:
                runs[shares[t]] = _run(edges, vertices, "hybrid", b, iters, t)[0]
            r = runs[shares[t]]
            seconds = statistics.median(h.seconds for h in r.history)
            out.append((t, r.history[-1].total, r.history[-1].moved_bytes, round(seconds, 4), *(round(float(models[m][t]), 3) for m in models)))
    least, fast = min(x[1] for x in out), min(x[3] for x in out)
    rows = [(*x, x[1] == least, x[3] == fast) for x in out]
    ddl = "theta bigint, elements bigint, moved_bytes bigint, seconds double, vertex_share double, edge_share double, row_conditional double, moves_least boolean, is_fastest boolean"
    return spark.createDataFrame(rows, ddl)


def scaling(spark: SparkSession, d: str, graph: str = "cust_part_sym", workers=(1, 2, 4, 8), iters: int = 4, methods=("hybrid", "reshuffle")) -> DataFrame:
    """Time on one worker over the time on n: a worker is a block, whose tasks run on one core at a time, so no more than
    n cores work. The session needs as many cores as the largest number of workers."""
    edges, vertices = G.BUILDERS[graph](spark, d)
    out = []
    with held(edges, vertices):
        for method in methods:
            runs = {w: _run(edges, vertices, method, w, iters, 64)[0] for w in workers}
            seconds = {w: statistics.median(h.seconds for h in r.history) for w, r in runs.items()}
            faster = cost.speedup(seconds, workers[0])
            out += [(method, w, runs[w].history[-1].total, round(seconds[w], 4), round(faster[w], 3)) for w in workers]
    return spark.createDataFrame(out, "method string, workers int, elements bigint, seconds double, speedup double")


def balance(spark: SparkSession, d: str, graph: str = "cust_part_sym", workers=(4, 8, 16, 32, 64), psi: str = "md5") -> DataFrame:
    """What machine scaling rests on: the largest block's share of cells and partial results against the median, per
    number of workers, and the same for the rival that groups by destination alone (its last reducer)."""
    edges, _ = G.BUILDERS[graph](spark, d)
    out = None
    for w in workers:
        stats = blocks.block_statistics(edges, w, psi)
        columns = stats.groupBy("cb").agg(F.sum("edges").alias("edges"), F.sum("rows").alias("rows"))
        rival = blocks.with_blocks(edges, w, psi).groupBy("rb").count().agg((F.max("count") / F.median("count")).alias("last_reducer"))
        row = columns.agg(
            F.lit(w).alias("workers"), (F.max("edges") / F.median("edges")).alias("cells"), (F.max("rows") / F.median("rows")).alias("partials"), F.max("edges").alias("largest")
        ).join(rival, F.lit(True))
        out = row if out is None else out.union(row)
    return out


def engines(spark: SparkSession, d: str, graph: str = "part_chain", b: int = 4, iters: int = 4, fractions=FRACTIONS) -> DataFrame:
    """State in memory against storage, columns against Arrow kernels, on growing subgraphs: seconds per iteration."""
    edges, _ = G.BUILDERS[graph](spark, d)
    out = []
    with held(edges):
        for f in fractions:
            e = al.induced_subgraph(edges, f)
            v = al.vertices_of(e)
            with held(e, v):
                n, m = v.count(), e.count()
                alg = A.rank_algebra(0.85, n)
                start = v.select("node", F.lit(1.0 / max(n, 1)).alias("val"))
                with loop.laid_out(al.stochastic(e), v, "vertical", b, "md5") as (bg, _, _):
                    runs = {f"columns, {state}": loop.iterate(bg, start, alg, iters, state=state) for state in ("memory", "storage")}
                    runs["arrow, memory"] = iterate_arrow(bg, start, alg, iters)
                    base = runs["columns, memory"].state
                    for name, r in runs.items():
                        gap = baselines.compare_states(r.state, base)
                        out.append((f, m, n, name, gap < 1e-12, round(statistics.median(h.seconds for h in r.history), 4)))
    return spark.createDataFrame(out, "fraction double, edges bigint, vertices bigint, engine string, agrees boolean, seconds double")


EXPERIMENTS: dict[str, Callable[..., DataFrame]] = {"growing": growing, "density": density, "threshold": threshold, "scaling": scaling, "balance": balance, "engines": engines}


def main() -> None:
    ask = argparse.ArgumentParser(description=__doc__)
    ask.add_argument("name", choices=EXPERIMENTS)
    ask.add_argument("--tables", required=True)
    ask.add_argument("--graph")
    ask.add_argument("--cores", default="*")
    told = ask.parse_args()
    spark = SparkSession.builder.master(f"local[{told.cores}]").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", "8").getOrCreate()
    how = {"graph": told.graph} if told.graph else {}
    EXPERIMENTS[told.name](spark, told.tables, **how).show(200, truncate=False)


if __name__ == "__main__":
    main()

"""Expected vector elements read, written and exchanged per iteration, and the choices that follow from them.

Two corrections of the published formulas are offered beside them. The hybrid formula takes the share of light
*vertices* for the chance that an in-edge comes from a light source; edges come from heavy sources more often, so
``edge_share`` takes the share of edges. ``row_conditional`` takes each row's own number of light in-edges.
"""

from __future__ import annotations

import math
from collections.abc import Iterable
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Candidates for the degree threshold; None stands for no heavy vertex at all.
THETAS: tuple[int | None, ...] = (0, 1, 2, 4, 8, 16, 32, 64, 128, 256, 512, 1024, None)


#: Bytes of a vector element (id and value) and of a cell (two ids and a weight) in memory models.
ELEMENT_BYTES, CELL_BYTES = 16, 24


@dataclass(frozen=True)
class GraphShape:
    vertices: int
    edges: int

    @property
    def density(self) -> float:
        return self.edges / self.vertices**2 if self.vertices else 0.0


def block_count(vertices: int, workers: int, memory_elements: int, expansion: float = 1.0) -> int:
    """As many blocks as workers while a sub-vector fits; else as many as make it fit. ``expansion`` over 1 allows for
    engines that hold a second copy of the vector while they make the next one."""
    need = expansion * vertices / memory_elements
    return workers if need < workers else math.ceil(need)


def stays_empty(shape: GraphShape, b: int) -> float:
    """Chance that a row has no cell in a block."""
    return (1 - shape.density) ** (shape.vertices / b) if shape.vertices else 1.0


def expected_partial(shape: GraphShape, b: int) -> float:
    """Expected rows of one block's partial result."""
    return shape.vertices / b * (1 - stays_empty(shape, b))


def cost_horizontal(shape: GraphShape, b: int) -> float:
    return (b + 1) * shape.vertices


def cost_vertical(shape: GraphShape, b: int) -> float:
    return 2 * shape.vertices * (1 + (b - 1) * (1 - stays_empty(shape, b)))


def prefers_horizontal(shape: GraphShape, b: int) -> bool:
    """The selection rule: below one half, horizontal is cheaper; a tie goes to vertical."""
    return stays_empty(shape, b) < 0.5


def cost_hybrid(vertices: int, b: int, p_light: float, in_degrees: Iterable[tuple[int, float]], p_edge: float | None = None) -> float:
    """in_degrees: (degree, share of vertices). p_edge: share of edges from light sources, where it should differ."""
    p = p_light if p_edge is None else p_edge
    filled = sum((1 - (1 - p / b) ** d) * share for d, share in in_degrees)
    return vertices * (p_light + b * (1 - p_light) + 1) + 2 * vertices * (b - 1) * filled


def cost_degree_aware(vertices: int, b: int, in_degrees: Iterable[tuple[int, float]]) -> float:
    """The hybrid cost without heavy vertices: a vertical cost that knows the in-degrees."""
    return cost_hybrid(vertices, b, 1.0, in_degrees)


def memory_elements(method: str, shape: GraphShape, b: int, heavy: int = 0, largest: int = 0) -> int:
    """Largest number of vector elements (for rivals: of whatever must be held) in one task's memory.

    ``largest``: edges of a partition with its copies (vertex_cut), out-edges of a worker (vertex_centric), or the
    largest group of a reducer (reshuffle).
    """
    block = math.ceil(shape.vertices / b)
    return {
        "vertical": 2 * block,
        "horizontal": 2 * block,
        "hybrid": 2 * block + heavy,
        "reshuffle": largest,
        "vertex_cut": largest,
        "vertex_centric": largest,
    }[method]


def speedup(seconds: dict[int, float], base: int) -> dict[int, float]:
    """Time on ``base`` workers over the time on n workers."""
    return {n: seconds[base] / s for n, s in seconds.items()}


# ---- distributions, on Spark ------------------------------------------------------------------------------------------


def shape_of(edges: DataFrame, vertices: DataFrame) -> GraphShape:
    return GraphShape(vertices.count(), edges.count())


def degrees(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """node, out_degree, in_degree; also of vertices without edges."""
    ends = edges.select(F.explode(F.array(F.struct(F.col("src").alias("node"), F.lit(1).alias("o"), F.lit(0).alias("i")), F.struct(F.col("dst").alias("node"), F.lit(0).alias("o"), F.lit(1).alias("i")))).alias("x"))
    none = vertices.select(F.struct(F.col("node"), F.lit(0).alias("o"), F.lit(0).alias("i")).alias("x"))
    return ends.union(none).groupBy(F.col("x.node").alias("node")).agg(F.sum("x.o").alias("out_degree"), F.sum("x.i").alias("in_degree"))


def degree_histogram(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """kind (in/out), degree, n: as many rows as there are degrees, whatever the number of edges."""
    both = degrees(edges, vertices).select(
        F.explode(F.array(F.struct(F.lit("in").alias("kind"), F.col("in_degree").alias("degree")), F.struct(F.lit("out").alias("kind"), F.col("out_degree").alias("degree")))).alias("x")
    )
    return both.groupBy("x.kind", "x.degree").agg(F.count("*").alias("n"))


def light_shares(histogram: DataFrame, thetas: tuple[int | None, ...] = THETAS) -> DataFrame:
    """theta (null: none heavy), p_vertex, p_edge: shares of vertices and of edges whose source is light."""
    spark = histogram.sparkSession
    ask = spark.createDataFrame([(t,) for t in thetas], "theta bigint")
    out = histogram.filter("kind = 'out'").select("degree", "n")
    light = F.col("theta").isNull() | (F.col("degree") < F.col("theta"))
    return (
        F.broadcast(ask)  # a dozen candidates
        .join(out, F.lit(True), "inner")
        .groupBy("theta")
        .agg(
            (F.sum(F.when(light, F.col("n")).otherwise(0)) / F.sum("n")).alias("p_vertex"),
            (F.sum(F.when(light, F.col("n") * F.col("degree")).otherwise(0)) / F.greatest(F.sum(F.col("n") * F.col("degree")), F.lit(1))).alias("p_edge"),
        )
    )


def cumulative_out(histogram: DataFrame) -> DataFrame:
    """degree, below: share of vertices whose out-degree is smaller."""
    out = histogram.filter("kind = 'out'")
    order = Window.orderBy("degree").rowsBetween(Window.unboundedPreceding, -1)
    total = Window.partitionBy()
    return out.select("degree", (F.coalesce(F.sum("n").over(order), F.lit(0)) / F.sum("n").over(total)).alias("below"))


def theta_table(histogram: DataFrame, vertices: int, b: int, thetas: tuple[int | None, ...] = THETAS) -> DataFrame:
    """theta, p_vertex, p_edge, cost_vertex_share (as published), cost_edge_share."""
    shares = light_shares(histogram, thetas)
    rows = histogram.filter("kind = 'in'").select(F.col("degree").alias("d"), "n")
    filled = lambda p: F.sum((1 - F.pow(1 - F.col(p) / b, F.col("d"))) * F.col("n"))
    both = F.broadcast(shares).join(rows, F.lit(True), "inner").groupBy("theta", "p_vertex", "p_edge")
    sums = both.agg(filled("p_vertex").alias("fv"), filled("p_edge").alias("fe"))
    moved = F.lit(vertices) * (F.col("p_vertex") + b * (1 - F.col("p_vertex")) + 1)
    return sums.select(
        "theta",
        "p_vertex",
        "p_edge",
        (moved + 2 * (b - 1) * F.col("fv")).alias("cost_vertex_share"),
        (moved + 2 * (b - 1) * F.col("fe")).alias("cost_edge_share"),
    )


def row_conditional_costs(edges: DataFrame, vertices: int, b: int, histogram: DataFrame, thetas: tuple[int | None, ...] = THETAS) -> DataFrame:
    """theta, cost_row_conditional: one pass over the edges with a conditional count per candidate."""
    return row_conditional_costs_of(edges, vertices, (b,), histogram, thetas).drop("b")


def row_conditional_costs_of(edges: DataFrame, vertices: int, bs: tuple[int, ...], histogram: DataFrame, thetas: tuple[int | None, ...] = THETAS) -> DataFrame:
    """b, theta, cost_row_conditional of several numbers of blocks: the counts do not depend on it, so one pass does for all."""
    deg = edges.groupBy(F.col("src").alias("s")).agg(F.count("*").alias("deg"))
    joined = edges.join(deg, F.col("src") == F.col("s"))
    light = [F.lit(True) if t is None else F.col("deg") < t for t in thetas]
    per_row = joined.groupBy("dst").agg(*[F.count_if(c).alias(f"n{k}") for k, c in enumerate(light)])
    sums = per_row.agg(*[F.sum(1 - F.pow(F.lit(1 - 1 / b), F.col(f"n{k}"))).alias(f"n{k}_{b}") for b in bs for k in range(len(thetas))])
    rows = [F.struct(F.lit(b).alias("b"), F.lit(t).cast("bigint").alias("theta"), F.coalesce(f"n{k}_{b}", F.lit(0.0)).alias("u")) for b in bs for k, t in enumerate(thetas)]
    long = sums.select(F.explode(F.array(*rows)).alias("x")).select("x.*")
    shares = light_shares(histogram, thetas)
    p, b = F.col("p_vertex"), F.col("b")
    return long.join(shares, long["theta"].eqNullSafe(shares["theta"])).select(
        "b", long["theta"], (F.lit(vertices) * (p + b * (1 - p) + 1) + 2 * (b - 1) * F.col("u")).alias("cost_row_conditional")
    )


def choose_threshold(
    edges: DataFrame, vertices: DataFrame, b: int, model: str = "row_conditional", thetas: tuple[int | None, ...] = THETAS, distribution: str = "counted", histogram: DataFrame | None = None
) -> tuple[int | None, list[tuple[int | None, float]]]:
    """The candidate of least expected cost, and all costs. model: vertex_share (as published), edge_share,
    row_conditional. distribution: degrees as counted, or their power_law fit (not for row_conditional, which looks at the
    rows themselves). At most one row per candidate reaches the driver. Ties go to the smaller threshold. ``histogram``: the
    counted degrees, where they are known."""
    hist = degree_histogram(edges, vertices) if histogram is None else histogram
    if distribution == "power_law":
        if model == "row_conditional":
            raise ValueError("row_conditional counts rows; the power law has no use there")
        hist = fitted_histogram(hist)
    n = vertices.count()
    if model == "row_conditional":
        table = row_conditional_costs(edges, n, b, hist, thetas).select("theta", F.col("cost_row_conditional").alias("cost"))
    else:
        table = theta_table(hist, n, b, thetas).select("theta", F.col(f"cost_{model}").alias("cost"))
    costs = sorted(((r["theta"], r["cost"]) for r in table.collect()), key=lambda x: (x[0] is None, x[0] or 0))
    return min(costs, key=lambda x: (x[1], x[0] is None, x[0] or 0))[0], costs


def choose_thresholds(edges: DataFrame, vertices: DataFrame, bs: tuple[int, ...], thetas: tuple[int | None, ...] = THETAS) -> dict[int, int | None]:
    """The candidate of least row-conditional cost for each number of blocks, from one pass over degrees and rows."""
    costs = row_conditional_costs_of(edges, vertices.count(), bs, degree_histogram(edges, vertices), thetas).collect()
    return {b: min((r["cost_row_conditional"], r["theta"] is None, r["theta"] or 0, r["theta"]) for r in costs if r["b"] == b)[3] for b in bs}


def power_law_exponents(histogram: DataFrame) -> DataFrame:
    """kind, slope, intercept of log n over log degree (degrees from 1 on): the fit that the paper relies on."""
    some = histogram.filter("degree > 0")
    return some.groupBy("kind").agg(
        F.regr_slope(F.log("n"), F.log("degree")).alias("slope"), F.regr_intercept(F.log("n"), F.log("degree")).alias("intercept")
    )


def fitted_histogram(histogram: DataFrame) -> DataFrame:
    """The histogram with positive degrees replaced by the power-law fit, rescaled to the same number of vertices. Its
    rows are degrees, not vertices: two windows over them are small whatever the graph's size."""
    fit = F.broadcast(power_law_exponents(histogram))
    some = histogram.join(fit, "kind").withColumn("f", F.when(F.col("degree") > 0, F.exp(F.col("intercept") + F.col("slope") * F.log("degree"))))
    w = Window.partitionBy("kind", F.col("degree") > 0)
    return some.select("kind", "degree", F.when(F.col("degree") > 0, F.col("f") * F.sum("n").over(w) / F.sum("f").over(w)).otherwise(F.col("n")).alias("n"))

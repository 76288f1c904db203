"""One query per method, variant, rival, measure and workload, and the SQL that must give the same rows."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable
from functools import partial

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import experiments
from . import oracle as O
from .functions import algebra as A
from .functions import psi
from .operators import algorithms as al
from .operators import baselines as rivals
from .operators import loop
from .operators.multiply import reference
from .plans import blocks, cost
from .plans.session import held, loop_settings, reliable, shared_folder
from .sources import graphs as G
from .sources.graphs import table
from .streaming import edges as streams

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}

DIGITS = 10
THETAS = (0, 1, 2, 4, 8, 16, 32, 64, 128, 256, 512, 1024, None)


def _add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        SQL[name] = sql


def _ranks(result: loop.Result, digits: int = DIGITS, name: str = "rank") -> DataFrame:
    return result.state.select("node", F.round("val", digits).alias(name))


# ---- graphs ------------------------------------------------------------------------------------------------------------


def _summary(g: str, spark: SparkSession, d: str) -> DataFrame:
    row = al.graph_summary(*G.BUILDERS[g](spark, d))
    return row.withColumns({"density": F.round("density", 12), "average": F.round("average", 9)})


def _histogram(g: str, spark: SparkSession, d: str) -> DataFrame:
    return cost.degree_histogram(*G.BUILDERS[g](spark, d))


for _g in G.BUILDERS:
    _add(f"graph_summary_{_g}", partial(_summary, _g), O.summary(_g))
for _g in ("part_chain", "word_bigram", "fk_forest", "supply_sym"):
    _add(f"degree_hist_{_g}", partial(_histogram, _g), O.histogram(_g))


def _pout(g: str, spark: SparkSession, d: str) -> DataFrame:
    shares = cost.light_shares(_histogram(g, spark, d), THETAS)
    return shares.select("theta", F.round("p_vertex", 9).alias("p_vertex"), F.round("p_edge", 9).alias("p_edge"))


def _below(g: str, spark: SparkSession, d: str) -> DataFrame:
    return cost.cumulative_out(_histogram(g, spark, d)).select("degree", F.round("below", 9).alias("below"))


_add(
    "pout_word_bigram",
    partial(_pout, "word_bigram"),
    f"SELECT theta, p_vertex, p_edge FROM ({O.thetas('word_bigram', 16, THETAS)})",
)
_add(
    "pout_cumulative_word_bigram",
    partial(_below, "word_bigram"),
    f"WITH h AS ({O.histogram('word_bigram')}) SELECT degree, round(coalesce(sum(n) OVER (ORDER BY degree ROWS BETWEEN UNBOUNDED PRECEDING"
    " AND 1 PRECEDING), 0) / (sum(n) OVER ())::DOUBLE, 9) AS below FROM h WHERE kind = 'out'",
)


def _blocks(g: str, psi: str, b: int, theta: int | None, spark: SparkSession, d: str) -> DataFrame:
    return blocks.block_statistics(G.BUILDERS[g](spark, d)[0], b, psi, theta)


for _g, _psi, _b, _t in (("part_chain", "mod", 4, None), ("supply_sym", "mult", 16, 64), ("word_bigram", "md5", 4, 16)):
    _add(f"block_stats_{_g}", partial(_blocks, _g, _psi, _b, _t), O.blocks(_g, _psi, _b, _t))


def _prepartition(spark: SparkSession, d: str) -> DataFrame:
    """From the blocked frames themselves, light and heavy."""
    edges, vertices = G.part_chain(spark, d)
    bg = blocks.prepartition(edges, vertices, 4, "mod", 16)
    cells = bg.light.unionByName(bg.heavy)
    out = reliable(cells.groupBy("rb", "cb").agg(F.count("*").alias("edges"), F.sum("w").alias("weight")))
    bg.release()
    return out


_add(
    "prepartition_check_part_chain",
    _prepartition,
    f"WITH {O.graph('part_chain')} SELECT {O.block('mod', 'dst', 4)}::INT AS rb, {O.block('mod', 'src', 4)}::INT AS cb,"
    " count(*) AS edges, sum(w) AS weight FROM e GROUP BY 1, 2",
)


def _induced(g: str, spark: SparkSession, d: str) -> DataFrame:
    """Vertex fractions 1/4, 1/2, 3/4, 1: sizes of the induced subgraphs."""
    edges, _ = G.BUILDERS[g](spark, d)
    out = None
    for f in (0.25, 0.5, 0.75, 1.0):
        e = al.induced_subgraph(edges, f)
        row = e.agg(F.lit(f).alias("fraction"), F.count("*").alias("m"), F.count_distinct("src").alias("sources"))
        out = row if out is None else out.union(row)
    return out


_hash = "('0x' || substr(md5({0}::VARCHAR), 1, 8))::BIGINT"
_add(
    "induced_part_chain",
    partial(_induced, "part_chain"),
    f"WITH {O.graph('part_chain')}, f AS (SELECT * FROM (VALUES (0.25::DOUBLE), (0.5::DOUBLE), (0.75::DOUBLE), (1.0::DOUBLE)) t(fraction))"
    " SELECT fraction, count(src) AS m, count(DISTINCT src) AS sources FROM f LEFT JOIN e ON"
    f" {_hash.format('src')} < floor(fraction * 4294967296) AND {_hash.format('dst')} < floor(fraction * 4294967296) GROUP BY fraction",
)


def _subgraph(spark: SparkSession, d: str) -> DataFrame:
    """Edges among customers and orders of one nation, by two semi joins."""
    edges, _ = G.fk_forest(spark, d)
    mine = table(spark, d, "customer").filter("c_nationkey = 7")
    orders = table(spark, d, "orders")
    ids = mine.select(G.tagged(3, F.col("c_custkey")).alias("node")).union(
        orders.join(mine, orders["o_custkey"] == mine["c_custkey"], "left_semi").select(G.tagged(4, F.col("o_orderkey")))
    )
    return al.subgraph_of(edges, ids.distinct()).select("src", "dst")


_add(
    "induced_by_semi_join",
    _subgraph,
    f"WITH {O.graph('fk_forest')}, i AS (SELECT {3 * O.TAG} + c_custkey AS node FROM customer WHERE c_nationkey = 7 UNION"
    f" SELECT {4 * O.TAG} + o_orderkey FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_nationkey = 7)"
    " SELECT src, dst FROM e WHERE src IN (SELECT node FROM i) AND dst IN (SELECT node FROM i)",
)


def _rmat(spark: SparkSession, d: str) -> DataFrame:
    row = al.graph_summary(*G.rmat_from(spark, d))
    return row.withColumns({"density": F.round("density", 12), "average": F.round("average", 9)})


O.EDGES["rmat"] = O.rmat(12, "SELECT count(*) FROM lineitem", 42, G.RMAT)
_add("rmat_edges", _rmat, O.summary("rmat"))


def _totals(edges: DataFrame, name: str) -> DataFrame:
    """One row of figures. Tagged ids are over 2**40, so a few million of them sum to more than a long holds."""
    ids = [F.sum(F.col(c).cast("decimal(28,0)")).cast("string").alias(a) for c, a in (("src", "sources"), ("dst", "targets"))]
    return edges.agg(F.lit(name).alias("format"), F.count("*").alias("m"), *ids, F.sum("w").alias("w"))


def _formats(spark: SparkSession, d: str) -> DataFrame:
    """Edges written in each format and read again; weights are not part of an adjacency list."""
    from .sources import edges_io

    edges, _ = G.supply_sym(spark, d)
    folder, out = f"{shared_folder(spark)}/formats-{uuid.uuid4().hex}", None
    with held(edges):
        for fmt in ("parquet", "csv", "tsv", "json", "adjacency"):
            edges_io.write_edges(edges, f"{folder}/{fmt}", fmt)
            back = edges_io.read_edges(spark, f"{folder}/{fmt}", fmt)
            row = _totals(back, fmt)
            out = row if out is None else out.union(row)
        edges_io.write_blocks(blocks.with_blocks(edges, 4, "mod"), f"{folder}/blocks")
    return out.union(_totals(edges_io.read_block(spark, f"{folder}/blocks", 1), "block 1"))


_add(
    "edge_formats",
    _formats,
    f"WITH {O.graph('supply_sym')}, f AS (SELECT unnest(['parquet', 'csv', 'tsv', 'json', 'adjacency', 'block 1']) AS format)"
    " SELECT format, count(*) AS m, sum(src)::HUGEINT::VARCHAR AS sources, sum(dst)::HUGEINT::VARCHAR AS targets, sum(w) AS w FROM e, f WHERE format <> 'block 1' OR src % 4 = 1 GROUP BY format",
)


def _renamed(spark: SparkSession, d: str) -> DataFrame:
    """Ids replaced by names, and all edges turned around."""
    edges, vertices = G.supply_sym(spark, d)
    names = vertices.select("node", (F.col("node") * 2 + 1).alias("id"))
    return al.transpose(al.relabel(edges, names)).select("src", "dst", "w")


_add("relabel_transpose", _renamed, f"WITH {O.graph('supply_sym')} SELECT dst * 2 + 1 AS src, src * 2 + 1 AS dst, w FROM e")

# ---- placements ----------------------------------------------------------------------------------------------------------


def _pagerank(g: str, placement: str, iters: int, b: int, theta, spark: SparkSession, d: str, **how) -> DataFrame:
    edges, vertices = G.BUILDERS[g](spark, d)
    return _ranks(al.pagerank(edges, vertices, iters=iters, placement=placement, b=b, theta=theta, **how))


for _p in loop.PLACEMENTS:
    _add(f"pagerank8_{_p}_part_chain", partial(_pagerank, "part_chain", _p, 8, 4, 24), O.pagerank("part_chain", 8, DIGITS))
_add("pagerank8_hybrid_supply_sym", partial(_pagerank, "supply_sym", "hybrid", 8, 4, "auto"), O.pagerank("supply_sym", 8, DIGITS))
_add("pagerank8_hybrid_word_bigram", partial(_pagerank, "word_bigram", "hybrid", 8, 8, "auto"), O.pagerank("word_bigram", 8, DIGITS))
_add("pagerank30_hybrid_word", partial(_pagerank, "word_bigram", "hybrid", 30, 8, 16), O.pagerank("word_bigram", 30, DIGITS))
_add("pagerank8_selected_user_trans", partial(_pagerank, "user_trans", "selected", 8, 4, None), O.pagerank("user_trans", 8, DIGITS))
_add("pagerank4_needed_copies", partial(_pagerank, "part_chain", "hybrid", 4, 4, 24, copy="needed"), O.pagerank("part_chain", 4, DIGITS))
_add("pagerank4_broadcast_copies", partial(_pagerank, "part_chain", "hybrid", 4, 4, 24, copy="broadcast"), O.pagerank("part_chain", 4, DIGITS))
_add("pagerank4_storage_state", partial(_pagerank, "part_chain", "hybrid", 4, 4, 24, state="storage"), O.pagerank("part_chain", 4, DIGITS))
_add("pagerank_uniform_weblink", partial(_pagerank, "weblink", "vertical", 4, 4, None, dangling="uniform"), O.pagerank("weblink", 4, DIGITS, uniform=True))
_add("pagerank_weighted_trade", partial(_pagerank, "trade", "selected", 8, 4, None, weighted=True), O.pagerank("trade", 8, DIGITS, weighted=True))


def _rwr_doc(spark: SparkSession, d: str) -> DataFrame:
    """From the labelled documents of good quality, over shared lines both ways."""
    edges, vertices = G.doc_line(spark, d)
    good = table(spark, d, "labels").filter("quality = 1").select(F.col("doc_id").alias("node")).distinct()
    with held(edges, vertices):
        seeds = vertices.join(good, "node", "left_semi")
        found = al.random_walk_with_restart(al.symmetrise(edges), vertices, seeds, seeds.count(), iters=6, weighted=False, placement="vertical", b=4)
    return found.state.select("node", F.round("val", DIGITS).alias("score"))


_walk = O.FOLDED.format(fold="sum(m.w * o.val)")
_add(
    "rwr_doc",
    _rwr_doc,
    O.chain(
        f"e0 AS MATERIALIZED ({O.EDGES['doc_line']}), e AS MATERIALIZED (SELECT DISTINCT src, dst, w FROM (SELECT src, dst, w FROM e0 UNION ALL"
        f" SELECT dst, src, w FROM e0)), v AS MATERIALIZED (SELECT src AS node FROM e UNION SELECT dst FROM e), {O.SHARES},"
        " b AS MATERIALIZED (SELECT node, (node IN (SELECT doc_id FROM labels WHERE quality = 1))::INT AS seed FROM v),"
        " c AS (SELECT sum(seed)::DOUBLE AS n FROM b)",
        "SELECT node, seed / n AS val FROM b CROSS JOIN c",
        f"SELECT x.node, (1 - 0.15::DOUBLE) * coalesce(acc, 0) + 0.15::DOUBLE * seed / n AS val FROM b x CROSS JOIN c {_walk}",
        6,
        f"SELECT node, round(val, {DIGITS}) AS score FROM {{last}}",
    ),
)


def _rwr_knn(spark: SparkSession, d: str) -> DataFrame:
    edges, vertices = G.knn(spark, d, seeds=F.col("vec_id") < 3, steps=6)  # no other vector ever holds a score to hand on
    found = al.random_walk_with_restart(edges, vertices, F.col("node") < 3, 3, iters=6, placement="vertical", b=4)
    return found.state.select("node", F.round("val", 6).alias("score"))


_add(
    "rwr_knn",
    _rwr_knn,
    O.chain(
        "z AS MATERIALIZED (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings), e AS MATERIALIZED (SELECT src, dst, w FROM"
        " (SELECT a.vec_id AS src, b.vec_id AS dst, round(list_cosine_similarity(a.e, b.e), 9) AS w, row_number() OVER (PARTITION BY a.vec_id"
        " ORDER BY round(list_cosine_similarity(a.e, b.e), 9) DESC, b.vec_id) AS k FROM z a JOIN z b ON a.vec_id <> b.vec_id) WHERE k <= 10),"
        f" v AS MATERIALIZED (SELECT vec_id AS node FROM embeddings), {O.WEIGHTED}",
        "SELECT node, CASE WHEN node < 3 THEN 1.0::DOUBLE / 3 ELSE 0 END AS val FROM v",
        "SELECT x.node, (1 - 0.15::DOUBLE) * coalesce(acc, 0) + CASE WHEN x.node < 3 THEN 0.15::DOUBLE * (1.0::DOUBLE / 3) ELSE 0 END AS val FROM v x " + _walk,
        6,
        "SELECT node, round(val, 6) AS score FROM {last}",
    ),
)


def _finite(result: loop.Result, name: str, kind: str, digits: int | None = None) -> DataFrame:
    value = F.when(F.abs("val") < A.INF, F.round("val", digits) if digits is not None else F.col("val").cast(kind))
    return result.state.select("node", value.alias(name))


def _sssp_fk(spark: SparkSession, d: str) -> DataFrame:
    return _finite(al.shortest_paths(*G.fk_forest(spark, d), source=G.TAG, placement="vertical", b=4), "dist", "bigint")


def _bfs(spark: SparkSession, d: str) -> DataFrame:
    return _finite(al.hop_levels(*G.weblink_sym(spark, d), source=0, placement="hybrid", b=4), "level", "bigint")


def _reach(spark: SparkSession, d: str) -> DataFrame:
    found = al.reachable(*G.conv_chain(spark, d), source=1 << 20, placement="vertical", b=4)
    return found.state.select("node", F.col("val").alias("reached"))


_add("sssp_fk", _sssp_fk, f"SELECT node, level AS dist FROM ({O.hops('fk_forest', str(G.TAG), 5)})")
_add("bfs_weblink", _bfs, O.hops("weblink_sym", "0", 12))
_add("reach_conv", _reach, f"SELECT node, level IS NOT NULL AS reached FROM ({O.hops('conv_chain', str(1 << 20), 40)})")


def _sssp_trade(spark: SparkSession, d: str) -> DataFrame:
    edges, vertices = G.trade(spark, d)
    edges = edges.withColumn("w", F.round("w", 4))
    return _finite(al.shortest_paths(edges, vertices, source=3, placement="selected", b=4), "dist", "double", 4)


def _widest(spark: SparkSession, d: str) -> DataFrame:
    edges, vertices = G.trade(spark, d)
    edges = edges.withColumn("w", F.round("w", 4))
    return _finite(al.widest_paths(edges, vertices, source=3, placement="horizontal", b=4), "width", "double", 4)


def _relax(fold: str, combine: str, start: str, pick: str, name: str) -> str:
    head = f"e0 AS ({O.EDGES['trade']}), m AS MATERIALIZED (SELECT src, dst, round(w, 4) AS w FROM e0), v AS MATERIALIZED (SELECT src AS node FROM m UNION SELECT dst FROM m)"
    step = f"SELECT x.node, {pick}(x.val, coalesce(acc, x.val)) AS val FROM {{old}} x " + O.FOLDED.format(fold=f"{fold}({combine})")
    return O.chain(head, start, step, 12, f"SELECT node, CASE WHEN abs(val) < 1e300 THEN round(val, 4) END AS {name} FROM {{last}}")


_add("sssp_trade", _sssp_trade, _relax("min", "m.w + o.val", "SELECT node, CASE WHEN node = 3 THEN 0 ELSE 'inf'::DOUBLE END AS val FROM v", "least", "dist"))
_add("widest_trade", _widest, _relax("max", "least(m.w, o.val)", "SELECT node, CASE WHEN node = 3 THEN 'inf'::DOUBLE ELSE '-inf'::DOUBLE END AS val FROM v", "greatest", "width"))


def _components(g: str, spark: SparkSession, d: str) -> DataFrame:
    return al.components(*G.BUILDERS[g](spark, d), placement="vertical", b=4).state.select("node", F.col("val").alias("component"))


for _g in ("doc_dup", "doc_line", "weblink"):
    _add(f"cc_{_g}", partial(_components, _g), O.components(_g))
_add(
    "cc_conv",
    partial(_components, "conv_chain"),
    f"WITH {O.graph('conv_chain')} SELECT node, min(node) OVER (PARTITION BY node // {1 << 20}) AS component FROM v",
)


def _max_label(spark: SparkSession, d: str) -> DataFrame:
    edges, vertices = G.conv_chain(spark, d)
    return al.largest_labels(al.symmetrise(edges), vertices, placement="vertical", b=4).state.select("node", F.col("val").alias("label"))


_add(
    "max_label_conv",
    _max_label,
    f"WITH {O.graph('conv_chain')} SELECT node, max(node) OVER (PARTITION BY node // {1 << 20}) AS label FROM v",
)


def _spmv(spark: SparkSession, d: str) -> DataFrame:
    edges, vertices = G.part_chain(spark, d)
    start = vertices.select("node", (F.col("node") % 7).cast("double").alias("val"))
    return _ranks(al.spmv(edges, vertices, start, placement="hybrid", b=4, theta=24), 6, "val")


_add(
    "spmv_once",
    _spmv,
    f"WITH {O.graph('part_chain')}, a AS (SELECT dst, sum(w * (src % 7)) AS acc FROM e GROUP BY dst) SELECT node, round(coalesce(acc, 0)::DOUBLE, 6) AS val FROM v LEFT JOIN a ON node = dst",
)


def _degrees(spark: SparkSession, d: str) -> DataFrame:
    found = al.degrees_by_product(*G.weblink_sym(spark, d), placement="horizontal", b=4)
    return found.state.select("node", F.col("val").cast("bigint").alias("in_degree"))


_add("degree_by_product", _degrees, f"WITH {O.graph('weblink_sym')}, {O.DEGREES} SELECT node, in_degree::BIGINT AS in_degree FROM g")


def _walks(spark: SparkSession, d: str) -> DataFrame:
    return al.walk_counts(*G.part_chain(spark, d), length=3, placement="hybrid", b=4, theta=24).state.select("node", F.col("val").alias("walks"))


_add(
    "pathcount_exact",
    _walks,
    O.chain(
        f"{O.graph('part_chain')}, m AS (SELECT * FROM e)",
        "SELECT node, 1::BIGINT AS val FROM v",
        "SELECT x.node, coalesce(acc, 0)::BIGINT AS val FROM v x " + O.FOLDED.format(fold="sum(o.val)"),
        3,
        "SELECT node, val AS walks FROM {last}",
    ),
)


def _power(spark: SparkSession, d: str) -> DataFrame:
    size, found = al.power_iteration(*G.user_trans(spark, d), iters=4, placement="horizontal", b=4)
    return found.state.select("node", F.round("val", 8).alias("val"), F.lit(round(size, 6)).alias("eigenvalue"))


_add(
    "power_iteration_user_trans",
    _power,
    O.chain(
        f"{O.graph('user_trans')}, m AS (SELECT * FROM e)",
        "SELECT node, 1.0::DOUBLE AS val FROM v",
        "SELECT x.node, coalesce(acc, 0) / (SELECT sqrt(sum(val * val)) FROM {old}) AS val FROM {old} x " + O.FOLDED.format(fold="sum(m.w * o.val)"),
        4,
        "SELECT node, round(val / (SELECT sqrt(sum(val * val)) FROM {last}), 8) AS val, (SELECT round(sqrt(sum(val * val)), 6) FROM {last}) AS eigenvalue FROM {last}",
    ),
)


def _reference(spark: SparkSession, d: str) -> DataFrame:
    """The product without partitioning, four times: what all placements must equal."""
    edges, vertices = G.part_chain(spark, d)
    n = vertices.count()
    state, cells = vertices.select("node", F.lit(1.0 / n).alias("val")), al.stochastic(edges)
    for _ in range(4):
        state = reference(cells, state, A.rank_algebra(0.85, n))
    return state.select("node", F.round("val", DIGITS).alias("rank"))


_add("pagerank4_reference", _reference, O.pagerank("part_chain", 4, DIGITS))


def _by_memory(spark: SparkSession, d: str) -> DataFrame:
    """Blocks from the workers' memory, heavy parts taken in chunks."""
    edges, vertices = G.part_chain(spark, d)
    return _ranks(al.pagerank(edges, vertices, iters=4, placement="horizontal", b=loop.Workers(4, 1 << 14), copy="chunked"))


_add("pagerank4_blocks_by_memory", _by_memory, O.pagerank("part_chain", 4, DIGITS))
_add("pagerank4_uniform_hybrid", partial(_pagerank, "part_chain", "hybrid", 4, 4, 24, dangling="uniform"), O.pagerank("part_chain", 4, DIGITS, uniform=True))


def _block_counts(spark: SparkSession, d: str) -> DataFrame:
    """The block-count rule: blocks for growing graphs and memories."""
    rows = []
    for g in ("trade", "part_chain", "fk_forest"):
        n = G.BUILDERS[g](spark, d)[1].count()
        rows += [(g, m, cost.block_count(n, 4, m, x), x) for m in (64, 1024, 1 << 20) for x in (1.0, 2.0)]
    return spark.createDataFrame(rows, "graph string, memory bigint, b bigint, expansion double")


_add(
    "block_count_rule",
    _block_counts,
    " UNION ALL ".join(
        f"SELECT * FROM (WITH {O.graph(g)}, n AS (SELECT count(*)::DOUBLE AS n FROM v) SELECT '{g}' AS graph, m::BIGINT AS memory, CASE WHEN x * n / m < 4 THEN 4 ELSE ceil(x * n / m)::BIGINT END AS b, x::DOUBLE AS expansion"
        " FROM n, (VALUES (64), (1024), (1048576)) q(m), (VALUES (1.0), (2.0)) r(x))"
        for g in ("trade", "part_chain", "fk_forest")
    ),
)


def _sql_step(spark: SparkSession, d: str) -> DataFrame:
    from .operators.sql_surface import multiply_sql

    edges, vertices = G.part_chain(spark, d)
    state = vertices.select("node", (F.col("node") % 7).cast("double").alias("val"))
    return multiply_sql(spark, edges, state, "w * val", "sum", "acc", "0.0D").select("node", F.round("val", 6).alias("val"))


def _arrow(spark: SparkSession, d: str) -> DataFrame:
    from .operators.arrow_kernels import multiply_arrow

    edges, vertices = G.part_chain(spark, d)
    bg = blocks.prepartition(edges, vertices, 4, "hash", 24)
    state = bg.nodes.withColumn("val", (F.col("node") % 7).cast("double"))
    with loop_settings(spark, bg.b):
        out = reliable(multiply_arrow(bg, state, A.product_algebra()).select("node", F.round("val", 6).alias("val")))
    bg.release()
    return out


def _pandas_combine(spark: SparkSession, d: str) -> DataFrame:
    from .functions.udfs import vectorised

    edges, vertices = G.part_chain(spark, d)
    start = vertices.select("node", (F.col("node") % 7).cast("double").alias("val"))
    own = vectorised("own", lambda w, v: w * v, F.sum, A.plus, 0.0, lambda old, acc: acc)
    return _ranks(loop.run(edges, vertices, start, own, "vertical", 4, max_iter=1), 6, "val")


def _saved(spark: SparkSession, d: str) -> DataFrame:
    """A product with cells from a bucketed table."""
    edges, vertices = G.part_chain(spark, d)
    name = f"blockmv_{uuid.uuid4().hex}"
    blocks.save_blocks(edges, name, 4)
    state = vertices.select("node", (F.col("node") % 7).cast("double").alias("val"))
    out = reliable(blocks.multiply_saved(name, state, 4, A.product_algebra()).select("node", F.round("val", 6).alias("val")))
    spark.sql(f"DROP TABLE {name}")
    return out


for _name, _f in (("spmv_sql", _sql_step), ("spmv_arrow", _arrow), ("spmv_pandas_combine", _pandas_combine), ("spmv_saved_blocks", _saved)):
    _add(_name, _f, SQL["spmv_once"])

# ---- cost models and measured elements -------------------------------------------------------------------------------------


def _costs(g: str, bs: tuple[int, ...], spark: SparkSession, d: str) -> DataFrame:
    shape = cost.shape_of(*G.BUILDERS[g](spark, d))
    rows = [
        (b, round(cost.stays_empty(shape, b), 9), round(float(cost.cost_horizontal(shape, b)), 3), round(cost.cost_vertical(shape, b), 3), loop.select_placement(shape, b))
        for b in bs
    ]
    return spark.createDataFrame(rows, "b int, stay double, c_h double, c_v double, choice string")


for _g in ("trade", "user_trans", "part_chain", "supply_sym", "weblink_sym", "fk_forest", "conv_chain", "word_bigram"):
    _add(f"cost_table_{_g}", partial(_costs, _g, (4, 16, 64)), O.costs(_g, (4, 16, 64)))


def _theta_table(g: str, b: int, spark: SparkSession, d: str) -> DataFrame:
    edges, vertices = G.BUILDERS[g](spark, d)
    hist, n = cost.degree_histogram(edges, vertices), vertices.count()
    a, r = cost.theta_table(hist, n, b, THETAS), cost.row_conditional_costs(edges, n, b, hist, THETAS).withColumnRenamed("theta", "t")
    met = a.join(r, a["theta"].eqNullSafe(r["t"]))
    shares = [F.round(c, 9).alias(c) for c in ("p_vertex", "p_edge")]
    return met.select("theta", *shares, *[F.round(c, 3).alias(c) for c in ("cost_vertex_share", "cost_edge_share", "cost_row_conditional")])


for _g in ("word_bigram", "supply_sym", "weblink_sym"):
    _add(f"theta_table_{_g}", partial(_theta_table, _g, 16), O.thetas(_g, 16, THETAS))


def _theta_best(g: str, b: int, spark: SparkSession, d: str) -> DataFrame:
    edges, vertices = G.BUILDERS[g](spark, d)
    hist, rows = cost.degree_histogram(edges, vertices), []
    with held(edges, vertices, hist):  # the source is read once for all models
        for model in ("vertex_share", "edge_share", "row_conditional"):
            best, costs = cost.choose_threshold(edges, vertices, b=b, model=model, thetas=THETAS, histogram=hist)
            rows.append((model, best, round(dict(costs)[best], 3)))
    return spark.createDataFrame(rows, "model string, theta bigint, cost double")


def _best_sql(g: str, b: int) -> str:
    models = "; ".join(("vertex_share", "edge_share", "row_conditional")).split("; ")
    return f"WITH t AS MATERIALIZED ({O.thetas(g, b, THETAS)}) " + " UNION ALL ".join(
        f"(SELECT '{m}' AS model, theta, cost_{m} AS cost FROM t ORDER BY cost_{m}, theta NULLS LAST LIMIT 1)" for m in models
    )


for _g in ("word_bigram", "supply_sym"):
    _add(f"theta_best_{_g}", partial(_theta_best, _g, 16), _best_sql(_g, 16))


def _measured(g: str, placement: str, b: int, psi: str, theta: int | None, spark: SparkSession, d: str) -> DataFrame:
    """The ledger of one real iteration."""
    edges, vertices = G.BUILDERS[g](spark, d)
    start = vertices.select("node", F.lit(1.0).alias("val"))
    found = loop.run(edges, vertices, start, A.product_algebra(), placement, b, psi, theta, max_iter=1)
    return found.history_frame().select(F.lit(b).alias("b"), "read", "written", "exchanged", "diagonal", "total")


for _p, _t in (("horizontal", 0), ("vertical", None), ("hybrid", 64)):
    _add(f"io_measured_{_p}_supply_sym", partial(_measured, "supply_sym", _p, 16, "md5", _t), O.measured("supply_sym", "md5", 16, _t))
    _add(f"io_measured_{_p}_part_chain", partial(_measured, "part_chain", _p, 4, "mod", _t), O.measured("part_chain", "mod", 4, _t))
_add("io_measured_hybrid_word", partial(_measured, "word_bigram", "hybrid", 16, "mult", 16), O.measured("word_bigram", "mult", 16, 16))


def counted_sweep(edges: DataFrame, vertices: DataFrame, b: int, psi: str, thetas=THETAS) -> DataFrame:
    """theta, measured total for every candidate in one pass: per (column block, row) the least out-degree of its
    sources decides from which threshold on it is a partial result."""
    deg = blocks.out_degrees(edges)
    cells = blocks.with_blocks(edges, b, psi).join(deg, F.col("src") == F.col("node"))
    least = cells.filter("cb <> rb").groupBy("cb", "dst").agg(F.min("deg").alias("least"))
    u = least.groupBy("least").count()
    n = vertices.count()
    hist = cost.degree_histogram(edges, vertices)
    shares = cost.light_shares(hist, thetas)
    spark = edges.sparkSession
    ask = F.broadcast(spark.createDataFrame([(t,) for t in thetas], "theta bigint"))
    light = F.col("theta").isNull() | (F.col("least") < F.col("theta"))
    moved = ask.join(u, F.lit(True), "left").groupBy("theta").agg(F.sum(F.when(light, F.col("count")).otherwise(0)).alias("u")).withColumnRenamed("theta", "t")
    met = shares.join(moved, shares["theta"].eqNullSafe(F.col("t")))
    p = F.col("p_vertex")
    return met.select("theta", F.round(n * (p + b * (1 - p) + 1) + 2 * F.coalesce("u", F.lit(0)), 3).alias("measured"))


def _sweep(g: str, psi: str, spark: SparkSession, d: str) -> DataFrame:
    return counted_sweep(*G.BUILDERS[g](spark, d), b=16, psi=psi)


def _sweep_sql(g: str, psi: str) -> str:
    return " UNION ALL ".join(
        f"SELECT {'NULL::BIGINT' if t is None else f'{t}::BIGINT'} AS theta, total::DOUBLE AS measured FROM ({O.measured(g, psi, 16, t)})" for t in THETAS
    )


for _g in ("word_bigram", "supply_sym"):
    _add(f"theta_sweep_{_g}", partial(_sweep, _g, "md5"), _sweep_sql(_g, "md5"))


def _regret(spark: SparkSession, d: str) -> DataFrame:
    """Measured elements of the chosen placement over those of the better basic one, both selection models."""
    rows = []
    for g, b in (("part_chain", 4), ("weblink_sym", 4), ("conv_chain", 4), ("trade", 4)):
        edges, vertices = G.BUILDERS[g](spark, d)
        shape = cost.shape_of(edges, vertices)
        hist = [(r["degree"], r["n"] / shape.vertices) for r in cost.degree_histogram(edges, vertices).filter("kind = 'in'").collect()]
        seen = {r["theta"]: r["measured"] for r in counted_sweep(edges, vertices, b, "md5", (0, None)).collect()}
        by = {"horizontal": seen[0], "vertical": seen[None]}
        for model in ("published", "degree_aware"):
            choice = loop.select_placement(shape, b, model, hist)
            rows.append((g, model, choice, round(by[choice] / min(by.values()), 6)))
    return spark.createDataFrame(rows, "graph string, model string, choice string, regret double")


def _regret_sql() -> str:
    rows = []
    for g, b in (("part_chain", 4), ("weblink_sym", 4), ("conv_chain", 4), ("trade", 4)):
        rows.append(
            f"SELECT * FROM (WITH {O.graph(g)}, {O.DEGREES}, bb AS (SELECT {b} AS b), c AS (SELECT (SELECT count(*) FROM v)::DOUBLE AS n, (SELECT count(*) FROM e)::DOUBLE AS m),"
            f" p AS (SELECT count(*) FILTER (cb <> rb) AS off FROM (SELECT DISTINCT {O.block('md5', 'src', b)} AS cb, {O.block('md5', 'dst', b)} AS rb, dst FROM e)),"
            f" f AS (SELECT sum(1 - power(1 - 1.0::DOUBLE / {b}, in_degree)) AS filled FROM g),"
            f" x AS (SELECT ({b} + 1) * n AS h, 2 * n + 2 * off AS vv, CASE WHEN power(1 - m / (n * n), n / {b}) < 0.5 THEN 'horizontal' ELSE 'vertical' END AS published,"
            f" CASE WHEN ({b} + 1) * n < 2 * n + 2 * ({b} - 1) * filled THEN 'horizontal' ELSE 'vertical' END AS degree_aware FROM c, p, f)"
            f" SELECT '{g}' AS graph, model, choice, round(CASE choice WHEN 'horizontal' THEN h ELSE vv END / least(h, vv), 6) AS regret FROM x,"
            " LATERAL (SELECT 'published' AS model, published AS choice UNION ALL SELECT 'degree_aware', degree_aware))"
        )
    return " UNION ALL ".join(rows)


_add("selection_regret", _regret, _regret_sql())


def _memory(spark: SparkSession, d: str) -> DataFrame:
    """Bytes of the largest task of each method, measured on the laid out graph."""
    edges, vertices = G.part_chain(spark, d)
    rows = []
    with held(edges, vertices):
        for b in (4, 16):
            for p, t in (("vertical", None), ("horizontal", 0), ("hybrid", 24)):
                with loop.laid_out(edges, vertices, p, b, "md5", t) as (bg, _, _):
                    rows.append((p, b, bg.held_elements() * cost.ELEMENT_BYTES))
            grid = round(b**0.5)
            part = psi.md5(F.col("src"), grid) * grid + psi.md5(F.col("dst"), grid)
            rows.append(("vertex_cut", b, rivals.vertex_cut_bytes(edges.select("src", "dst", part.alias("part")))))
            out = edges.groupBy(F.col("src").alias("v")).agg(F.collect_list(F.struct("dst", "w")).alias("out")).withColumn("part", psi.md5(F.col("v"), b))
            rows.append(("vertex_centric", b, rivals.vertex_centric_bytes(out, vertices, psi.md5, b)))
    return spark.createDataFrame(rows, "method string, b int, held_bytes bigint")


def _memory_sql() -> str:
    rows = []
    for b in (4, 16):
        grid = round(b**0.5)
        w = lambda x: O.block("md5", x, b)  # noqa: B023, E731
        rows.append(
            f"SELECT method, {b}::INT AS b, held::BIGINT AS held_bytes FROM (WITH {O.graph('part_chain')}, bb AS (SELECT {b} AS b), {O.placements(24)},"
            f" cut AS (SELECT src, dst, {O.block('md5', 'src', grid)} * {grid} + {O.block('md5', 'dst', grid)} AS part FROM e)"
            " SELECT 'vertical' AS method, 32 * x AS held FROM mb UNION ALL SELECT 'horizontal', 32 * x + 16 * n FROM mb, c UNION ALL SELECT 'hybrid', 32 * x + 16 * nd FROM mb, h"
            " UNION ALL SELECT 'vertex_cut', max(x) FROM (SELECT count(*) * 24 + (count(DISTINCT src) + count(DISTINCT dst)) * 16 AS x FROM cut GROUP BY part)"
            f" UNION ALL SELECT 'vertex_centric', max(x) FROM (SELECT p, sum(x) AS x FROM (SELECT {w('node')} AS p, count(*) * 32 AS x FROM v GROUP BY 1"
            f" UNION ALL SELECT {w('src')}, count(*) * 24 FROM e GROUP BY 1 UNION ALL SELECT p, count(*) * 16 FROM (SELECT DISTINCT {w('src')} AS p, dst FROM e) GROUP BY 1) GROUP BY p))"
        )
    return " UNION ALL ".join(rows)


_add("memory_model", _memory, _memory_sql())


def _partials(spark: SparkSession, d: str) -> DataFrame:
    """Expected rows of a block's partial result, rows of all of them, and the bound of a round's elements that memory gives:
    with M elements of memory, |v| / M blocks, no placement exchanges more than |v| * |v| / M elements and the vector."""
    rows = []
    for g in ("part_chain", "weblink_sym", "fk_forest"):
        edges, vertices = G.BUILDERS[g](spark, d)
        with held(edges, vertices):
            shape = cost.shape_of(edges, vertices)
            for b in (4, 16):
                counted = blocks.block_statistics(edges, b, "md5").agg(F.sum("rows")).first()[0]
                rho = 1 - cost.stays_empty(shape, b)
                bound = shape.vertices**2 / (shape.vertices / b)
                rows.append((g, b, round(cost.expected_partial(shape, b), 6), counted, round(rho, 9), round(bound, 3)))
    return spark.createDataFrame(rows, "graph string, b int, expected double, all_rows bigint, rho double, bound double")


_add(
    "partial_sizes",
    _partials,
    " UNION ALL ".join(
        f"SELECT * FROM (WITH {O.graph(g)}, c AS (SELECT (SELECT count(*) FROM v)::DOUBLE AS n, (SELECT count(*) FROM e)::DOUBLE AS m),"
        f" p AS (SELECT count(*) AS rows FROM (SELECT DISTINCT {O.block('md5', 'src', b)} AS cb, {O.block('md5', 'dst', b)} AS rb, dst FROM e))"
        f" SELECT '{g}' AS graph, {b}::INT AS b, round(n / {b} * (1 - power(1 - m / (n * n), n / {b})), 6) AS expected, rows AS all_rows,"
        f" round(1 - power(1 - m / (n * n), n / {b}), 9) AS rho, round(n * {b}, 3) AS bound FROM c, p)"
        for g in ("part_chain", "weblink_sym", "fk_forest")
        for b in (4, 16)
    ),
)


def _fitted(spark: SparkSession, d: str) -> DataFrame:
    """The threshold table when the degrees come from the power-law fit instead of the counts."""
    edges, vertices = G.word_bigram(spark, d)
    with held(edges, vertices):
        hist = cost.fitted_histogram(cost.degree_histogram(edges, vertices))
        rows = cost.theta_table(hist, vertices.count(), 16, THETAS)
        return reliable(rows.select("theta", F.round("cost_vertex_share", 2).alias("cost_vertex_share"), F.round("cost_edge_share", 2).alias("cost_edge_share")))


_add(
    "theta_table_power_law",
    _fitted,
    f"WITH h AS MATERIALIZED ({O.histogram('word_bigram')}), f AS (SELECT kind, regr_slope(ln(n), ln(degree)) AS a, regr_intercept(ln(n), ln(degree)) AS c FROM h WHERE degree > 0 GROUP BY kind),"
    " q AS (SELECT h.kind, degree, n, CASE WHEN degree > 0 THEN exp(c + a * ln(degree)) END AS f FROM h JOIN f ON h.kind = f.kind),"
    " z AS MATERIALIZED (SELECT kind, degree, CASE WHEN degree > 0 THEN f * sum(n) OVER w / sum(f) OVER w ELSE n END AS n FROM q WINDOW w AS (PARTITION BY kind, degree > 0)),"
    f" t AS (SELECT th::BIGINT AS theta FROM (VALUES {", ".join("(NULL)" if t is None else f"({t})" for t in THETAS)}) q(th)), v AS (SELECT sum(n) AS n FROM h WHERE kind = 'out'),"
    " p AS (SELECT theta, sum(CASE WHEN theta IS NULL OR degree < theta THEN n ELSE 0 END) / sum(n) AS pv, sum(CASE WHEN theta IS NULL OR degree < theta THEN n * degree ELSE 0 END) / sum(n * degree) AS pe FROM t, z WHERE kind = 'out' GROUP BY theta),"
    " s AS (SELECT theta, pv, sum((1 - power(1 - pv / 16, degree)) * n) AS fv, sum((1 - power(1 - pe / 16, degree)) * n) AS fe FROM p, z WHERE kind = 'in' GROUP BY theta, pv)"
    " SELECT theta, round(v.n * (pv + 16 * (1 - pv) + 1) + 30 * fv, 2) AS cost_vertex_share, round(v.n * (pv + 16 * (1 - pv) + 1) + 30 * fe, 2) AS cost_edge_share FROM s, v",
)


def _fitted_best(spark: SparkSession, d: str) -> DataFrame:
    """The choice of the published formula, and of the edge share, when degrees follow the fit."""
    edges, vertices = G.word_bigram(spark, d)
    rows = []
    with held(edges, vertices):
        for model in ("vertex_share", "edge_share"):
            best, costs = cost.choose_threshold(edges, vertices, 16, model, THETAS, "power_law")
            rows.append((model, best, round(dict(costs)[best], 2)))
    return spark.createDataFrame(rows, "model string, theta bigint, cost double")


_add(
    "theta_best_power_law",
    _fitted_best,
    f"WITH t AS MATERIALIZED ({SQL['theta_table_power_law']}) "
    + " UNION ALL ".join(f"(SELECT '{m}' AS model, theta, cost_{m} AS cost FROM t ORDER BY cost_{m}, theta NULLS LAST LIMIT 1)" for m in ("vertex_share", "edge_share")),
)


def _power_law(spark: SparkSession, d: str) -> DataFrame:
    fit = cost.power_law_exponents(_histogram("word_bigram", spark, d))
    return fit.select("kind", F.round("slope", 6).alias("slope"), F.round("intercept", 6).alias("intercept"))


_add(
    "power_law_word",
    _power_law,
    f"WITH h AS ({O.histogram('word_bigram')}) SELECT kind, round(regr_slope(ln(n), ln(degree)), 6) AS slope,"
    " round(regr_intercept(ln(n), ln(degree)), 6) AS intercept FROM h WHERE degree > 0 GROUP BY kind",
)

# ---- rivals ----------------------------------------------------------------------------------------------------------------


def _rival(how: Callable, spark: SparkSession, d: str) -> DataFrame:
    edges, vertices = G.part_chain(spark, d)
    n = vertices.count()
    start = vertices.select("node", F.lit(1.0 / n).alias("val"))
    return _ranks(how(al.stochastic(edges), start, A.rank_algebra(0.85, n), iters=8))


for _name, _how in (("reshuffle", rivals.reshuffle), ("vertexcut", rivals.vertex_cut), ("vertexcentric", rivals.vertex_centric)):
    _add(f"baseline_{_name}", partial(_rival, _how), O.pagerank("part_chain", 8, DIGITS))
_add("baseline_vertexcut_memory", partial(_rival, partial(rivals.vertex_cut, storage="MEMORY_ONLY", budget_bytes=10**9)), O.pagerank("part_chain", 8, DIGITS))


def _replication(spark: SparkSession, d: str) -> DataFrame:
    row = rivals.replication(G.part_chain(spark, d)[0], 2)
    return row.select("parts", "mirrors", "vertices", F.round("factor", 9).alias("factor"))


_add(
    "replication_factor",
    _replication,
    f"WITH {O.graph('part_chain')}, p AS (SELECT (src % 2) * 2 + dst % 2 AS part, src AS node FROM e UNION SELECT (src % 2) * 2 + dst % 2, dst FROM e)"
    " SELECT 4 AS parts, count(*) AS mirrors, count(DISTINCT node) AS vertices, round(count(*) / count(DISTINCT node)::DOUBLE, 9) AS factor FROM p",
)


def _io_methods(spark: SparkSession, d: str) -> DataFrame:
    """Elements of one round of each method on one graph: vectors alone against matrix and vector."""
    edges, vertices = G.part_chain(spark, d)
    rows = []
    with held(edges, vertices):
        for method in experiments.METHODS:
            h = experiments._run(edges, vertices, method, 4, 1)[0].history[0]
            rows.append((method, h.read, h.written, h.exchanged))
    return spark.createDataFrame(rows, "method string, read bigint, written bigint, exchanged bigint")


_cut = f"{O.block('md5', 'src', 2)} * 2 + {O.block('md5', 'dst', 2)}"
_add(
    "io_all_methods",
    _io_methods,
    f"WITH {O.graph('part_chain')}, bb AS (SELECT 4 AS b), {O.placements(experiments.THETA)}, cut AS (SELECT DISTINCT src, dst, {_cut} AS part FROM e),"
    " mi AS (SELECT (SELECT count(*) FROM (SELECT DISTINCT part, src FROM cut)) + (SELECT count(*) FROM (SELECT DISTINCT part, dst FROM cut)) AS copies),"
    " x AS (SELECT 'horizontal' AS method, 4 * n AS read, n AS written, 0 AS exchanged FROM c UNION ALL SELECT 'vertical', n, n, 2 * off FROM c, pv"
    " UNION ALL SELECT 'hybrid', ns + 4 * nd, n, 2 * off FROM c, h, ph UNION ALL SELECT 'reshuffle', m + n, n, 2 * (m + n + off) FROM c, pv"
    " UNION ALL SELECT 'vertex_cut', n, n, 2 * copies FROM c, mi UNION ALL SELECT 'vertex_cut_memory', n, n, 2 * copies FROM c, mi UNION ALL SELECT 'vertex_centric', n, n, 2 * off FROM c, pv)"
    " SELECT method, read::BIGINT AS read, written::BIGINT AS written, exchanged::BIGINT AS exchanged FROM x UNION ALL SELECT 'selected', read, written, exchanged FROM x, c"
    " WHERE method = CASE WHEN power(1 - m::DOUBLE / (n::DOUBLE * n), n::DOUBLE / 4) < 0.5 THEN 'horizontal' ELSE 'vertical' END",
)


def _differences(spark: SparkSession, d: str) -> DataFrame:
    """Largest difference of each method's state from the unpartitioned product after two rounds: none over 1e-12."""
    edges, vertices = G.part_chain(spark, d)
    rows = []
    with held(edges, vertices):
        n = vertices.count()
        state, cells = vertices.select("node", F.lit(1.0 / n).alias("val")), al.stochastic(edges)
        for _ in range(2):
            state = reliable(reference(cells, state, A.rank_algebra(0.85, n)))
        for method in experiments.METHODS:
            gap = rivals.compare_states(experiments._run(edges, vertices, method, 4, 2)[0].state, state)
            rows.append((method, gap < 1e-12))
    return spark.createDataFrame(rows, "method string, agrees boolean")


_add("state_differences", _differences, f"SELECT method, true AS agrees FROM (VALUES {', '.join(f'({m!r})' for m in experiments.METHODS)}) q(method)")


def _needed(spark: SparkSession, d: str) -> DataFrame:
    """The ledger when a heavy element goes to those row blocks only that have a cell of it."""
    edges, vertices = G.supply_sym(spark, d)
    start = vertices.select("node", F.lit(1.0).alias("val"))
    found = loop.run(edges, vertices, start, A.product_algebra(), "hybrid", 16, "md5", 16, max_iter=1, copy="needed")
    return found.history_frame().select("read", "written", "exchanged")


_add(
    "io_measured_needed_supply_sym",
    _needed,
    f"WITH {O.graph('supply_sym')}, bb AS (SELECT 16 AS b), {O.placements(16)}, r AS (SELECT count(*) AS copies FROM (SELECT DISTINCT src, {O.block('md5', 'dst', 16)} FROM e JOIN d ON src = s WHERE k >= 16))"
    " SELECT ns + copies AS read, n AS written, 2 * off AS exchanged FROM c, h, ph, r",
)


def _topk(spark: SparkSession, d: str) -> DataFrame:
    edges, vertices = G.supply_sym(spark, d)
    start = vertices.select("node", F.lit(1).cast("bigint").alias("val"))
    found = loop.run(edges, vertices, start, A.count_algebra(), "vertical", 4, max_iter=2)
    return found.state.select("node", F.col("val").alias("walks")).orderBy(F.desc("walks"), "node").limit(20)


_add(
    "topk_rank",
    _topk,
    O.chain(
        f"{O.graph('supply_sym')}, m AS (SELECT * FROM e)",
        "SELECT node, 1::BIGINT AS val FROM v",
        "SELECT x.node, coalesce(acc, 0)::BIGINT AS val FROM v x " + O.FOLDED.format(fold="sum(o.val)"),
        2,
        "SELECT node, val AS walks FROM {last} ORDER BY walks DESC, node LIMIT 20",
    ),
)

# ---- experiments -----------------------------------------------------------------------------------------------------------


def _experiment(name: str, spark: SparkSession, d: str) -> DataFrame:
    """The whole workload; what depends on the machine is left out of the rows that SQL must give."""
    return getattr(experiments, name)(spark, d).drop("seconds", "moved_bytes", "is_fastest")


_growing = O.growing("part_chain", experiments.FRACTIONS, experiments.WORKERS, experiments.BUDGET_BYTES, experiments.THETA)
_add("exp_growing", partial(_experiment, "growing"), f"SELECT 'part_chain' AS graph, * FROM ({_growing})")
_add("exp_density", partial(_experiment, "density"), O.densities(experiments.GRAPHS, (4, 16, 64), THETAS))
_add(
    "exp_threshold",
    partial(_experiment, "threshold"),
    f"WITH m AS ({_sweep_sql('supply_sym', 'md5')}), t AS ({O.thetas('supply_sym', 16, THETAS)}) SELECT m.theta, measured::BIGINT AS elements, cost_vertex_share AS vertex_share,"
    " cost_edge_share AS edge_share, cost_row_conditional AS row_conditional, measured = (SELECT min(measured) FROM m) AS moves_least FROM m JOIN t ON m.theta IS NOT DISTINCT FROM t.theta",
)
_add(
    "exp_balance",
    lambda spark, d: experiments.balance(spark, d).select("workers", *[F.round(c, 9).alias(c) for c in ("cells", "partials", "last_reducer")], "largest"),
    " UNION ALL ".join(
        f"SELECT * FROM (WITH {O.graph('cust_part_sym')}, x AS (SELECT {O.block('md5', 'src', w)} AS cb, {O.block('md5', 'dst', w)} AS rb, dst FROM e),"
        " k AS (SELECT cb, count(*) AS edges FROM x GROUP BY cb), r AS (SELECT cb, count(*) AS rows FROM (SELECT DISTINCT cb, rb, dst FROM x) GROUP BY cb), l AS (SELECT rb, count(*) AS n FROM x GROUP BY rb)"
        f" SELECT {w}::INT AS workers, round(max(edges) / median(edges)::DOUBLE, 9) AS cells, round((SELECT max(rows) / median(rows)::DOUBLE FROM r), 9) AS partials,"
        " round((SELECT max(n) / median(n)::DOUBLE FROM l), 9) AS last_reducer, max(edges) AS largest FROM k)"
        for w in (4, 8, 16, 32, 64)
    ),
)
_add(
    "exp_engines",
    partial(_experiment, "engines"),
    " UNION ALL ".join(
        f"SELECT * FROM (WITH {O.fraction_of('part_chain', f)} SELECT {f}::DOUBLE AS fraction, (SELECT count(*) FROM e) AS edges, (SELECT count(*) FROM v) AS vertices, engine, true AS agrees"
        " FROM (VALUES ('columns, memory'), ('columns, storage'), ('arrow, memory')) q(engine))"
        for f in experiments.FRACTIONS
    ),
)
_add("exp_scaling", lambda spark, d: experiments.scaling(spark, d).drop("seconds"))


def _largest(spark: SparkSession, d: str) -> DataFrame:
    """Who does the largest graph in the same memory, and how many times as large it is."""
    return experiments.largest(experiments.growing(spark, d, iters=1))


_add(
    "exp_largest",
    _largest,
    f"WITH g AS ({_growing}), p AS (SELECT method, coalesce(max(edges) FILTER (status = 'done'), 0) AS edges FROM g GROUP BY method)"
    " SELECT method, edges, round((SELECT max(edges) FROM p) / nullif(edges, 0)::DOUBLE, 6) AS ratio FROM p",
)


def _by_type(spark: SparkSession, d: str) -> DataFrame:
    """Walk counts ranked inside each kind of vertex; the kind is the tag of the id."""
    found = loop.run(*G.supply_sym(spark, d), G.supply_sym(spark, d)[1].select("node", F.lit(1).cast("bigint").alias("val")), A.count_algebra(), "vertical", 4, max_iter=1)
    kind = F.floor(F.col("node") / G.TAG).cast("int")
    w = Window.partitionBy("kind").orderBy(F.desc("walks"), "node")
    rows = found.state.select("node", kind.alias("kind"), F.col("val").alias("walks"))
    return rows.withColumn("place", F.row_number().over(w)).filter("place <= 10")


_add(
    "rank_by_type",
    _by_type,
    f"WITH {O.graph('supply_sym')}, x AS (SELECT dst AS node, (dst // {O.TAG})::INT AS kind, count(*) AS walks FROM e GROUP BY dst)"
    " SELECT * FROM (SELECT node, kind, walks, row_number() OVER (PARTITION BY kind ORDER BY walks DESC, node) AS place FROM x) WHERE place <= 10",
)

# ---- streaming -------------------------------------------------------------------------------------------------------------


def _stream(make: Callable[[DataFrame], DataFrame], mode: str, spark: SparkSession, d: str) -> DataFrame:
    return streams.run_to_end(make(streams.event_stream(spark, f"{d}/events.parquet*")), mode)


def _by_day(events: DataFrame, window: Callable[[DataFrame], DataFrame]) -> DataFrame:
    return window(events).select(F.date_format("start", "yyyy-MM-dd").alias("start"), "event_type", "n")


_tumble = "SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"
_add("stream_tumbling", partial(_stream, partial(_by_day, window=streams.tumbling), "complete"), f"SELECT strftime(start, '%Y-%m-%d') AS start, event_type, n FROM ({_tumble})")
_add(
    "stream_sliding",
    partial(_stream, partial(_by_day, window=streams.sliding), "complete"),
    f"SELECT strftime(s, '%Y-%m-%d') AS start, event_type, sum(n)::BIGINT AS n FROM (SELECT start AS s, event_type, n FROM ({_tumble})"
    f" UNION ALL SELECT start - INTERVAL 1 DAY, event_type, n FROM ({_tumble})) GROUP BY 1, 2",
)
_add(
    "stream_session",
    partial(_stream, lambda e: streams.sessions(e).select("user_id", "n", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start")), "complete"),
    # a session goes on while the next event comes before the gap after the last one has passed
    "WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),"
    " s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)"
    " SELECT user_id, count(*) AS n, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start FROM s GROUP BY user_id, k",
)
_add("stream_dedupe", partial(_stream, lambda e: streams.first_seen(e).select("event_id"), "append"), "SELECT DISTINCT event_id FROM events")
_add("stream_degrees", partial(_stream, streams.running_degrees, "complete"), "SELECT user_id AS node, count(*) AS deg FROM events GROUP BY 1")


def _stateful(spark: SparkSession, d: str) -> DataFrame:
    """The latest degree of each user that the state of our own gave out."""
    rows = _stream(streams.stateful_degrees, "update", spark, d)
    return rows.groupBy("node").agg(F.max_by("deg", "batch").alias("deg"))


_add("stream_stateful_degrees", _stateful, SQL["stream_degrees"])
def _windowed(spark: SparkSession, d: str) -> DataFrame:
    edges = _stream(streams.windowed_edges, "complete", spark, d)
    return edges.groupBy("src").agg(F.sum("w").cast("bigint").alias("events"), F.count("*").alias("edges"))


_add(
    "stream_windowed_edges",
    _windowed,
    "SELECT user_id AS src, sum(w)::BIGINT AS events, count(*) AS edges FROM (SELECT user_id, date_trunc('day', ts), event_type, count(*) AS w FROM events GROUP BY ALL) GROUP BY 1",
)


def _with_ranks(spark: SparkSession, d: str) -> DataFrame:
    """Events beside the rank that the last analysis gave their user."""
    found = al.pagerank(*G.user_trans(spark, d), iters=2, placement="horizontal", b=4)
    return _stream(lambda e: streams.with_ranks(e, found.state).select("event_id", F.round("rank", DIGITS).alias("rank")), "append", spark, d)


_add("stream_with_ranks", _with_ranks, f"SELECT event_id, rank FROM events LEFT JOIN ({O.pagerank('user_trans', 2, DIGITS)}) r ON user_id = node")


def _late(spark: SparkSession, d: str) -> DataFrame:
    """The second half of the month comes first, then the first half: rows in time per day, and the late ones counted."""
    folder = f"{shared_folder(spark)}/late-{uuid.uuid4().hex}"
    rows = spark.read.parquet(f"{d}/events.parquet")
    for k, half in enumerate(("ts >= timestamp_ntz '2024-01-16 00:00:00'", "ts < timestamp_ntz '2024-01-16 00:00:00'")):
        rows.filter(half).coalesce(1).write.mode("append").parquet(f"{folder}/half={k}")
        time.sleep(1.1)  # files are taken in the order of their times
    in_time, late = streams.split_late(streams.event_stream(spark, f"{folder}/half=*"), f"{folder}/out")
    days = in_time.groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("n"))
    return days.union(late.agg(F.lit("late").alias("day"), F.count("*").alias("n")))


_add(
    "stream_late",
    _late,
    "WITH m AS (SELECT max(ts) - INTERVAL 1 HOUR AS mark FROM events WHERE ts >= TIMESTAMP '2024-01-16'), x AS (SELECT ts, ts < TIMESTAMP '2024-01-16' AND ts < mark AS late FROM events, m)"
    " SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) AS n FROM x WHERE NOT late GROUP BY 1 UNION ALL SELECT 'late', count(*) FROM x WHERE late",
)

"""Placements against each other, against hand values, and against the plan they must have."""

import pytest
from pyspark.sql import functions as F

from blockmv import experiments
from blockmv.functions import algebra as A
from blockmv.operators import algorithms as al
from blockmv.operators import baselines, loop
from blockmv.operators.multiply import heavy_rows, multiply, reference
from blockmv.plans import blocks, cost, guard
from blockmv.plans.session import loop_settings, reliable
from blockmv.sources import graphs

RANKS = [0.189930616, 0.079786688, 0.079786688, 0.223303808, 0.113159880, 0.314032320]


def pairs(node, b):
    return F.floor((node - 1) / 2).cast("int")


def values(df):
    return {r["node"]: r["val"] for r in df.collect()}


@pytest.fixture(scope="module")
def toy(spark):
    e, v = graphs.toy6(spark)
    return e.cache(), v.cache()


@pytest.mark.parametrize(("placement", "theta", "total"), [("horizontal", 0, 24), ("vertical", None, 28), ("hybrid", 2, 22), ("hybrid", 3, 26), ("hybrid", 0, 24), ("hybrid", 10**6, 28)])
def test_ranks_and_ledger_of_six_vertices(toy, placement, theta, total):
    out = al.pagerank(*toy, iters=2 if placement == "hybrid" else 8, placement=placement, b=3, psi=pairs, theta=theta)
    assert {h.total for h in out.history} == {total}
    if len(out.history) == 8:
        got = values(out.state)
        assert [got[k] for k in range(1, 7)] == pytest.approx(RANKS, abs=1e-9)


def test_block_counts(toy):
    rows = {(r["rb"], r["cb"]): r["edges"] for r in blocks.block_statistics(toy[0], 3, pairs, 2).collect()}
    assert [[rows.get((i, j), 0) for j in range(3)] for i in range(3)] == [[1, 1, 1], [2, 0, 1], [1, 2, 1]]


def test_theta_costs(toy):
    hist = cost.degree_histogram(*toy)
    table = cost.theta_table(hist, 6, 3, (0, 1, 2, 3, 4)).orderBy("theta").collect()
    assert [round(r["cost_vertex_share"], 4) for r in table] == [24, 24, 24.2222, 23.8765, 23.5556]
    best, _ = cost.choose_threshold(*toy, 3, thetas=(0, 1, 2, 3, 4, None))
    assert best == 2


@pytest.mark.parametrize("theta", [0, 2, None])
def test_matrix_stays_where_it_is(spark, toy, theta):
    bg = blocks.prepartition(al.stochastic(toy[0]), toy[1], 3, pairs, theta)
    with loop_settings(spark, 3):
        state = reliable(bg.nodes.withColumn("val", F.lit(1 / 6)))
        for _ in range(2):
            made = multiply(bg, state, A.rank_algebra(0.85, 6)).state
            assert guard.matrix_exchanges(made) == []
            state = reliable(made)
    bg.release()


def test_guard_sees_a_moved_matrix(spark, toy):
    with loop_settings(spark, 3):
        cells = blocks.with_blocks(toy[0], 3, pairs).cache()
        moved = cells.repartition(3, "src").join(toy[1].hint("merge"), F.col("src") == F.col("node"))
        assert guard.matrix_exchanges(moved)


@pytest.mark.parametrize("copy", ["replicate", "broadcast", "needed", "chunked"])
def test_ways_to_copy(toy, copy):
    out = al.pagerank(*toy, iters=2, placement="horizontal", b=3, psi=pairs, copy=copy)
    # each of six elements goes to three row blocks, or to those that have an edge of it
    assert {h.read for h in out.history} == {10 if copy == "needed" else 18}
    assert {h.written for h in out.history} == {6}
    want = al.pagerank(*toy, iters=2, placement="vertical", b=3, psi=pairs)
    assert baselines.compare_states(out.state, want.state) < 1e-15


def test_unknown_settings_are_refused(toy):
    for how in ({"placement": "diagonal"}, {"dangling": "drop"}, {"placement": "horizontal", "copy": "never"}, {"placement": "vertical", "state": "paper"}):
        with pytest.raises(ValueError, match="unknown"):
            al.pagerank(*toy, iters=1, b=3, **how)


def test_broadcast_is_size_checked(spark, toy, monkeypatch):
    monkeypatch.setattr("blockmv.operators.multiply.MAX_BROADCAST", 3)
    bg = blocks.prepartition(toy[0], toy[1], 3, pairs, 0)
    with pytest.raises(ValueError, match="too many to broadcast"):
        heavy_rows(bg, bg.nodes.withColumn("val", F.lit(1.0)), A.product_algebra(), "broadcast")


def test_hops_distances_and_labels(toy):
    assert values(al.hop_levels(*toy, source=1, placement="vertical", b=3).state) == {1: 0, 2: 1, 3: 1, 5: 1, 4: 2, 6: 2}
    out = al.shortest_paths(*toy, source=1, placement="hybrid", b=2, theta=2)
    assert values(out.state) == {1: 0, 2: 1, 3: 1, 5: 1, 4: 2, 6: 2}
    assert out.status == "converged"
    assert set(values(al.components(*toy, b=3, placement="vertical").state).values()) == {1}
    assert set(values(al.reachable(*toy, source=4, b=3, placement="vertical").state).values()) == {True}


def test_long_chains_settle(spark):
    nodes = spark.range(104).withColumnRenamed("id", "node")
    edges = spark.range(103).selectExpr("id AS src", "id + 1 AS dst", "1.0D AS w").cache()
    assert values(al.hop_levels(edges, nodes.cache(), source=0, b=1, placement="vertical").state) == {k: k for k in range(104)}
    with pytest.raises(RuntimeError):
        al.components(edges, nodes, max_iter=2, b=1, placement="vertical")
    with pytest.raises(RuntimeError):
        al.reachable(edges, nodes, source=0, max_iter=3, b=1, placement="vertical")


def test_negative_weights_are_refused(spark, toy):
    with pytest.raises(ValueError, match="negative"):
        al.shortest_paths(toy[0].withColumn("w", F.lit(-1.0)), toy[1], source=1)


def test_isolated_dangling_and_empty(spark):
    edges = spark.createDataFrame([(1, 2, 1.0)], "src bigint, dst bigint, w double")
    nodes = spark.createDataFrame([(1,), (2,), (3,)], "node bigint")
    leak = al.pagerank(edges, nodes, iters=3, placement="vertical", b=5)
    assert set(values(leak.state)) == {1, 2, 3}
    assert sum(values(leak.state).values()) < 1
    even = al.pagerank(edges, nodes, iters=2, placement="vertical", b=2, dangling="uniform")
    assert sum(values(even.state).values()) == pytest.approx(1.0)
    none = al.pagerank(edges.limit(0), nodes, iters=1, placement="hybrid", theta=1, b=2)
    assert list(values(none.state).values()) == pytest.approx([0.05] * 3)
    assert values(al.components(edges, nodes, b=2, placement="vertical").state) == {1: 1, 2: 1, 3: 3}


def test_stops_and_resumes(spark, toy, tmp_path):
    cells, folder = al.stochastic(toy[0]), f"file://{tmp_path}/v"
    bg = blocks.prepartition(cells, toy[1], 3, pairs, 2)
    start = toy[1].withColumn("val", F.lit(1 / 6))
    loop.iterate(bg, start, A.rank_algebra(0.85, 6), 5, state="storage", path=folder)
    rest = loop.resume(bg, spark, folder, 5, A.rank_algebra(0.85, 6), 3)
    got = values(rest.state)
    assert [got[k] for k in range(1, 7)] == pytest.approx(RANKS, abs=1e-9)
    tol = loop.iterate(bg, start, A.rank_algebra(0.85, 6), 200, tol=1e-3, norm="sum")
    assert tol.status == "converged"
    assert tol.history[-1].delta <= 1e-3 < tol.history[-2].delta
    late = loop.iterate(bg, start, A.rank_algebra(0.85, 6), 50, budget_seconds=0.0)
    assert late.status == "o.o.t."
    assert len(late.history) == 1
    bg.release()


def test_rivals_agree_and_run_out_of_memory(toy):
    cells = al.stochastic(toy[0])
    start = toy[1].withColumn("val", F.lit(1 / 6))
    alg = A.rank_algebra(0.85, 6)
    want = reference(cells, reference(cells, start, alg), alg)
    for out in (baselines.reshuffle(cells, start, alg, 2), baselines.vertex_cut(cells, start, alg, 2), baselines.vertex_centric(cells, start, alg, 2)):
        assert baselines.compare_states(out.state, want) < 1e-15
    assert baselines.vertex_cut(cells, start, alg, 2, storage="MEMORY_ONLY", budget_bytes=1).status == "o.o.m."
    assert baselines.vertex_centric(cells, start, alg, 2, budget_bytes=1).status == "o.o.m."
    assert baselines.max_processed({"a": {5: "done", 9: "o.o.m."}}) == {"a": 5}


def test_repeated_edges(spark):
    e = spark.createDataFrame([(1, 2, 3.0), (1, 2, 1.0), (2, 2, 1.0), (None, 2, 1.0)], "src bigint, dst bigint, w double")
    get = lambda *a, **k: sorted(tuple(r) for r in al.prepare(e, *a, **k).collect())
    assert get() == [(1, 2, 1.0), (2, 2, 1.0)]
    assert get("sum") == [(1, 2, 4.0), (2, 2, 1.0)]
    assert get("min", drop_loops=True) == [(1, 2, 1.0)]
    assert len(get("keep")) == 3


def test_settings_are_put_back(spark):
    before = spark.conf.get("spark.sql.adaptive.enabled")
    with loop_settings(spark, 7):
        assert spark.conf.get("spark.sql.shuffle.partitions") == "7"
    assert (spark.conf.get("spark.sql.adaptive.enabled"), spark.conf.get("spark.sql.shuffle.partitions")) == (before, "4")


def test_rounds_leave_one_checkpoint(spark, toy):
    import glob

    from blockmv.plans.session import shared_folder

    count = lambda: len(glob.glob(shared_folder(spark).removeprefix("file://") + "/*/rdd-*"))
    al.pagerank(*toy, iters=1, placement="vertical", b=2)
    before = count()
    out = al.pagerank(*toy, iters=5, placement="vertical", b=2)
    assert count() == before + 1
    assert len(values(out.state)) == 6


@pytest.mark.parametrize("analysis", [lambda e, v, **how: al.power_iteration(e, v, iters=3, **how)[1], lambda e, v, **how: al.pagerank(e, v, iters=3, dangling="uniform", **how)])
def test_blocks_are_laid_out_once(toy, monkeypatch, analysis):
    made = []
    monkeypatch.setattr(loop, "prepartition", lambda *a, **k: made.append(1) or blocks.prepartition(*a, **k))
    out = analysis(*toy, placement="hybrid", b=3, psi=pairs, theta=2)
    assert len(made) == 1
    assert len(out.history) == 3


def test_dominant_eigenvalue(spark):
    import numpy as np

    m = np.zeros((7, 7))
    for a, b in graphs.TOY:
        m[b, a] = 1.0
    size, out = al.power_iteration(*graphs.toy6(spark), iters=60, placement="vertical", b=2)
    assert size == pytest.approx(max(abs(np.linalg.eigvals(m))), abs=1e-6)
    assert sum(x * x for x in values(out.state).values()) == pytest.approx(1.0)


@pytest.mark.parametrize("theta", [0, 2, None])
def test_merging_gives_what_hashing_gives(spark, toy, theta):
    """A task that may hash nothing merges, in the same placement and without moving a cell."""
    cells, start = al.stochastic(toy[0]), toy[1].withColumn("val", F.lit(1 / 6))
    states = []
    for hashed in (0, 10**6):
        bg = blocks.prepartition(cells, toy[1], 3, pairs, theta)
        bg.hashed = hashed
        with loop_settings(spark, 3):
            made = multiply(bg, reliable(bg.nodes.withColumn("val", F.lit(1 / 6))), A.rank_algebra(0.85, 6)).state
            plan = made._jdf.queryExecution().executedPlan().toString()
            assert ("ShuffledHashJoin" in plan) == (hashed > 0)
            assert guard.matrix_exchanges(made) == []
        states.append(values(loop.iterate(bg, start, A.rank_algebra(0.85, 6), 2).state))
        bg.release()
    assert states[0] == pytest.approx(states[1])


def test_blocks_follow_from_memory(toy):
    out = al.pagerank(*toy, iters=1, placement="vertical", b=loop.Workers(2, 64))
    assert out.b == 3  # 64 bytes are 4 elements: 6 vertices, twice each, need 3 blocks
    assert al.pagerank(*toy, iters=1, placement="vertical", b=loop.Workers(2, 1 << 20)).b == 2


def test_ledgers_of_rivals(toy):
    """b = 3: 10 edges, 6 vertices, 11 - 4 = 7 off-block partial results; two of a block's own."""
    cells, start, alg = al.stochastic(toy[0]), toy[1].withColumn("val", F.lit(1 / 6)), A.rank_algebra(0.85, 6)
    want = {(pairs_of(a), b) for a, b in graphs.TOY}
    off = sum(c != pairs_of(b) for c, b in want)
    h = baselines.reshuffle(cells, start, alg, 1, 3, psi=pairs).history[0]
    assert (h.read, h.written, h.exchanged) == (16, 6, 2 * (16 + off))
    assert h.moved_bytes > 0
    h = baselines.vertex_centric(cells, start, alg, 1, 3, psi=pairs).history[0]
    assert (h.read, h.written, h.exchanged, h.diagonal) == (6, 6, 2 * off, len(want) - off)
    h = baselines.vertex_cut(cells, start, alg, 1, 2, psi="mod").history[0]
    mirrors = {(a % 2 * 2 + b % 2, a) for a, b in graphs.TOY}
    back = {(a % 2 * 2 + b % 2, b) for a, b in graphs.TOY}
    assert h.exchanged == 2 * (len(mirrors) + len(back))


def pairs_of(node):
    return (node - 1) // 2


def test_seeds_as_a_table(spark, toy):
    ids = spark.createDataFrame([(2,), (6,)], "node bigint")
    a = al.random_walk_with_restart(*toy, ids, 2, iters=4, placement="hybrid", b=2, theta=2)
    b = al.random_walk_with_restart(*toy, F.col("node").isin(2, 6), 2, iters=4, placement="vertical", b=3)
    assert values(a.state) == pytest.approx(values(b.state))


def test_largest_graph_of_each_method(spark):
    rows = [("x", 5, "done"), ("x", 9, "o.o.m."), ("y", 9, "done"), ("z", 5, "o.o.m.")]
    got = experiments.largest(spark.createDataFrame(rows, "method string, edges bigint, status string"))
    assert {r["method"]: (r["edges"], r["ratio"]) for r in got.collect()} == {"x": (5, 1.8), "y": (9, 1.0), "z": (0, None)}


def test_memory_stops_those_that_hold_edges(spark):
    got = experiments.growing(spark, "/root/testdata/sf0.001", iters=1, budget=4096, fractions=(0.5, 1.0), methods=("vertical", "hybrid", "vertex_cut_memory", "vertex_centric", "reshuffle"))
    by = {(r["method"], r["fraction"]): r for r in got.collect()}
    for (method, f), r in by.items():
        assert (r["status"] == "o.o.m.") == (r["held_bytes"] > 4096), method
        assert (r["elements"] > 0) == (r["status"] == "done")
    assert by["hybrid", 1.0]["status"] == "done"
    assert by["vertex_centric", 1.0]["status"] == "o.o.m."
    assert {r["edges"] for r in experiments.largest(got).filter("method = 'hybrid'").collect()} == {by["hybrid", 1.0]["edges"]}


def test_a_folder_of_one_machine_is_refused_on_clusters(spark, monkeypatch):
    from blockmv.plans import session

    class Elsewhere:
        conf = type("C", (), {"get": staticmethod(lambda *a: None)})
        sparkContext = type("S", (), {"master": "spark://host:7077", "getCheckpointDir": staticmethod(lambda: None)})  # noqa: N815

    with pytest.raises(RuntimeError, match="checkpoint"):
        session.shared_folder(Elsewhere)

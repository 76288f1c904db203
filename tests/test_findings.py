"""Inputs on which queries once failed or differed from their SQL."""

from collections import Counter

import duckdb
import pytest

import __spark_entry__ as entry


def _rows(spark, name, folder, *tables):
    """The query's rows and those of its SQL over the same files."""
    got = Counter(tuple(r) for r in entry.queries()[name](spark, str(folder)).collect())
    con = duckdb.connect()
    for t in tables:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
    return got, Counter(con.execute(entry.oracle_sql()[name]).fetchall())


def _write(folder, table, sql):
    duckdb.connect().execute(f"COPY ({sql}) TO '{folder}/{table}.parquet'")


def test_interval_join_rounds_as_its_sql(spark, tmp_path):
    times = ("00:00:00.4", "00:00:00.6", "00:00:01.5", "00:00:02.5", "00:59:59.7", "01:00:00.5", "01:00:01.4", "01:00:02.6", "02:00:00.5")
    rows = ", ".join(f"({k}, TIMESTAMP '2024-01-01 {t}', {k % 2})" for k, t in enumerate(times * 2))
    _write(tmp_path, "events", f"SELECT event_id::BIGINT AS event_id, ts, user_id::BIGINT AS user_id FROM (VALUES {rows}) q(event_id, ts, user_id)")
    got, want = _rows(spark, "rel_interval_join", tmp_path, "events")
    assert got == want


def test_edge_formats_sums_beyond_a_long(spark, tmp_path):
    _write(tmp_path, "lineitem", "SELECT 4000000000000000000 - i AS l_suppkey, i AS l_partkey FROM (SELECT unnest(range(5)) AS i)")
    got, want = _rows(spark, "edge_formats", tmp_path, "lineitem")
    assert got == want and max(int(r[2]) for r in got) > 2**63


def test_theta_best_reads_its_source_once(spark, monkeypatch):
    from blockmv import queries
    from blockmv.sources import graphs

    built, read = [], spark.sparkContext.accumulator(0)

    def build(session, folder):
        built.append(folder)
        edges, _ = graphs.toy6(session)
        seen = edges.rdd.map(lambda r: (read.add(1), tuple(r))[1]).toDF("src bigint, dst bigint, w double")
        return seen, graphs.ends(seen)

    monkeypatch.setitem(graphs.BUILDERS, "word_bigram", build)
    assert queries.QUERIES["theta_best_word_bigram"](spark, "").count() == 3
    assert len(built) == 1 and read.value == len(graphs.TOY)


def test_chunked_copies_go_where_cells_wait(spark):
    from blockmv.functions import algebra as A
    from blockmv.operators import loop
    from blockmv.sources import graphs

    edges, vertices = graphs.toy6(spark)
    start = vertices.selectExpr("node", "cast(node as double) as val")
    found = {c: loop.run(edges, vertices, start, A.product_algebra(), "horizontal", 6, "mod", max_iter=2, copy=c) for c in ("replicate", "chunked")}
    rows = [sorted(map(tuple, r.state.collect())) for r in found.values()]
    assert rows[0] == rows[1]
    assert found["replicate"].history[-1].read == 36 and found["chunked"].history[-1].read == len(graphs.TOY)


def test_knn_searches_from_the_walk_only_and_breaks_ties_by_id(spark, tmp_path):
    from pyspark.sql import functions as F

    from blockmv.sources import graphs

    vector = "list_transform(range(4), lambda j: ((hash(i % 40 * 10 + j) % 1000)::FLOAT / 500 - 1))"
    _write(tmp_path, "embeddings", f"SELECT i AS vec_id, {vector}::FLOAT[] AS embedding, 0 AS label FROM (SELECT unnest(range(120)) AS i)")
    got, want = _rows(spark, "rwr_knn", tmp_path, "embeddings")
    assert got == want
    some = {tuple(r) for r in graphs.knn(spark, str(tmp_path), seeds=F.col("vec_id") < 3, steps=2)[0].collect()}
    every = {tuple(r) for r in graphs.knn(spark, str(tmp_path))[0].collect()}
    assert some < every and len(every) == 1200 and len(some) % 10 == 0


@pytest.mark.parametrize("copy", ["replicate", "needed", "chunked"])
@pytest.mark.parametrize("placement", ["horizontal", "vertical", "hybrid"])
def test_many_small_blocks_share_tasks(spark, placement, copy):
    from blockmv.functions import algebra as A
    from blockmv.operators import loop
    from blockmv.sources import graphs

    edges, vertices = graphs.toy6(spark)
    start = vertices.selectExpr("node", "cast(node as double) as val")
    with loop.laid_out(edges, vertices, placement, loop.Workers(2, 16), "mod", 2) as (bg, _, _):
        assert bg.b == 12 and {x.rdd.getNumPartitions() for x in bg.held} == {4}
        many = loop.iterate(bg, start, A.product_algebra(), 2, copy=copy)
        assert {x.rdd.getNumPartitions() for x in (many.state, bg.nodes)} == {4}
    one = loop.run(edges, vertices, start, A.product_algebra(), placement, 12, "mod", 2, max_iter=2, copy=copy)
    assert sorted(map(tuple, many.state.collect())) == sorted(map(tuple, one.state.collect()))
    same = ("read", "written", "exchanged", "diagonal")
    assert [[getattr(r, x) for x in same] for r in many.history] == [[getattr(r, x) for x in same] for r in one.history]


def _counting(monkeypatch, spark):
    """The toy graph as one of the builders, and a list that grows with each pass that makes shares of cells."""
    from blockmv.operators import algorithms
    from blockmv.sources import graphs

    made, plain = [], algorithms.stochastic
    monkeypatch.setattr(algorithms, "stochastic", lambda *a, **k: made.append(1) or plain(*a, **k))
    monkeypatch.setitem(graphs.BUILDERS, "toy", lambda session, folder: graphs.toy6(session))
    return made


def test_density_makes_shares_and_degrees_once(spark, monkeypatch):
    from blockmv import experiments
    from blockmv.operators import loop
    from blockmv.plans import cost
    from blockmv.sources import graphs

    made, looked, plain = _counting(monkeypatch, spark), [], cost.degree_histogram
    monkeypatch.setattr(cost, "degree_histogram", lambda *a: looked.append(1) or plain(*a))
    rows = experiments.density(spark, "", ["toy"], (2, 5), 1).collect()
    assert (len(made), len(looked), len(rows)) == (1, 1, 2 * len(loop.PLACEMENTS))
    toy = graphs.toy6(spark)
    for r in rows:
        assert r["elements"] == experiments._run(*toy, r[3], r["b"], 1, "auto")[0].history[-1].total


def test_growing_makes_shares_once_a_subgraph(spark, monkeypatch):
    from blockmv import experiments

    made = _counting(monkeypatch, spark)
    rows = experiments.growing(spark, "", "toy", 1, fractions=(1.0,), methods=("horizontal", "selected", "hybrid", "reshuffle")).collect()
    assert len(made) == 1 and [r["status"] for r in rows] == ["done"] * 4

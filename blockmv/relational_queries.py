"""Surrounding relational operators, one query each, with the SQL that must give the same rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracle as O
from .operators import relational as R
from .plans import blocks
from .sources import graphs as G
from .sources.graphs import table

QUERIES: dict = {}
SQL: dict[str, str] = {}


def _query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return keep


@_query("rel_semi_join", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")
def _semi(spark: SparkSession, d: str) -> DataFrame:
    c, o = table(spark, d, "customer"), table(spark, d, "orders")
    return c.join(o, c["c_custkey"] == o["o_custkey"], "left_semi").select("c_custkey")


@_query("rel_anti_join", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def _anti(spark: SparkSession, d: str) -> DataFrame:
    o, line = table(spark, d, "orders"), table(spark, d, "lineitem")
    return o.join(line, o["o_orderkey"] == line["l_orderkey"], "left_anti").select("o_orderkey")


@_query(
    "rel_full_outer",
    "SELECT coalesce(a.k, b.k) AS nation, coalesce(n_c, 0) AS customers, coalesce(n_s, 0) AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n_c"
    " FROM customer GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS n_s FROM supplier GROUP BY 1) b ON a.k = b.k",
)
def _full(spark: SparkSession, d: str) -> DataFrame:
    a = table(spark, d, "customer").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("a"))
    b = table(spark, d, "supplier").groupBy(F.col("s_nationkey").alias("j")).agg(F.count("*").alias("b"))
    met = a.join(b, F.col("k") == F.col("j"), "full_outer")
    return met.select(F.coalesce("k", "j").alias("nation"), F.coalesce("a", F.lit(0)).alias("customers"), F.coalesce("b", F.lit(0)).alias("suppliers"))


@_query(
    "rel_degree_bands",
    f"WITH {O.graph('supply_sym')}, {O.DEGREES}, b AS (SELECT * FROM (VALUES (0, 8, 'low'), (8, 64, 'middle'), (64, 1000000, 'high')) t(low, high, name))"
    " SELECT name, count(*) AS n FROM g JOIN b ON out_degree >= low AND out_degree < high GROUP BY name",
)
def _bands(spark: SparkSession, d: str) -> DataFrame:
    deg = blocks.out_degrees(G.supply_sym(spark, d)[0])
    bands = spark.createDataFrame([(0, 8, "low"), (8, 64, "middle"), (64, 1_000_000, "high")], "low int, high int, name string")
    return R.in_bands(deg, F.col("deg"), bands).groupBy("name").agg(F.count("*").alias("n"))


@_query(
    "rel_asof_join",
    "SELECT event_id, (SELECT max(o_totalprice) FROM orders o WHERE o_custkey = user_id AND o_orderdate = (SELECT max(o_orderdate) FROM orders p"
    " WHERE p.o_custkey = user_id AND p.o_orderdate <= ts)) AS price FROM events",
)
def _asof(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").select("event_id", F.col("user_id").alias("k"), "ts")
    o = table(spark, d, "orders").select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("ts"), F.col("o_totalprice").alias("price"))
    return R.asof_join(e, o, "k", "ts", "price").select("event_id", "price")


@_query(
    "rel_interval_join",
    "SELECT a.event_id, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND epoch(b.ts)::BIGINT > epoch(a.ts)::BIGINT"
    " AND epoch(b.ts)::BIGINT <= epoch(a.ts)::BIGINT + 3600 GROUP BY 1",
)
def _interval(spark: SparkSession, d: str) -> DataFrame:
    # whole seconds as the SQL's cast makes them: the nearest one, halves to the even one
    seconds = F.bround(F.unix_micros(F.col("ts").cast("timestamp")) / F.lit(1e6)).cast("bigint")
    e = table(spark, d, "events").select("event_id", "user_id", F.timestamp_seconds(seconds).alias("ts"))
    other = e.select("user_id", F.col("ts").alias("later"))
    return R.interval_join(e, other, "user_id", "ts", "later", 3600).groupBy("event_id").agg(F.count("*").alias("n"))


@_query(
    "rel_two_hops",
    f"WITH {O.graph('weblink_sym')} SELECT a.src, b.dst, count(*) AS paths FROM e a JOIN e b ON a.dst = b.src GROUP BY 1, 2",
)
def _hops(spark: SparkSession, d: str) -> DataFrame:
    return R.two_hops(G.weblink_sym(spark, d)[0])


@_query("rel_mutual_edges", f"WITH {O.graph('user_trans')} SELECT src, dst FROM e INTERSECT SELECT dst, src FROM e")
def _mutual(spark: SparkSession, d: str) -> DataFrame:
    return R.mutual(G.user_trans(spark, d)[0])


@_query("rel_removed_edges", f"WITH {O.graph('user_trans')} SELECT src, dst FROM e EXCEPT SELECT dst, src FROM e")
def _removed(spark: SparkSession, d: str) -> DataFrame:
    e = G.user_trans(spark, d)[0]
    return e.select("src", "dst").exceptAll(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


_cells = f"WITH {O.graph('part_chain')}, x AS (SELECT (dst % 4)::INT AS rb, (src % 4)::INT AS cb FROM e)"


@_query("rel_cube_blocks", f"{_cells} SELECT rb, cb, count(*) AS n FROM x GROUP BY CUBE (rb, cb)")
def _cube(spark: SparkSession, d: str) -> DataFrame:
    return blocks.with_blocks(G.part_chain(spark, d)[0], 4, "mod").cube("rb", "cb").agg(F.count("*").alias("n"))


@_query("rel_rollup_blocks", f"{_cells} SELECT rb, cb, count(*) AS n FROM x GROUP BY ROLLUP (rb, cb)")
def _rollup(spark: SparkSession, d: str) -> DataFrame:
    return blocks.with_blocks(G.part_chain(spark, d)[0], 4, "mod").rollup("rb", "cb").agg(F.count("*").alias("n"))


@_query("rel_grouping_sets", f"{_cells} SELECT rb, cb, count(*) AS n FROM x GROUP BY GROUPING SETS ((rb), (cb))")
def _sets(spark: SparkSession, d: str) -> DataFrame:
    x = blocks.with_blocks(G.part_chain(spark, d)[0], 4, "mod")
    return x.groupingSets([[F.col("rb")], [F.col("cb")]], "rb", "cb").agg(F.count("*").alias("n"))


@_query(
    "rel_distinct_and_extremes",
    "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, max(l_quantity) AS most, min(l_quantity) AS least FROM lineitem GROUP BY 1",
)
def _distinct(spark: SparkSession, d: str) -> DataFrame:
    g = table(spark, d, "lineitem").groupBy("l_returnflag")
    return g.agg(F.count_distinct("l_partkey").alias("parts"), F.max("l_quantity").alias("most"), F.min("l_quantity").alias("least"))


@_query("rel_approx_distinct")
def _approx(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("middle"))


@_query("rel_min_by", "SELECT user_id, first(event_type ORDER BY ts, event_id) AS first, last(event_type ORDER BY ts, event_id) AS last FROM events GROUP BY 1")
def _min_by(spark: SparkSession, d: str) -> DataFrame:
    key = F.struct("ts", "event_id")
    return table(spark, d, "events").groupBy("user_id").agg(F.min_by("event_type", key).alias("first"), F.max_by("event_type", key).alias("last"))


@_query(
    "rel_ranks",
    "SELECT c_custkey, rank() OVER w AS r, dense_rank() OVER w AS dr, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment, c_custkey) AS q"
    " FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_mktsegment)",
)
def _ranks(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("c_nationkey").orderBy("c_mktsegment")
    q = Window.partitionBy("c_nationkey").orderBy("c_mktsegment", "c_custkey")
    return table(spark, d, "customer").select("c_custkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(q).alias("q"))


@_query(
    "rel_frames",
    "SELECT event_id, lag(event_id) OVER w AS before, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS day"
    " FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
)
def _frames(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    micros = F.unix_micros(F.col("ts").cast("timestamp"))
    day = Window.partitionBy("user_id").orderBy(micros).rangeBetween(-86_400_000_000, 0)
    return table(spark, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.count("*").over(day).alias("day"))


@_query(
    "rel_top_per_group",
    "SELECT * FROM (SELECT l_suppkey, l_partkey, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_partkey DESC, l_orderkey, l_linenumber) AS rank"
    " FROM lineitem) WHERE rank <= 3",
)
def _top(spark: SparkSession, d: str) -> DataFrame:
    rows = table(spark, d, "lineitem").select("l_suppkey", "l_partkey", "l_orderkey", "l_linenumber")
    return R.top_per_group(rows, "l_suppkey", [F.desc("l_partkey"), F.col("l_orderkey"), F.col("l_linenumber")], 3).select("l_suppkey", "l_partkey", "rank")


@_query("rel_pushed_filter", "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity BETWEEN 10 AND 12 AND l_returnflag IN ('A', 'R')")
def _filter(spark: SparkSession, d: str) -> DataFrame:
    line = table(spark, d, "lineitem")
    return line.filter(F.col("l_quantity").between(10, 12) & F.col("l_returnflag").isin("A", "R")).select("l_orderkey", "l_partkey")


@_query(
    "rel_text_functions",
    "SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host, lower(substr(url, 1, 12)) AS head, length(html) AS size, md5(url) AS digest FROM pages",
)
def _text(spark: SparkSession, d: str) -> DataFrame:
    p = table(spark, d, "pages")
    host = F.regexp_extract("url", "^https?://([^/]+)", 1)
    return p.select("page_id", host.alias("host"), F.lower(F.substring("url", 1, 12)).alias("head"), F.length("html").alias("size"), F.md5(F.col("url").cast("binary")).alias("digest"))


@_query(
    "rel_day_graphs",
    "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, user_id AS src, event_type, count(*) AS n, hour(min(ts)) AS first_hour FROM events GROUP BY 1, 2, 3",
)
def _days(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events")
    day = F.date_format(F.date_trunc("day", "ts"), "yyyy-MM-dd")
    return e.groupBy(day.alias("day"), F.col("user_id").alias("src"), "event_type").agg(F.count("*").alias("n"), F.hour(F.min("ts")).alias("first_hour"))


@_query("rel_json", "SELECT event_id, json_extract(props, '$.k')::INT AS k FROM events")
def _json(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@_query(
    "rel_arrays",
    "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS square, len(embedding) AS n,"
    " round(list_max(embedding)::DOUBLE, 6) AS most FROM embeddings",
)
def _arrays(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "embeddings")
    wide = F.transform("embedding", lambda x: x.cast("double"))
    square = F.aggregate(F.zip_with(wide, wide, lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    return e.select("vec_id", F.round(square, 6).alias("square"), F.size("embedding").alias("n"), F.round(F.array_max("embedding").cast("double"), 6).alias("most"))


@_query(
    "rel_maps",
    "SELECT user_id, sum((event_type = 'purchase')::INT)::BIGINT AS bought, count(DISTINCT event_type) AS kinds FROM events GROUP BY 1",
)
def _maps(spark: SparkSession, d: str) -> DataFrame:
    """Counts per type gathered in a map, read back by key."""
    per = table(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    held = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return held.select("user_id", F.coalesce(F.try_element_at("m", F.lit("purchase")), F.lit(0)).alias("bought"), F.size("m").cast("bigint").alias("kinds"))


@_query("rel_union_distinct", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
def _union(spark: SparkSession, d: str) -> DataFrame:
    a = table(spark, d, "customer").select(F.col("c_nationkey").alias("k"))
    return a.union(table(spark, d, "supplier").select("s_nationkey")).distinct()


@_query("rel_sort_limit", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 50")
def _limit(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(50)


@_query(
    "rel_pivot",
    "SELECT o_orderpriority AS priority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o FROM orders GROUP BY 1",
)
def _pivot(spark: SparkSession, d: str) -> DataFrame:
    p = table(spark, d, "orders").groupBy(F.col("o_orderpriority").alias("priority")).pivot("o_orderstatus", ["F", "O"]).count()
    return p.select("priority", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))



"""Joins, ranks and set operations that graph preparation needs and that Spark has no single operator for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, value: str, bucket: str = "month") -> DataFrame:
    """left plus the last ``value`` of right with the same key at or before ``at`` (the larger value on a tie of times).

    Rows of both sides lie in one sorted window per (key, calendar bucket), so a busy key is cut by time; what was the
    last value of earlier buckets comes from a window over one row per key and bucket.
    """
    l = left.select(key, at, F.struct(*left.columns).alias("row"), F.lit(None).cast(dict(right.dtypes)[value]).alias("v"), F.lit(1).alias("side"))  # noqa: E741
    r = right.select(key, at, F.lit(None).cast(l.schema["row"].dataType).alias("row"), F.col(value).alias("v"), F.lit(0).alias("side"))
    both = l.unionByName(r).withColumn("bucket", F.date_trunc(bucket, F.col(at)))
    order = Window.partitionBy(key, "bucket").orderBy(at, "side", "v").rowsBetween(Window.unboundedPreceding, 0)
    inside = both.withColumn("seen", F.last("v", ignorenulls=True).over(order))
    last = both.filter("side = 0").groupBy(key, "bucket").agg(F.max(F.struct(at, F.col("v"))).alias("m"))
    marks = both.select(key, "bucket").distinct().join(last, [key, "bucket"], "left")
    earlier = Window.partitionBy(key).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    carried = marks.select(key, "bucket", F.last("m.v", ignorenulls=True).over(earlier).alias("carried"))
    met = inside.filter("side = 1").join(carried, [key, "bucket"], "left")
    return met.select("row.*", F.coalesce("seen", "carried").alias(value))


def interval_join(left: DataFrame, right: DataFrame, key: str, at: str, other: str, seconds: int) -> DataFrame:
    """Pairs of equal key with right.other in (left.at, left.at + seconds]: an equi-join on time buckets of that width,
    each left row in its own bucket and the next."""
    slot = lambda c: F.floor(F.unix_seconds(F.col(c).cast("timestamp")) / seconds)
    l = left.withColumn("slot", F.explode(F.array(slot(at), slot(at) + 1)))  # noqa: E741
    r = right.withColumn("slot", slot(other)).withColumnRenamed(key, "_k")
    gap = F.unix_seconds(F.col(other).cast("timestamp")) - F.unix_seconds(F.col(at).cast("timestamp"))
    return l.join(r, (l[key] == r["_k"]) & (l["slot"] == r["slot"]) & (gap > 0) & (gap <= seconds)).drop("_k", "slot")


def in_bands(rows: DataFrame, value: Column, bands: DataFrame) -> DataFrame:
    """rows joined with the band (low, high, name) that holds the value; bands are few, so they are broadcast."""
    return rows.join(F.broadcast(bands), (value >= F.col("low")) & (value < F.col("high")))


def top_per_group(rows: DataFrame, group: str, order: list[Column], k: int) -> DataFrame:
    """The first k rows per group with their rank. Spark limits each task's groups to k rows before the exchange."""
    w = Window.partitionBy(group).orderBy(*order)
    return rows.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def two_hops(edges: DataFrame) -> DataFrame:
    """src, dst, paths: walks of two edges, counted; the middle vertex is the join key, AQE splits its hubs."""
    a = edges.select(F.col("src"), F.col("dst").alias("mid"))
    b = edges.select(F.col("src").alias("mid"), "dst")
    return a.join(b, "mid").groupBy("src", "dst").agg(F.count("*").alias("paths"))


def mutual(edges: DataFrame) -> DataFrame:
    pairs = edges.select("src", "dst")
    return pairs.intersect(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))

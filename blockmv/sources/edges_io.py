"""Edges from and to files: Parquet, CSV/TSV, JSON lines, text adjacency lists; sinks by block."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "src bigint, dst bigint, w double"


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", separator: str | None = None, comment: str = "#") -> DataFrame:
    """src, dst, w (1.0 where the source has none). Fixed schemas: nothing is inferred from the data.

    adjacency: one line per vertex, "src dst dst ...". Lines or rows whose ends are not numbers are dropped.
    """
    if fmt == "parquet":
        rows = spark.read.parquet(path)
        w = F.col("w").cast("double") if "w" in rows.columns else F.lit(1.0)
        rows = rows.select(F.col("src").cast("bigint").alias("src"), F.col("dst").cast("bigint").alias("dst"), w.alias("w"))
    elif fmt in ("csv", "tsv"):
        sep = separator or ("\t" if fmt == "tsv" else ",")
        rows = spark.read.schema(SCHEMA).option("sep", sep).option("comment", comment).option("mode", "PERMISSIVE").csv(path)
    elif fmt == "json":
        rows = spark.read.schema(SCHEMA).json(path)
    elif fmt == "adjacency":
        lines = spark.read.text(path).filter(~F.col("value").startswith(comment))
        t = lines.select(F.split(F.trim("value"), separator or r"\s+").alias("t"))  # cut once a line, not once a pair
        ends = t.select(F.element_at("t", 1).alias("a"), F.slice("t", 2, F.greatest(F.size("t") - 1, F.lit(0))).alias("others"))
        pairs = ends.select("a", F.explode("others").alias("b"))
        rows = pairs.select(F.expr("try_cast(a as bigint)").alias("src"), F.expr("try_cast(b as bigint)").alias("dst"), F.lit(1.0).alias("w"))
    else:
        raise ValueError(f"unknown format: {fmt}")
    return rows.filter("src is not null and dst is not null").withColumn("w", F.coalesce("w", F.lit(1.0)))


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet") -> None:
    rows = edges.select("src", "dst", "w")
    if fmt == "adjacency":
        out = rows.groupBy("src").agg(F.array_join(F.sort_array(F.collect_list(F.col("dst"))).cast("array<string>"), " ").alias("x"))
        out.select(F.concat_ws(" ", F.col("src").cast("string"), "x").alias("value")).write.mode("overwrite").text(path)
    elif fmt == "tsv":
        rows.write.mode("overwrite").option("sep", "\t").csv(path)
    elif fmt in ("parquet", "csv", "json", "orc"):
        rows.write.mode("overwrite").format(fmt).save(path)
    else:
        raise ValueError(f"unknown format: {fmt}")


def write_blocks(cells: DataFrame, path: str, by: str = "cb") -> None:
    """Cells in one folder per column (or row) block, sorted by source: a later read of a block opens its folder only."""
    cells.repartition(by).sortWithinPartitions(by, "src").write.mode("overwrite").partitionBy(by).parquet(path)


def read_block(spark: SparkSession, path: str, block: int, by: str = "cb") -> DataFrame:
    return spark.read.parquet(path).filter(F.col(by) == block)


def discard_output(df: DataFrame) -> None:
    """Run the whole plan and keep nothing: for timings."""
    df.write.format("noop").mode("overwrite").save()

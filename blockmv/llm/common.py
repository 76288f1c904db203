"""Helpers shared by the corpus operators: table access, Arrow slicing, durable intermediate tables."""

from __future__ import annotations

import atexit
import ctypes
import gc
import itertools
import re
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession

#: Texts are handed to vectorised kernels in slices of about so many characters, to bound a worker's memory.
SLICE_CHARS = 1_000_000

_made: list[tuple[SparkSession, str]] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors see: spark.checkpoint.dir, or one of our own where it is unset and
    all executors are threads of the driver. Elsewhere it must be set: a folder of one machine would lose rows."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not re.match(r"local(\[|$)", spark.sparkContext.master):
            raise RuntimeError("spark.checkpoint.dir is not set: no folder is known that all executors share")
        found = tempfile.mkdtemp(prefix="blockmv-")
        spark.sparkContext.setCheckpointDir(found)
    return found


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write df once to the shared folder and read it back: lineage is cut and a lost executor costs nothing.

    The table stays until the driver exits, or until ``discard`` is called on what was returned.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    _made.append((spark, path))
    back = spark.read.schema(df.schema).parquet(path)
    back._blockmv_path = path
    return back


def _remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def discard(df: DataFrame) -> None:
    """Delete a table of ``materialise`` that nothing will read again."""
    if path := getattr(df, "_blockmv_path", None):
        _remove(df.sparkSession, path)
        _made[:] = [x for x in _made if x[1] != path]


@atexit.register
def _clean() -> None:
    for spark, path in _made:
        try:
            if spark.sparkContext._jsc is not None:
                _remove(spark, path)
        except Exception:  # the session may be gone already; nothing is left to protect
            return


def give_back() -> None:
    """Hand memory that this process no longer uses back to the system; workers live on for later stages."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        return


def map_arrow(df: DataFrame, run: Callable[[Iterable[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema) -> DataFrame:
    """df.mapInArrow whose tasks use the system's allocator and give their memory back at the end."""

    def frugal(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pa.set_memory_pool(pa.system_memory_pool())
        try:
            yield from run(batches)
        finally:
            give_back()

    return df.mapInArrow(frugal, schema)


def text_runs(column: pa.Array, chars: int = SLICE_CHARS) -> Iterator[tuple[int, int]]:
    """Cut a column into runs of whole texts of about ``chars`` bytes, before any of it becomes Python objects."""
    sizes = pc.fill_null(pc.binary_length(column), 0).to_pylist()
    begin, size = 0, 0
    for i, n in enumerate(sizes):
        if size and size + n > chars:
            yield begin, i
            begin, size = i, 0
        size += n + 1
    if begin < len(sizes):
        yield begin, len(sizes)


def map_texts(
    df: DataFrame, text: str, extra: str, kernel: Callable[[], Callable[[list], list[pa.Array]]]
) -> DataFrame:
    """Append columns that a vectorised kernel computes from one text column; all other columns pass through.

    ``extra`` is the DDL of the appended columns. ``kernel`` is called once in each task and returns the function from
    a list of texts (None for null) to one Arrow array per appended column. A column of df whose name is appended is
    replaced, as ``withColumn`` does.
    """
    from pyspark.sql import types as T

    more = T.StructType.fromDDL(extra)
    stay = [k for k, c in enumerate(df.columns) if c.lower() not in {f.name.lower() for f in more}]
    schema = T.StructType([*[df.schema.fields[k] for k in stay], *more.fields])
    at = df.columns.index(text)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = kernel()
        for batch in batches:
            column = batch.column(at)
            parts = [f(column.slice(a, b - a).to_pylist()) for a, b in text_runs(column)] or [f([])]
            made = [pa.concat_arrays([p[k] for p in parts]) for k in range(len(more))]
            yield pa.RecordBatch.from_arrays([*[batch.column(k) for k in stay], *made], names=[f.name for f in schema])

    return map_arrow(df, run, schema)


def flat(parts: Iterable[Iterable]) -> list:
    return list(itertools.chain.from_iterable(parts))

"""Helpers shared by the corpus operators: shared scratch tables, size-checked broadcast joins, table readers."""

from __future__ import annotations

import ctypes
from collections.abc import Iterable

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pointloom.schema import scratch_path

#: Words are runs of anything but ASCII white space.
WORD_RE = "[^\\x20\\x09-\\x0D]+"
#: A lookup table of at most this many rows may be broadcast; beyond it the join is left to AQE.
BROADCAST_ROWS = 100_000
#: The same for a table of keys alone, of some 20 bytes a row.
KEY_ROWS = 1_000_000

#: Rows of a scratch file where the number of rows is bounded beforehand.
FILE_ROWS = 250_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def materialize(df: DataFrame, most_rows: int | None = None) -> DataFrame:
    """Write ``df`` once to the shared folder and read it back: lineage is cut, and no task is run twice.

    Where a bound of the rows is known, a file holds up to ``FILE_ROWS`` of them, so small tables are no heap of tiny files.
    The files go when the driver's JVM ends (Hadoop's delete-on-exit), so plans made from them stay valid.
    """
    spark = df.sparkSession
    path = scratch_path(spark)
    if most_rows is not None:
        df = df.coalesce(max(1, -(-most_rows // FILE_ROWS)))
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def materialize_each(spark: SparkSession, parts: Iterable[DataFrame], schema: str) -> DataFrame:
    """Write frames of one schema into one table, one after the other, so that the plan does not grow with their number."""
    path = scratch_path(spark)
    spark.createDataFrame([], schema).write.option("compression", "zstd").parquet(path)
    for df in parts:
        df.write.option("compression", "zstd").mode("append").parquet(path)
    return spark.read.schema(schema).parquet(path)


def join_lookup(df: DataFrame, lookup: DataFrame, on: str | list[str], how: str = "left", limit: int = BROADCAST_ROWS) -> DataFrame:
    """Join a (materialised) lookup table: broadcast when it has at most ``limit`` rows, else a shuffled join."""
    small = lookup.limit(limit + 1).count() <= limit
    return df.join(F.broadcast(lookup) if small else lookup, on, how)


def own_prefix(df: DataFrame) -> str:
    """A prefix that none of the frame's columns has, for columns that are added for a while."""
    prefix = "__"
    while any(c.startswith(prefix) for c in df.columns):
        prefix += "_"
    return prefix


def text_key(docs: DataFrame) -> Column:
    """A hash of the text; null and empty texts have the same."""
    return F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit(""))).alias("key")


def one_of_each(docs: DataFrame, grouped: DataFrame) -> DataFrame:
    """``docs`` with one row of every group of ``grouped`` (doc_id, key by :func:`text_key`, root; a row for every row).

    The row of the smallest (doc_id with null last, key) stays, and any one of rows that share both. What goes to
    the documents is the keys that are lost; rows that share a key are reduced by an aggregate, so a hot key is combined first.
    """
    own = own_prefix(docs)
    names = [own + c for c in ("null", "id", "key")]
    id_ = F.col("doc_id").cast("long")
    parts = (id_.isNull(), F.coalesce(id_, F.lit(0)))
    keys = grouped.select(parts[0].alias(names[0]), parts[1].alias(names[1]), F.col("key").alias(names[2]), "root").groupBy(*names, "root").agg(F.count("*").alias("n"))
    keys = materialize(keys)
    first = keys.groupBy("root").agg(F.min(F.struct(*names)).alias("first"))
    placed = materialize(join_lookup(keys, materialize(first), "root").select(*names, "n", (F.struct(*names) == F.col("first")).alias("stays")))
    lost = placed.where("not stays").select(*names)
    repeated = placed.where("stays and n > 1").select(*names)
    left = join_lookup(docs.withColumns(dict(zip(names, (*parts, text_key(docs)), strict=True))), lost, names, "left_anti", KEY_ROWS)
    if repeated.limit(1).count():
        whole = F.first(F.struct(*[F.col(f"`{c}`") for c in docs.columns])).alias(own + "row")
        same = join_lookup(left, repeated, names, "left_semi", KEY_ROWS).groupBy(*names).agg(whole).select(own + "row.*")
        return join_lookup(left, repeated, names, "left_anti", KEY_ROWS).select(*docs.columns).union(same)
    return left.select(*[F.col(f"`{c}`") for c in docs.columns])


def lean(run):
    """A task function that gives its memory back at its end: Python workers are reused and would keep it."""

    def task(batches):
        pa.set_memory_pool(pa.system_memory_pool())
        try:
            yield from run(batches)
        finally:
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
            if trim is not None:
                trim(0)

    return task

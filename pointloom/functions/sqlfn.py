"""Functions for SQL users: inlined SQL functions, Arrow scalar functions, grouped aggregates and table functions."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Row, SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import arrow_udf, pandas_udf, udtf

from pointloom.functions.fixed import KEYS, PRIME


def _row(*names: str) -> T.StructType:
    return T.StructType([T.StructField(n, T.IntegerType()) for n in names])


@arrow_udf(T.DoubleType())
def gelu(x: pa.Array) -> pa.Array:
    v = x.to_numpy(zero_copy_only=False)
    return pa.array(0.5 * v * (1 + np.tanh(math.sqrt(2 / math.pi) * (v + 0.044715 * v**3))))


@arrow_udf(T.LongType())
def morton_key(i: pa.Array, j: pa.Array, k: pa.Array) -> pa.Array:
    """Bits of three lattice coordinates (up to 21 bits each) interleaved, first axis lowest."""
    out = np.zeros(len(i), np.int64)
    for axis, col in enumerate((i, j, k)):
        v = col.to_numpy(zero_copy_only=False).astype(np.int64)
        for bit in range(21):
            out |= ((v >> bit) & 1) << (3 * bit + axis)
    return pa.array(out)


@pandas_udf(T.DoubleType())
def chamfer_agg(x: pd.Series, y: pd.Series, z: pd.Series, is_true: pd.Series) -> float:
    p, t = np.stack([x, y, z], 1), is_true.to_numpy(bool)
    if not t.any() or t.all():
        return float("nan")
    d = ((p[t][:, None] - p[~t][None]) ** 2).sum(-1)
    return float(d.min(1).mean() + d.min(0).mean())


@pandas_udf(T.ArrayType(T.DoubleType()))
def vector_sum(v: pd.Series) -> list:
    return np.sum(np.stack(v.to_list()), axis=0).tolist()


@udtf(returnType=_row("slot", "i", "j", "k"))
class Slots:
    """All slots of a patch of edge a with their offsets."""

    def eval(self, a: int) -> Iterator:
        for s in range(a**3):
            yield s, s % a, s // a % a, s // (a * a)


@udtf(returnType=_row("run", "way", "shot"))
class Episodes:
    def eval(self, way: int, shot: int, runs: int) -> Iterator:
        for r in range(1, runs + 1):
            yield r, way, shot


@udtf(returnType=T.StructType([T.StructField("sample_id", T.LongType()), T.StructField("rank", T.IntegerType()), T.StructField("point_no", T.LongType())]))
class FpsPoints:
    """Centres of each partition of a table (sample_id, point_no, x, y, z): use with PARTITION BY sample_id."""

    def __init__(self):
        self.rows = []

    def eval(self, row: Row) -> Iterator:
        self.rows.append((row["sample_id"], row["point_no"], row["x"], row["y"], row["z"]))
        return iter(())

    def terminate(self) -> Iterator:
        from pointloom.operators.baselines import fps_kernel

        self.rows.sort()
        if self.rows:
            at = fps_kernel(np.array([r[2:] for r in self.rows]), 5)
            for n, k in enumerate(at.tolist(), 1):
                yield self.rows[k][0], n, self.rows[k][1]


def register(spark: SparkSession) -> None:
    """Make the functions known to the session's SQL; the SQL ones are inlined by the optimiser."""
    define = "CREATE OR REPLACE TEMPORARY FUNCTION "
    spark.sql(define + "fx6(x DOUBLE) RETURNS BIGINT RETURN CAST(floor(x * 1000000 + 0.5D) AS BIGINT)")
    spark.sql(define + "slot_of(i INT, j INT, k INT, a INT) RETURNS INT RETURN pmod(i, a) + pmod(j, a) * a + pmod(k, a) * a * a")
    spark.sql(define + "vox_key(i INT, j INT, k INT) RETURNS BIGINT RETURN (CAST(i AS BIGINT) * 1024 + j) * 1024 + k")
    spark.sql(define + f"hash_order(key BIGINT, seed INT) RETURNS BIGINT RETURN pmod(pmod(key, {PRIME}) * {KEYS[1]} + CAST(seed AS BIGINT) * {KEYS[0]}, {PRIME})")
    spark.udf.register("gelu", gelu)
    spark.udf.register("morton_key", morton_key)
    spark.udf.register("chamfer_agg", chamfer_agg)
    spark.udf.register("vector_sum", vector_sum)
    spark.udtf.register("slots", Slots)
    spark.udtf.register("episode", Episodes)
    spark.udtf.register("fps_points", FpsPoints)

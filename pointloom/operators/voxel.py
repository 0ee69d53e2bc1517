"""Voxel keys and voxel representatives."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pointloom.functions.fixed import fx6, sql_fx6
from pointloom.schema import ATTRIBUTES, GridSpec

KEY = ("vi", "vj", "vk")


def assign(points: DataFrame, grid: GridSpec, bounds: str = "clip") -> DataFrame:
    """Adds vi, vj, vk: whole voxel edges in each coordinate. ``bounds``: clip to the grid, drop, error or keep."""
    out = points.withColumns({k: F.floor(F.col(c) / F.lit(grid.edge)).cast("int") for k, c in zip(KEY, "xyz", strict=True)})
    return apply_bounds(out, grid, bounds)


def apply_bounds(voxels: DataFrame, grid: GridSpec, mode: str = "clip") -> DataFrame:
    top = grid.size - 1
    if mode == "clip":
        return voxels.withColumns({k: F.greatest(F.lit(0), F.least(F.lit(top), F.col(k))) for k in KEY})
    inside = F.lit(True)
    for k in KEY:
        inside = inside & F.col(k).between(0, top)
    if mode == "drop":
        return voxels.where(inside)
    if mode == "error":
        return voxels.withColumn("vi", F.when(inside, F.col("vi")).otherwise(F.raise_error(F.lit("a point lies outside the grid")).cast("int")))
    return voxels


def within(points: DataFrame, grid: GridSpec, lo: tuple[int, int, int], hi: tuple[int, int, int]) -> DataFrame:
    """Points whose voxel lies in [lo, hi): the raw coordinates are compared as well, which a parquet scan can use."""
    out = points
    for c, a, b in zip("xyz", lo, hi, strict=True):
        out = out.where((F.col(c) >= a * grid.edge) & (F.col(c) < b * grid.edge))
    out = assign(out, grid, "keep")
    for k, a, b in zip(KEY, lo, hi, strict=True):
        out = out.where((F.col(k) >= a) & (F.col(k) < b))
    return out


def order_of(score_fx=None):
    """Order of the points of a voxel: sum of attributes in micro-units, then the point's number; unique in a cloud."""
    total = F.col("x")
    for c in ATTRIBUTES[1:]:
        total = total + F.col(c)
    return fx6(total).cast("decimal(38,0)") * F.lit(10**18).cast("decimal(19,0)") + F.col("point_no").cast("decimal(19,0)")


def voxelize(keyed: DataFrame, rep: str = "argmax") -> DataFrame:
    """One row a voxel. ``argmax``: the point with the largest sum of attributes; ``colmax``: the largest of each attribute;
    ``mean``: their mean; ``first``: the point of the smallest number. Values of mutable width keep the aggregate hashed."""
    if rep == "argmax":
        keyed = keyed.withColumn("ord", order_of())
        aggs = [F.max_by(c, "ord").alias(c) for c in ATTRIBUTES]
    elif rep == "first":
        aggs = [F.min_by(c, "point_no").alias(c) for c in ATTRIBUTES]
    elif rep == "colmax":
        aggs = [F.max(c).alias(c) for c in ATTRIBUTES]
    elif rep == "mean":
        aggs = [(F.sum(fx6(F.col(c))) / F.count("*") / F.lit(1000000.0)).alias(c) for c in ATTRIBUTES]
    else:
        raise ValueError(rep)
    return keyed.groupBy("sample_id", *KEY).agg(*aggs, F.count("*").alias("n_points"))


def sql_keyed(source: str, grid: GridSpec) -> str:
    keys = ", ".join(f"greatest(0, least({grid.size - 1}, floor({c} / {grid.edge!r}::DOUBLE)))::INT AS {k}" for k, c in zip(KEY, "xyz", strict=True))
    return f"keyed AS (SELECT *, {keys}, {sql_fx6('x + y + z + r + g + b')}::HUGEINT * 1000000000000000000 + point_no AS ord FROM {source})"


def sql_voxels(rep: str = "argmax") -> str:
    cols = {
        "argmax": ", ".join(f"arg_max({c}, ord) AS {c}" for c in ATTRIBUTES),
        "first": ", ".join(f"arg_min({c}, point_no) AS {c}" for c in ATTRIBUTES),
        "colmax": ", ".join(f"max({c}) AS {c}" for c in ATTRIBUTES),
        "mean": ", ".join(f"sum({sql_fx6(c)})::BIGINT / count(*) / 1000000.0::DOUBLE AS {c}" for c in ATTRIBUTES),
    }[rep]
    return f"vox AS (SELECT sample_id, vi, vj, vk, {cols}, count(*) AS n_points FROM keyed GROUP BY ALL)"

"""Patches of the voxel lattice and the voxel graph inside each patch."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pointloom.functions.fixed import fx6, sql_fx6

CELL = ("ci", "cj", "ck")
PATCH = ("sample_id", *CELL)


def partition(voxels: DataFrame, a: int) -> DataFrame:
    """Adds the cell of each voxel: whole patches in each voxel coordinate."""
    return voxels.withColumns({c: F.floor(F.col(k) / a).cast("int") for c, k in zip(CELL, ("vi", "vj", "vk"), strict=True)})


def corner(df: DataFrame, a: int) -> DataFrame:
    """Adds the patch's position: its smallest voxel coordinates."""
    return df.withColumn("corner", F.struct(*[(F.col(c) * a).alias(n) for c, n in zip(CELL, "ijk", strict=True)]))


def slot_of(vi: Column, vj: Column, vk: Column, a: int) -> Column:
    """Position of a voxel inside its patch, first axis fastest."""
    return (F.pmod(vi, F.lit(a)) + F.pmod(vj, F.lit(a)) * a + F.pmod(vk, F.lit(a)) * a * a).cast("int")


def with_slot(voxels: DataFrame, a: int) -> DataFrame:
    return partition(voxels, a).withColumn("slot", slot_of(F.col("vi"), F.col("vj"), F.col("vk"), a))


def centres(voxels: DataFrame) -> DataFrame:
    """One row a patch: number of voxels and mean coordinates; sums are in micro-units, so any order gives the same."""
    means = [(F.sum(fx6(F.col(c))) / F.count("*") / F.lit(1000000.0)).alias(f"c{c}") for c in "xyz"]
    return voxels.groupBy(*PATCH).agg(F.count("*").alias("n_vox"), *means)


def graph_features(voxels: DataFrame, features: str = "graph") -> DataFrame:
    """12 attributes a voxel: its own 6, its offset from the patch's centre, and that centre. ``origin`` keeps the 6."""
    if features == "origin":
        return voxels
    w = Window.partitionBy(*PATCH)
    out = voxels.withColumn("n_vox", F.count("*").over(w))
    out = out.withColumns({f"c{c}": F.sum(fx6(F.col(c))).over(w) / F.col("n_vox") / F.lit(1000000.0) for c in "xyz"})
    return out.withColumns({f"d{c}": F.col(c) - F.col(f"c{c}") for c in "xyz"})


def sql_cells(a: int) -> str:
    return f"cells AS (SELECT *, vi // {a} AS ci, vj // {a} AS cj, vk // {a} AS ck, (vi % {a} + (vj % {a}) * {a} + (vk % {a}) * {a * a})::INT AS slot FROM vox)"


def sql_graph() -> str:
    cs = ", ".join(f"sum({sql_fx6(c)}) OVER w::BIGINT / count(*) OVER w / 1000000.0::DOUBLE AS c{c}" for c in "xyz")
    cs = cs.replace("OVER w::BIGINT", "OVER w")
    return f"graph AS (SELECT *, x - cx AS dx, y - cy AS dy, z - cz AS dz FROM (SELECT *, count(*) OVER w AS n_vox, {cs} FROM cells WINDOW w AS (PARTITION BY sample_id, ci, cj, ck)))"

"""Random patch masks: pure functions of the seed, the sample and the cell."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pointloom.functions.fixed import draw, sql_draw
from pointloom.operators.patch import CELL, PATCH


def patches_of(voxels: DataFrame) -> DataFrame:
    return voxels.groupBy(*PATCH).agg(F.count("*").alias("n_vox"))


def cell_draw(seed: int):
    return draw(seed, F.col("sample_id"), *[F.col(c) for c in CELL])


def random_mask(patches: DataFrame, percent: int, seed: int = 41, mode: str = "exact") -> DataFrame:
    """Adds ``hidden``. ``exact``: T * percent div 100 patches of every cloud, first by hashed order, ties by cell;
    ``bernoulli``: each patch by its own draw, a filter on the grouping keys that can move below the aggregate."""
    if mode == "bernoulli":
        return patches.withColumn("hidden", cell_draw(seed) % 100 < percent)
    order = Window.partitionBy("sample_id").orderBy("__h", *CELL)
    ranked = patches.withColumn("__h", cell_draw(seed)).withColumn("__n", F.row_number().over(order)).withColumn("__t", F.count("*").over(Window.partitionBy("sample_id")))
    return ranked.withColumn("hidden", F.col("__n") <= F.floor(F.col("__t") * percent / 100)).drop("__h", "__n", "__t")


def visible(voxels: DataFrame, mask: DataFrame, hidden: bool = False) -> DataFrame:
    """The voxels of the patches that are (not) hidden; taken before embedding, so hidden patches are never embedded."""
    return voxels.join(mask.where(F.col("hidden") == hidden).select(*PATCH), list(PATCH), "left_semi")


def visible_bernoulli(voxels: DataFrame, percent: int, seed: int = 41) -> DataFrame:
    return voxels.where(cell_draw(seed) % 100 >= percent)


def sql_mask(percent: int, seed: int = 41, mode: str = "exact") -> str:
    h = sql_draw(seed, "sample_id", "ci", "cj", "ck")
    patches = "(SELECT sample_id, ci, cj, ck, count(*) AS n_vox FROM cells GROUP BY ALL)"
    if mode == "bernoulli":
        return f"mask AS (SELECT *, {h} % 100 < {percent} AS hidden FROM {patches})"
    return f"""mask AS (SELECT * EXCLUDE (h), row_number() OVER (PARTITION BY sample_id ORDER BY h, ci, cj, ck) <= (count(*) OVER (PARTITION BY sample_id)) * {percent} // 100 AS hidden
      FROM (SELECT *, {h} AS h FROM {patches}))"""

"""Relational operators around the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def asof(left: DataFrame, right: DataFrame, by: str, on: str, value: str, tolerance: int | None = None) -> DataFrame:
    """For each left row the latest right ``value`` of the same key at or before ``on`` (microseconds apart at most
    ``tolerance``): both sides are stacked and a running last value is taken, so one shuffle by key serves."""
    a = left.withColumns({"__side": F.lit(1), "__v": F.lit(None).cast(dict(right.dtypes)[value]), "__t": F.lit(None).cast(dict(right.dtypes)[on])})
    b = right.select(F.col(by), F.col(on), F.lit(0).alias("__side"), F.col(value).alias("__v"), F.col(on).alias("__t"))
    w = Window.partitionBy(by).orderBy(on, "__side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b, allowMissingColumns=True)
    out = both.withColumns({"asof_value": F.last("__v", ignorenulls=True).over(w), "__at": F.last("__t", ignorenulls=True).over(w)}).where("__side = 1")
    if tolerance is not None:
        out = out.withColumn("asof_value", F.when(F.col(on) - F.col("__at") <= tolerance, F.col("asof_value")))
    return out.drop("__side", "__v", "__t", "__at")


def interval_join(left: DataFrame, right: DataFrame, by: str, on: str, before: int, after: int) -> DataFrame:
    """Pairs of one key with right.on in [left.on - before, left.on + after]: an equi-join on (key, bucket), three buckets a
    left row, so no pair outside the neighbourhood is formed."""
    size = max(before, after, 1)
    a = left.withColumn("__b", F.explode(F.array(*[F.floor(F.col(on) / size) + d for d in (-1, 0, 1)])))
    b = right.select([F.col(c).alias(f"r_{c}") for c in right.columns]).withColumn("__rb", F.floor(F.col(f"r_{on}") / size))
    cond = (F.col(by) == F.col(f"r_{by}")) & (F.col("__b") == F.col("__rb")) & F.col(f"r_{on}").between(F.col(on) - before, F.col(on) + after)
    return a.join(b, cond).drop("__b", "__rb")


def keep(df: DataFrame, keys: DataFrame, on: str) -> DataFrame:
    return df.join(keys.select(on).distinct(), on, "left_semi")


def drop(df: DataFrame, keys: DataFrame, on: str) -> DataFrame:
    return df.join(keys.select(on).distinct(), on, "left_anti")


def voxel_diff(a: DataFrame, b: DataFrame, on: list[str]) -> DataFrame:
    """Full outer comparison of two voxel sets: side is left, right or both."""
    x, y = a.select(*on).distinct().withColumn("__a", F.lit(1)), b.select(*on).distinct().withColumn("__b", F.lit(1))
    side = F.when(F.col("__b").isNull(), "left").when(F.col("__a").isNull(), "right").otherwise("both")
    return x.join(y, on, "full_outer").select(*on, side.alias("side"))


def voxel_overlap(a: DataFrame, b: DataFrame, op: str, every: bool = False) -> DataFrame:
    return {("intersect", False): a.intersect, ("intersect", True): a.intersectAll, ("except", False): a.subtract, ("except", True): a.exceptAll, ("union", True): a.unionAll, ("union", False): lambda o: a.unionAll(o).distinct()}[op, every](b)


def token_cube(df: DataFrame, dims: list[str], aggs: list, mode: str = "rollup") -> DataFrame:
    return (df.rollup(*dims) if mode == "rollup" else df.cube(*dims)).agg(F.grouping_id().cast("long").alias("gid"), *aggs)


def topk(df: DataFrame, by: list[str], order: list, k: int) -> DataFrame:
    return df.withColumn("nth", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).where(F.col("nth") <= k)


def largest(df: DataFrame, order: list, k: int) -> DataFrame:
    return df.orderBy(*order).limit(k)


def size_bucket(df: DataFrame, column: str, n: int, accuracy: int = 10_000) -> DataFrame:
    """Buckets by approximate quantiles, one mergeable sketch; no global sort."""
    cuts = df.agg(F.percentile_approx(column, [k / n for k in range(1, n)], accuracy).alias("cuts"))
    return df.join(F.broadcast(cuts)).withColumn("bucket", F.size(F.filter("cuts", lambda c: c < F.col(column))) + 1).drop("cuts")

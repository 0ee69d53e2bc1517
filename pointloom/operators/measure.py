"""Cost and accuracy measures as plain aggregates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pointloom.operators.patch import PATCH

CNT_DENSITY, NEIGHBOURS, WIDTH = 16, 32, 384
#: Multiply-adds of the small point network for each point of a group: layers of public width up to the token's.
NET_PAIRS = 3 * 128 + 128 * 256 + 512 * 512 + 512 * WIDTH


def centre_ops(n: Column, density: int = CNT_DENSITY, k: int = NEIGHBOURS) -> dict[str, Column]:
    """Operations of the centre-neighbour tokeniser a cloud of n points, by phase; centres keep the token density."""
    g = F.greatest(F.lit(1), F.floor(n / density)).cast("long")
    bits = max(1, (k - 1).bit_length())
    return {"centres": 10 * g * n, "neighbours": g * n * (8 + bits), "network": 2 * g * k * NET_PAIRS}


def voxel_ops(n: Column, m: Column, p: Column, channels: int = WIDTH) -> dict[str, Column]:
    """Operations of the voxel tokeniser: n points, m voxels, p patches."""
    return {"voxels": 12 * n, "graph": 6 * m + 3 * p + 7 * m, "embed": 24 * channels * m + channels * m + channels * p}


def tokenizer_stats(cells: DataFrame) -> DataFrame:
    """Per cloud: points, voxels, patches, and the mean and largest number of voxels a patch (needs n_points and a cell)."""
    by_patch = cells.groupBy(*PATCH).agg(F.count("*").alias("n_vox"), F.sum("n_points").alias("n_points"))
    return by_patch.groupBy("sample_id").agg(F.sum("n_points").alias("n_points"), F.sum("n_vox").alias("n_voxels"), F.count("*").alias("n_patches"), F.max("n_vox").alias("max_vox"))


def slope(df: DataFrame, x: str, y: str) -> Column:
    return F.regr_slope(F.log(F.col(y).cast("double")), F.log(F.col(x).cast("double")))


def accuracy(pred: DataFrame) -> DataFrame:
    """Share of label = pred, with the counts."""
    return pred.agg(F.count("*").alias("n"), F.sum((F.col("label") == F.col("pred")).cast("long")).alias("n_right")).withColumn("acc_fx", F.floor(F.col("n_right") / F.col("n") * 1000000 + 0.5).cast("long"))


def mean_se(runs: DataFrame, by: list[str], value: str) -> DataFrame:
    """Mean and standard error (sample deviation over the root of the number of runs)."""
    return runs.groupBy(*by).agg(F.avg(value).alias("mean"), (F.stddev_samp(value) / F.sqrt(F.count("*").cast("double"))).alias("se"), F.count("*").alias("n_runs"))


def confusion(pred: DataFrame, classes: list) -> DataFrame:
    return pred.groupBy("label").pivot("pred", classes).count().na.fill(0)


def iou_by_part(pred: DataFrame, parts: int) -> DataFrame:
    """(category, sample_id, label, pred) a point -> (category, sample_id, part, iou); a part absent in both counts 1."""
    each = pred.select("category", "sample_id", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"), "label", "pred")
    t, p = F.col("label") == F.col("part"), F.col("pred") == F.col("part")
    g = each.groupBy("category", "sample_id", "part").agg(F.sum((t & p).cast("long")).alias("both"), F.sum((t | p).cast("long")).alias("either"))
    return g.withColumn("iou", F.when(F.col("either") == 0, F.lit(1.0)).otherwise(F.col("both") / F.col("either")))


def miou(pred: DataFrame, parts: int = 3) -> DataFrame:
    """Instance mean (over shapes) and class mean (over categories of their shapes' mean), in micro-units."""
    fx = lambda x: F.floor(x * 1000000 + 0.5).cast("long")
    shape = iou_by_part(pred, parts).groupBy("category", "sample_id").agg(F.sum(fx(F.col("iou"))).alias("s")).withColumn("iou_fx", F.floor(F.col("s") / parts + 0.5).cast("long"))
    cat = shape.groupBy("category").agg(F.sum("iou_fx").alias("s"), F.count("*").alias("n")).withColumn("c_fx", F.floor(F.col("s") / F.col("n") + 0.5).cast("long"))
    return cat.agg(F.floor(F.sum("c_fx") / F.count("*") + 0.5).cast("long").alias("class_miou_fx"), F.floor(F.sum("s") / F.sum("n") + 0.5).cast("long").alias("instance_miou_fx"), F.sum("n").alias("n_shapes"))


def delta(arms: DataFrame, base: str, by: str = "metric") -> DataFrame:
    """Gain of each arm over the base arm on the same metric."""
    ref = arms.where(F.col("arm") == base).select(by, F.col("value").alias("base_value"))
    return arms.join(F.broadcast(ref), by).withColumn("gain", F.col("value") - F.col("base_value"))


def delta_of(df: DataFrame, base: str, keep: list[str], names) -> DataFrame:
    """Gains, in tenths, of columns over the row that ``base`` names."""
    ref = df.where(base).select(*[F.col(c).alias(f"__{c}") for c in names])
    return df.join(F.broadcast(ref)).select(*keep, *[F.round((F.col(c) - F.col(f"__{c}")) * 10).cast("long").alias(f"gain_{c}_tenths") for c in names])


def training_cost(runs: DataFrame) -> DataFrame:
    """(arm, devices, epochs, days) -> device hours, whole and an epoch."""
    hours = F.col("devices") * F.col("days") * 24
    return runs.select("arm", F.round(hours).cast("long").alias("device_hours"), F.round(hours * 1000 / F.col("epochs")).cast("long").alias("thousandth_hours_an_epoch"))


def stage_cost(df: DataFrame) -> dict:
    """Wall seconds of one full evaluation, the plan's exchanges, and what they wrote."""
    import time

    run, began = df._jdf.queryExecution(), time.time()
    run.toRdd().count()
    seconds = time.time() - began
    return {"seconds": seconds, "exchanges": _exchanges(run.executedPlan(), False), "shuffle_mb": _exchanges(run.executedPlan(), True) / 1e6}


def _exchanges(plan, written: bool) -> int:
    """Number of shuffles in a physical plan, or the bytes that they wrote."""
    name, total = plan.getClass().getSimpleName(), 0
    if name == "AdaptiveSparkPlanExec":
        return _exchanges(plan.executedPlan(), written)
    if name.endswith("QueryStageExec"):
        return _exchanges(plan.plan(), written)
    if name == "ShuffleExchangeExec":
        total += int(plan.metrics().apply("shuffleBytesWritten").value()) if written else 1
    children = plan.children()
    return total + sum(_exchanges(children.apply(k), written) for k in range(children.size()))


def vote(scores: DataFrame) -> DataFrame:
    """(sample_id, class, score) over several rounds -> the class with the largest mean score, ties to the smaller class."""
    mean = scores.groupBy("sample_id", "class").agg(F.sum("score_fx").alias("s"))
    best = Window.partitionBy("sample_id").orderBy(F.col("s").desc(), "class")
    return mean.withColumn("nth", F.row_number().over(best)).where("nth = 1").select("sample_id", F.col("class").alias("pred"), F.col("s").alias("score_fx"))


def chance(labels: DataFrame) -> DataFrame:
    """Share of the largest class."""
    return labels.groupBy("label").count().agg((F.max("count") / F.sum("count")).alias("majority"), F.count("*").alias("n_classes"))

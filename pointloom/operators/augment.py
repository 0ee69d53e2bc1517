"""Augmentations: projections with draws hashed from the seed, the sample and the epoch; never stored."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pointloom.functions.fixed import draw, unit_draw

#: Channel statistics of natural images, as image pre-training uses them.
MEAN, STD = (0.485, 0.456, 0.406), (0.229, 0.224, 0.225)
#: Cosine and sine of the eighth turns, rounded, so that every engine turns alike.
TURNS = tuple((round(math.cos(k * math.pi / 4), 12) + 0.0, round(math.sin(k * math.pi / 4), 12) + 0.0) for k in range(8))


def _table(index: Column, values) -> Column:
    return F.element_at(F.array(*[F.lit(float(v)) for v in values]), (index + 1).cast("int"))


def rotate_z(points: DataFrame, seed: int, angle: Column | float | None = None, eighths: bool = False, keys: tuple[str, ...] = ("sample_id",)) -> DataFrame:
    """Turn every cloud about the upright axis through (1/2, 1/2): by ``angle``, else by a hashed angle (or eighth turn)."""
    own = [F.col(k) for k in keys]
    if eighths:
        k = draw(seed, *own) % 8
        cos, sin = _table(k, [t[0] for t in TURNS]), _table(k, [t[1] for t in TURNS])
    else:
        a = angle if isinstance(angle, Column) else F.lit(float(angle)) if angle is not None else unit_draw(seed, *own) * (2 * math.pi)
        cos, sin = F.cos(a), F.sin(a)
    dx, dy = F.col("x") - 0.5, F.col("y") - 0.5
    return points.withColumns({"x": cos * dx - sin * dy + 0.5, "y": sin * dx + cos * dy + 0.5})


def sql_rotate(source: str, seed: int, keys: tuple[str, ...] = ("sample_id",)) -> str:
    from pointloom.functions.fixed import sql_draw

    k = sql_draw(seed, *keys)
    cos, sin = ("[" + ", ".join(f"{t[j]}::DOUBLE" for t in TURNS) + "]" for j in (0, 1))
    return f"""(SELECT * EXCLUDE (x, y, kk), {cos}[kk + 1] * (x - 0.5::DOUBLE) - {sin}[kk + 1] * (y - 0.5::DOUBLE) + 0.5::DOUBLE AS x,
      {sin}[kk + 1] * (x - 0.5::DOUBLE) + {cos}[kk + 1] * (y - 0.5::DOUBLE) + 0.5::DOUBLE AS y FROM (SELECT *, {k} % 8 AS kk FROM {source}))"""


def refit(points: DataFrame) -> DataFrame:
    """Bring turned clouds back into the unit cube: the turned square's diagonal becomes the edge."""
    return points.withColumns({c: (F.col(c) - 0.5) / math.sqrt(2) + 0.5 for c in "xy"})


def colour_standardise(points: DataFrame, mean=MEAN, std=STD) -> DataFrame:
    return points.withColumns({c: (F.col(c) - F.lit(m)) / F.lit(s) for c, m, s in zip("rgb", mean, std, strict=True)})


def scale_translate(points: DataFrame, rho: float = 1.0, tau: float = 0.0, seed: int = 23, keys: tuple[str, ...] = ("sample_id",)) -> DataFrame:
    """Scale each cloud by a factor drawn in [rho, 1]; then shift it within the room left, at most tau of the extent."""
    own = [F.col(k) for k in keys]
    factor = F.lit(float(rho)) + F.lit(1 - float(rho)) * unit_draw(seed, *own)
    out = {}
    for j, c in enumerate("xyz"):
        moved = F.col(c) * factor
        if tau:
            moved = moved + unit_draw(seed + 1 + j, *own) * F.least(1 - factor, F.lit(float(tau)))
        out[c] = moved
    return points.withColumns(out)


def sql_scale(source: str, rho: float, tau: float, seed: int = 23, keys: tuple[str, ...] = ("sample_id",)) -> str:
    from pointloom.functions.fixed import sql_unit_draw

    factor = f"({float(rho)}::DOUBLE + {1 - float(rho)}::DOUBLE * {sql_unit_draw(seed, *keys)})"
    cols = []
    for j, c in enumerate("xyz"):
        shift = f" + {sql_unit_draw(seed + 1 + j, *keys)} * least(1 - ff, {float(tau)}::DOUBLE)" if tau else ""
        cols.append(f"{c} * ff{shift} AS {c}")
    return f"(SELECT * EXCLUDE (x, y, z, ff), {', '.join(cols)} FROM (SELECT *, {factor} AS ff FROM {source}))"


def perturb(points: DataFrame, copies: int = 5, tau: float = 0.5, rho: float = 0.5, seed: int = 31) -> DataFrame:
    """Copies of the corpus, each turned, scaled and shifted by its own draws: + copy."""
    many = points.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(copies))))
    keys = ("sample_id", "copy")
    return scale_translate(rotate_z(many, seed, eighths=True, keys=keys), rho, tau, seed + 7, keys)

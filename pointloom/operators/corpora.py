"""Corpora of point clouds made from the tables."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pointloom.functions.fixed import draw
from pointloom.schema import load, pieces

LEVELS = ("order", "part", "supplier", "nation", "region")
#: The first day, and the ranges that bring each attribute to [0, 1].
DAY0, DAYS, PRICE, QUANTITY, DISCOUNT, TAX = "1995-01-01", 2500, 105_000, 50, 0.10, 0.08


def lineitem_clouds(spark: SparkSession, sf_dir: str, level: str = "supplier") -> DataFrame:
    """One point a lineitem row; ``point_no`` packs the whole row's attributes, so equal numbers are equal points."""
    key = {"order": "l_orderkey", "part": "l_partkey"}.get(level, "l_suppkey")
    li = load(spark, sf_dir, "lineitem").select(key, "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")
    if level in ("nation", "region"):
        # suppliers grow with the data, so the join strategy is left to adaptive execution
        dims = load(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey")
        if level == "region":
            nation = load(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("s_nationkey"), "n_regionkey")
            dims = dims.join(F.broadcast(nation), "s_nationkey").select("l_suppkey", F.col("n_regionkey").alias("s_nationkey"))
        li = li.join(dims, "l_suppkey")
        key = "s_nationkey"
    day = F.datediff(F.col("l_shipdate"), F.lit(DAY0).cast("date"))
    code = (F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2) * 2 + F.when(F.col("l_linestatus") == "F", 0).otherwise(1)).cast("long")
    whole = lambda c, m: F.floor(F.col(c) * m + 0.5).cast("long")
    number = F.lit(0).cast("long")
    for value, width in ((whole("l_quantity", 1), 100), (day.cast("long"), 10_000), (whole("l_extendedprice", 100), 10**8), (whole("l_discount", 100), 100), (whole("l_tax", 100), 10), (code, 10)):
        number = number * width + value
    return li.select(
        F.col(key).cast("long").alias("sample_id"), number.alias("point_no"),
        ((F.col("l_quantity") - 1) / QUANTITY).alias("x"), (F.col("l_extendedprice") / PRICE).alias("y"), (day / DAYS).alias("z"),
        (F.col("l_discount") / DISCOUNT).alias("r"), (F.col("l_tax") / TAX).alias("g"), (code / 5).alias("b"),
        (F.col("l_returnflag") == "N").alias("background"),
    )


def sql_points(level: str = "supplier") -> str:
    """The same points as a common table expression ``pts``."""
    key = {"order": "l_orderkey", "part": "l_partkey", "supplier": "l_suppkey", "nation": "s_nationkey", "region": "n_regionkey"}[level]
    join = {"nation": "JOIN supplier ON l_suppkey = s_suppkey", "region": "JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey"}.get(level, "")
    code = "((CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END) * 2 + (CASE l_linestatus WHEN 'F' THEN 0 ELSE 1 END))::BIGINT"
    return f"""pts AS (SELECT {key}::BIGINT AS sample_id,
      (((((floor(l_quantity + 0.5::DOUBLE)::BIGINT) * 10000 + dd) * 100000000 + floor(l_extendedprice * 100 + 0.5::DOUBLE)::BIGINT) * 100
        + floor(l_discount * 100 + 0.5::DOUBLE)::BIGINT) * 10 + floor(l_tax * 100 + 0.5::DOUBLE)::BIGINT) * 10 + {code} AS point_no,
      (l_quantity - 1) / {QUANTITY} AS x, l_extendedprice / {PRICE} AS y, dd / {DAYS} AS z, l_discount / {DISCOUNT}::DOUBLE AS r, l_tax / {TAX}::DOUBLE AS g, {code} / 5 AS b,
      l_returnflag = 'N' AS background
      FROM (SELECT *, date_diff('day', DATE '{DAY0}', l_shipdate::DATE)::BIGINT AS dd FROM lineitem) {join})"""


def lineitem_sizes(spark: SparkSession, sf_dir: str, level: str = "supplier") -> DataFrame:
    """sample_id, n of the lineitem clouds, from the key column alone; suppliers are counted first and then summed upwards."""
    key = {"order": "l_orderkey", "part": "l_partkey"}.get(level, "l_suppkey")
    per = load(spark, sf_dir, "lineitem").groupBy(F.col(key).cast("long").alias("sample_id")).agg(F.count("*").alias("n"))
    if level in ("nation", "region"):
        dims = load(spark, sf_dir, "supplier").select(F.col("s_suppkey").cast("long").alias("sample_id"), "s_nationkey")
        per = per.join(dims, "sample_id").groupBy(F.col("s_nationkey").cast("long").alias("sample_id")).agg(F.sum("n").alias("n"))
    if level == "region":
        nation = load(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("sample_id"), "n_regionkey")
        per = per.join(F.broadcast(nation), "sample_id").groupBy(F.col("n_regionkey").cast("long").alias("sample_id")).agg(F.sum("n").alias("n"))
    return per


def size_profile(points: DataFrame) -> DataFrame:
    """Points a cloud: how many clouds, and the smallest, mean and largest."""
    return profile_of(points.groupBy("sample_id").agg(F.count("*").alias("n")))


def profile_of(per: DataFrame) -> DataFrame:
    return per.agg(F.count("*").alias("n_samples"), F.min("n").alias("min_points"), F.max("n").alias("max_points"), F.floor(F.sum("n") / F.count("*") * 1000000 + 0.5).cast("long").alias("mean_points_fx"))


# rasters ---------------------------------------------------------------------------------------------------------

VOWELS = "aeiouAEIOU"
#: Vowel flag and class by code point; what no vowel or letter is stands from 255 on.
_VOWEL = np.array([float(chr(k) in VOWELS) for k in range(256)])
_CLASS = np.array([0 if 97 <= k <= 122 else 1 if 65 <= k <= 90 else 2 if k in (10, 32) else 3 for k in range(256)]) / 3


def raster_shape(n: int) -> tuple[int, int]:
    """(height, width) of the near-square raster of n pixels."""
    w = math.isqrt(n - 1) + 1 if n else 0
    return (-(-n // w) if w else 0), w


def packed_rasters(df: DataFrame, key: str, text: str) -> DataFrame:
    """sample_id, cps: one packed row an image, a pixel a character; nothing is exploded or shuffled."""

    def run(batches):
        for b in (piece for whole in batches for piece in pieces(whole, pc.utf8_length(whole.column(1)))):
            rows = [np.frombuffer((t or "").encode("utf-32-le"), np.int32) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(rows, pa.list_(pa.int32()))], ["sample_id", "cps"])

    return df.select(F.col(key).cast("long"), F.col(text)).mapInArrow(run, "sample_id long, cps array<int>")


def raster_pixels(df: DataFrame, key: str, text: str) -> DataFrame:
    """Exploded form for SQL users: sample_id, i, u, v, w, h, cp."""
    n = F.length(text)
    w = F.ceil(F.sqrt(n.cast("double"))).cast("int")
    own = df.where(F.length(text) > 0).select(F.col(key).cast("long").alias("sample_id"), w.alias("w"), F.ceil(n / w).cast("int").alias("h"), F.posexplode(F.split(text, "")).alias("i", "ch"))
    return own.select("sample_id", "i", (F.col("i") % F.col("w")).alias("u"), F.floor(F.col("i") / F.col("w")).cast("int").alias("v"), "w", "h", F.expr("CASE WHEN length(ch) = 1 THEN ascii(ch) ELSE 0 END").alias("cp"))


def image_colours(cps: np.ndarray):
    """Luminance (255 and above are white), vowel flag and character class (letter lower 0, upper 1, white space 2, other 3) of code points."""
    r = np.minimum(cps, 255) / 255
    low = np.minimum(cps, 255)
    return r, _VOWEL[low], _CLASS[low]


def embedding_images(spark: SparkSession, sf_dir: str) -> DataFrame:
    """64 values as an 8 x 8 image: sample_id, u, v, value in [0, 1], label."""
    e = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("sample_id"), "label", F.posexplode("embedding").alias("i", "val"))
    return e.select("sample_id", "label", (F.col("i") % 8).alias("u"), F.floor(F.col("i") / 8).cast("int").alias("v"), ((F.col("val").cast("double") + 1) / 2).alias("value"))


SQL_EMBEDDING_IMAGES = """px AS (SELECT vec_id AS sample_id, label, (i - 1) % 8 AS u, ((i - 1) // 8)::INT AS v, (embedding[i]::DOUBLE + 1) / 2 AS value
  FROM embeddings, generate_series(1, 64) t(i))"""


def event_clouds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One point an event, one cloud a user: time of day, capped value, and k of the JSON properties."""
    ev = load(spark, sf_dir, "events")
    t = F.col("ts").cast("timestamp")
    second = F.hour(t) * 3600 + F.minute(t) * 60 + F.second(t)
    kind = F.when(F.col("event_type") == "click", 1).otherwise(0)
    return ev.select(
        F.col("user_id").cast("long").alias("sample_id"), F.col("event_id").cast("long").alias("point_no"), (second / 86400).alias("x"), (F.least(F.col("value"), F.lit(600.0)) / 600).alias("y"),
        (F.get_json_object("props", "$.k").cast("long") / 100).alias("z"), kind.cast("double").alias("r"), F.lit(0.0).alias("g"), F.lit(0.0).alias("b"), "ts", "event_type",
    )


# parametric shapes -------------------------------------------------------------------------------------------------

FAMILIES = ("sphere", "box", "cylinder", "cone", "torus", "plane", "helix", "saddle", "ellipsoid", "prism")


def shape_clouds(spark: SparkSession, sf_dir: str, level: str = "supplier", background: bool = True) -> DataFrame:
    """Points on ten families of surfaces, parameters from lineitem rows: + family, aspect, zone (part label), background."""
    p = lineitem_clouds(spark, sf_dir, level)
    u, v, e = (F.col("x") * QUANTITY + 0.5) / 50, F.col("z"), F.col("y")
    t, hh = 2 * math.pi * u, math.pi * v
    face = F.floor(6 * e).cast("int") % 6
    a, b = 2 * u - 1, 2 * v - 1
    side = F.when(face % 2 == 0, -1.0).otherwise(1.0)
    axis = F.floor(face / 2)
    k = F.floor(3 * e) % 3
    corner = lambda j, f: f(2 * math.pi * j / 3)
    prism = [(1 - u) * corner(k, f) + u * corner(k + 1, f) for f in (F.cos, F.sin)]
    zero = F.lit(0.0)
    forms = {
        0: (F.sin(hh) * F.cos(t), F.sin(hh) * F.sin(t), F.cos(hh)),
        1: tuple(F.when(axis == j, side).when(axis == (j + 1) % 3, a).otherwise(b) for j in range(3)),
        2: (0.6 * F.cos(t), 0.6 * F.sin(t), b),
        3: ((1 - v) * F.cos(t), (1 - v) * F.sin(t), b),
        4: ((0.7 + 0.3 * F.cos(2 * hh)) * F.cos(t), (0.7 + 0.3 * F.cos(2 * hh)) * F.sin(t), 0.3 * F.sin(2 * hh)),
        5: (a, b, zero),
        6: (0.7 * F.cos(6 * hh), 0.7 * F.sin(6 * hh), b),
        7: (a, b, a * a - b * b),
        8: (F.sin(hh) * F.cos(t), 0.5 * F.sin(hh) * F.sin(t), 0.4 * F.cos(hh)),
        9: (prism[0], prism[1], b),
    }
    family, aspect = F.pmod("sample_id", F.lit(10)).cast("int"), (F.floor(F.col("sample_id") / 10) % 4).cast("int")
    shrink = 1 - 0.25 * aspect
    out = p.withColumns({"family": family, "aspect": aspect, "zone": F.least(F.lit(2), F.floor(3 * v)).cast("int")})
    noise = (a, 2 * e - 1, b)
    axes = {}
    for j, name in enumerate("xyz"):
        value = zero
        for f, form in forms.items():
            value = F.when(F.col("family") == f, form[j]).otherwise(value)
        value = value * shrink if name == "z" else value
        axes[name] = (F.when(F.col("background"), noise[j]).otherwise(value) + 1.5) / 3
    out = out.select("sample_id", "point_no", *[axes[c].alias(c) for c in "xyz"], "r", "g", "b", "family", "aspect", "zone", "background")
    return out if background else out.where(~F.col("background"))


# subsets and mixtures ------------------------------------------------------------------------------------------------


def subset(df: DataFrame, thousandths: int, seed: int = 11, key: str = "sample_id") -> DataFrame:
    """A hashed share of the samples; a smaller share is contained in every larger one."""
    return df.where(draw(seed, F.col(key)) % 1000 < thousandths)


def mix(corpora: dict[str, DataFrame]) -> DataFrame:
    """Union of corpora with their name in ``corpus``."""
    out = None
    for name, df in corpora.items():
        part = df.withColumn("corpus", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out


def strip_background(points: DataFrame) -> DataFrame:
    return points.where(~F.col("background"))


def store(points: DataFrame, path: str, buckets: int = 16) -> None:
    """Write a corpus partitioned by a hash bucket of the sample, so that a nested subset reads only its buckets."""
    bucket = (draw(11, F.col("sample_id")) % 1000 * buckets / 1000).cast("int")
    points.withColumn("bucket", bucket).repartition("bucket", "sample_id").sortWithinPartitions("bucket", "sample_id").write.partitionBy("bucket").mode("overwrite").parquet(path)


def read_store(spark: SparkSession, path: str, thousandths: int = 1000, buckets: int = 16) -> DataFrame:
    last = (max(1, thousandths) - 1) * buckets // 1000
    return subset(spark.read.parquet(path).where(F.col("bucket") <= last), thousandths).drop("bucket")

"""Every method, variant, baseline and measure as a query, with the SQL that gives the same rows where SQL can express it."""

from __future__ import annotations

import math

from pyspark.sql import Window
from pyspark.sql import functions as F

from pointloom.functions.fixed import draw, fx6, sql_draw, sql_fx6
from pointloom.operators import augment, baselines, corpora, embed, lift, losses, masking, measure, patch, relops, voxel
from pointloom.operators.corpora import lineitem_clouds, sql_points
from pointloom.operators.patch import PATCH
from pointloom.operators.tokenizer import CentreTokenizer, VoxelTokenizer, sequences
from pointloom.schema import ATTRIBUTES, G32, G224, GridSpec, load

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def wrap(f):
        key = name or f.__name__
        QUERIES[key] = f
        if sql is not None:
            ORACLES[key] = sql
        return f

    return wrap


# shared pieces -----------------------------------------------------------------------------------------------------


def fxs(names, prefix=""):
    return [fx6(F.col(c)).alias(f"{prefix}{c}") for c in names]


def sum_fx(names):
    return [F.sum(fx6(F.col(c))).cast("long").alias(f"sum_{c}") for c in names]


def sql_fxs(names, prefix=""):
    return ", ".join(f"{sql_fx6(c)} AS {prefix}{c}" for c in names)


def sql_sum_fx(names):
    return ", ".join(f"sum({sql_fx6(c)})::BIGINT AS sum_{c}" for c in names)


def voxels(spark, sf_dir, grid: GridSpec = G32, rep="argmax", level="supplier"):
    return patch.with_slot(voxel.voxelize(voxel.assign(lineitem_clouds(spark, sf_dir, level), grid), rep), grid.patch)


def sql_base(grid: GridSpec = G32, rep="argmax", level="supplier", source="pts"):
    return f"WITH RECURSIVE {sql_points(level)}, {voxel.sql_keyed(source, grid)}, {voxel.sql_voxels(rep)}, {patch.sql_cells(grid.patch)}"


def named_levels(make):
    out = None
    for level in corpora.LEVELS:
        part = make(level).select(F.lit(level).alias("level"), "*")
        out = part if out is None else out.unionByName(part)
    return out


# corpora -------------------------------------------------------------------------------------------------------------

_PROFILE = "SELECT '{level}' AS level, count(*) AS n_samples, min(n) AS min_points, max(n) AS max_points, floor(sum(n) / count(*) * 1000000 + 0.5::DOUBLE)::BIGINT AS mean_points_fx FROM (WITH {pts} SELECT sample_id, count(*) AS n FROM pts GROUP BY ALL)"


@query(" UNION ALL ".join(_PROFILE.format(level=x, pts=sql_points(x)) for x in corpora.LEVELS))
def corpus_size_profile(spark, sf_dir):
    """The two upper levels are sums of the suppliers' sizes."""
    return named_levels(lambda level: corpora.profile_of(corpora.lineitem_sizes(spark, sf_dir, level)))


@query(f"WITH {sql_points()} SELECT sample_id, point_no, {sql_fxs(ATTRIBUTES)} FROM pts")
def lineitem_cloud_points(spark, sf_dir):
    return lineitem_clouds(spark, sf_dir).select("sample_id", "point_no", *fxs(ATTRIBUTES))


_SHAPE = "ceil(sqrt(length(text)::DOUBLE))::BIGINT"
_RASTER = """px AS (SELECT {key}::BIGINT AS sample_id, i - 1 AS i, (i - 1) % w AS u, (i - 1) // w AS v, w, ceil(n / w)::BIGINT AS h, ord(chars[i])::BIGINT AS cp
  FROM (SELECT {key}, string_split({text}, '') AS chars, length({text}) AS n, ceil(sqrt(length({text})::DOUBLE))::BIGINT AS w FROM {table} WHERE length({text}) > 0), unnest(range(1, n + 1)) t(i))"""


def sql_raster(table="documents", key="doc_id", text="text"):
    return _RASTER.format(table=table, key=key, text=text)


@query(f"WITH {sql_raster()} SELECT sample_id, count(*) AS n, max(w)::INT AS w, max(h)::INT AS h, sum(cp)::BIGINT AS sum_cp, sum(u * cp)::BIGINT AS sum_u, sum(v * cp)::BIGINT AS sum_v FROM px GROUP BY sample_id")
def raster_pixels(spark, sf_dir):
    px = corpora.raster_pixels(load(spark, sf_dir, "documents"), "doc_id", "text")
    return px.groupBy("sample_id").agg(F.count("*").alias("n"), F.max("w").alias("w"), F.max("h").alias("h"), F.sum("cp").cast("long").alias("sum_cp"), F.sum(F.col("u") * F.col("cp")).cast("long").alias("sum_u"), F.sum(F.col("v") * F.col("cp")).cast("long").alias("sum_v"))


# a column's rows above and below, at the pixel's own place: the window over rows sums the three pixels of each row first
_LIFTED = f"""pts AS (SELECT sample_id, i AS point_no, (u + 0.5::DOUBLE) / w AS x, depth AS y, 1 - (v + 0.5::DOUBLE) / h AS z, least(cp, 255) / 255 AS r,
    CASE WHEN chr(cp::INT) IN ({', '.join(f"'{c}'" for c in corpora.VOWELS)}) THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END AS g,
    (CASE WHEN cp BETWEEN 97 AND 122 THEN 0 WHEN cp BETWEEN 65 AND 90 THEN 1 WHEN cp IN (32, 10) THEN 2 ELSE 3 END) / 3 AS b FROM blur)"""
def sql_lifted(table="documents", key="doc_id", text="text"):
    """Depth: sums of three pixels along each row, at every place of the grid, then over three rows."""
    rows1 = """grid AS (SELECT s.sample_id, u, v, w, h FROM (SELECT DISTINCT sample_id, w, h FROM px) s, unnest(range(w)) a(u), unnest(range(h)) b(v)),
    rows1 AS (SELECT g.sample_id, g.u, g.v, sum(least(coalesce(px.cp, 0), 255)) OVER q AS s1, count(px.cp) OVER q AS n1 FROM grid g LEFT JOIN px ON px.sample_id = g.sample_id AND px.u = g.u AND px.v = g.v
      WINDOW q AS (PARTITION BY g.sample_id, g.v ORDER BY g.u ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING)),
    rows2 AS (SELECT sample_id, u, v, sum(s1) OVER q AS s2, sum(n1) OVER q AS n2 FROM rows1 WINDOW q AS (PARTITION BY sample_id, u ORDER BY v ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING)),
    blur AS (SELECT px.*, s2 / (n2 * 255.0::DOUBLE) AS depth FROM px JOIN rows2 USING (sample_id, u, v))"""
    return f"{sql_raster(table, key, text)}, {rows1}, {_LIFTED}"


def cloud_sums(spark, sf_dir, table, key, text):
    """Raster, lift and sums in one map over the texts: of a cloud only its sums leave the task."""
    import numpy as np
    import pyarrow as pa

    teacher = lift.BlurTeacher(1)

    def run(batches):
        for b in batches:
            rows = []
            for k, t in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                cps = np.frombuffer((t.as_py() or "").encode("utf-32-le"), np.int32)
                if len(cps):
                    rows.append((k, len(cps), *(int(np.floor(c * 1e6 + 0.5).astype(np.int64).sum()) for c in lift.lifted(cps, teacher))))
            columns = zip(*rows, strict=True) if rows else [()] * 8
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], ["sample_id", "n", *(f"sum_{c}" for c in ATTRIBUTES)])

    return load(spark, sf_dir, table).select(F.col(key).cast("long"), text).mapInArrow(run, "sample_id long, n long, " + ", ".join(f"sum_{c} long" for c in ATTRIBUTES))


_SUMS = "SELECT sample_id, count(*) AS n, " + sql_sum_fx(ATTRIBUTES) + " FROM pts GROUP BY sample_id"


@query(f"WITH {sql_lifted()} SELECT sample_id, min({sql_fx6('y')}) AS min_depth, max({sql_fx6('y')}) AS max_depth, sum({sql_fx6('y')})::BIGINT AS sum_depth FROM pts GROUP BY sample_id")
def raster_min_mean_depth(spark, sf_dir):
    return lift.depth_table(load(spark, sf_dir, "documents"), "doc_id", "text").where("n > 0").drop("n")


@query(f"WITH {sql_lifted()} {_SUMS}")
def lift_document_clouds(spark, sf_dir):
    return cloud_sums(spark, sf_dir, "documents", "doc_id", "text")


@query(f"WITH {sql_lifted('pages', 'page_id', 'html')} {_SUMS}")
def lift_page_clouds(spark, sf_dir):
    return cloud_sums(spark, sf_dir, "pages", "page_id", "html")


@query(f"WITH {sql_lifted('benchmark', 'item_id', 'text')} {_SUMS}")
def lift_benchmark_clouds(spark, sf_dir):
    return cloud_sums(spark, sf_dir, "benchmark", "item_id", "text")


@query(f"""WITH {corpora.SQL_EMBEDDING_IMAGES} SELECT sample_id, count(*) AS n, {sql_sum_fx(('x', 'y', 'z', 'r'))} FROM (
  SELECT sample_id, (u + 0.5::DOUBLE) / 8 AS x, value AS y, 1 - (v + 0.5::DOUBLE) / 8 AS z, value AS r FROM px) GROUP BY sample_id""")
def lift_embedding_images(spark, sf_dir):
    px = corpora.embedding_images(spark, sf_dir).withColumns({"w": F.lit(8), "h": F.lit(8), "r": F.col("value"), "g": F.lit(0.0), "b": F.lit(0.0)})
    return lift.lift_pixels(px, "value").groupBy("sample_id").agg(F.count("*").alias("n"), *sum_fx(("x", "y", "z", "r")))


@query(" UNION ALL ".join(f"SELECT '{t}' AS corpus, count(*) AS n_clouds, sum(length({c}))::BIGINT AS n_points FROM {t}" for t, c in (("documents", "text"), ("pages", "html"), ("conversations", "text"), ("benchmark", "text"))))
def mixed_corpus_union(spark, sf_dir):
    parts = {t: load(spark, sf_dir, t).select(F.length(c).alias("n")) for t, c in (("documents", "text"), ("pages", "html"), ("conversations", "text"), ("benchmark", "text"))}
    return corpora.mix(parts).groupBy("corpus").agg(F.count("*").alias("n_clouds"), F.sum("n").cast("long").alias("n_points"))


@query(f"SELECT u AS thousandths, count(*) AS n FROM documents, (VALUES (10), (20), (40), (80), (420), (1000)) t(u) WHERE {sql_draw(11, 'doc_id')} % 1000 < u GROUP BY u")
def corpus_subset_ladder(spark, sf_dir):
    docs = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("sample_id"))
    out = None
    for u in (10, 20, 40, 80, 420, 1000):
        part = corpora.subset(docs, u).agg(F.count("*").alias("n")).select(F.lit(u).alias("thousandths"), "n").where("n > 0")
        out = part if out is None else out.union(part)
    return out


_SIDE = "(('0x' || substr(md5(text), 1, 8))::BIGINT % 5 = 0)"


@query(f"SELECT {_SIDE} AS is_test, count(*) AS n, count(DISTINCT text) AS n_texts, (SELECT count(*) FROM (SELECT text FROM documents WHERE {_SIDE} INTERSECT SELECT text FROM documents WHERE NOT {_SIDE})) AS n_shared FROM documents GROUP BY ALL")
def split_by_text_hash(spark, sf_dir):
    docs = load(spark, sf_dir, "documents").select(F.md5("text").alias("m")).withColumn("is_test", F.conv(F.substring("m", 1, 8), 16, 10).cast("long") % 5 == 0)
    # equal texts have equal hashes, so texts need not be shuffled
    texts = docs.groupBy("m").agg(F.count("*").alias("n"), F.min("is_test").alias("is_test"), (F.min("is_test") != F.max("is_test")).cast("long").alias("both"))
    every = Window.partitionBy()
    sides = texts.groupBy("is_test").agg(F.sum("n").alias("n"), F.count("*").alias("n_texts"), F.sum("both").alias("both"))
    return sides.select("is_test", "n", "n_texts", F.sum("both").over(every).alias("n_shared"))


@query(f"WITH {sql_points()} SELECT background, count(*) AS n, count(DISTINCT sample_id) AS n_samples FROM pts GROUP BY background")
def strip_background(spark, sf_dir):
    pts = lineitem_clouds(spark, sf_dir)
    kept = corpora.strip_background(pts)
    gone = pts.where("background")
    return kept.unionByName(gone).groupBy("background").agg(F.count("*").alias("n"), F.countDistinct("sample_id").alias("n_samples"))


@query(f"""WITH pts AS (SELECT user_id::BIGINT AS sample_id, event_id AS point_no, (hour(ts) * 3600 + minute(ts) * 60 + second(ts)) / 86400 AS x, least(value, 600.0::DOUBLE) / 600 AS y,
  json_extract_string(props, '$.k')::BIGINT / 100 AS z FROM events) SELECT sample_id, count(*) AS n, {sql_sum_fx('xyz')} FROM pts GROUP BY sample_id""")
def event_json_points(spark, sf_dir):
    return corpora.event_clouds(spark, sf_dir).groupBy("sample_id").agg(F.count("*").alias("n"), *sum_fx("xyz"))


@query(f"""WITH {sql_points('order')}, c AS (SELECT sample_id, count(*) AS n, {sql_sum_fx('y')} FROM pts GROUP BY sample_id)
  SELECT o_orderpriority, c_mktsegment, count(*) AS n_clouds, sum(n)::BIGINT AS n_points, sum(sum_y)::BIGINT AS sum_y FROM c JOIN orders ON o_orderkey = sample_id JOIN customer ON c_custkey = o_custkey GROUP BY ALL""")
def order_clouds(spark, sf_dir):
    c = lineitem_clouds(spark, sf_dir, "order").groupBy("sample_id").agg(F.count("*").alias("n"), *sum_fx("y"))
    o, cust = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderpriority"), load(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    j = c.join(o, c.sample_id == o.o_orderkey).join(cust, F.col("o_custkey") == F.col("c_custkey"))
    return j.groupBy("o_orderpriority", "c_mktsegment").agg(F.count("*").alias("n_clouds"), F.sum("n").alias("n_points"), F.sum("sum_y").alias("sum_y"))


# augmentation --------------------------------------------------------------------------------------------------------


@query(f"WITH {sql_points()} SELECT sample_id, {sql_sum_fx('xyz')} FROM {augment.sql_rotate('pts', 3)} GROUP BY sample_id")
def rotate_z_points(spark, sf_dir):
    return augment.rotate_z(lineitem_clouds(spark, sf_dir), 3, eighths=True).groupBy("sample_id").agg(*sum_fx("xyz"))


_STD = ", ".join(f"({c} - {m}::DOUBLE) / {s}::DOUBLE AS {c}" for c, m, s in zip("rgb", augment.MEAN, augment.STD, strict=True))


@query(f"WITH {sql_points()} SELECT sample_id, {sql_sum_fx('rgb')} FROM (SELECT sample_id, {_STD} FROM pts) GROUP BY sample_id")
def colour_standardise(spark, sf_dir):
    return augment.colour_standardise(lineitem_clouds(spark, sf_dir)).groupBy("sample_id").agg(*sum_fx("rgb"))


for _name, _rho, _tau in (("34", 3 / 4, 0.0), ("23", 2 / 3, 0.0), ("12", 1 / 2, 0.0), ("12t", 1 / 2, 1 / 2)):

    @query(f"WITH {sql_points()} SELECT sample_id, {sql_sum_fx('xyz')} FROM {augment.sql_scale('pts', _rho, _tau)} GROUP BY sample_id", f"scale_translate_{_name}")
    def _scaled(spark, sf_dir, rho=_rho, tau=_tau):
        return augment.scale_translate(lineitem_clouds(spark, sf_dir), rho, tau).groupBy("sample_id").agg(*sum_fx("xyz"))


_COPIES = "(SELECT * FROM pts, unnest(range(1, 6)) c(copy))"
_PERTURBED = augment.sql_scale(augment.sql_rotate(_COPIES, 31, ("sample_id", "copy")), 0.5, 0.5, 38, ("sample_id", "copy"))


@query(f"WITH {sql_points()} SELECT copy::INT AS copy, count(*) AS n, {', '.join(f'min({sql_fx6(c)}) AS min_{c}, max({sql_fx6(c)}) AS max_{c}' for c in 'xyz')} FROM {_PERTURBED} GROUP BY copy")
def perturb_five_copies(spark, sf_dir):
    out = augment.perturb(lineitem_clouds(spark, sf_dir))
    return out.groupBy("copy").agg(F.count("*").alias("n"), *[f(fx6(F.col(c))).alias(f"{n}_{c}") for c in "xyz" for n, f in (("min", F.min), ("max", F.max))])


@query(f"""WITH {sql_points()}, l AS (SELECT *, {', '.join(f'min({c}) OVER w AS lo{c}, max({c}) OVER w AS hi{c}' for c in 'xyz')} FROM pts WINDOW w AS (PARTITION BY sample_id))
  SELECT sample_id, {sql_sum_fx('xyz')} FROM (SELECT sample_id, {', '.join(f'CASE WHEN hi{c} > lo{c} THEN ({c} - lo{c}) / (hi{c} - lo{c}) ELSE 0.0::DOUBLE END AS {c}' for c in 'xyz')} FROM l) GROUP BY sample_id""")
def normalise_per_sample(spark, sf_dir):
    return lift.normalise(lineitem_clouds(spark, sf_dir)).groupBy("sample_id").agg(*sum_fx("xyz"))


# voxels and patches --------------------------------------------------------------------------------------------------


@query(f"{sql_base()} SELECT sample_id, count(*) AS n, count(DISTINCT (vi * 1024 + vj) * 1024 + vk) AS n_voxels, sum(vi)::BIGINT AS si, sum(vj)::BIGINT AS sj, sum(vk)::BIGINT AS sk FROM keyed GROUP BY sample_id")
def voxel_assign(spark, sf_dir):
    k = voxel.assign(lineitem_clouds(spark, sf_dir), G32)
    return k.groupBy("sample_id").agg(F.count("*").alias("n"), F.countDistinct((F.col("vi") * 1024 + F.col("vj")) * 1024 + F.col("vk")).alias("n_voxels"), *[F.sum(c).alias(f"s{c[1]}") for c in voxel.KEY])


for _rep in ("argmax", "colmax", "mean", "first"):

    @query(f"{sql_base(rep=_rep)} SELECT sample_id, vi, vj, vk, n_points, {sql_fxs(ATTRIBUTES)} FROM vox", f"voxelize_{_rep}")
    def _voxelized(spark, sf_dir, rep=_rep):
        return voxel.voxelize(voxel.assign(lineitem_clouds(spark, sf_dir), G32), rep).select("sample_id", *voxel.KEY, "n_points", *fxs(ATTRIBUTES))


_TURNED = f"WITH {sql_points()}, t AS (SELECT *, {', '.join(f'floor({c} / {G32.edge!r}::DOUBLE)::INT AS {k}' for k, c in zip(voxel.KEY, 'xyz', strict=True))} FROM {augment.sql_rotate('pts', 3)})"
_INSIDE = " AND ".join(f"{k} BETWEEN 0 AND 31" for k in voxel.KEY)


@query(f"{_TURNED} SELECT sample_id, count(*) AS n, {', '.join(f'sum(greatest(0, least(31, {k})))::BIGINT AS s{k[1]}' for k in voxel.KEY)} FROM t GROUP BY sample_id")
def voxel_bounds_clip(spark, sf_dir):
    k = voxel.assign(augment.rotate_z(lineitem_clouds(spark, sf_dir), 3, eighths=True), G32, "clip")
    return k.groupBy("sample_id").agg(F.count("*").alias("n"), *[F.sum(c).alias(f"s{c[1]}") for c in voxel.KEY])


@query(f"{_TURNED} SELECT sample_id, count(*) AS n, {', '.join(f'sum({k})::BIGINT AS s{k[1]}' for k in voxel.KEY)} FROM t WHERE {_INSIDE} GROUP BY sample_id")
def voxel_bounds_drop(spark, sf_dir):
    k = voxel.assign(augment.rotate_z(lineitem_clouds(spark, sf_dir), 3, eighths=True), G32, "drop")
    return k.groupBy("sample_id").agg(F.count("*").alias("n"), *[F.sum(c).alias(f"s{c[1]}") for c in voxel.KEY])


_BY_PATCH = "p AS (SELECT sample_id, ci, cj, ck, count(*) AS n_vox, sum(n_points)::BIGINT AS n_points FROM cells GROUP BY ALL)"
_STATS = "SELECT sample_id, sum(n_points)::BIGINT AS n_points, sum(n_vox)::BIGINT AS n_voxels, count(*) AS n_patches, max(n_vox) AS max_vox FROM p GROUP BY sample_id"


@query(f"{sql_base()}, {_BY_PATCH} {_STATS}")
def voxel_compression(spark, sf_dir):
    return measure.tokenizer_stats(voxels(spark, sf_dir))


@query(f"{sql_base(G224)}, {_BY_PATCH} {_STATS}")
def voxel_compression_fine(spark, sf_dir):
    return measure.tokenizer_stats(voxels(spark, sf_dir, G224))


@query(f"{sql_base(level='region')}, {_BY_PATCH} {_STATS}")
def voxel_compression_large(spark, sf_dir):
    return measure.tokenizer_stats(voxels(spark, sf_dir, level="region"))


@query(f"{sql_base(G224)} SELECT sample_id, ci, cj, ck, count(*) AS n_vox FROM cells GROUP BY ALL")
def patch_partition(spark, sf_dir):
    return masking.patches_of(voxels(spark, sf_dir, G224))


@query(f"{sql_base()} SELECT DISTINCT sample_id, ci * 8 AS i, cj * 8 AS j, ck * 8 AS k FROM cells")
def patch_corners(spark, sf_dir):
    return patch.corner(masking.patches_of(voxels(spark, sf_dir)), 8).select("sample_id", "corner.i", "corner.j", "corner.k")


@query(f"{sql_base()}, {patch.sql_graph()} SELECT DISTINCT sample_id, ci, cj, ck, n_vox, {', '.join(f'{sql_fx6(c)} AS {c}' for c in ('cx', 'cy', 'cz'))} FROM graph")
def patch_centres(spark, sf_dir):
    return patch.centres(voxels(spark, sf_dir)).select(*PATCH, "n_vox", *fxs(("cx", "cy", "cz")))


@query(f"{sql_base()}, {patch.sql_graph()} SELECT sample_id, vi, vj, vk, {sql_fxs(('dx', 'dy', 'dz'))} FROM graph")
def graph_edges(spark, sf_dir):
    return patch.graph_features(voxels(spark, sf_dir)).select("sample_id", *voxel.KEY, *fxs(("dx", "dy", "dz")))


_TWELVE = (*ATTRIBUTES, "dx", "dy", "dz", "cx", "cy", "cz")


@query(f"{sql_base()}, {patch.sql_graph()} SELECT sample_id, ci, cj, ck, slot, {sql_fxs(_TWELVE)} FROM graph")
def graph_features_12(spark, sf_dir):
    return patch.graph_features(voxels(spark, sf_dir)).select(*PATCH, "slot", *fxs(_TWELVE))


@query(f"{sql_base()} SELECT sample_id, ci, cj, ck, slot, {sql_fxs(ATTRIBUTES)} FROM cells")
def origin_features_6(spark, sf_dir):
    return patch.graph_features(voxels(spark, sf_dir), "origin").select(*PATCH, "slot", *fxs(ATTRIBUTES))


@query(f"{sql_base()} SELECT slot, count(*) AS n FROM cells GROUP BY slot")
def slot_index(spark, sf_dir):
    return voxels(spark, sf_dir).groupBy("slot").agg(F.count("*").alias("n"))


# tokens --------------------------------------------------------------------------------------------------------------

_TOKENS = f"{sql_base()}, {embed.sql_tokens(8)} SELECT {embed.SQL_TOKEN_COLUMNS} FROM tok"

for _name, _path in (("tokens", "sql"), ("onepass", "onepass"), ("kernel", "kernel")):

    @query(_TOKENS, f"slot_embed_{_name}")
    def _embedded(spark, sf_dir, path=_path):
        return VoxelTokenizer(G32, path=path).transform(lineitem_clouds(spark, sf_dir))


@query(f"{sql_base(G224)}, {embed.sql_tokens(16)} SELECT {embed.SQL_TOKEN_COLUMNS} FROM tok")
def slot_embed_full_grid(spark, sf_dir):
    """The published sizes: 224 voxels an axis, patches of 16, one matrix for each of 4 096 slots."""
    return VoxelTokenizer(G224, path="kernel").transform(lineitem_clouds(spark, sf_dir))


@query(f"{sql_base()}, {embed.sql_tokens(8, 16)} SELECT {embed.SQL_TOKEN_COLUMNS} FROM tok")
def slot_embed_wide(spark, sf_dir):
    return VoxelTokenizer(G32, channels=16, path="kernel").transform(lineitem_clouds(spark, sf_dir))


@query(f"{sql_base()}, {embed.sql_tokens(8, features='origin')} SELECT {embed.SQL_TOKEN_COLUMNS} FROM tok")
def slot_embed_origin(spark, sf_dir):
    return VoxelTokenizer(G32, features="origin").transform(lineitem_clouds(spark, sf_dir))


@query(f"WITH {sql_lifted()}, {voxel.sql_keyed('pts', G32)}, {voxel.sql_voxels()}, {patch.sql_cells(8)}, {embed.sql_tokens(8, 1)} SELECT sample_id, count(*) AS n_tokens, sum(n_vox)::BIGINT AS n_voxels, sum(num)::BIGINT AS sum_num FROM tok GROUP BY sample_id")
def tokenize_documents(spark, sf_dir):
    """Images are one packed row each, so raster, lift and tokens are one map over the texts; nothing is shuffled."""
    import numpy as np
    import pyarrow as pa

    from pointloom.kernels import packed_tokens

    teacher = lift.BlurTeacher(1)

    def run(batches):
        for b in batches:
            ids, out = [], []
            for key, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                cps = np.frombuffer((text.as_py() or "").encode("utf-32-le"), np.int32)
                if len(cps):
                    n, num = packed_tokens(np.stack(lift.lifted(cps, teacher), 1), G32, 1)
                    ids.append(key)
                    out.append((len(n), int(n.sum()), int(num.sum())))
            columns = zip(*out, strict=True) if out else [()] * 3
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), *[pa.array(c, pa.int64()) for c in columns]], ["sample_id", "n_tokens", "n_voxels", "sum_num"])

    texts = load(spark, sf_dir, "documents").select(F.col("doc_id").cast("long"), "text")
    return texts.mapInArrow(run, "sample_id long, n_tokens long, n_voxels long, sum_num long")


@query(f"{sql_base()} SELECT sample_id, count(*)::INT AS n_tokens FROM (SELECT DISTINCT sample_id, ci, cj, ck FROM cells) GROUP BY sample_id")
def tokens_per_cloud(spark, sf_dir):
    return sequences(VoxelTokenizer(G32, channels=2).transform(lineitem_clouds(spark, sf_dir))).select("sample_id", "n_tokens")


for _which, _name in enumerate(("encoder", "decoder")):

    @query(f"{sql_base()} {embed.sql_pos(8, 32, _which)}", f"pos_embed_{_name}")
    def _positions(spark, sf_dir, which=_which):
        return embed.pos_embed(masking.patches_of(voxels(spark, sf_dir)), 8, 32, which)


@query(f"""{sql_base()}, {embed.sql_tokens(8)}, t AS (SELECT sample_id, ci * 100 + cj * 10 + ck AS pos, list(floor(num / (n_vox * n_vox * 100) + 0.5::DOUBLE) / 1000000.0::DOUBLE ORDER BY c) AS t FROM tok GROUP BY ALL),
  s AS (SELECT q.sample_id, q.pos, k.t AS k, exp(list_dot_product(q.t, k.t) / sqrt(4.0::DOUBLE)) AS e FROM t q JOIN t k ON q.sample_id = k.sample_id)
  SELECT sample_id, pos, {', '.join(f'{sql_fx6(f"sum(e * k[{c + 1}]) / sum(e)")} AS o{c}' for c in range(4))} FROM s GROUP BY sample_id, pos""")
def masked_attention_head(spark, sf_dir):
    tok = VoxelTokenizer(G32).transform(lineitem_clouds(spark, sf_dir))
    pos = (F.col("ci") * 100 + F.col("cj") * 10 + F.col("ck")).alias("pos")
    rows = tok.groupBy("sample_id", pos).agg(F.transform(F.array_sort(F.collect_list(F.struct("c", "token_fx"))), lambda x: x["token_fx"] / 1000000.0).alias("t"))
    return embed.attention_head(rows)


# masks and losses ----------------------------------------------------------------------------------------------------

for _pct in (15, 30, 45, 60, 75, 90):

    @query(f"{sql_base()}, {masking.sql_mask(_pct)} SELECT sample_id, ci, cj, ck, hidden FROM mask", f"mask_patches_{_pct}")
    def _masked(spark, sf_dir, pct=_pct):
        return masking.random_mask(masking.patches_of(voxels(spark, sf_dir)), pct).select(*PATCH, "hidden")


@query(f"{sql_base()}, {masking.sql_mask(60, mode='bernoulli')} SELECT sample_id, count(*) AS n_patches, count(*) FILTER (WHERE hidden) AS n_hidden FROM mask GROUP BY sample_id")
def mask_bernoulli(spark, sf_dir):
    m = masking.random_mask(masking.patches_of(voxels(spark, sf_dir)), 60, mode="bernoulli")
    return m.groupBy("sample_id").agg(F.count("*").alias("n_patches"), F.count(F.when(F.col("hidden"), 1)).alias("n_hidden"))


@query(f"{sql_base()}, {masking.sql_mask(60)}, {embed.sql_tokens(8)} SELECT {embed.SQL_TOKEN_COLUMNS} FROM tok SEMI JOIN (SELECT * FROM mask WHERE NOT hidden) m USING (sample_id, ci, cj, ck)")
def visible_tokens(spark, sf_dir):
    """Hidden patches go before embedding; the SQL embeds everything first."""
    v = voxels(spark, sf_dir)
    return embed.slot_embed(masking.visible(v, masking.random_mask(masking.patches_of(v), 60)), 8)


def _loss_parts(spark, sf_dir, features="graph"):
    v = patch.graph_features(voxels(spark, sf_dir), features)
    mask = masking.random_mask(masking.patches_of(v), 60)
    vis, hid = masking.visible(v, mask), masking.visible(v, mask, True)
    pred, prob = losses.mean_predictor(vis, hid, 8, G32.edge)
    if features == "graph":
        # a predictor of the relative attributes: slot centres' own graph
        pred = patch.graph_features(pred)
    return hid, pred, prob


_AT = {c: f"({k} + 0.5::DOUBLE) * {G32.edge!r}::DOUBLE" for c, k in zip("xyz", voxel.KEY, strict=True)}


def sql_loss(features="graph"):
    rel = losses.RELATIVE if features == "graph" else losses.RELATIVE[:3]
    err = " + ".join(["0.0::DOUBLE", *(f"(t.{c} - p.{c}) * (t.{c} - p.{c})" for c in rel)])
    p = lambda q: f"greatest({losses.EPS!r}::DOUBLE, least({1 - losses.EPS!r}::DOUBLE, {q}))"
    return f"""{sql_base()}, {patch.sql_graph()}, {masking.sql_mask(60)},
    vis AS (SELECT g.* FROM graph g SEMI JOIN (SELECT * FROM mask WHERE NOT hidden) m USING (sample_id, ci, cj, ck)),
    hid AS (SELECT g.* FROM graph g SEMI JOIN (SELECT * FROM mask WHERE hidden) m USING (sample_id, ci, cj, ck)),
    col AS (SELECT sample_id, {', '.join(f'sum({sql_fx6(c)})::BIGINT / count(*) / 1000000.0::DOUBLE AS {c}' for c in 'rgb')} FROM vis GROUP BY sample_id),
    pr0 AS (SELECT h.sample_id, ci, cj, ck, slot, {', '.join(f'{e} AS {c}' for c, e in _AT.items())}, col.r, col.g, col.b FROM hid h JOIN col ON h.sample_id = col.sample_id),
    pr1 AS (SELECT *, {', '.join(f'sum({sql_fx6(c)}) OVER w / count(*) OVER w / 1000000.0::DOUBLE AS c{c}' for c in 'xyz')} FROM pr0 WINDOW w AS (PARTITION BY sample_id, ci, cj, ck)),
    pr AS (SELECT *, x - cx AS dx, y - cy AS dy, z - cz AS dz FROM pr1),
    mse AS (SELECT t.sample_id, t.ci, t.cj, t.ck, sum({sql_fx6(err)})::BIGINT / count(*) AS mse_fx FROM hid t JOIN pr p USING (sample_id, ci, cj, ck, slot) GROUP BY ALL),
    pair AS (SELECT t.sample_id, t.ci, t.cj, t.ck, t.slot AS ti, p.slot AS pi, 0.0::DOUBLE + (t.x - p.x) * (t.x - p.x) + (t.y - p.y) * (t.y - p.y) + (t.z - p.z) * (t.z - p.z) AS d
             FROM hid t JOIN pr p USING (sample_id, ci, cj, ck)),
    cd AS (SELECT a.sample_id, a.ci, a.cj, a.ck, a.m + b.m AS cd_fx FROM
      (SELECT sample_id, ci, cj, ck, sum({sql_fx6('d')})::BIGINT / count(*) AS m FROM (SELECT sample_id, ci, cj, ck, ti, min(d) AS d FROM pair GROUP BY ALL) GROUP BY ALL) a JOIN
      (SELECT sample_id, ci, cj, ck, sum({sql_fx6('d')})::BIGINT / count(*) AS m FROM (SELECT sample_id, ci, cj, ck, pi, min(d) AS d FROM pair GROUP BY ALL) GROUP BY ALL) b USING (sample_id, ci, cj, ck)),
    np AS (SELECT greatest(1, count(*))::DOUBLE AS n FROM (SELECT DISTINCT sample_id, ci, cj, ck FROM vis)),
    prob AS (SELECT slot, count(*) / (SELECT n FROM np) AS p FROM vis GROUP BY slot),
    slots AS (SELECT s::INT AS slot, {p('coalesce(p, 0.0::DOUBLE)')} AS p FROM range(512) t(s) LEFT JOIN prob ON prob.slot = s),
    occ AS (SELECT q.sample_id, q.ci, q.cj, q.ck, sum({sql_fx6('CASE WHEN h.slot IS NOT NULL THEN -ln(s.p) ELSE -ln(1 - s.p) END')})::BIGINT / 512 AS occ_fx
      FROM (SELECT DISTINCT sample_id, ci, cj, ck FROM hid) q CROSS JOIN slots s LEFT JOIN hid h ON h.sample_id = q.sample_id AND h.ci = q.ci AND h.cj = q.cj AND h.ck = q.ck AND h.slot = s.slot GROUP BY ALL)"""


_ROUND = "floor({0} + 0.5::DOUBLE)::BIGINT"


def rounded(df, *names):
    return df.select(*PATCH, *[F.floor(F.col(c) + 0.5).cast("long").alias(c) for c in names])


@query(f"{sql_loss()} SELECT sample_id, ci, cj, ck, {_ROUND.format('mse_fx')} AS mse_fx FROM mse")
def loss_relative_mse(spark, sf_dir):
    hid, pred, _ = _loss_parts(spark, sf_dir)
    return rounded(losses.relative_mse(hid, pred), "mse_fx")


@query(f"{sql_loss()} SELECT sample_id, ci, cj, ck, {_ROUND.format('cd_fx')} AS cd_fx FROM cd")
def loss_chamfer(spark, sf_dir):
    hid, pred, _ = _loss_parts(spark, sf_dir)
    return rounded(losses.chamfer(hid, pred), "cd_fx")


for _name, _form in (("loss_occupancy", losses.occupancy_sparse), ("loss_occupancy_dense", losses.occupancy_dense)):

    @query(f"{sql_loss()} SELECT sample_id, ci, cj, ck, {_ROUND.format('occ_fx')} AS occ_fx FROM occ", _name)
    def _occupied(spark, sf_dir, form=_form):
        hid, _, prob = _loss_parts(spark, sf_dir)
        return rounded(form(hid, prob, 8), "occ_fx")


@query(f"SELECT count(*) AS n, 0::BIGINT AS n_different FROM ({sql_loss()} SELECT * FROM occ)")
def occupancy_sparse_vs_dense(spark, sf_dir):
    hid, _, prob = _loss_parts(spark, sf_dir)
    a, b = rounded(losses.occupancy_sparse(hid, prob, 8), "occ_fx"), rounded(losses.occupancy_dense(hid, prob, 8), "occ_fx").withColumnRenamed("occ_fx", "dense_fx")
    return a.join(b, list(PATCH)).agg(F.count("*").alias("n"), F.count(F.when(F.col("occ_fx") != F.col("dense_fx"), 1)).alias("n_different"))


def _sql_total(features, terms):
    loss = " + ".join(f"{t}_fx" for t in terms)
    cols = {"mse_fx": "mse_fx", "cd_fx": "cd_fx", "occ_fx": "occ_fx", "loss_fx": loss}
    per = ", ".join(f"floor(sum({_ROUND.format(e)})::BIGINT / count(*) + 0.5::DOUBLE)::BIGINT AS {n}" for n, e in cols.items())
    return f"{sql_loss(features)} SELECT sample_id, count(*) AS n_patches, {per} FROM mse JOIN cd USING (sample_id, ci, cj, ck) JOIN occ USING (sample_id, ci, cj, ck) GROUP BY sample_id"


_ALL = ("mse", "cd", "occ")


@query(_sql_total("graph", _ALL))
def loss_total(spark, sf_dir):
    t = losses.total(*_loss_parts(spark, sf_dir), 8)
    return t.select("sample_id", "n_patches", *[F.floor(F.col(c) + 0.5).cast("long").alias(c) for c in ("mse_fx", "cd_fx", "occ_fx", "loss_fx")])


_ARMS = (("graph", ("mse",)), ("graph", ("mse", "cd")), ("graph", _ALL), ("origin", _ALL))


@query(" UNION ALL ".join(f"SELECT '{f} {'+'.join(t)}' AS arm, sum(loss_fx)::BIGINT AS loss_fx, sum(n_patches)::BIGINT AS n_patches FROM ({_sql_total(f, t)})" for f, t in _ARMS))
def loss_terms_ablation(spark, sf_dir):
    """The arms on the same attributes share one pass over the patches."""
    out, parts = None, _loss_parts(spark, sf_dir)
    for features in ("graph", "origin"):
        arms = {f"{f} {'+'.join(t)}": t for f, t in _ARMS if f == features}
        each = losses.arms_total(losses.patch_terms(*parts, 8, features), arms)
        whole = each.agg(F.array(*[F.struct(F.lit(a).alias("arm"), F.sum(F.floor(F.col(f"l{k}") + 0.5).cast("long")).alias("loss_fx"), F.sum("n_patches").alias("n_patches")) for k, a in enumerate(arms)]).alias("a"))
        part = whole.select(F.explode("a").alias("a")).select("a.*")
        out = part if out is None else out.union(part)
    return out


@query(f"{sql_loss()} SELECT slot, {sql_fx6('p')} AS p_fx FROM prob")
def mean_predictor(spark, sf_dir):
    _, _, prob = _loss_parts(spark, sf_dir)
    return prob.select("slot", fx6(F.col("p")).alias("p_fx"))


# baselines -------------------------------------------------------------------------------------------------------------

_D = "(0.0::DOUBLE + (p.x - c.x) * (p.x - c.x) + (p.y - c.y) * (p.y - c.y) + (p.z - c.z) * (p.z - c.z))"
_FPS = f"""WITH RECURSIVE {sql_points()}, p0 AS (SELECT DISTINCT sample_id, point_no, x, y, z FROM pts),
  rec AS (SELECT *, 1 AS rank, 'inf'::DOUBLE AS near, row_number() OVER (PARTITION BY sample_id ORDER BY point_no) = 1 AS pick FROM p0
    UNION ALL
    SELECT sample_id, point_no, x, y, z, rank, near, row_number() OVER (PARTITION BY sample_id ORDER BY near DESC, point_no) = 1 AS pick FROM (
      SELECT p.sample_id, p.point_no, p.x, p.y, p.z, p.rank + 1 AS rank, least(p.near, {_D}) AS near FROM rec p JOIN rec c ON p.sample_id = c.sample_id AND c.pick WHERE p.rank < 5)),
  cen AS (SELECT sample_id, rank, point_no, x, y, z FROM rec WHERE pick)"""


def _distinct_points(spark, sf_dir, level="supplier"):
    return lineitem_clouds(spark, sf_dir, level).select("sample_id", "point_no", *ATTRIBUTES).dropDuplicates(["sample_id", "point_no"])


@query(f"{_FPS} SELECT sample_id, rank, point_no FROM cen")
def fps_centres(spark, sf_dir):
    return baselines.fps(_distinct_points(spark, sf_dir), 5).select("sample_id", "rank", "point_no")


_KNN = f"knn AS (SELECT * FROM (SELECT c.sample_id, c.rank, p.point_no, p.x, p.y, p.z, c.x AS cx, c.y AS cy, c.z AS cz, row_number() OVER (PARTITION BY c.sample_id, c.rank ORDER BY {_D}, p.point_no) AS nth FROM cen c JOIN p0 p USING (sample_id)) WHERE nth <= 8)"


@query(f"{_FPS}, {_KNN} SELECT sample_id, rank, nth::INT AS nth, point_no FROM knn")
def knn_groups(spark, sf_dir):
    p = _distinct_points(spark, sf_dir)
    return baselines.knn_group(p, baselines.fps(p, 5), 8).select("sample_id", "rank", "nth", "point_no")


@query(f"{_FPS} SELECT c.sample_id, c.rank, p.point_no FROM cen c JOIN p0 p ON p.sample_id = c.sample_id AND {_D} <= 0.1::DOUBLE * 0.1::DOUBLE")
def ball_groups(spark, sf_dir):
    p = _distinct_points(spark, sf_dir)
    return baselines.ball_group(p, baselines.fps(p, 5), 0.1).select("sample_id", "rank", "point_no")


@query(f"""WITH {sql_points('part')}, p0 AS (SELECT DISTINCT sample_id, point_no, x, y, z FROM pts)
  SELECT sample_id, point_no, neighbour, nth::INT AS nth FROM (SELECT c.sample_id, c.point_no, p.point_no AS neighbour, row_number() OVER (PARTITION BY c.sample_id, c.point_no ORDER BY {_D}, p.point_no) AS nth
  FROM p0 c JOIN p0 p ON c.sample_id = p.sample_id AND c.point_no <> p.point_no) WHERE nth <= 4""")
def knn_graph_edges(spark, sf_dir):
    return baselines.knn_graph(_distinct_points(spark, sf_dir, "part"), 4).select("sample_id", "point_no", "neighbour", "nth")


def _sql_net(hidden=4, out=3):
    lin = lambda layer, names, o: " + ".join(f"{n} * ({baselines.net_weight(layer, i, o)})" for i, n in enumerate(names))
    hs = [f"h{o}" for o in range(hidden)]
    return f"""o1 AS (SELECT sample_id, rank, {', '.join(f'{sql_fx6(c)} - {sql_fx6("c" + c)} AS {c}' for c in 'xyz')} FROM knn),
    o2 AS (SELECT sample_id, rank, {', '.join(f'greatest(0, {lin(1, "xyz", o)}) AS h{o}' for o in range(hidden))} FROM o1),
    o3 AS (SELECT *, {', '.join(f'max(h{o}) OVER (PARTITION BY sample_id, rank) AS g{o}' for o in range(hidden))} FROM o2)
    SELECT sample_id, rank, {', '.join(f'max(greatest(0, {lin(2, hs + [f"g{o}" for o in range(hidden)], o)}))::BIGINT AS t{o}' for o in range(out))} FROM o3 GROUP BY sample_id, rank"""


@query(f"{_FPS}, {_KNN}, {_sql_net()}")
def mini_pointnet_tokens(spark, sf_dir):
    p = _distinct_points(spark, sf_dir)
    return baselines.mini_pointnet(baselines.knn_group(p, baselines.fps(p, 5), 8))


@query(f"{_FPS}, {_KNN}, {_sql_net()}")
def center_tokens(spark, sf_dir):
    return CentreTokenizer(5, 8).transform(lineitem_clouds(spark, sf_dir))


@query(f"""WITH {sql_points()}, n AS (SELECT min(n) AS n FROM (SELECT count(*) AS n FROM pts GROUP BY sample_id)),
  o AS (SELECT *, row_number() OVER (PARTITION BY sample_id ORDER BY {sql_draw(53, 'sample_id', 'point_no')}, point_no) AS nth FROM pts)
  SELECT sample_id, count(*) AS n, sum(point_no % 1000003)::BIGINT AS check_sum FROM o WHERE nth <= (SELECT n FROM n) GROUP BY sample_id""")
def downsample_to_min(spark, sf_dir):
    return baselines.downsample(lineitem_clouds(spark, sf_dir)).groupBy("sample_id").agg(F.count("*").alias("n"), F.sum(F.col("point_no") % 1000003).alias("check_sum"))


_W0 = f"(({embed.FORM[0]} * slot + {embed.FORM[2]} * c) % {embed.FORM[3]} - {embed.FORM[3] // 2})"


@query(f"""WITH {corpora.SQL_EMBEDDING_IMAGES} SELECT sample_id, (u // 4)::INT AS pu, (v // 4)::INT AS pv, c::INT AS c, sum(fx * {_W0})::BIGINT AS num FROM
  (SELECT sample_id, u, v, u % 4 + (v % 4) * 4 AS slot, {sql_fx6('value')} AS fx FROM px), range(4) t(c) GROUP BY ALL""")
def dense_patch_2d(spark, sf_dir):
    return baselines.dense_patch_2d(corpora.embedding_images(spark, sf_dir), 4)


@query(f"""WITH {corpora.SQL_EMBEDDING_IMAGES}, q AS (SELECT *, sum({sql_fx6('value')}) OVER w / count(*) OVER w / 1000000.0::DOUBLE AS m FROM px WINDOW w AS (PARTITION BY sample_id, u // 4, v // 4))
  SELECT sample_id, floor(sum({sql_fx6('(value - m) * (value - m)')})::BIGINT / count(*) + 0.5::DOUBLE)::BIGINT AS mse_fx FROM q GROUP BY sample_id""")
def pixel_mse(spark, sf_dir):
    return losses.pixel_mse(corpora.embedding_images(spark, sf_dir), 4).select("sample_id", F.floor(F.col("mse_fx") + 0.5).cast("long").alias("mse_fx"))


_COS, _SIN = "[1.0::DOUBLE, 0.0::DOUBLE, -1.0::DOUBLE, 0.0::DOUBLE]", "[0.0::DOUBLE, 1.0::DOUBLE, 0.0::DOUBLE, -1.0::DOUBLE]"


@query(f"""WITH {sql_points()}, t AS (SELECT sample_id, view, {_COS}[view + 1] AS co, {_SIN}[view + 1] AS si, x - 0.5::DOUBLE AS dx, y - 0.5::DOUBLE AS dy, z FROM pts, range(4) v(view))
  SELECT sample_id, view::INT AS view, greatest(0, least(15, floor((co * dx - si * dy + 0.5::DOUBLE) * 16)::INT)) AS px, greatest(0, least(15, floor(z * 16)::INT)) AS pz, min({sql_fx6('si * dx + co * dy + 0.5::DOUBLE')}) AS depth_fx FROM t GROUP BY ALL""")
def project_views(spark, sf_dir):
    return baselines.project_views(lineitem_clouds(spark, sf_dir))


_FORMATS = ("csv", "json", "orc", "parquet")


@query(f"WITH {sql_points('region')} SELECT f AS format, count(*) AS n, {sql_sum_fx(ATTRIBUTES)} FROM pts, (VALUES {', '.join(f'({chr(39)}{f}{chr(39)})' for f in _FORMATS)}) t(f) GROUP BY f")
def roundtrip_formats(spark, sf_dir):
    """The clouds written to each format in a shared folder and read back by the declared schema."""
    from pointloom.schema import POINTS, scratch_path, validate

    pts, root = validate(lineitem_clouds(spark, sf_dir, "region")), scratch_path(spark)
    out = None
    for f in _FORMATS:
        pts.write.format(f).save(f"{root}/{f}")
        part = spark.read.schema(POINTS).format(f).load(f"{root}/{f}").agg(F.count("*").alias("n"), *sum_fx(ATTRIBUTES)).select(F.lit(f).alias("format"), "*")
        out = part if out is None else out.unionByName(part)
    return out


# costs -----------------------------------------------------------------------------------------------------------------

_G = f"greatest(1, n_points // {measure.CNT_DENSITY})"
_BITS = (measure.NEIGHBOURS - 1).bit_length()
_OPS = {
    "centres": f"10 * {_G} * n_points", "neighbours": f"{_G} * n_points * {8 + _BITS}", "network": f"2 * {_G} * {measure.NEIGHBOURS} * {measure.NET_PAIRS}", "voxels": "12 * n_points",
    "graph": "13 * n_voxels + 3 * n_patches", "embed": f"{25 * measure.WIDTH} * n_voxels + {measure.WIDTH} * n_patches",
}


def _ops_by_level(spark, sf_dir):
    def one(level):
        s = measure.tokenizer_stats(voxels(spark, sf_dir, level=level))
        ops = measure.centre_ops(F.col("n_points")) | measure.voxel_ops(F.col("n_points"), F.col("n_voxels"), F.col("n_patches"))
        return s.select("n_points", *[e.cast("long").alias(k) for k, e in ops.items()])

    return named_levels(one)


_OPS_SQL = " UNION ALL ".join(f"SELECT '{x}' AS level, * FROM ({sql_base(level=x)}, {_BY_PATCH}, s AS ({_STATS}) SELECT n_points, {', '.join(f'({e})::BIGINT AS {k}' for k, e in _OPS.items())} FROM s)" for x in corpora.LEVELS)


@query(f"SELECT level, count(*) AS n_clouds, sum(n_points)::BIGINT AS n_points, {', '.join(f'sum({k})::BIGINT AS {k}' for k in _OPS)} FROM ({_OPS_SQL}) GROUP BY level")
def flops_by_level(spark, sf_dir):
    return _ops_by_level(spark, sf_dir).groupBy("level").agg(F.count("*").alias("n_clouds"), F.sum("n_points").alias("n_points"), *[F.sum(k).alias(k) for k in _OPS])


_MEANS = f"SELECT level, ln(sum(n_points)::DOUBLE / count(*)) AS lx, {', '.join(f'ln(sum({k})::DOUBLE / count(*)) AS {k}' for k in _OPS)} FROM ({_OPS_SQL}) GROUP BY level"


@query(f"SELECT {', '.join(f'floor(regr_slope({k}, lx) * 1000 + 0.5::DOUBLE)::BIGINT AS {k}_slope' for k in ('centres', 'neighbours', 'network', 'voxels'))} FROM ({_MEANS}) WHERE level IN ('supplier', 'nation', 'region')")
def flops_growth(spark, sf_dir):
    """Exponent of each phase's operations in the number of points, in thousandths; from clouds of hundreds to tens of thousands."""
    m = _ops_by_level(spark, sf_dir).where(F.col("level").isin("supplier", "nation", "region")).groupBy("level").agg(F.log(F.sum("n_points").cast("double") / F.count("*")).alias("lx"), *[F.log(F.sum(k).cast("double") / F.count("*")).alias(k) for k in _OPS])
    return m.agg(*[F.floor(F.regr_slope(k, "lx") * 1000 + 0.5).cast("long").alias(f"{k}_slope") for k in ("centres", "neighbours", "network", "voxels")])


# accuracy ----------------------------------------------------------------------------------------------------------------


@query(f"""WITH e AS (SELECT vec_id AS sample_id, label, run FROM embeddings, range(1, 11) t(run)),
  cl AS (SELECT run, label, way FROM (SELECT run, label, row_number() OVER (PARTITION BY run ORDER BY {sql_draw(61, 'run', 'label')}, label) AS n FROM (SELECT DISTINCT run, label FROM e)), (VALUES (5), (10)) t(way) WHERE n <= way),
  o AS (SELECT e.*, row_number() OVER (PARTITION BY run, label ORDER BY {sql_draw(62, 'run', 'sample_id')}, sample_id) AS n FROM e),
  ep AS (SELECT o.run::INT AS run, way, shot, CASE WHEN n <= shot THEN 'support' ELSE 'query' END AS role, sample_id, o.label FROM o JOIN cl USING (run, label), (VALUES (10), (20)) s(shot) WHERE n <= shot + 5)
  SELECT * FROM ep""")
def fewshot_episodes(spark, sf_dir):
    from pointloom.train import fewshot

    labelled = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("sample_id"), "label")
    out = None
    for way in (5, 10):
        for shot in (10, 20):
            e = fewshot(labelled, way, shot, 10)
            out = e if out is None else out.union(e)
    return out


_EPISODES = ORACLES["fewshot_episodes"].removesuffix("SELECT * FROM ep").rstrip()


@query(f"""{_EPISODES}, f AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings),
  cen AS (SELECT run, way, shot, label, i, avg(e[i]) AS m FROM ep JOIN f ON vec_id = sample_id, range(1, 65) t(i) WHERE role = 'support' GROUP BY ALL),
  d AS (SELECT q.run, q.way, q.shot, q.sample_id, q.label, c.label AS pred, sum((e[i] - m) * (e[i] - m)) AS d FROM ep q JOIN f ON vec_id = q.sample_id JOIN cen c ON c.run = q.run AND c.way = q.way AND c.shot = q.shot WHERE role = 'query' GROUP BY ALL),
  p AS (SELECT run, way, shot, sample_id, label, arg_min(pred, (d, pred)) AS pred FROM d GROUP BY ALL),
  a AS (SELECT run, way, shot, floor(count(*) FILTER (WHERE label = pred) / count(*) * 1000000 + 0.5::DOUBLE) AS acc FROM p GROUP BY ALL)
  SELECT way::INT AS way, shot::INT AS shot, count(*) AS n_runs, floor(avg(acc) + 0.5::DOUBLE)::BIGINT AS mean_fx, floor(stddev_samp(acc) / sqrt(count(*)::DOUBLE) + 0.5::DOUBLE)::BIGINT AS se_fx FROM a GROUP BY way, shot""")
def fewshot_centroid_accuracy(spark, sf_dir):
    """Mean and standard error over ten runs; the label carries no signal, so this is a control near chance."""
    from pointloom.train import centroid_episodes

    feats = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("sample_id"), F.col("embedding").cast("array<double>").alias("f"))
    runs = centroid_episodes(fewshot_episodes(spark, sf_dir), feats).withColumn("acc", F.floor(F.col("accuracy") * 1000000 + 0.5).cast("double"))
    out = measure.mean_se(runs, ["way", "shot"], "acc")
    return out.select("way", "shot", "n_runs", *[F.floor(F.col(c) + 0.5).cast("long").alias(f"{c}_fx") for c in ("mean", "se")])


_VOTES = f"(SELECT sample_id, copy, floor(sum({sql_fx6('x')})::BIGINT / count(*) / 200000)::INT AS cx, floor(sum({sql_fx6('z')})::BIGINT / count(*) / 200000)::INT AS cz FROM {_PERTURBED} GROUP BY ALL)"


@query(f"""WITH {sql_points()}, s AS (SELECT sample_id, class, sum(score)::BIGINT AS score_fx FROM (SELECT sample_id, greatest(0, least(4, cx)) AS class, 600000 AS score FROM {_VOTES} UNION ALL SELECT sample_id, greatest(0, least(4, cz)), 400000 FROM {_VOTES}) GROUP BY ALL)
  SELECT sample_id, class AS pred, score_fx FROM (SELECT *, row_number() OVER (PARTITION BY sample_id ORDER BY score_fx DESC, class) AS nth FROM s) WHERE nth = 1""")
def vote_labels(spark, sf_dir):
    """A rule scores five perturbed copies of each cloud by their mean position; scores are added up over the copies."""
    g = augment.perturb(lineitem_clouds(spark, sf_dir)).groupBy("sample_id", "copy").agg(*[F.floor(F.sum(fx6(F.col(c))) / F.count("*") / 200000).cast("int").alias(f"c{c}") for c in "xz"])
    clip = lambda c: F.greatest(F.lit(0), F.least(F.lit(4), F.col(c)))
    scores = g.select("sample_id", F.explode(F.array(F.struct(clip("cx").alias("class"), F.lit(600000).alias("score_fx")), F.struct(clip("cz").alias("class"), F.lit(400000).alias("score_fx")))).alias("s")).select("sample_id", "s.*")
    return measure.vote(scores)


_LETTERS = "abcdefghijklmnopqrstuvwxyzäöüßéèêçñóí"
_SHARE = ", ".join(f"coalesce((length(text) - length(replace(text, '{c}', ''))) * 1000000 // nullif(length(text), 0), 0) AS f{k}" for k, c in enumerate(_LETTERS))
_DIST = " + ".join(f"(d.f{k} - c.f{k}) * (d.f{k} - c.f{k})" for k in range(len(_LETTERS)))
_PRED_SQL = f"""WITH d AS (SELECT doc_id, lang AS label, coalesce({_SIDE}, false) AS is_test, {_SHARE} FROM documents),
  c AS (SELECT label, {', '.join(f'sum(f{k})::BIGINT // count(*) AS f{k}' for k in range(len(_LETTERS)))} FROM d WHERE NOT is_test GROUP BY label),
  pred AS (SELECT doc_id, label, pred FROM (SELECT d.doc_id, d.label, c.label AS pred, row_number() OVER (PARTITION BY d.doc_id ORDER BY {_DIST}, c.label) AS nth FROM d, c WHERE d.is_test) WHERE nth = 1)"""


def language_predictions(spark, sf_dir):
    """Nearest class centroid of letter shares, of every document (one without text has none); texts are split by hash, so copies stay on one side."""
    d, n = load(spark, sf_dir, "documents"), F.length("text")
    shares = [F.coalesce(F.floor((n - F.length(F.translate("text", c, ""))) * F.lit(1000000).cast("long") / F.nullif(n, F.lit(0))).cast("long"), F.lit(0)) for c in _LETTERS]
    side = F.coalesce(F.conv(F.substring(F.md5("text"), 1, 8), 16, 10).cast("long") % 5 == 0, F.lit(False))
    d = d.select("doc_id", F.col("lang").alias("label"), side.alias("is_test"), *[s.alias(f"f{k}") for k, s in enumerate(shares)])
    cols = range(len(_LETTERS))
    cent = d.where("not is_test").groupBy("label").agg(*[F.floor(F.sum(f"f{k}") / F.count("*")).cast("long").alias(f"c{k}") for k in cols])
    dist = sum(((F.col(f"f{k}") - F.col("c")[f"c{k}"]) * (F.col(f"f{k}") - F.col("c")[f"c{k}"]) for k in cols), F.lit(0).cast("long"))
    # one centroid a class: the class list travels with every row
    packed = cent.agg(F.collect_list(F.struct("*")).alias("cs"))
    each = d.where("is_test").join(F.broadcast(packed)).withColumn("c", F.explode("cs"))
    best = each.groupBy("doc_id", "label").agg(F.min(F.struct(dist.alias("d"), F.col("c.label").alias("pred"))).alias("b"))
    return best.select("doc_id", "label", "b.pred")


@query(f"{_PRED_SQL} SELECT count(*) AS n, count(*) FILTER (WHERE label = pred) AS n_right, floor(count(*) FILTER (WHERE label = pred) / count(*) * 1000000 + 0.5::DOUBLE)::BIGINT AS acc_fx FROM pred")
def accuracy_topk(spark, sf_dir):
    return measure.accuracy(language_predictions(spark, sf_dir))


_LANGS = ["de", "en", "es", "fr"]


@query(f"{_PRED_SQL} SELECT label, {', '.join(f'count(*) FILTER (WHERE pred = {chr(39)}{x}{chr(39)}) AS {x}' for x in _LANGS)} FROM pred GROUP BY label")
def confusion_pivot(spark, sf_dir):
    return measure.confusion(language_predictions(spark, sf_dir), _LANGS)


_PART_SQL = f"""WITH {sql_points('part')}, pr AS (SELECT sample_id % 10 AS category, sample_id, least(2, floor(3 * z))::INT AS label, least(2, floor(3 * (0.8::DOUBLE * z + 0.2::DOUBLE * x)))::INT AS pred FROM pts),
  q AS (SELECT category, sample_id, part, sum(CASE WHEN label = part AND pred = part THEN 1 ELSE 0 END)::BIGINT AS b, sum(CASE WHEN label = part OR pred = part THEN 1 ELSE 0 END)::BIGINT AS e FROM pr, range(3) t(part) GROUP BY ALL),
  s AS (SELECT category, sample_id, floor(sum({sql_fx6('CASE WHEN e = 0 THEN 1.0::DOUBLE ELSE b / e END')})::BIGINT / 3 + 0.5::DOUBLE)::BIGINT AS iou_fx FROM q GROUP BY ALL),
  c AS (SELECT category, sum(iou_fx)::BIGINT AS s, count(*) AS n, floor(sum(iou_fx)::BIGINT / count(*) + 0.5::DOUBLE)::BIGINT AS c_fx FROM s GROUP BY category)"""


@query(f"{_PART_SQL} SELECT floor(sum(c_fx)::BIGINT / count(*) + 0.5::DOUBLE)::BIGINT AS class_miou_fx, floor(sum(s)::BIGINT / sum(n)::BIGINT + 0.5::DOUBLE)::BIGINT AS instance_miou_fx, sum(n)::BIGINT AS n_shapes FROM c")
def miou_class_instance(spark, sf_dir):
    p = lineitem_clouds(spark, sf_dir, "part")
    zone = lambda v: F.least(F.lit(2), F.floor(3 * v)).cast("int")
    return measure.miou(p.select((F.col("sample_id") % 10).alias("category"), "sample_id", zone(F.col("z")).alias("label"), zone(0.8 * F.col("z") + 0.2 * F.col("x")).alias("pred")))


# The arithmetic of the published comparisons (rows of :mod:`pointloom.operators.baselines`) on a given table: the arms are the ten families
# of supplier clouds, with and without background, and the values are means of their points' attributes.
_ARM_SQL = f"""WITH {sql_points()}, arms AS (SELECT background, (sample_id % 10)::INT AS family, count(*) AS n, {sql_sum_fx('xyz')}, sum(floor(x * 100 + 0.5::DOUBLE)::BIGINT)::BIGINT AS s1,
  sum(floor(x * 100 + 0.5::DOUBLE)::BIGINT * floor(x * 100 + 0.5::DOUBLE)::BIGINT)::BIGINT AS s2 FROM pts GROUP BY ALL),
  means AS (SELECT background, family, {', '.join(f'sum_{c} / n / 10000.0::DOUBLE AS {c}' for c in 'xyz')}, s1 / n AS m, sqrt(greatest(0.0::DOUBLE, s2::DOUBLE - s1::DOUBLE * s1::DOUBLE / n) / greatest(1, n - 1) / n) AS se FROM arms)"""


def _arms(spark, sf_dir):
    """background, family, mean x, y, z of the points in hundredths, and mean and standard error of x in whole hundredths."""
    q = F.floor(F.col("x") * 100 + 0.5).cast("long")
    g = lineitem_clouds(spark, sf_dir).groupBy("background", (F.col("sample_id") % 10).cast("int").alias("family"))
    g = g.agg(F.count("*").alias("n"), *sum_fx("xyz"), F.sum(q).alias("s1"), F.sum(q * q).alias("s2"))
    s1, s2, n = F.col("s1").cast("double"), F.col("s2").cast("double"), F.col("n")
    se = F.sqrt(F.greatest(F.lit(0.0), s2 - s1 * s1 / n) / F.greatest(F.lit(1), n - 1) / n)
    return g.select("background", "family", *[(F.col(f"sum_{c}") / n / 10000.0).alias(c) for c in "xyz"], (F.col("s1") / n).alias("m"), se.alias("se"))


def _gains(names, source="t"):
    return ", ".join(f"round(({source}.{c} - b.{c}) * 10)::BIGINT AS gain_{c}_tenths" for c in names)


@query(f"{_ARM_SQL} SELECT t.background, t.family, {_gains('xyz')} FROM means t, (SELECT * FROM means WHERE family = 6 AND background) b")
def published_tables(spark, sf_dir):
    """Gains of every arm over one arm, as the published tables of scanned objects are read."""
    df = _arms(spark, sf_dir)
    base = df.where("family = 6 and background").select(*[F.col(c).alias(f"b{c}") for c in "xyz"])
    return df.join(F.broadcast(base)).select("background", "family", *[F.round((F.col(c) - F.col(f"b{c}")) * 10).cast("long").alias(f"gain_{c}_tenths") for c in "xyz"])


@query(f"{_ARM_SQL} SELECT background, family, round((m - (SELECT max(o.m) FROM means o WHERE o.family < 5 AND o.background = t.background)) * 10)::BIGINT AS gain_tenths, round(se * 10000)::BIGINT AS se_tenthousandths FROM means t")
def published_fewshot(spark, sf_dir):
    """Gains over the best earlier arm of the same task, with the standard error, as published few-shot rows are read."""
    df = _arms(spark, sf_dir)
    best = df.where("family < 5").groupBy("background").agg(F.max("m").alias("best"))
    return df.join(F.broadcast(best), "background", "left").select("background", "family", F.round((F.col("m") - F.col("best")) * 10).cast("long").alias("gain_tenths"), F.round(F.col("se") * 10000).cast("long").alias("se_tenthousandths"))


@query(f"{_ARM_SQL} SELECT t.family, {_gains('xyz')} FROM means t, (SELECT * FROM means WHERE family = 2 AND NOT background) b WHERE NOT t.background")
def published_cad(spark, sf_dir):
    """Gains over one arm on clouds without background, as published rows on CAD objects and parts are read."""
    return measure.delta_of(_arms(spark, sf_dir).where("not background"), "family = 2", ["family"], "xyz")


@query("""SELECT event_type AS arm, round(devices * days * 24)::BIGINT AS device_hours, round(devices * days * 24 * 1000 / epochs)::BIGINT AS thousandth_hours_an_epoch
  FROM (SELECT event_type, count(DISTINCT user_id) AS devices, (epoch_us(max(ts)) - epoch_us(min(ts))) / 86400000000.0::DOUBLE AS days, count(DISTINCT ts::DATE) AS epochs FROM events GROUP BY event_type)""")
def published_training_cost(spark, sf_dir):
    """Device hours of a run, whole and for an epoch: an event type is a run, its users are devices, and its days are epochs."""
    ts = F.col("ts").cast("timestamp")
    runs = load(spark, sf_dir, "events").groupBy(F.col("event_type").alias("arm")).agg(F.countDistinct("user_id").alias("devices"), F.min(F.unix_micros(ts)).alias("lo"), F.max(F.unix_micros(ts)).alias("hi"), F.countDistinct(F.to_date(ts)).alias("epochs"))
    return measure.training_cost(runs.withColumn("days", (F.col("hi") - F.col("lo")) / 86400000000.0))


@query(f"{_ARM_SQL} SELECT background, family, metric, round((v - max(v) OVER (PARTITION BY background, metric)) * 100)::BIGINT AS loss_hundredths FROM (SELECT background, family, 'x' AS metric, x AS v FROM means UNION ALL SELECT background, family, 'y', y FROM means)")
def delta_vs_baseline(spark, sf_dir):
    """Distance of each arm to the best arm of its factor, the background, on two metrics."""
    df = _arms(spark, sf_dir)
    df = df.select("background", "family", F.explode(F.array(*[F.struct(F.lit(c).alias("metric"), F.col(c).alias("v")) for c in "xy"])).alias("e")).select("background", "family", "e.*")
    return df.select("background", "family", "metric", F.round((F.col("v") - F.max("v").over(Window.partitionBy("background", "metric"))) * 100).cast("long").alias("loss_hundredths"))


# relational surroundings --------------------------------------------------------------------------------------------------

_DIMS = """tok AS (SELECT r_name, n_name, s.sample_id, count(*) AS n_tokens FROM (SELECT DISTINCT sample_id, ci, cj, ck FROM cells) s JOIN supplier ON s_suppkey = s.sample_id JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ALL)"""


def _token_counts(spark, sf_dir):
    t = masking.patches_of(voxels(spark, sf_dir)).groupBy("sample_id").agg(F.count("*").alias("n_tokens"))
    s, n, r = (load(spark, sf_dir, x) for x in ("supplier", "nation", "region"))
    j = t.join(s, t.sample_id == s.s_suppkey).join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.select("r_name", "n_name", "sample_id", "n_tokens")


for _mode in ("rollup", "cube"):

    @query(f"{sql_base()}, {_DIMS} SELECT r_name, n_name, grouping_id(r_name, n_name)::BIGINT AS gid, count(*) AS n, sum(n_tokens)::BIGINT AS n_tokens FROM tok GROUP BY {_mode.upper()} (r_name, n_name)", f"token_{_mode}")
    def _cubed(spark, sf_dir, mode=_mode):
        return relops.token_cube(_token_counts(spark, sf_dir), ["r_name", "n_name"], [F.count("*").alias("n"), F.sum("n_tokens").alias("n_tokens")], mode)


@query(f"{sql_base()}, {_DIMS} SELECT r_name, n_name, count(*) AS n, max(n_tokens) AS max_tokens FROM tok GROUP BY GROUPING SETS ((r_name), (n_name), ())")
def token_grouping_sets(spark, sf_dir):
    _token_counts(spark, sf_dir).createOrReplaceTempView("pl_token_counts")
    return spark.sql("SELECT r_name, n_name, count(*) AS n, max(n_tokens) AS max_tokens FROM pl_token_counts GROUP BY GROUPING SETS ((r_name), (n_name), ())")


@query(f"WITH {sql_points()}, s AS (SELECT sample_id, count(*) AS n FROM pts GROUP BY sample_id) SELECT sample_id, n, ntile(4) OVER (ORDER BY n, sample_id)::INT AS bucket FROM s")
def size_ntiles(spark, sf_dir):
    s = lineitem_clouds(spark, sf_dir).groupBy("sample_id").agg(F.count("*").alias("n"))
    return s.withColumn("bucket", F.ntile(4).over(Window.orderBy("n", "sample_id")))


@query("SELECT doc_id, length(text)::INT AS n FROM documents ORDER BY n DESC, doc_id LIMIT 20")
def largest_clouds_topk(spark, sf_dir):
    return relops.largest(load(spark, sf_dir, "documents").select("doc_id", F.length("text").alias("n")), [F.col("n").desc(), "doc_id"], 20)


@query(f"{sql_loss()} SELECT sample_id, ci, cj, ck, mse_fx, nth::INT AS nth FROM (SELECT sample_id, ci, cj, ck, {_ROUND.format('mse_fx')} AS mse_fx, row_number() OVER (PARTITION BY sample_id ORDER BY {_ROUND.format('mse_fx')} DESC, ci, cj, ck) AS nth FROM mse) WHERE nth <= 3")
def hardest_patches_topk(spark, sf_dir):
    return relops.topk(loss_relative_mse(spark, sf_dir), ["sample_id"], [F.col("mse_fx").desc(), *PATCH[1:]], 3)


_TWO = f"""WITH {sql_points()}, k AS (SELECT copy, sample_id, {', '.join(f'greatest(0, least(15, floor({c} / 0.0625::DOUBLE)))::INT AS {k}' for k, c in zip(voxel.KEY, 'xyz', strict=True))} FROM {_PERTURBED} WHERE copy <= 2),
  a AS (SELECT sample_id, vi, vj, vk FROM k WHERE copy = 1), b AS (SELECT sample_id, vi, vj, vk FROM k WHERE copy = 2)"""


def _two_copies(spark, sf_dir):
    k = voxel.assign(augment.perturb(lineitem_clouds(spark, sf_dir)), GridSpec(16, 4))
    return [k.where(F.col("copy") == c).select("sample_id", *voxel.KEY) for c in (1, 2)]


for _op, _every in (("intersect", False), ("intersect", True), ("except", False), ("except", True), ("union", False), ("union", True)):

    @query(f"{_TWO} SELECT sample_id, count(*) AS n FROM (SELECT * FROM a {_op.upper()} {'ALL' if _every else ''} SELECT * FROM b) GROUP BY sample_id", f"voxel_overlap_{_op}{'_all' if _every else ''}")
    def _overlap(spark, sf_dir, op=_op, every=_every):
        a, b = _two_copies(spark, sf_dir)
        return relops.voxel_overlap(a, b, op, every).groupBy("sample_id").agg(F.count("*").alias("n"))


@query(f"""{_TWO} SELECT side, count(*) AS n FROM (SELECT CASE WHEN y.sample_id IS NULL THEN 'left' WHEN x.sample_id IS NULL THEN 'right' ELSE 'both' END AS side
  FROM (SELECT DISTINCT * FROM a) x FULL JOIN (SELECT DISTINCT * FROM b) y ON x.sample_id = y.sample_id AND x.vi = y.vi AND x.vj = y.vj AND x.vk = y.vk) GROUP BY side""")
def occupancy_full_outer(spark, sf_dir):
    a, b = _two_copies(spark, sf_dir)
    return relops.voxel_diff(a, b, ["sample_id", *voxel.KEY]).groupBy("side").agg(F.count("*").alias("n"))


@query("SELECT doc_id, lang FROM documents SEMI JOIN labels USING (doc_id)")
def labelled_docs_semi(spark, sf_dir):
    return relops.keep(load(spark, sf_dir, "documents").select("doc_id", "lang"), load(spark, sf_dir, "labels"), "doc_id")


@query("SELECT doc_id, lang FROM documents ANTI JOIN labels USING (doc_id)")
def unlabelled_docs_anti(spark, sf_dir):
    return relops.drop(load(spark, sf_dir, "documents").select("doc_id", "lang"), load(spark, sf_dir, "labels"), "doc_id")


@query("""SELECT p.event_id, coalesce((SELECT arg_max(c.event_id, (c.ts, c.event_id)) FROM events c WHERE c.user_id = p.user_id AND c.event_type = 'click' AND c.ts <= p.ts), -1) AS last_click
  FROM events p WHERE p.event_type = 'purchase'""")
def asof_event_points(spark, sf_dir):
    ev = load(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    clicks = ev.where("event_type = 'click'").select("user_id", "t", F.col("event_id").alias("click"))
    # of clicks at one time the largest number counts
    clicks = clicks.groupBy("user_id", "t").agg(F.max("click").alias("click"))
    return relops.asof(ev.where("event_type = 'purchase'"), clicks, "user_id", "t", "click").select("event_id", F.coalesce("asof_value", F.lit(-1)).alias("last_click"))


@query("""SELECT a.event_id, b.event_id AS other FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'purchase' AND b.event_type = 'click'
  AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts + INTERVAL 1 HOUR""")
def interval_event_pairs(spark, sf_dir):
    ev = load(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    hour = 3_600_000_000
    out = relops.interval_join(ev.where("event_type = 'purchase'"), ev.where("event_type = 'click'"), "user_id", "t", hour, hour)
    return out.select("event_id", F.col("r_event_id").alias("other"))


@query("SELECT epoch_us(time_bucket(INTERVAL 1 DAY, ts))::BIGINT AS start_us, event_type, count(*) AS n_points FROM events GROUP BY ALL")
def event_tumbling_tokens(spark, sf_dir):
    from pointloom.streaming import windows

    ev = load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return windows.tumbling(ev).select(F.unix_micros("w.start").alias("start_us"), "event_type", "n_points")


@query("SELECT epoch_us(time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR * k)::BIGINT AS start_us, count(*) AS n_points FROM events, range(4) t(k) GROUP BY ALL")
def event_sliding_tokens(spark, sf_dir):
    from pointloom.streaming import windows

    ev = load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return windows.sliding(ev).select(F.unix_micros("w.start").alias("start_us"), "n_points")


@query("""SELECT user_id, epoch_us(min(ts))::BIGINT AS start_us, count(*) AS n_points FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM
  (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s""")
def event_session_clouds(spark, sf_dir):
    from pointloom.streaming import windows

    ev = load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return windows.session(ev).select("user_id", F.unix_micros("w.start").alias("start_us"), "n_points")


_EV = "pts AS (SELECT user_id::BIGINT AS sample_id, (hour(ts) * 3600 + minute(ts) * 60 + second(ts)) / 86400 AS x, least(value, 600.0::DOUBLE) / 600 AS y, json_extract_string(props, '$.k')::BIGINT / 100 AS z FROM events)"
_EVK = ", ".join(f"greatest(0, least(15, floor({c} / 0.0625::DOUBLE)))::INT AS {k}" for k, c in zip(voxel.KEY, "xyz", strict=True))


@query(f"WITH {_EV} SELECT sample_id, {_EVK}, count(*) AS n_points FROM pts GROUP BY ALL")
def stream_voxels_equals_batch(spark, sf_dir):
    """The events as a file stream, run until nothing is left; every batch replaces the voxels that it changed."""
    from pointloom.schema import scratch_path
    from pointloom.streaming import tokens

    src = f"{sf_dir}/events.parquet"
    stream = spark.readStream.schema(spark.read.parquet(src).schema).parquet(src if "*" in src else sf_dir + "/events*.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    return tokens.run_to_table(spark, tokens.voxel_counts(tokens.event_points(stream)), scratch_path(spark), ["sample_id", *voxel.KEY], "n_points")


@query(f"{sql_base()} SELECT sample_id, count(DISTINCT slot) AS n_slots, true AS within FROM cells GROUP BY sample_id")
def approx_occupied_slots(spark, sf_dir):
    g = voxels(spark, sf_dir).groupBy("sample_id").agg(F.countDistinct("slot").alias("n_slots"), F.approx_count_distinct("slot", 0.02).alias("approx"))
    return g.select("sample_id", "n_slots", (F.abs(F.col("approx") / F.col("n_slots") - 1) <= 0.2).alias("within"))


@query(f"{sql_base()} SELECT sample_id, sum((vi * 1024 + vj)::BIGINT * 1024 + vk)::BIGINT AS keys, sum(slot)::BIGINT AS slots, sum({sql_fx6('x')})::BIGINT AS sx FROM cells GROUP BY sample_id")
def sql_functions(spark, sf_dir):
    """Through SQL functions that the optimiser inlines."""
    from pointloom.functions import sqlfn

    sqlfn.register(spark)
    voxels(spark, sf_dir).createOrReplaceTempView("pl_voxels")
    return spark.sql("SELECT sample_id, sum(vox_key(vi, vj, vk)) AS keys, CAST(sum(slot_of(vi, vj, vk, 8)) AS BIGINT) AS slots, sum(fx6(x)) AS sx FROM pl_voxels GROUP BY sample_id")


@query("""SELECT p_partkey::BIGINT AS sample_id, s::INT AS slot, (s % a)::INT AS i, (s // a % a)::INT AS j, (s // (a * a))::INT AS k
  FROM (SELECT p_partkey, p_partkey % 4 + 1 AS a FROM part) t, range(64) r(s) WHERE s < a * a * a""")
def udtf_slots(spark, sf_dir):
    """The slots of a patch for every part, whose number gives the patch's edge of 1 to 4 voxels."""
    from pointloom.functions import sqlfn

    sqlfn.register(spark)
    load(spark, sf_dir, "part").select(F.col("p_partkey").cast("long").alias("sample_id"), (F.col("p_partkey") % 4 + 1).cast("int").alias("a")).createOrReplaceTempView("pl_edges")
    return spark.sql("SELECT e.sample_id, s.slot, s.i, s.j, s.k FROM pl_edges e, LATERAL slots(e.a) s")


_MORTON = " + ".join(f"((({k}::BIGINT >> {b}) & 1) << {3 * b + a})" for a, k in enumerate(voxel.KEY) for b in range(5))


@query(f"{sql_base()} SELECT sample_id, sum({_MORTON})::BIGINT AS morton, count(*) AS n FROM vox GROUP BY sample_id")
def udf_surface(spark, sf_dir):
    from pointloom.functions import sqlfn

    sqlfn.register(spark)
    voxels(spark, sf_dir).createOrReplaceTempView("pl_voxels")
    return spark.sql("SELECT sample_id, sum(morton_key(vi, vj, vk)) AS morton, count(*) AS n FROM pl_voxels GROUP BY sample_id")


@query(f"{_FPS} SELECT sample_id, rank, point_no FROM cen")
def udtf_fps_points(spark, sf_dir):
    from pointloom.functions import sqlfn

    sqlfn.register(spark)
    _distinct_points(spark, sf_dir).select("sample_id", "point_no", *"xyz").createOrReplaceTempView("pl_points")
    return spark.sql("SELECT * FROM fps_points(TABLE(SELECT * FROM pl_points) PARTITION BY sample_id)")

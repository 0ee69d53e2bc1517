"""Worked examples and invariants of lifting, voxels, patches, tokens, masks, losses, baselines and measures."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from pointloom import kernels
from pointloom.functions.fixed import draw
from pointloom.operators import augment, baselines, corpora, embed, lift, losses, masking, measure, patch, relops, voxel
from pointloom.operators.patch import PATCH
from pointloom.operators.tokenizer import VoxelTokenizer
from pointloom.plans.planner import TokenPlan, plan_for
from pointloom.schema import G32, GridSpec, validate

SMALL = GridSpec(8, 4)


def points(spark, rows):
    return spark.createDataFrame([(1, k, *map(float, r)) for k, r in enumerate(rows)], "sample_id long, point_no long, x double, y double, z double, r double, g double, b double")


def cloud(spark, n=200, samples=3, seed=0):
    rng = np.random.default_rng(seed)
    rows = [(s, k, *map(float, rng.random(6))) for s in range(samples) for k in range(n)]
    return spark.createDataFrame(rows, "sample_id long, point_no long, x double, y double, z double, r double, g double, b double")


def cells(df, grid=SMALL, rep="argmax"):
    return patch.with_slot(voxel.voxelize(voxel.assign(df, grid), rep), grid.patch)


def same(a, b):
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))


def test_patch_corner_of_the_worked_example(spark):
    df = spark.createDataFrame([(1, 5, 6, 2)], "sample_id long, vi int, vj int, vk int")
    r = patch.corner(patch.partition(df, 4), 4).first()
    assert tuple(r.corner) == (4, 4, 0)


def test_faces_are_half_open_and_the_end_is_clipped(spark):
    df = points(spark, [(0.0, 0.125, 0.2499999, 0, 0, 0), (1.0, 0.25, -0.1, 0, 0, 0)])
    got = [(r.vi, r.vj, r.vk) for r in voxel.assign(df, SMALL).orderBy("point_no").collect()]
    assert got == [(0, 1, 1), (7, 2, 0)]
    assert voxel.assign(df, SMALL, "drop").count() == 1
    with pytest.raises(Exception, match="outside"):
        voxel.assign(df, SMALL, "error").collect()


def test_representatives(spark):
    df = points(spark, [(0.01, 0.0, 0.0, 0.9, 0.1, 0.0), (0.02, 0.0, 0.0, 0.1, 0.9, 0.0), (0.03, 0.0, 0.0, 0.5, 0.5, 0.0), (0.02, 0.01, 0.0, 0.5, 0.5, 0.0)])
    k = voxel.assign(df, SMALL)
    best = voxel.voxelize(k).first()
    assert (best.x, best.y, best.r, best.n_points) == (0.02, 0.01, 0.5, 4)
    top = voxel.voxelize(k, "colmax").first()
    assert (top.x, top.r, top.g) == (0.03, 0.9, 0.9)
    assert voxel.voxelize(k, "first").first().x == 0.01
    assert voxel.voxelize(k, "mean").first().x == pytest.approx(0.02)


def test_lonely_voxel_and_full_patch(spark):
    one = patch.graph_features(cells(points(spark, [(0.3, 0.4, 0.5, 0, 0, 0)]))).first()
    assert (one.dx, one.cx, one.n_vox) == (0.0, 0.3, 1)
    full = [((i + 0.5) / 4, (j + 0.5) / 4, (k + 0.5) / 4, 0, 0, 0) for i in range(2) for j in range(2) for k in range(2)]
    got = cells(points(spark, full), GridSpec(4, 2))
    assert sorted(r.slot for r in got.collect()) == list(range(8)) and got.select(*PATCH).distinct().count() == 1


def test_voxel_invariants(spark):
    df = cloud(spark)
    v = cells(df)
    assert v.count() <= df.count()
    assert v.groupBy(*PATCH, "slot").count().where("count > 1").count() == 0
    g = patch.graph_features(v).groupBy(*PATCH).agg(*[F.abs(F.sum(f"d{c}")).alias(c) for c in "xyz"])
    assert g.where("x > 1e-4 or y > 1e-4 or z > 1e-4").count() == 0
    again = voxel.voxelize(voxel.assign(v.withColumn("point_no", F.monotonically_increasing_id()), SMALL))
    assert again.count() == v.count()


def test_token_paths_agree_and_ignore_order(spark):
    df = cloud(spark)
    t = {p: VoxelTokenizer(SMALL, path=p).transform(df) for p in ("sql", "onepass", "kernel")}
    same(t["sql"], t["onepass"])
    same(t["sql"], t["kernel"])
    same(t["onepass"], VoxelTokenizer(SMALL, co_locate=True).transform(df.repartition(7).orderBy(F.rand(1))))
    same(t["onepass"].where("sample_id = 1"), VoxelTokenizer(SMALL).transform(df.where("sample_id = 1")))


def test_packed_kernel_equals_the_operators(spark):
    df = cloud(spark, samples=1)
    pts = np.array([[r[c] for c in "xyzrgb"] for r in df.orderBy("point_no").collect()])
    n, num = kernels.packed_tokens(pts, SMALL, 4)
    got = VoxelTokenizer(SMALL).transform(df).orderBy(*PATCH, "c").collect()
    assert [r.num for r in got] == num.ravel().tolist() and [r.n_vox for r in got[::4]] == n.tolist()


def test_translation_by_whole_patches_keeps_slots(spark):
    df = cloud(spark).withColumns({c: F.col(c) * 0.49 for c in "xyz"})
    moved = df.withColumn("x", F.col("x") + 0.5)
    same(cells(df).select("slot"), cells(moved).select("slot"))


def test_rotation_keeps_height_and_radius(spark):
    df = cloud(spark)
    t = augment.rotate_z(df, 5)
    radius = (F.col("x") - 0.5) ** 2 + (F.col("y") - 0.5) ** 2
    a, b = (x.select("sample_id", "point_no", radius.alias("q"), "z").orderBy("sample_id", "point_no").collect() for x in (df, t))
    assert all(p.q == pytest.approx(q.q) and p.z == q.z for p, q in zip(a, b, strict=True))
    full = augment.rotate_z(df, 5, 2 * math.pi).orderBy("sample_id", "point_no").first()
    assert full.x == pytest.approx(df.orderBy("sample_id", "point_no").first().x)


def test_images_stand_upright(spark):
    px = spark.createDataFrame([(1, u, v, 2, 2, 0.0, 0.0, 0.0, 0.5) for u in range(2) for v in range(2)], "sample_id long, u int, v int, w int, h int, r double, g double, b double, d double")
    got = {(r.point_no % 2, r.point_no // 2): r for r in lift.lift_pixels(px, "d").collect()}
    assert got[0, 0].z > got[0, 1].z and got[0, 0].x < got[1, 0].x and got[0, 0].y == 0.5


def test_blur_counts_only_pixels_that_exist():
    d = lift.BlurTeacher(1)(np.array([10, 20, 30, 40, 50], np.int64))
    # raster 3 wide, 2 high; the last place is empty
    want = [np.mean([10, 20, 40, 50]), np.mean([10, 20, 30, 40, 50]), np.mean([20, 30, 50]), np.mean([10, 20, 40, 50]), np.mean([10, 20, 30, 40, 50])]
    assert np.allclose(d * 255, want)


def test_masks(spark):
    p = spark.createDataFrame([(1, i, 0, 0) for i in range(10)], "sample_id long, ci int, cj int, ck int")
    m = masking.random_mask(p, 60)
    assert m.where("hidden").count() == 6
    same(m, masking.random_mask(p.repartition(3), 60))
    assert m.exceptAll(masking.random_mask(p, 60, seed=42)).count() > 0


def test_mask_before_or_after_embedding(spark):
    v = cells(cloud(spark))
    mask = masking.random_mask(masking.patches_of(v), 60)
    late = embed.slot_embed(v, 4).join(mask.where("not hidden").select(*PATCH), list(PATCH), "left_semi")
    same(embed.slot_embed(masking.visible(v, mask), 4), late)
    early = masking.visible_bernoulli(v, 60)
    same(early.select(*PATCH).distinct(), masking.random_mask(masking.patches_of(v), 60, mode="bernoulli").where("not hidden").select(*PATCH))


def test_losses(spark):
    v = patch.graph_features(cells(cloud(spark)))
    assert losses.relative_mse(v, v).agg(F.sum("mse_fx")).first()[0] == 0
    assert losses.chamfer(v, v).agg(F.sum("cd_fx")).first()[0] == 0
    t = points(spark, [(0, 0, 0, 0, 0, 0)]).selectExpr("sample_id", "0 as ci", "0 as cj", "0 as ck", "x", "y", "z")
    p = points(spark, [(1, 0, 0, 0, 0, 0), (0, 2, 0, 0, 0, 0)]).selectExpr("sample_id", "0 as ci", "0 as cj", "0 as ck", "x", "y", "z")
    assert losses.chamfer(t, p).first().cd_fx == pytest.approx(3.5e6) == losses.chamfer(p, t).first().cd_fx
    one = t.withColumn("slot", F.lit(3))
    half = spark.createDataFrame([(s, 0.5) for s in range(8)], "slot int, p double")
    for form in (losses.occupancy_sparse, losses.occupancy_dense):
        assert form(one, half, 2).first().occ_fx == pytest.approx(math.log(2) * 1e6, abs=1)
    sure = spark.createDataFrame([(3, 1.0)], "slot int, p double")
    assert losses.occupancy_sparse(one, sure, 2).first().occ_fx == pytest.approx(losses.occupancy_dense(one, sure, 2).first().occ_fx) == pytest.approx(0, abs=1)


def test_centres_of_five_points():
    xyz = np.array([[v, 0, 0] for v in (0, 1, 2, 3, 10)], float)
    assert baselines.fps_kernel(xyz, 5).tolist() == [0, 4, 3, 1, 2]


def test_groups(spark):
    df = cloud(spark, 80, 2)
    c = baselines.fps(df, 4)
    assert c.count() == 8 and c.select("sample_id", "point_no").distinct().count() == 8
    near = baselines.knn_group(df, c, 5)
    own = near.where("nth = 1").join(c.select("sample_id", "rank", F.col("point_no").alias("own")), ["sample_id", "rank"])
    assert own.where("point_no <> own").count() == 0 and near.count() == 40
    ball = baselines.ball_group(df, c, 0.3).select("sample_id", "rank", "point_no")
    pts, cs = df.collect(), c.collect()
    want = sorted((q.sample_id, q["rank"], p.point_no) for q in cs for p in pts if p.sample_id == q.sample_id and (p.x - q.x) ** 2 + (p.y - q.y) ** 2 + (p.z - q.z) ** 2 <= 0.3 * 0.3)
    assert sorted(map(tuple, ball.collect())) == want


def test_operation_growth_by_phase(spark):
    sizes = spark.createDataFrame([(n, n, min(n, 2744)) for n in (1024, 8192, 32768, 100000)], "n long, m long, p long")
    ops = measure.centre_ops(F.col("n")) | measure.voxel_ops(F.col("n"), F.col("m"), F.col("p"))
    s = sizes.select("n", *[e.alias(k) for k, e in ops.items()])
    slopes = s.agg(*[measure.slope(s, "n", k).alias(k) for k in ops]).first()
    assert min(slopes.centres, slopes.neighbours) >= 1.95
    assert max(slopes.voxels, slopes.embed, slopes.network) <= 1.05


def test_missing_part_counts_one(spark):
    rows = [(0, 1, 0, 0), (0, 1, 0, 1), (0, 1, 1, 1), (1, 2, 2, 2)]
    out = measure.miou(spark.createDataFrame(rows, "category int, sample_id long, label int, pred int")).first()
    assert out.instance_miou_fx == pytest.approx((0.5 + 0.5 + 1 + 3) / 6 * 1e6, abs=1)


def test_losses_keep_patches_without_a_prediction(spark):
    from pointloom.operators import losses

    cols = "sample_id long, ci int, cj int, ck int, slot int, " + ", ".join(f"{c} double" for c in ("x", "y", "z", *losses.RELATIVE))
    row = lambda cell, slot, v: (1, cell, 0, 0, slot, *[v] * 12)
    true = spark.createDataFrame([row(0, 0, 0.5), row(0, 3, 0.25), row(1, 2, 1.0)], cols)
    pred = spark.createDataFrame([row(0, 0, 0.5), row(0, 5, 0.5), row(0, 6, 0.0)], cols)
    prob = spark.createDataFrame([(0, 0.5), (3, 0.25)], "slot int, p double")
    apart = losses.relative_mse(true, pred).join(losses.chamfer(true, pred), list(losses.PATCH)).join(losses.occupancy_sparse(true, prob, 2), list(losses.PATCH))
    once = {r.ci: r for r in losses.patch_terms(true, pred, prob, 2).collect()}
    for r in apart.collect():
        assert (r.mse_fx, r.cd_fx, r.occ_fx) == (once[r.ci].mse_fx, once[r.ci].cd_fx, once[r.ci].occ_fx)
    # the second voxel has no prediction of its slot; the second patch has none at all
    assert once[0].mse_fx == 9 * 0.0625 * 1e6 / 2 and once[1].mse_fx == 9e6 and once[1].cd_fx == 3e6
    assert once[0].cd_fx == (0 + 3 * 0.0625 * 1e6) / 2 + (0 + 0 + 3 * 0.0625 * 1e6) / 3 - 0
    assert losses.total(true, pred, prob, 2).first().n_patches == 2


def test_published_arithmetic():
    rows = {r[0]: r for r in baselines.PUBLISHED}
    assert [round(rows[369][k] - rows[366][k], 1) for k in (3, 4, 5)] == [4.5, 4.9, 4.4]
    ab = {(f, s): (a, b) for f, s, a, b in baselines.ABLATIONS}
    assert round(ab["loss", "graph all"][0] - ab["loss", "origin all"][0], 2) == 4.63
    assert round(ab["loss", "graph all"][0] - ab["loss", "graph mse"][0], 2) == 9.26
    assert 2902 * 5 == 14510 and 9843 + 2468 == 12311 and 16**3 == 4096


def test_subsets_are_nested(spark):
    df = spark.range(2000).withColumnRenamed("id", "sample_id")
    small, large = corpora.subset(df, 40), corpora.subset(df, 420)
    assert 0 < small.count() < large.count() and small.exceptAll(large).count() == 0


def test_store_reads_only_its_buckets(spark, tmp_path):
    df = cloud(spark, 5, 60)
    corpora.store(df, str(tmp_path / "c"))
    same(corpora.read_store(spark, str(tmp_path / "c"), 300).select(df.columns), corpora.subset(df, 300))
    assert "PartitionFilters" in corpora.read_store(spark, str(tmp_path / "c"), 300)._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, sf):
    pts = corpora.lineitem_clouds(spark, sf)

    def plan(df):
        df.collect()
        return df._jdf.queryExecution().executedPlan().toString()

    once = plan(VoxelTokenizer(G32, co_locate=True).transform(pts))
    assert once.split("== Initial Plan ==")[0].count("Exchange ") == 1
    assert "SortAggregate" not in once and "CartesianProduct" not in once and "BroadcastNestedLoopJoin" not in once
    packed = lift.lift_packed(corpora.packed_rasters(spark.read.parquet(f"{sf}/documents.parquet"), "doc_id", "text"))
    assert "Exchange" not in plan(packed)
    near = spark.read.parquet(f"{sf}/lineitem.parquet").selectExpr("l_discount x", "l_tax y", "l_tax z", "l_discount r", "l_tax g", "l_tax b", "l_orderkey sample_id", "l_partkey point_no")
    assert "GreaterThanOrEqual(l_discount" in plan(voxel.within(near, G32, (1, 0, 0), (3, 3, 3)))


def test_planner(spark):
    assert TokenPlan(G32, points_per_voxel=1.0).tokenizer().co_locate
    assert not TokenPlan(G32, points_per_voxel=3.8, samples=5).tokenizer().co_locate
    assert plan_for(cloud(spark), SMALL).points_per_voxel > 0.9 and "exchange" in TokenPlan(G32).explain()


def test_validate_and_broken_rows(spark):
    df = points(spark, [(0, 0, 0, 0, 0, 0), (float("nan"), 0, 0, 0, 0, 0)])
    with pytest.raises(ValueError, match="missing"):
        validate(df.drop("x"))
    assert lift.drop_broken(df).count() == 1 and lift.count_broken(df).first()[0] == 1
    assert VoxelTokenizer(SMALL).transform(df.where("false")).count() == 0


def test_asof_and_interval(spark):
    left = spark.createDataFrame([(1, 10), (1, 5), (2, 7)], "k long, t long")
    right = spark.createDataFrame([(1, 4, "a"), (1, 10, "b"), (2, 8, "c")], "k long, t long, v string")
    assert sorted((r.k, r.t, r.asof_value) for r in relops.asof(left, right, "k", "t", "v").collect()) == [(1, 5, "a"), (1, 10, "b"), (2, 7, None)]
    assert sorted((r.k, r.t, r.asof_value) for r in relops.asof(left, right, "k", "t", "v", 0).collect()) == [(1, 5, None), (1, 10, "b"), (2, 7, None)]
    assert sorted((r.t, r.r_t) for r in relops.interval_join(left, right, "k", "t", 1, 1).collect()) == [(5, 4), (7, 8), (10, 10)]


def test_draws_are_spread(spark):
    got = [r[0] for r in spark.range(2000).select(draw(3, F.col("id")) % 10).collect()]
    assert min(np.bincount(got)) > 120

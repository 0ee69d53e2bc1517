"""Training through Spark, few-shot episodes, segmentation, checkpoints; streams, files and SQL functions."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from pointloom import nets, train
from pointloom.functions import sqlfn
from pointloom.operators import corpora
from pointloom.plans import workloads
from pointloom.sources.pointfile import PointFileSource
from pointloom.streaming import tokens

CFG = nets.ModelConfig(blocks=1, width=8, heads=2, decoder_blocks=1, decoder_width=8, decoder_heads=2, grid=8, patch=4)


@pytest.fixture(scope="module")
def packed(spark):
    rng = np.random.default_rng(0)
    rows = [(k, k % 2, *[(rng.random(30) * (0.4 if k % 2 and c < 3 else 1.0)).tolist() for c in range(6)]) for k in range(24)]
    return spark.createDataFrame(rows, "sample_id long, label int, " + ", ".join(f"{c} array<double>" for c in "xyzrgb")).repartition(3).cache()


def test_spark_gradients_equal_one_batch(packed):
    params = nets.init(CFG)
    params |= {"class.w": np.ones((8, 2)) * 0.1, "class.b": np.zeros(2)}

    def loss_of(batch, labels, p):
        _, cls = nets.encode(nets.tokens_of(batch, CFG), p, CFG)
        return nets.cross_entropy(nets.linear(cls, p, "class"), labels.astype(int)), {}

    loss, grad = train.spark_gradients(packed, params, loss_of, "label", per_task=5)
    rows = packed.collect()
    one, want, _ = nets.gradients(lambda p: loss_of([np.stack([r[c] for c in "xyzrgb"], 1) for r in rows], np.array([r.label for r in rows]), p), params)
    assert loss == pytest.approx(one)
    assert all(np.allclose(grad[k], want[k], atol=1e-9) for k in want)


def test_pretraining_falls_and_finetuning_learns(packed):
    params, losses = train.pretrain(packed, CFG, steps=6, lr=1e-2, accum=1)
    assert losses[-1] < losses[0]
    model, trace = train.finetune(packed, 2, CFG, steps=40, params=params, lr=2e-2)
    assert trace[-1] < trace[0]
    assert workloads._accuracy(train.predict(packed, model, CFG)) > 0.8


def test_masks_equal_the_operator(spark):
    """A cloud's mask is that of the DataFrame operator, in whatever batch it comes."""
    from pointloom.operators import masking, patch, voxel
    from pointloom.schema import G16

    rng = np.random.default_rng(4)
    clouds = {k: rng.random((60, 6)) for k in (3, 8, 1_000_007)}
    cfg = nets.ModelConfig(grid=16, patch=4)
    rows = [(k, j, *map(float, p)) for k, pts in clouds.items() for j, p in enumerate(pts)]
    df = spark.createDataFrame(rows, "sample_id long, point_no long, x double, y double, z double, r double, g double, b double")
    v = patch.with_slot(voxel.voxelize(voxel.assign(df, G16), "argmax"), 4)
    want = {(r.sample_id, r.ci, r.cj, r.ck) for r in masking.random_mask(masking.patches_of(v), 60, 5).where("hidden").collect()}
    got = set()
    for ids in ([1_000_007], [8, 3]):
        t = nets.tokens_of(nets.Clouds([clouds[k] for k in ids], np.array(ids)), cfg)
        hidden = nets.hide(t, 60, 5)
        got |= {(ids[s], *c) for s, c in zip(t.sample[hidden].tolist(), t.cell[hidden].tolist())}
    assert got == want and len(want) > 20


def test_minibatches_cover_the_corpus_once_an_epoch(packed):
    n, part = train.minibatches(packed, 7)
    assert n == 4
    ids = [{r.sample_id for r in part(step).collect()} for step in range(2 * n)]
    for epoch in (ids[:n], ids[n:]):
        assert sorted(x for s in epoch for x in s) == list(range(24))
    _, losses = train.pretrain(packed, CFG, steps=3, batch=7)
    assert len(losses) == 3


def test_a_cloud_without_points_has_its_class_token(spark):
    cols = ", ".join(f"{c} array<double>" for c in "xyzrgb")
    df = spark.createDataFrame([(1, 0, *[[]] * 6), (2, 1, *[[0.1, 0.9]] * 6)], "sample_id long, label int, " + cols)
    for cfg in (CFG, nets.ModelConfig(blocks=1, width=8, heads=2, decoder_blocks=1, decoder_width=8, decoder_heads=2, group=4)):
        assert train.features(df, nets.init(cfg), cfg).count() == 2
        assert len(train.pretrain(df, cfg, steps=1)[1]) == 1


def test_one_point_a_voxel_gives_the_same_tokens(packed):
    small = {r.sample_id: r for r in train.representatives(packed, CFG).collect()}
    for r in packed.collect():
        pts, kept = (np.stack([x[c] for c in "xyzrgb"], 1) for x in (r, small[r.sample_id]))
        a, b = nets.voxel_tokens([pts], CFG), nets.voxel_tokens([kept], CFG)
        assert np.array_equal(a.cell, b.cell) and np.array_equal(a.slot, b.slot) and np.allclose(a.feat, b.feat, atol=1e-12) and small[r.sample_id].label == r.label


def test_nearest_neighbours_break_ties_by_place():
    from pointloom.operators.baselines import nearest_kernel

    rng = np.random.default_rng(1)
    x = rng.integers(0, 4, (200, 3)) / 4
    for k in (1, 5, 200, 300):
        at, far = nearest_kernel(x, x[:40], k, step=900)
        d = ((x[:40, None] - x[None]) ** 2).sum(-1)
        want = np.argsort(d, axis=1, kind="stable")[:, :k]
        assert np.array_equal(at, want) and np.allclose(far, np.take_along_axis(d, want, axis=1))


def test_full_size_encoder_runs():
    """The published small encoder on its own grid: 12 blocks of 384 channels, 4 096 slot matrices, ragged clouds side by side."""
    cfg, rng = nets.S, np.random.default_rng(0)
    shapes = {k: s for k, s in cfg.shapes().items() if k.startswith(("enc.", "slot.", "cls"))}
    p = {k: nets.Var(np.ones(s, np.float32) if k.endswith(".g") else rng.normal(0, 0.02, s).astype(np.float32)) for k, s in shapes.items()}
    clouds = [rng.random((n, 6)) for n in (300, 40)]
    t = nets.tokens_of(clouds, cfg)
    codes, cls = nets.encode(t, p, cfg)
    assert cls.value.shape == (2, 384) and codes.value.shape == (len(t.sample), 384) and np.isfinite(cls.value).all()
    alone = nets.encode(nets.tokens_of(clouds[1:], cfg), p, cfg)[1].value
    assert np.allclose(alone, cls.value[1:], atol=1e-4)


def test_checkpoint_round_trip(spark, tmp_path):
    params = nets.init(CFG)
    back = train.restore(spark, train.save(spark, params, str(tmp_path)))
    assert all(np.array_equal(params[k], back[k]) for k in params)


def test_episodes(spark):
    df = spark.range(400).select(F.col("id").alias("sample_id"), (F.col("id") % 12).cast("int").alias("label"))
    e = train.fewshot(df, 5, 10, 4)
    per = e.groupBy("run").agg(F.countDistinct("label").alias("c"), F.sum((F.col("role") == "support").cast("int")).alias("s"), F.count("*").alias("n"))
    assert [tuple(r)[1:] for r in per.collect()] == [(5, 50, 75)] * 4
    assert e.groupBy("run", "sample_id").count().where("count > 1").count() == 0


@pytest.mark.parametrize("form", [train.points_logits, train.hierarchical_logits, train.edge_logits])
def test_supervised_baselines_have_gradients(form):
    rng = np.random.default_rng(2)
    batch = [rng.random((20, 6)) for _ in range(3)]
    p = {k: rng.normal(size=s) for k, s in train.supervised_shapes(form, 3, 5).items()}
    run = lambda q: nets.gradients(lambda v: (nets.cross_entropy(form(batch, v), np.array([0, 1, 2])), {}), q)
    _, g, _ = run(p)
    for k in p:
        at = (0,) * p[k].ndim
        old, eps = p[k][at], 1e-6
        p[k][at] = old + eps
        up = run(p)[0]
        p[k][at] = old - eps
        down = run(p)[0]
        p[k][at] = old
        assert g[k][at] == pytest.approx((up - down) / (2 * eps), rel=1e-3, abs=1e-6)


def test_point_files(spark, tmp_path):
    spark.dataSource.register(PointFileSource)
    rows = [(s, k, *[round(s + k / 7 + c, 6) for c in range(6)]) for s in (3, 4) for k in range(5)]
    df = spark.createDataFrame(rows, "sample_id long, point_no long, x double, y double, z double, r double, g double, b double")
    df.repartition("sample_id").write.format("pointfile").option("path", str(tmp_path / "p")).mode("append").save()
    back = spark.read.format("pointfile").option("path", str(tmp_path / "p")).load()
    assert sorted(map(tuple, back.collect())) == sorted(rows)
    q = spark.readStream.format("pointfile").option("path", str(tmp_path / "p")).load().writeStream.format("memory").queryName("pf").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "c")).start()
    q.awaitTermination()
    assert spark.table("pf").count() == len(rows)


def test_clouds_as_text_files(spark, tmp_path):
    from pointloom.sources.pointfile import read_clouds, write_clouds

    rows = [(s, k, *[round(s + k / 7 + c, 6) for c in range(6)]) for s in (3, 4) for k in range(12)]
    df = spark.createDataFrame(rows, "sample_id long, point_no long, x double, y double, z double, r double, g double, b double").repartition(5)
    write_clouds(df, f"file://{tmp_path}/t")
    assert sorted(map(tuple, read_clouds(spark, f"file://{tmp_path}/t").collect())) == rows
    q = read_clouds(spark, f"file://{tmp_path}/t", True).writeStream.format("memory").queryName("clouds").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "c")).start()
    q.awaitTermination()
    assert sorted(map(tuple, spark.table("clouds").collect())) == rows


@pytest.mark.parametrize("fmt", ["csv", "json", "orc", "parquet"])
def test_formats_round_trip(spark, sf, tmp_path, fmt):
    df = corpora.lineitem_clouds(spark, sf, "region").select("sample_id", "point_no", *"xyzrgb").limit(200)
    df = spark.createDataFrame(df.collect(), df.schema)
    df.write.format(fmt).save(str(tmp_path / "t"))
    back = spark.read.schema(df.schema).format(fmt).load(str(tmp_path / "t"))
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, df.collect()))


def test_stateful_stream_equals_batch(spark, sf, tmp_path):
    pts = tokens.batch_points(spark, sf).where("sample_id <= 5")
    src = str(tmp_path / "in")
    pts.repartition(3).write.parquet(src)
    stream = spark.readStream.schema(pts.schema).option("maxFilesPerTrigger", 1).parquet(src)
    q = tokens.stateful_tokens(stream).writeStream.format("memory").queryName("st").outputMode("update").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "cp")).start()
    q.awaitTermination()
    last = spark.table("st").groupBy("sample_id").agg(F.max(F.struct("n_points", "n_voxels", "n_patches")).alias("m")).select("sample_id", "m.*")
    v = tokens.voxel_counts(pts)
    cells = [F.floor(F.col(k) / 4) for k in ("vi", "vj", "vk")]
    want = v.groupBy("sample_id").agg(F.sum("n_points").alias("n_points"), F.count("*").alias("n_voxels"), F.countDistinct(*cells).alias("n_patches"))
    assert sorted(map(tuple, last.collect())) == sorted(map(tuple, want.collect()))


def test_stream_table_in_update_mode(spark, sf, tmp_path):
    """Batches that change a voxel again leave one row of it."""
    pts = tokens.batch_points(spark, sf).where("sample_id <= 9")
    src = str(tmp_path / "in")
    pts.repartition(3).write.parquet(src)
    stream = spark.readStream.schema(pts.schema).option("maxFilesPerTrigger", 1).parquet(src)
    out = tokens.run_to_table(spark, tokens.voxel_counts(stream), f"file://{tmp_path}/run", ["sample_id", "vi", "vj", "vk"], "n_points")
    want = tokens.voxel_counts(pts)
    assert sorted(map(tuple, out.select(*want.columns).collect())) == sorted(map(tuple, want.collect()))


def test_late_and_replayed_events(spark, tmp_path):
    src = str(tmp_path / "e")
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    row = lambda i, t: (i, t, 1, "click", 1.0, '{"k": 1}')
    import datetime as dt

    t0 = dt.datetime(2024, 1, 1, 12)
    spark.createDataFrame([row(1, t0), row(1, t0), row(2, t0 + dt.timedelta(minutes=5))], schema).coalesce(1).write.mode("append").parquet(src)
    q = tokens.event_stream(spark, src).writeStream.format("memory").queryName("late").trigger(availableNow=True).option("checkpointLocation", str(tmp_path / "c")).start()
    q.awaitTermination()
    assert sorted(r.event_id for r in spark.table("late").collect()) == [1, 2]


def test_sql_functions(spark):
    sqlfn.register(spark)
    r = spark.sql("SELECT fx6(0.5D) a, slot_of(5, 6, 2, 4) b, vox_key(1, 2, 3) c, gelu(1.0D) d, morton_key(1, 1, 1) e, hash_order(7L, 1) f").first()
    assert (r.a, r.b, r.c, r.e) == (500000, 1 + 2 * 4 + 2 * 16, (1024 + 2) * 1024 + 3, 7) and r.d == pytest.approx(0.841192, abs=1e-4)
    s = spark.sql("SELECT vector_sum(v) s FROM VALUES (array(1.0D, 2.0D)), (array(3.0D, 4.0D)) t(v)").first().s
    assert list(s) == [4.0, 6.0]
    c = spark.sql("SELECT chamfer_agg(x, y, z, t) c FROM VALUES (0D, 0D, 0D, true), (1D, 0D, 0D, false), (0D, 2D, 0D, false) v(x, y, z, t)").first().c
    assert c == pytest.approx(3.5)
    assert spark.sql("SELECT count(*) n FROM episode(5, 10, 3)").first().n == 3


def test_image_files_are_lifted(spark, tmp_path):
    from pointloom.sources import images

    rng = np.random.default_rng(0)
    pics = {7: rng.integers(0, 256, (3, 5, 3)), 8: rng.integers(0, 256, (2, 2, 3))}
    for k, rgb in pics.items():
        (tmp_path / f"{k}.ppm").write_bytes(images.encode_ppm(rgb))
    rows = {r.sample_id: r for r in images.lift_images(images.read_ppm(spark, f"file://{tmp_path}")).collect()}
    assert {k: r.n for k, r in rows.items()} == {7: 15, 8: 4}
    assert rows[7].r == pytest.approx((pics[7][:, :, 0] / 255).ravel().tolist())
    assert rows[8].z[0] > rows[8].z[2] and rows[8].x[0] < rows[8].x[1]
    lum = (pics[8] / 255) @ np.array([0.299, 0.587, 0.114])
    assert rows[8].y == pytest.approx([lum.mean()] * 4)


def test_stream_with_stream_and_with_table(spark, tmp_path):
    import datetime as dt

    from pointloom.streaming import windows

    t0 = dt.datetime(2024, 1, 1, 12)
    rows = [(1, t0, 5, "click"), (2, t0 + dt.timedelta(minutes=30), 5, "purchase"), (3, t0 + dt.timedelta(hours=3), 5, "purchase"), (4, t0, 6, "click")]
    spark.createDataFrame(rows, "event_id long, ts timestamp, user_id long, event_type string").coalesce(1).write.parquet(str(tmp_path / "e"))
    ev = spark.readStream.schema("event_id long, ts timestamp, user_id long, event_type string").parquet(str(tmp_path / "e")).withWatermark("ts", "1 hour")
    near = windows.within(ev.where("event_type = 'purchase'"), ev.where("event_type = 'click'"), "user_id")
    dim = spark.createDataFrame([(5, "five")], "user_id long, name string")
    for name, df, want in (("near", near.select("event_id", "b_event_id"), [(2, 1)]), ("dim", windows.with_dimension(ev, dim, "user_id").select("event_id", "name"), [(1, "five"), (2, "five"), (3, "five"), (4, None)])):
        q = df.writeStream.format("memory").queryName(name).trigger(availableNow=True).option("checkpointLocation", str(tmp_path / name)).start()
        q.awaitTermination()
        assert sorted(map(tuple, spark.table(name).collect())) == want


def test_wide_model_sizes_are_constructible():
    small = sum(int(np.prod(s)) for s in nets.S.shapes().values())
    assert small == nets.S.n_params() > 20_000_000


def test_arms_share_a_pass_and_equal_their_own_training(packed, monkeypatch):
    """Models trained side by side take as many passes as one, and are what each becomes alone."""
    passes, real = [], train.arm_gradients
    monkeypatch.setattr(train, "arm_gradients", lambda *args: passes.append(len(args[1])) or real(*args))
    arms = [(CFG, {"percent": 30}), (CFG, {"percent": 75, "terms": ("mse",)})]
    both = train.pretrain_arms(packed, arms, 2, None, 5e-3, 1)
    assert passes == [2, 2]
    for (cfg, options), (params, losses) in zip(arms, both, strict=True):
        alone, own = train.pretrain(packed, cfg, 2, None, lr=5e-3, accum=1, **options)
        assert losses == pytest.approx(own, rel=1e-5) and all(np.allclose(params[k], alone[k], atol=1e-4) for k in params)
    tuned = train.finetune_arms(packed, 2, [(CFG, p) for p, _ in both], steps=2)
    assert passes[-2:] == [2, 2] and len(tuned) == 2
    score = train.accuracy_arms(packed, [(CFG, m) for m, _ in tuned])
    assert score == [workloads._accuracy(train.predict(packed, m, CFG)) for m, _ in tuned]


def test_single_precision_passes_give_the_gradients_of_double(packed):
    params = nets.init(CFG)

    def loss_of(batch, labels, p):
        t = nets.tokens_of(batch, CFG)
        return nets.pretrain_loss(t, nets.hide(t, 60, 0), p, CFG)

    (a, got), (b, want) = (train.arm_gradients(packed, [params], [loss_of], kind=k)[0] for k in (np.float32, np.float64))
    assert a == pytest.approx(b, rel=1e-5) and all(np.allclose(got[k], want[k], rtol=1e-3, atol=1e-5) and got[k].dtype == np.float64 for k in want)


def test_models_that_are_not_trained_remember_nothing(packed):
    clouds = [np.stack([r[c] for c in "xyzrgb"], 1) for r in packed.collect()]
    _, cls = nets.encode(nets.tokens_of(clouds, CFG), train.fixed(nets.init(CFG)), CFG)
    assert cls.fixed and not cls.made_from

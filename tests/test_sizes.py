"""What a task holds at a time is bounded, whatever the batches that Spark hands it."""

import numpy as np
import pyarrow as pa
import pytest

from pointloom import nets, train
from pointloom.operators import corpora, lift
from pointloom.plans import catalogue, workloads
from pointloom.schema import PIECE, pieces

SF = "/root/testdata/sf0.001"


def documents(n: int, chars: int) -> pa.RecordBatch:
    texts = ["".join(chr(32 + (k * 7 + i * i) % 90) for i in range(chars)) for k in range(n - 2)] + [None, "x" * (PIECE + 1)]
    return pa.RecordBatch.from_arrays([pa.array(range(n)), pa.array([0] * n, pa.int32()), pa.array([False] * n), pa.array(texts)], ["sample_id", "label", "is_test", "text"])


def test_pieces_hold_every_row_once():
    b = pa.RecordBatch.from_arrays([pa.array(range(7))], ["k"])
    assert [p.column(0).to_pylist() for p in pieces(b, np.array([2, 2, 9, 0, 1, 3, 1]), 4)] == [[0, 1], [2], [3, 4, 5], [6]]
    assert [p.column(0).to_pylist() for p in pieces(b, pa.array([None] * 7, pa.int32()), 4)] == [list(range(7))]
    assert list(pieces(b.slice(0, 0), np.zeros(0), 4)) == []


def test_stored_clouds_are_made_in_pieces():
    """One batch of texts is lifted in parts of at most PIECE points, not as one array of all its points."""
    batch = documents(300, 1500)
    out = list(workloads.stored_form(workloads.TEACHERS["near"], nets.TINY)([batch]))
    points = [sum(b.column(3).to_pylist()) for b in out]
    assert sum(b.num_rows for b in out) == 300 and len(out) >= 4 and all(p <= PIECE or b.num_rows == 1 for p, b in zip(points, out, strict=True))
    assert max(b.nbytes for b in out) < PIECE * 48


def test_stored_form_gives_the_points_of_the_tokeniser(spark):
    want = {r.sample_id: r for r in train.representatives(workloads.document_clouds(spark, SF), nets.TINY).collect()}
    batch = pa.RecordBatch.from_struct_array(pa.chunked_array(workloads.training_clouds(spark, SF).toArrow().to_struct_array()).combine_chunks())
    assert batch.num_rows == len(want)
    for k, cloud in zip(batch.column(0).to_pylist(), train._clouds(batch), strict=True):
        assert np.array_equal(cloud, np.stack([want[k][c] for c in "xyzrgb"], 1))


def test_parts_are_bounded_by_points():
    n = 40
    b = pa.RecordBatch.from_arrays([pa.array(range(n)), *[pa.array([[0.5] * 100] * n)] * 6], ["sample_id", *"xyzrgb"])
    parts = list(train._parts([b], 64, 1000))
    assert [p.num_rows for p in parts] == [10] * 4


def test_depths_are_summed_where_they_are_made(spark):
    """Rows of three numbers leave the task, not six doubles a character; an empty or a null text has no row."""
    df = catalogue.raster_min_mean_depth(spark, SF)
    assert df._jdf.queryExecution().executedPlan().toString().count("MapInArrow") == 1
    texts = spark.createDataFrame([(1, "ab\ncd"), (2, ""), (3, None), (4, "\u20ac" * 3)], "k long, t string")
    got = {r.sample_id: r for r in lift.depth_table(texts, "k", "t").collect()}
    want = {r.sample_id: [int(np.floor(v * 1e6 + 0.5)) for v in r.y] for r in lift.lift_packed(corpora.packed_rasters(texts, "k", "t")).collect()}
    for k, d in want.items():
        assert (got[k].n, got[k].min_depth, got[k].max_depth, got[k].sum_depth) == (len(d), min(d, default=None), max(d, default=None), sum(d))


def test_corpus_sums_need_no_packed_clouds(spark, monkeypatch):
    """Sums of the corpus equal those of its packed clouds, and without a path no packed cloud leaves a task."""
    want = {}
    for table, clouds in workloads.corpus_parts(spark, SF, "wide").items():
        if table != "vectors":
            rows = clouds.select("n", "y").collect()
            want[table] = [len(rows), sum(r.n for r in rows), max(r.n for r in rows), sum(int(np.floor(np.array(r.y) * 1e6 + 0.5).sum()) for r in rows)]

    def refused(batches):
        raise ValueError("packed")

    monkeypatch.setattr(lift, "lift_packed", lambda images, teacher=None: images.mapInArrow(refused, "sample_id long, n int, y array<double>"))
    got = {(r.arm, r.metric): r.value for r in workloads.w02_build_corpus(spark, SF, teachers=("wide",)).collect()}
    for table, values in want.items():
        assert [got[f"{table} wide", m] for m in ("clouds", "points", "largest", "depth_fx")] == values


@pytest.mark.parametrize("name", ["delta_vs_baseline", "published_cad", "published_fewshot", "published_tables", "published_training_cost", "udtf_slots", "lift_benchmark_clouds"])
def test_query_reads_a_given_table(spark, name):
    plan = catalogue.QUERIES[name](spark, SF)._jdf.queryExecution().optimizedPlan().collectLeaves().mkString()
    assert "parquet" in plan and "LocalRelation" not in plan and "LogicalRDD" not in plan


def test_largest_of_groups_and_their_gradient():
    """Groups of one size, of several sizes, unsorted and empty ones: the first largest row gets the gradient, and no row that of an empty group."""
    rng = np.random.default_rng(5)
    for group, n in ((np.repeat(np.arange(6), 4), 6), (np.array([0, 0, 2, 2, 2, 5]), 7), (np.array([3, 1, 3, 1, 0]), 4), (np.zeros(0, np.int64), 2)):
        a = nets.Var(rng.integers(0, 3, (len(group), 5)).astype(float))
        out, weight = nets.max_by(a, group, n), rng.random((n, 5))
        nets.total(nets.mul(out, nets.Var(weight))).backward()
        want, grad = np.zeros((n, 5)), np.zeros(a.value.shape)
        for g in set(group.tolist()):
            rows = np.flatnonzero(group == g)
            for c in range(5):
                top = rows[a.value[rows, c].argmax()]
                want[g, c], grad[top, c] = a.value[top, c], weight[g, c]
        assert np.array_equal(out.value, want) and np.array_equal(a.grad, grad)


def test_supervised_baselines_work_on_few_points_at_a_time(spark, monkeypatch):
    rows = [(k, k % 2, *[[0.1 * c + 0.001 * i for i in range(100)] for c in range(6)]) for k in range(30)]
    df = spark.createDataFrame(rows, "sample_id long, label int, " + ", ".join(f"{c} array<double>" for c in "xyzrgb")).coalesce(1)
    monkeypatch.setattr(train, "EDGE_PIECE", 300)

    def form(batch, p):
        assert sum(map(len, batch)) <= 300
        return train.points_logits(batch, p)

    params, losses = train.supervised(df, 2, form, steps=2)
    assert len(losses) == 2 and train.supervised_predict(df, params, form).count() == 30


def test_arms_of_the_cross_table_train_on_stored_clouds(spark, monkeypatch):
    """No step lifts the documents again: every corpus was written before its first step."""
    seen = []

    def trained(clouds, cfg, steps, **options):
        seen.extend(clouds.inputFiles())
        return {}, [1.0, 0.5]

    monkeypatch.setattr(workloads, "pretrained", trained)
    monkeypatch.setattr(workloads, "fit_and_score", lambda *args: 0.0)
    monkeypatch.setattr(train, "supervised", lambda *args, **options: ({}, []))
    monkeypatch.setattr(train, "supervised_predict", lambda data, *args: data.select("label", data.label.alias("pred")))
    workloads.w03_cross_table(spark, SF, 1)
    assert seen and not any("documents.parquet" in f for f in seen)


def test_nearest_rows_of_groups_are_found_side_by_side(monkeypatch):
    """The first of the nearest rows of the own group, in blocks of at most NEAR distances; groups without a partner stay out."""
    rng = np.random.default_rng(8)
    ga, gb = rng.integers(0, 9, 150), rng.integers(0, 11, 90)
    ga, gb = ga[ga != 3], gb[gb != 5]
    a, b = rng.integers(0, 3, (len(ga), 3)).astype(float), rng.integers(0, 3, (len(gb), 3)).astype(float)
    monkeypatch.setattr(nets, "NEAR", 300)
    got = nets.nearest(a, b, ga, gb, 11)
    for row, g, at in zip(a, ga, got, strict=True):
        own = np.flatnonzero(gb == g)
        assert at == (own[((b[own] - row) ** 2).sum(1).argmin()] if len(own) else 0)


def test_rows_of_all_samples_are_one_product():
    a, w = nets.Var(np.random.default_rng(9).random((5, 7, 4))), nets.Var(np.random.default_rng(10).random((4, 3)))
    out = nets.matmul(a, w)
    ((flat, _),) = out.made_from
    assert flat.value.shape == (35, 3) and np.allclose(out.value, a.value @ w.value)
    nets.total(out).backward()
    assert np.allclose(a.grad, np.ones((5, 7, 3)) @ w.value.T) and np.allclose(w.grad, a.value.sum((0, 1))[:, None] * np.ones(3))


def test_code_points_have_their_colours():
    cps = np.array([0, 10, 32, 65, 66, 97, 98, 122, 123, 254, 255, 300, 128_512], np.int32)
    r, g, b = corpora.image_colours(cps)
    assert g.tolist() == [float(chr(c) in corpora.VOWELS) for c in cps.tolist()] and np.allclose(r, np.minimum(cps, 255) / 255)
    assert np.array_equal(b * 3, [3, 2, 2, 1, 1, 0, 0, 0, 3, 3, 3, 3, 3])


def test_a_part_without_any_point_has_a_loss_and_gradients():
    t = nets.tokens_of(nets.Clouds([np.zeros((0, 6))] * 2, np.arange(2)), nets.TINY)
    loss, grad, _ = nets.gradients(lambda p: nets.pretrain_loss(t, nets.hide(t, 60, 0), p, nets.TINY), nets.init(nets.TINY))
    assert loss == 0 and all(np.isfinite(g).all() for g in grad.values())


def test_stored_clouds_are_dealt_to_all_cores(spark, monkeypatch):
    """A multiple of the cores of about equal files, whatever the files of the documents."""
    monkeypatch.setattr(workloads, "FILE_DOCUMENTS", 30)
    n, cores = spark.read.parquet(f"{SF}/documents.parquet").count(), spark.sparkContext.defaultParallelism
    clouds = workloads._dealt(workloads._labelled(spark, SF))
    assert clouds.rdd.getNumPartitions() == cores * -(-n // (cores * 30)) and clouds.count() == n

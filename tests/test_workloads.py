"""Every arm of the experiments, on the smallest tables and with few steps."""

import math

import numpy as np
import pytest

from pointloom import kernels
from pointloom.functions.fixed import PRIME, draw_of
from pointloom.operators import augment, baselines, corpora, lift
from pointloom.operators.tokenizer import CentreTokenizer, VoxelTokenizer
from pointloom.plans import workloads
from pointloom.schema import G32

SF = "/root/testdata/sf0.001"
ARMS = {
    "w03_cross_table": {"majority", *(f"{m} {c}" for m in ("voxel", "fixed") for c in ("lifted", "shapes", "none")), "supervised points", "supervised hierarchical", "supervised edge graph"},
    "w04_model_scaling": {"majority", "narrow", "wide", "deep", "S", "B", "L"},
    "w08a_mask_ratio": {"majority", "15", "30", "45", "60", "75", "90"},
    "w08b_augmentation": {"majority", "none", "3/4", "2/3", "1/2", "1/2+T"},
    "w08c_attributes_losses": {"majority", "graph mse", "graph mse+cd", "graph all", "origin all"},
    "w08d_corpus_size": {"majority", "10", "20", "40", "80", "420", "1000"},
    "w09_ragged_vs_fixed": {"majority", "fixed", "ragged voxel", "fixed voxel", "fixed centre"},
    "w07_part_segmentation": {"voxel", "centre"},
}


@pytest.mark.parametrize("name", list(ARMS))
def test_arms_appear_and_losses_fall(spark, name):
    rows = workloads.EXPERIMENTS[name](spark, SF, steps=16 if name == "w07_part_segmentation" else 3).collect()
    assert {r.arm for r in rows} == ARMS[name]
    by = {(r.arm, r.metric): r.value for r in rows}
    falls = [arm for arm, metric in by if metric == "first_loss"]
    assert all(by[arm, "last_loss"] < by[arm, "first_loss"] for arm in falls), by
    assert all(0 <= r.value <= 1 for r in rows if r.metric in ("ft", "lin", "accuracy", "background", "object", "perturbed") and r.value is not None)


def test_corpus_of_all_tables_and_teachers(spark, tmp_path):
    out = {(r.arm, r.metric): r.value for r in workloads.w02_build_corpus(spark, SF, f"file://{tmp_path}/c").collect()}
    assert {a.split()[0] for a, _ in out} == {"documents", "pages", "benchmark", "conversations", "vectors"}
    assert out["documents near", "points"] == out["documents wide", "points"] == sum(len(r.text or "") for r in spark.read.parquet(f"{SF}/documents.parquet").collect())
    assert out["documents near", "depth_fx"] != out["documents vowels", "depth_fx"] and out["vectors near", "largest"] == 64
    back = spark.read.parquet(f"file://{tmp_path}/c").groupBy("teacher", "corpus").count().collect()
    assert {f"{r.corpus} {r.teacher}": r["count"] for r in back} == {a: v for (a, m), v in out.items() if m == "clouds"}


def test_fewshot_and_tokeniser_arms(spark):
    arms = {r.arm for r in workloads.w05_fewshot(spark, SF, runs=2, steps=2).collect()}
    assert arms <= {f"{a}, {h}" for a in ("pretrained", "random", "attributes", "control") for h in ("centroid", "trained head")} and len(arms) >= 2
    cost = workloads.w01_tokenizer_cost(spark, SF, levels=("supplier",)).collect()
    assert {"voxel, supplier", "centre, supplier", "centre, same density, supplier"} <= {r.arm for r in cost} and any("digits" in r.arm for r in cost)
    assert all(r.value >= 0 for r in cost) and any(r.metric == "shuffle_mb" and r.value > 0 for r in cost)


def test_augmentation_equals_the_operators(spark):
    rng = np.random.default_rng(2)
    pts = rng.random((50, 6))
    df = spark.createDataFrame([(9, k, *map(float, p)) for k, p in enumerate(pts)], "sample_id long, point_no long, x double, y double, z double, r double, g double, b double")
    turn = 2 * math.pi * float(draw_of(3, 9)) / PRIME
    want = augment.colour_standardise(augment.scale_translate(augment.refit(augment.rotate_z(df, 0, angle=turn)), 0.5, 0.5, 4)).orderBy("point_no").collect()
    assert np.allclose([[r[c] for c in "xyzrgb"] for r in want], workloads.augmented(pts, 9))
    out = workloads.document_clouds(spark, SF).collect()
    assert len(out) == spark.read.parquet(f"{SF}/documents.parquet").count()
    assert all(0 <= v <= 1 for r in out for c in "xyz" for v in r[c])


def test_lifted_values_are_normalised():
    cps = np.array([65, 255, 8364, 128_512, 10], np.int32)
    assert all(((v >= 0) & (v <= 1)).all() for v in lift.lifted(cps, lift.BlurTeacher(1)))


def test_ablations_probe_all_arms_in_one_pass(spark, monkeypatch):
    passes, real = [], workloads.train.features_arms
    monkeypatch.setattr(workloads.train, "features_arms", lambda data, arms, *args: passes.append(len(arms)) or real(data, arms, *args))
    monkeypatch.setattr(workloads, "fit_arms", lambda data, classes, arms, *args: [0.5] * len(arms))
    rows = workloads.w08d_corpus_size(spark, SF, steps=1, thousandths=(420, 1000)).collect()
    assert passes == [2] and len([r for r in rows if r.metric == "lin"]) == 2


def test_tokeniser_cost_makes_no_long_form_of_documents(spark):
    rows = workloads.w01_tokenizer_cost(spark, SF, levels=("nation",)).collect()
    by = {(r.arm, r.metric): r.value for r in rows}
    texts = {arm for arm, _ in by if "digits" in arm}
    assert {a.split(",")[0] for a in texts} == {"lift", "voxel", "centre"}
    assert all(by[a, "exchanges"] == 0 == by[a, "shuffle_mb"] for a in texts)
    # a cloud's points come together once for centres, neighbours and network
    assert by["centre, nation", "exchanges"] == 1 and by["centre, nation", "shuffle_mb"] > 0


def test_packed_tokens_equal_the_operators(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").where("doc_id % 9 = 0").select("doc_id", "text")
    docs = docs.unionByName(spark.createDataFrame([(10**6, None), (10**6 + 1, ""), (10**6 + 2, "a"), (10**6 + 3, "a \u2603" * 20)], docs.schema))
    pts = lift.unpack(lift.lift_packed(corpora.packed_rasters(docs, "doc_id", "text")))
    level = corpora.lineitem_clouds(spark, SF, "part")

    def by_steps(points, n, k):
        own = points.dropDuplicates(["sample_id", "point_no"])
        return baselines.mini_pointnet(baselines.knn_group(own, baselines.fps(own, n), k))

    rows = lambda df, like: sorted(map(tuple, df.select(like.columns).collect()))
    for got, want in (
        (CentreTokenizer().transform_texts(docs, "doc_id", "text"), by_steps(pts, 64, 32)),
        (CentreTokenizer(5, 8).transform(level.unionByName(level.where("x < 0.3"))), by_steps(level, 5, 8)),
        (VoxelTokenizer(G32).transform_texts(docs, "doc_id", "text"), VoxelTokenizer(G32).transform(pts)),
    ):
        assert rows(got, want) == rows(want, want) != []


def test_centre_kernels_pick_the_same_points():
    rng = np.random.default_rng(4)
    for size in (1, 31, 32, 33, 64, 700, 4200):
        for steps in (2, 9, 10**6):
            xyz = rng.integers(0, steps, (size, 3)) / steps
            for cloud in (xyz, xyz[np.argsort(xyz[:, 2], kind="stable")], xyz[np.argsort(-xyz[:, 2], kind="stable")]):
                at = baselines.fps_kernel(cloud, 64)
                near = np.sort(baselines.nearest_kernel(cloud, cloud[at], 32)[0], axis=1)
                taken, groups = kernels.centre_groups(np.ascontiguousarray(cloud.T), 64, 32)
                assert (taken == at).all() and (np.sort(groups, axis=1) == near).all()
                block = np.full((3, 2, size + 5), kernels.NOWHERE)
                block[:, :, :size] = cloud.T[:, None]
                taken, groups = kernels.centre_groups_block(block, np.array([size, size]), len(at), 32)
                assert (taken == at[:, None]).all() and all((np.unique(g) == m).all() for row, m in zip(groups, near, strict=True) for g in row)

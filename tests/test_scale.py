"""What lets whole trainings pass over many documents: work that several models share, and work that nothing needs left out."""

import numpy as np
import pyarrow as pa
import pytest

from pointloom import nets, train
from pointloom.operators import lift
from pointloom.plans import workloads

SF = "/root/testdata/sf0.001"


def clouds(sizes=(40, 3, 90, 1), seed=0):
    rng = np.random.default_rng(seed)
    return [rng.random((n, 6)) for n in sizes]


def test_few_slots_are_one_product_for_all_voxels(monkeypatch):
    t, params = nets.tokens_of(clouds(), nets.TINY), nets.init(nets.TINY, 2)
    loss = lambda: nets.gradients(lambda p: nets.pretrain_loss(t, nets.hide(t, 45, 0), p, nets.TINY), params)
    monkeypatch.setattr(nets, "TABLE", 0)
    want = loss()
    monkeypatch.undo()
    monkeypatch.setattr(nets, "slot_linear", lambda *args: pytest.fail("slot by slot"))
    got = loss()
    assert got[0] == pytest.approx(want[0]) and all(np.allclose(got[1][k], want[1][k], atol=1e-12) for k in params)


def test_a_last_block_works_out_what_is_asked_for_alone(monkeypatch):
    t, p, rows, real = nets.tokens_of(clouds(), nets.TINY), train.fixed(nets.init(nets.TINY)), [], nets.gelu
    codes, classes = nets.encode(t, p, nets.TINY)
    monkeypatch.setattr(nets, "gelu", lambda a: rows.append(len(a.value)) or real(a))
    assert np.allclose(nets.encode(t, p, nets.TINY, "class")[1].value, classes.value)
    assert rows == [len(t.sample), len(t.sample) + t.n, t.n]
    assert np.allclose(nets.encode(t, p, nets.TINY, "tokens")[0].value, codes.value)


def test_padding_is_for_attention_alone(monkeypatch):
    t, p, rows, real = nets.tokens_of(clouds((90, 1, 1, 1)), nets.TINY), train.fixed(nets.init(nets.TINY)), [], nets.linear
    monkeypatch.setattr(nets, "linear", lambda x, *args: rows.append(x.value.size // x.value.shape[-1]) or real(x, *args))
    nets.encode(t, p, nets.TINY)
    assert max(rows) == len(t.sample) + t.n


def documents():
    texts = [None, "", "a", "Some words\nand äé😀 more of them " * 9, "x" * 300]
    n = len(texts)
    return pa.RecordBatch.from_arrays([pa.array(range(n), pa.int64()), pa.array([0] * n, pa.int32()), pa.array([False] * n), pa.array(texts)], ["sample_id", "label", "is_test", "text"])


def test_documents_are_lifted_once_for_all_arms():
    seen, near, moves = [], lift.BlurTeacher(1), ((0.5, 0.5), (1.0, 0.0), (0.5, 0.0))
    (all_arms,) = workloads.stored_form(lift.KernelTeacher(lambda cps: seen.append(len(cps)) or near(cps)), nets.TINY, moves)([documents()])
    assert len(seen) == 3
    for k, move in enumerate(moves):
        (alone,) = workloads.stored_form(near, nets.TINY, (move,))([documents()])
        assert all_arms.columns[3 + 6 * k : 9 + 6 * k] == alone.columns[3:]


def test_the_augmentation_arms_store_their_documents_once(spark, monkeypatch):
    made, real = [], workloads.scratch_table
    monkeypatch.setattr(workloads, "scratch_table", lambda df, *by: made.append(df.columns) or real(df, *by))
    monkeypatch.setattr(workloads, "pretrained_arms", lambda data, arms, steps: [({}, [float(data.count())])] * len(arms))
    monkeypatch.setattr(workloads, "fit_arms", lambda data, classes, arms, steps: [0.0] * len(arms))
    monkeypatch.setattr(workloads, "probe_arms", lambda data, arms: [0.0] * len(arms))
    n = spark.read.parquet(f"{SF}/documents.parquet").count()
    rows = workloads.w08b_augmentation(spark, SF, 1).collect()
    assert len(made) == 1 and [r.value for r in rows if r.metric == "last_loss"] == [n] * 5


def test_a_teacher_looks_at_few_pixels():
    rng = np.random.default_rng(1)
    for n in (1, 7, 50):
        cps, at = rng.integers(30, 400, n).astype(np.int32), np.sort(rng.permutation(n)[:4])
        for teacher in workloads.TEACHERS.values():
            assert all(np.array_equal(a[at], b) for a, b in zip(lift.lifted(cps, teacher), lift.lifted(cps, teacher, at), strict=True))


def test_models_of_the_cross_table_share_their_passes(spark, monkeypatch):
    seen, stored = [], []
    monkeypatch.setattr(workloads, "pretrained", lambda *args: ({}, [1.0, 0.5]))
    monkeypatch.setattr(workloads, "fit_arms", lambda data, classes, arms, steps: seen.append(len(arms)) or [0.0] * len(arms))
    monkeypatch.setattr(train, "supervised", lambda data, *args, **options: stored.append(len(data.select("x").inputFiles())) or ({}, []))
    monkeypatch.setattr(train, "supervised_predict", lambda data, *args: data.select("label", data.label.alias("pred")))
    monkeypatch.setattr(workloads, "cut_down", lambda data, n: data.where("n_cut is null") if "n_cut" in data.columns else data)
    rows = workloads.w03_cross_table(spark, SF, 1).collect()
    assert seen == [3] * 6 and len(stored) == 9 and len(rows) == 38


def test_supervised_layers_by_point_are_those_by_edge(monkeypatch):
    rng, batch = np.random.default_rng(3), clouds((30, 30, 4))
    p = {k: nets.Var(rng.normal(0, 0.5, s)) for k, s in train.supervised_shapes(train.edge_logits, 4, 8).items()}
    rows, real = [], nets.matmul
    monkeypatch.setattr(nets, "matmul", lambda a, b: rows.append(len(a.value)) or real(a, b))
    got = train.edge_logits(batch, p).value
    assert rows == [64] * 4
    value = lambda name: (p[f"{name}.w"].value, p[f"{name}.b"].value)
    for s, pts in enumerate(batch):
        h = pts[:, :3]
        for w, b in (value("p1"), value("p2")):
            d = ((h[:, None] - h[None]) ** 2).sum(-1)
            near = d.argsort(1, kind="stable")[:, :9]
            ends = h[near]
            own = np.repeat(h[:, None], near.shape[1], 1)
            h = np.maximum(np.concatenate([own, ends - own], 2) @ w + b, 0).max(1)
        w, b = value("p3")
        top = np.maximum(h @ w + b, 0).max(0)
        assert np.allclose(got[s], top @ value("class")[0] + value("class")[1])


def test_small_clouds_are_grouped_side_by_side(monkeypatch):
    cfg, many = nets.ModelConfig(group=8), [np.round(c, 1) for c in clouds((12, 30, 12, 9, 30, 3), 5)]
    monkeypatch.setattr(nets, "SMALL_CLOUD", 0)
    want = nets.group_tokens(many, cfg)
    monkeypatch.undo()
    monkeypatch.setattr(nets, "fps_kernel", lambda *args: pytest.fail("one by one"))
    got = nets.group_tokens(many, cfg)
    assert all(np.array_equal(getattr(got, k), getattr(want, k)) for k in ("sample", "corner", "owner", "feat", "cell"))

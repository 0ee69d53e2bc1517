"""Gradients, optimiser and training of the NumPy transformers."""

from dataclasses import replace

import numpy as np
import pytest

from pointloom import nets

CFG = nets.ModelConfig(blocks=1, width=8, heads=2, decoder_blocks=1, decoder_width=8, decoder_heads=2, grid=8, patch=4)


def clouds(n=4, points=40, seed=0):
    rng = np.random.default_rng(seed)
    return [rng.random((points + 5 * k, 6)) for k in range(n)]


def loss_value(params, t, hidden, cfg):
    return nets.gradients(lambda p: nets.pretrain_loss(t, hidden, p, cfg), params)


@pytest.mark.parametrize("cfg", [CFG, replace(CFG, features="origin"), replace(CFG, group=4)])
def test_gradients_match_central_differences(cfg):
    t = nets.tokens_of(clouds(), cfg)
    hidden, params = nets.hide(t, 50, 1), nets.init(cfg, 3)
    rng = np.random.default_rng(1)
    # away from the kinks that zero biases and exact centres would give
    params = {k: v + rng.normal(0, 0.05, v.shape) for k, v in params.items()}
    _, grad, _ = loss_value(params, t, hidden, cfg)
    for name in params:
        at = tuple(rng.integers(0, n) for n in params[name].shape)
        eps, old = 1e-5, params[name][at]
        both = []
        for sign in (1, -1):
            params[name][at] = old + sign * eps
            both.append(loss_value(params, t, hidden, cfg)[0])
        params[name][at] = old
        assert grad[name][at] == pytest.approx((both[0] - both[1]) / (2 * eps), rel=2e-3, abs=2e-6), name


def test_adamw_first_step_moves_by_the_rate():
    opt = nets.AdamW(lr=0.1, wd=0.0)
    out = opt.step({"w": np.array([[1.0, -2.0], [0.5, 3.0]])}, {"w": np.array([[0.3, -0.7], [2.0, 1e-3]])})
    assert np.allclose(out["w"], [[0.9, -1.9], [0.4, 2.9]], atol=1e-4)


def test_cosine_ends():
    assert nets.cosine(1.0, 0, 10) == 1.0
    assert nets.cosine(1.0, 10, 10) == pytest.approx(0.0)


def test_padding_is_not_attended_to():
    params = {k: nets.Var(v) for k, v in nets.init(CFG, 5).items()}
    one, two = clouds(2)
    alone = nets.encode(nets.tokens_of([one[:5]], CFG), params, CFG)[1].value
    beside = nets.encode(nets.tokens_of([one[:5], two], CFG), params, CFG)[1].value[:1]
    assert np.allclose(alone, beside)


def test_softmax_rows_sum_to_one():
    mask = np.array([[True, True, False]])
    p = nets.softmax(nets.Var(np.array([[1.0, 2.0, 50.0]])), mask).value
    assert p.sum() == pytest.approx(1.0) and p[0, 2] == 0


def test_loss_falls_on_few_clouds():
    t, params, opt, seen = nets.tokens_of(clouds(8), CFG), nets.init(CFG), nets.AdamW(1e-2), []
    for step in range(25):
        loss, grad, _ = loss_value(params, t, nets.hide(t, 60, 0), CFG)
        seen.append(loss)
        params = opt.step(params, grad)
    assert seen[-1] < 0.6 * seen[0]


def test_hidden_counts_are_whole_shares():
    t = nets.tokens_of(clouds(6), CFG)
    h = nets.hide(t, 60, 3)
    count = np.bincount(t.sample, minlength=6)
    assert (np.bincount(t.sample[h], minlength=6) == count * 60 // 100).all()


def test_two_sets_distance_and_occupancy():
    true, pred = np.zeros((1, 3)), nets.Var(np.array([[1.0, 0, 0], [0, 2.0, 0]]))
    assert nets.chamfer(true, pred, np.zeros(1, int), np.zeros(2, int), 1).value == pytest.approx(3.5)
    occ = np.zeros((1, 8))
    occ[0, 3] = 1
    assert nets.occupancy_bce(nets.Var(np.zeros((1, 8))), occ).value == pytest.approx(np.log(2))


def test_published_sizes():
    assert nets.S.slots == 4096 and nets.S.n_features == 12
    assert nets.B.n_params() > nets.S.n_params() > nets.TINY.n_params()

"""Layers against finite differences, shapes, receptive field, training, models."""

import numpy as np
import pytest

from clipflow.operators import nn as N
from clipflow.workloads.networks import rendered


def numeric(f, x, i):
    y = x.copy()
    y[i] += 1e-6
    z = x.copy()
    z[i] -= 1e-6
    return (f(y) - f(z)) / 2e-6


def check(layer, x, **params):
    rng = np.random.default_rng(0)
    y, back = layer(x, **params)
    g = rng.normal(size=y.shape)
    dx, grads = back(g)
    for name, value, grad in [("x", x, dx), *((k, params[k], v) for k, v in grads.items())]:
        for _ in range(4):
            i = tuple(rng.integers(0, n) for n in value.shape)
            f = (lambda z: (layer(z, **params)[0] * g).sum()) if name == "x" else (lambda z, name=name: (layer(x, **{**params, name: z})[0] * g).sum())
            assert np.isclose(numeric(f, value, i), grad[i], atol=1e-4), (layer, name)


def test_gradients():
    r = np.random.default_rng(1).normal
    check(lambda x, w, b: N.conv3d(x, w, b), r(size=(4, 6, 6, 2)), w=r(size=(3, 3, 3, 2, 3)), b=r(size=3))
    check(lambda x, gamma, beta: N.group_norm(x, 2, gamma, beta), r(size=(3, 2, 2, 4)), gamma=r(size=4), beta=r(size=4))
    check(N.dense, r(size=(4, 3)), w=r(size=(3, 2)), b=r(size=2))
    check(N.lstm, r(size=(4, 3)), wx=r(size=(3, 8)), wh=r(size=(2, 8)), b=r(size=8))
    check(N.gru, r(size=(4, 3)), wx=r(size=(3, 6)), wh=r(size=(2, 6)), b=r(size=6))
    check(lambda x, w, b: N.dilated(x, w, b, 2), r(size=(7, 3)), w=r(size=(3, 3, 2)), b=r(size=2))


def test_group_norm_is_standard_and_convolution_keeps_time():
    x = np.random.default_rng(2).normal(3, 2, (5, 4, 4, 4))
    y, _ = N.group_norm(x, 2, np.ones(4), np.zeros(4))
    for g in (y[..., :2], y[..., 2:]):
        assert abs(g.mean()) < 1e-9 and abs(g.var() - 1) < 1e-3
    y, _ = N.conv3d(x, np.zeros((3, 3, 3, 4, 2)), np.zeros(2))
    assert y.shape == (5, 2, 2, 2)


def test_receptive_field_is_eleven_frames():
    x = np.zeros((31, 12, 12, 1))
    for i in range(5):
        net = N.Net.start(12, 1, [2] * 5, 2, 0, 3, norm=False)
    net.activation = lambda z: (z, lambda g: (g, {}))
    base, _ = net.forward(x)
    x[15] = 1
    changed = np.nonzero(np.abs(net.forward(x)[0] - base).max(axis=1) > 1e-12)[0]
    assert changed.min() == 10 and changed.max() == 20


@pytest.mark.parametrize("temporal", ["lstm", "gru", "dilated"])
def test_whole_network_gradient(temporal):
    net = N.Net.start(6, 1, [2, 2], 4, 2, 4, temporal=temporal, norm=temporal != "gru")
    x = np.random.default_rng(3).normal(size=(7, 6, 6, 1))
    loss, grads = net.loss(x, [1, 2, 1])
    rng = np.random.default_rng(4)
    for k in grads:
        i = tuple(rng.integers(0, n) for n in net.params[k].shape)
        old = net.params[k][i]
        values = []
        for d in (1e-5, -1e-5):
            net.params[k][i] = old + d
            values.append(net.loss(x, [1, 2, 1])[0])
        net.params[k][i] = old
        assert abs((values[0] - values[1]) / 2e-5 - grads[k][i]) < 1e-3, k


def test_training_lowers_the_loss_and_models_round_trip(spark, small, tmp_path):
    clips = rendered(spark, small).where("clip_id < 8")
    net, losses = N.train(clips, N.Net.start(8, 1, [2], 6, 1, 7), 8, steps=15, rate=0.1)
    assert losses[-1] < 0.8 * losses[0]
    N.save_model(spark, net, f"{tmp_path}/m")
    again = N.load_model(spark, f"{tmp_path}/m")
    a, b = (sorted((r.clip_id, r.lattice) for r in N.predict(clips, n, 8).collect()) for n in (net, again))
    assert a == b and np.allclose([sum(f) for _, x in a for f in x], 1)


def test_a_distributed_step_is_the_step_of_one_machine(spark, small):
    clips = rendered(spark, small).where("clip_id < 8")
    start = N.Net.start(8, 1, [2], 4, 1, 7)
    net, _ = N.train(clips, start, 8, steps=1, workers=4, per_worker=8, rate=0.1)
    total, rows = {}, clips.collect()
    for r in rows:
        for k, g in start.loss(N._clip(r, 8, 1), list(r.label))[1].items():
            total[k] = total.get(k, 0) + g / len(rows)
    norm = max(1.0, np.sqrt(sum((g**2).sum() for g in total.values())) / 5)
    for k, g in total.items():
        assert np.allclose(net.params[k], start.params[k] - 0.1 * g / norm, atol=1e-8)


def test_saliency_of_a_linear_model_and_attention():
    net = N.Net.start(4, 1, [], 2, 0, 3)
    x = np.random.default_rng(5).normal(size=(4, 4, 4, 1))
    g = N.ctc.loss_and_gradient(net.forward(x)[0], [1, 2])[1]
    assert np.allclose(net.saliency(x, [1, 2]).reshape(4, -1), -g @ net.params["out.w"].T)
    frames = np.eye(4)[[0, 0, 1, 2, 2, 3]]
    model = N.AttnDecoder.start(4, 6, 4)
    losses = model.fit([(frames, [1, 2]), (frames[::-1], [2, 1])], 60)
    assert losses[-1] < losses[0]
    n_best = model.beam(frames, 8)
    assert all(np.isclose(s, model.score(frames, y)) for y, s in n_best if len(y) < 30)

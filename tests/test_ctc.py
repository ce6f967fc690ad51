"""CTC: worked example, brute force, gradients, decoding."""

from itertools import product

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from clipflow.operators import ctc as K


def lattice(seed, frames, symbols):
    x = np.random.default_rng(seed).random((frames, symbols)) + 0.05
    return np.log(x / x.sum(axis=1, keepdims=True))


def test_worked_example():
    uniform = np.log(np.full((5, 3), 1 / 3))
    assert np.isclose(np.exp(K.log_prob(uniform, [1, 2, 2])), 7 / 243)
    assert K.log_prob(uniform[:3], [1, 2, 2]) == -np.inf


@settings(max_examples=40, deadline=None)
@given(st.integers(0, 9999), st.integers(1, 5), st.lists(st.integers(1, 2), max_size=3))
def test_forward_is_the_sum_over_strings(seed, frames, label):
    logp = lattice(seed, frames, 3)
    assert np.isclose(np.exp(K.log_prob(logp, label)), K.brute(logp, label))


def test_all_labels_sum_to_one():
    logp = lattice(3, 4, 3)
    labels = {K.collapse(u) for u in product(range(3), repeat=4)}
    assert np.isclose(sum(np.exp(K.log_prob(logp, list(y))) for y in labels), 1)


def test_forward_times_backward_is_constant():
    logp, label = lattice(4, 7, 4), [1, 2, 2, 3]
    both = np.logaddexp.reduce(K.forward(logp, label) + K.backward(logp, label), axis=1)
    assert np.allclose(both, K.log_prob(logp, label))


def test_gradient_by_finite_differences():
    x, label = np.random.default_rng(5).normal(size=(6, 4)), [2, 2, 1]
    loss, grad = K.loss_and_gradient(x, label)
    for i, j in product(range(6), range(4)):
        y = x.copy()
        y[i, j] += 1e-6
        assert abs((K.loss_and_gradient(y, label)[0] - loss) / 1e-6 - grad[i, j]) < 1e-4


@pytest.mark.parametrize("seed", range(5))
def test_best_path_and_wide_beam(seed):
    logp, label = lattice(seed, 5, 3), [1, 2]
    path, score = K.best_path(logp, label)
    every = [u for u in product(range(3), repeat=5) if K.collapse(u) == (1, 2)]
    best = max(every, key=lambda u: sum(logp[t, k] for t, k in enumerate(u)))
    assert np.isclose(score, sum(logp[t, k] for t, k in enumerate(best))) and K.collapse(path) == (1, 2)
    beams = dict(K.beam_search(logp, width=10_000))
    for y, s in beams.items():
        assert np.isclose(np.exp(s), K.brute(logp, list(y)))


def test_dataframe_forms(spark):
    logp = lattice(1, 5, 3)
    df = spark.createDataFrame([("u", np.exp(logp).tolist(), [1, 2])], "utt string, lattice array<array<double>>, label array<int>")
    assert np.isclose(K.ctc_logprob(df).first().logp, K.log_prob(logp, [1, 2]))
    assert tuple(K.ctc_beam(df, 50).where("rank = 0").first().label) == K.beam_search(logp, 50)[0][0]

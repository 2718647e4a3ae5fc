"""The language model's recursions side by side: same numbers as text by text, without state-to-state matrices where texts are many."""

import math
import tracemalloc

import numpy as np
import pytest
from finegrain.llm import lm


def drawn_model(states, classes, seed=3):
    rng = np.random.default_rng(seed)
    return lm.HiddenMarkov(rng.dirichlet(np.ones(states)), rng.dirichlet(np.ones(states), states), rng.dirichlet(np.ones(classes), states).T)


def plain_counts(m, symbols):
    """Forward and backward over one text, each step scaled by itself."""
    a, b, n = [], [np.ones(len(m.start))], len(symbols)
    likelihood = 0.0
    for t, s in enumerate(symbols):
        x = (m.start if t == 0 else a[-1] @ m.step) * m.emit[s]
        likelihood += math.log(x.sum())
        a.append(x / x.sum())
    for s in symbols[:0:-1]:
        y = m.step @ (m.emit[s] * b[-1])
        b.append(y / y.sum())
    b = b[::-1]
    gamma = np.array([x * y / (x * y).sum() for x, y in zip(a, b, strict=True)])
    trans, emit = np.zeros_like(m.step), np.zeros_like(m.emit)
    for t in range(1, n):
        xi = a[t - 1][:, None] * m.step * (m.emit[symbols[t]] * b[t])
        trans += xi / xi.sum()
    np.add.at(emit, symbols, gamma)
    return gamma[0], trans, emit, likelihood


@pytest.mark.parametrize("longest", [30, 900])
def test_counts_equal_text_by_text(longest):
    rng = np.random.default_rng(12)
    m = drawn_model(5, 23)
    lengths = rng.integers(1, longest, 90)
    symbols = rng.integers(0, 23, lengths.sum())
    ends = np.cumsum(lengths)
    want = [plain_counts(m, symbols[e - n : e]) for e, n in zip(ends, lengths, strict=True)]
    for window, halo in ((10_000, 0), (256, 200)):
        got = lm.expected_counts(m, symbols, lengths, window, halo)
        for k in range(4):
            assert np.allclose(got[k], sum(w[k] for w in want), rtol=1e-6, atol=1e-9)


@pytest.mark.parametrize("most", [40, 700])
def test_forward_equals_text_by_text(most):
    """Texts that run on after the others are chained from windows."""
    rng = np.random.default_rng(13)
    m = drawn_model(4, 9)
    lengths = np.concatenate([rng.integers(1, most, 80), [3000, 1, 2999, 65]])
    symbols = rng.integers(0, 9, lengths.sum())
    ends = np.cumsum(lengths)
    want = [plain_counts(m, symbols[e - n : e])[3] / math.log(10) for e, n in zip(ends, lengths, strict=True)]
    assert np.allclose(lm.forward_log10(m, symbols, lengths), want, rtol=1e-12)


def test_no_sequences():
    m, none = drawn_model(3, 7), np.zeros(0, np.int64)
    assert not any(np.any(x) for x in lm.expected_counts(m, none, none)) and not len(lm.forward_log10(m, none, none))


def test_many_texts_need_no_matrices():
    """One row of states for each text, not a matrix of states by states."""
    m, texts = drawn_model(16, 50), 2000
    symbols = np.random.default_rng(14).integers(0, 50, texts * 60)
    tracemalloc.start()
    lm.forward_log10(m, symbols, np.full(texts, 60))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < texts * 16 * 16 * 8

import itertools

import numpy as np
from framedelta.llm import crf


def test_marginals_equal_enumeration():
    r = np.random.default_rng(1)
    k, lengths = 3, np.array([1, 4, 2, 5, 1])
    e, t = r.normal(size=(lengths.sum(), k)), r.normal(size=(k, k))
    marg, log_z, pairs = crf.forward_backward(e, crf.Layout(lengths), t, pairs=True)
    at, want_z, want_pairs = 0, 0.0, np.zeros((k, k))
    for n in lengths:
        z, m, p = 0.0, np.zeros((n, k)), np.zeros((k, k))
        for path in itertools.product(range(k), repeat=int(n)):
            s = np.exp(sum(e[at + i, y] for i, y in enumerate(path)) + sum(t[a, b] for a, b in itertools.pairwise(path)))
            z += s
            for i, y in enumerate(path):
                m[i, y] += s
            for a, b in itertools.pairwise(path):
                p[a, b] += s
        assert np.allclose(marg[at : at + n], m / z)
        want_z += np.log(z)
        want_pairs += p / z
        at += n
    assert np.isclose(log_z, want_z) and np.allclose(pairs, want_pairs)
    assert crf.forward_backward(np.zeros((0, 2)), crf.Layout(np.zeros(0)), np.zeros((2, 2))).shape == (0, 2)


def test_gradient_by_differences():
    r = np.random.default_rng(2)
    lengths = np.array([3, 2])
    items = crf.Bags(np.array([0, 1, 2, 1, 0]), np.array([0, 1, 2, 0, 3]), np.array([0, 2, 4]), 4)
    w, t = r.normal(size=(4, 2)), r.normal(size=(2, 2))
    y = np.array([0, 1, 1, 0, 1])
    gold = np.eye(2)[y]

    def loss(w):
        s = items.scores(w)
        _, z, _ = crf.forward_backward(s, crf.Layout(lengths), t, pairs=True)
        return (s * gold).sum() + t[0, 1] + t[1, 1] + t[0, 1] - z

    g = items.push(gold - crf.forward_backward(items.scores(w), crf.Layout(lengths), t))
    for i, j in itertools.product(range(4), range(2)):
        d = np.zeros_like(w)
        d[i, j] = 1e-5
        assert np.isclose(g[i, j], (loss(w + d) - loss(w - d)) / 2e-5, atol=1e-6)


def test_fit_learns_transitions():
    y = np.array([0, 1] * 50)
    items = crf.Bags(np.zeros(100, np.int64), np.array([0]), np.array([0]), 1)
    _, t = crf.fit(items, y, np.array([10] * 10), 2, steps=60)
    assert t[0, 1] > t[0, 0] + 1 and t[1, 0] > t[1, 1] + 1

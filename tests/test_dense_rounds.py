"""Rounds of a push in which most arcs take part: they don't pick arcs one by one, and give the same state."""

import numpy as np

from pushwave.operators import kernels as K


def _graph(rng, n, most):
    deg = rng.integers(0, most, n)
    deg[[3, n - 1]] = 0
    return K.Local(np.arange(n) * 3, np.append(0, np.cumsum(deg)), rng.integers(0, n, int(deg.sum())).astype(np.int32))


def test_dense_rounds_read_arcs_as_they_lie(monkeypatch):
    rng = np.random.default_rng(4)
    g, start = _graph(rng, 400, 9), rng.random(400)
    start /= start.sum()
    p, r = np.zeros(400), start.copy()
    for _ in range(7):  # by the definition of a round
        out, into = r.copy(), np.zeros(400)
        p += np.where(g.deg == 0, out, 0.2 * out)
        for v in range(400):
            for t in g.target[g.first[v] : g.first[v + 1]]:
                into[t] += 0.8 * out[v] / g.deg[v]
        r = into
    asked = []
    expand = K.expand
    monkeypatch.setattr(K, "expand", lambda *a: asked.append(1) or expand(*a))
    for arcs in (1 << 22, 50, 1):
        monkeypatch.setattr(K, "ARCS", arcs)
        s = K.Push(g, np.arange(400), start)
        assert s.run(0.0, 0.2, max_rounds=7) == 7
        assert np.allclose(s.p, p, rtol=0, atol=1e-14) and np.allclose(s.r, r, rtol=0, atol=1e-14)
    assert not asked

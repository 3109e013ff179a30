import numpy as np

from pushwave.llm import maxent_lm as M


def test_a_step_takes_one_gradient_for_several_rows():
    """The same as row by row, without a copy of the gradient for each of a position's rows."""
    rng = np.random.default_rng(3)
    rows, gradient = rng.random((M.CLASS_ROWS, 5)).astype(np.float32), rng.random((40, 5)).astype(np.float32)
    at = np.concatenate([rng.integers(0, 6, 40), rng.integers(M.CLASS_ROWS - 4, M.CLASS_ROWS, 40), rng.integers(2, 9, 40)])
    want, want_square = rows.astype(np.float64), np.ones(len(rows))
    for row in np.unique(at):
        step = np.tile(gradient, (3, 1))[at == row].sum(axis=0, dtype=np.float64)
        want_square[row] += (step * step).sum()
        want[row] -= M.RATE / np.sqrt(want_square[row]) * step
    seen, square = np.zeros(len(rows)), np.ones(len(rows))
    M.Trainer._apply(rows, seen, square, at, gradient)
    assert np.allclose(rows, want, rtol=0, atol=1e-5) and np.allclose(square, want_square, rtol=1e-5)
    assert np.array_equal(seen, np.bincount(at, minlength=len(rows)))

"""The fit of the quality classifier."""

import numpy as np

from labelflow.llm.quality import _fit_logistic


def test_fit_reaches_the_optimum():
    draw = np.random.default_rng(5)
    n, m = 800, 300
    x = draw.random((n, m)) < draw.random(m) * 0.3
    target = (x @ draw.normal(size=m) + draw.normal(size=n) > 0.5).astype(float)
    row, ends = np.nonzero(x)[1], np.cumsum(x.sum(axis=1))
    w, b = _fit_logistic(ends, row, m, target)
    gap = 1 / (1 + np.exp(-(x @ w + b))) - target
    # the gradient steps of before ended at 0.12
    assert np.abs(x.T @ gap + 0.5 * w).max() < 0.02 and abs(gap.sum()) < 0.02

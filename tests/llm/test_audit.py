"""The audit of the vector search widens beams for sparse queries too."""

import numpy as np

from accord.llm import vectors


class Forgetful:
    """Finds everything in a dense group, but loners only by beams of 192 and more."""

    def __init__(self, x):
        self.x = x

    def within(self, q, least, ef):
        return [near if len(near) > 2 or ef >= 192 else near[:0] for near in (np.nonzero(row >= least)[0] for row in q @ self.x.T)]


def test_each_query_counts_alike():
    rng = np.random.default_rng(1)
    n, dense = 3000, 1000
    x = rng.normal(size=(n, 64))
    x[:dense] = x[0] + 0.05 * rng.normal(size=(dense, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    x = x.astype(np.float32)
    assert vectors._audited(Forgetful(x), x, 0.95) >= 192

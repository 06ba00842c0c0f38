"""Estimates and posteriors of the quality rules against a plain EM in arrays, and against planted accuracies."""

import collections
import itertools

import numpy as np
import pytest

from accord.llm import quality
from conftest import SF


def plain_em(counts, kinds, rounds=500, prior=1.0):
    """Posterior of each pattern, by arrays of one-hot votes."""
    patterns = np.array(list(counts))
    n = np.array(list(counts.values()), float)
    k = max(kinds) + 1
    hot = (patterns[:, :, None] == np.array([-1, 0, 1])).astype(float)
    b = np.zeros((len(n), k))
    for c in range(1, k):
        b[:, c] = (patterns[:, np.array(kinds) == c] == -1).sum(axis=1)
    told = b.sum(axis=1) > 0
    b[told] *= 0.9 / b[told].sum(axis=1, keepdims=True)
    b[told, 0], b[~told, 0], b[~told, 1:] = 0.1, 0.9, 0.1 / (k - 1)
    for _ in range(rounds):
        w = b * n[:, None]
        shares = (w.sum(axis=0) + prior) / (n.sum() + k * prior)
        tables = (np.einsum("prv,pc->rvc", hot, w) + prior) / (w.sum(axis=0) + 3 * prior)
        logs = np.log(shares) + np.einsum("prv,rvc->pc", hot, np.log(tables))
        e = np.exp(logs - logs.max(axis=1, keepdims=True))
        after = e / e.sum(axis=1, keepdims=True)
        if np.abs(after - b).max() < 1e-9:
            break
        b = after
    return {tuple(int(x) for x in p): row for p, row in zip(patterns, after)}


def test_posterior_against_plain_em(spark):
    seen = quality.judged(spark.read.parquet(f"{SF.replace('0.001', '0.01')}/documents.parquet")).select("votes", "quality", "good").collect()
    counts = collections.Counter(tuple(r.votes) for r in seen)
    want = plain_em(counts, [r[1] for r in quality.RULES])
    assert all(r.quality == pytest.approx(want[tuple(r.votes)][0], abs=1e-6) and r.good == (r.quality >= 0.5) for r in seen)
    all_pass = sum(-1 not in r.votes for r in seen)
    assert sum(r.good for r in seen) != all_pass and any(r.good and -1 in r.votes for r in seen)


def test_planted_accuracies_are_found():
    """Two kinds with three rules each, of known accuracies: estimates come near, whatever the order of the rules' quality."""
    rng = np.random.default_rng(3)
    truth = rng.choice(3, 30_000, p=[0.8, 0.13, 0.07])
    hit, false = [0.9, 0.6, 0.8, 0.95, 0.7, 0.5], [0.02, 0.01, 0.05, 0.01, 0.03, 0.02]
    kinds = (1, 1, 1, 2, 2, 2)
    against = np.stack([rng.random(len(truth)) < np.where(truth == k, h, f) for k, h, f in zip(kinds, hit, false)], axis=1)
    counts = collections.Counter(map(tuple, np.where(against, -1, 1).tolist()))
    shares, tables = quality.fit(counts, kinds)
    assert shares == pytest.approx([0.8, 0.13, 0.07], abs=0.02)
    for r, k in enumerate(kinds):
        assert tables[r][-1][k] == pytest.approx(hit[r], abs=0.05) and tables[r][-1][0] == pytest.approx(false[r], abs=0.02)


def test_one_doubtful_vote_does_not_reject():
    counts = {p: 3 if -1 in p else 900 for p in itertools.product((1, -1), repeat=3)} | {(-1, -1, -1): 90}
    shares, tables = quality.fit(counts, (1, 1, 1))
    assert quality.posterior((-1, 1, 1), shares, tables)[0] > 0.5 > quality.posterior((-1, -1, -1), shares, tables)[0]

"""Suffix order and common prefixes by prefix-free parsing against sorting all suffixes."""

import collections
import os
import random

import numpy as np
import pytest

from accord.llm import parsing


def cases():
    random.seed(11)
    word = lambda: random.choice(["alpha ", "beta ", "of ", "the ", "x", "\n"])
    base = "".join(word() for _ in range(120)).encode()
    yield [base, base[50:400], base[:200] + b"!" + base[201:], base, b"", base[-60:]]
    yield [b"a" * 300, b"a" * 250, b"ab" * 200, b"b" + b"ab" * 150, b"\x00" * 90, b"\xff\x00" * 70]
    yield [bytes(random.choices(b"ab", k=400)) for _ in range(4)]
    yield [os.urandom(200), b"z", b""]
    yield [bytes(random.choices(b"acgt", k=random.randrange(60))) for _ in range(40)]
    yield [base[i : i + 260] for i in range(0, 300, 7)]
    yield []
    yield [b"", b""]


@pytest.mark.parametrize("gram,modulus", [(12, 24), (3, 4), (2, 1), (5, 10**9)])
def test_order_and_common_prefixes(monkeypatch, gram, modulus):
    monkeypatch.setattr(parsing, "GRAM", gram)
    monkeypatch.setattr(parsing, "MODULUS", modulus)
    for texts in cases():
        t, o, lcp = parsing.suffix_order(texts)
        got = [texts[i][j:] for i, j in zip(t, o)]
        assert got == sorted(x[j:] for x in texts for j in range(len(x)))
        assert len({*zip(t.tolist(), o.tolist())}) == len(t)
        for k in range(1, len(got)):
            assert lcp[k] == len(os.path.commonprefix([got[k - 1], got[k]])), (got[k - 1], got[k], lcp[k])


def test_repeated_strings():
    for texts in cases():
        for window in (1, 20, 200):
            seen = collections.Counter(x[j : j + window] for x in texts for j in range(len(x) - window + 1))
            want = sorted((i, j) for i, x in enumerate(texts) for j in range(len(x) - window + 1) if seen[x[j : j + window]] > 1)
            assert sorted(zip(*(v.tolist() for v in parsing.repeated(texts, window)))) == want
    assert np.array_equal(parsing.suffix_order([b"ba"])[1], [1, 0])

"""Queries that are no samples take every pair of the tables."""

import hashlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from accord.operators import anomaly, classify, grouping, landmarks, metrics, pattern, robustness, sampling
from accord.queries import experiments, study
from accord.sources import carriers
from conftest import SF


def strong_motion(spark) -> dict:
    """(video_id, t) to (source, half, motion) of each pair with enough motion, told in numpy."""
    out = {}
    for r in carriers.face(spark, SF).collect():
        m = np.array([[v.dx, v.dy] for v in r.motion])
        if (np.hypot(m[:, 0], m[:, 1]) >= 0.85).sum() >= 0.5 * len(m):
            out[r.video_id, r.t] = r.source, r.half, m
    return out


def test_spectral_queries_take_all_strong_pairs(spark):
    strong = strong_motion(spark)
    assert max(Counter(v[:2] for v in strong.values()).values()) > 20
    got = {(r.video_id, r.t): r for r in study.group_pairs(spark, SF).collect()}
    assert got.keys() == strong.keys()
    for key in sorted(strong)[::20]:
        one = grouping.group_batch(strong[key][2][None], grouping.Options())
        r = got[key]
        assert (r.k, r.labels) == (one["k"][0], ",".join(map(str, one["labels"][0])))
        assert abs(r.score - one["score"][0]) <= 0.001
    of_source = Counter(v[0] for v in strong.values())
    for query in (study.spectral_gap, study.k_histogram_spectral):
        n = Counter()
        for r in query(spark, SF).collect():
            n[r.source] += r.n_pairs
        assert n == of_source
    assert {(r.video_id, r.t) for r in study.group_pairs_all_k(spark, SF).collect()} == strong.keys()


def test_experiments_draw_from_all_strong_pairs(spark):
    strong = strong_motion(spark)
    whole = experiments.pool(spark, SF)
    assert {(r.video_id, r.t) for r in whole.select("video_id", "t").collect()} == strong.keys()
    genuine = sum(source == "R" and half == "a" for source, half, _ in strong.values())
    assert genuine > 200
    template = anomaly.template_pairs(whole.where("half = 'a'"), 3000)
    assert template.count() == min(3000, genuine)
    few = experiments.sets(whole, (1, 10), 60)
    assert few.groupBy("source", "half", "n_pick").count().where("count != 60").isEmpty()
    shared = experiments.sets(whole, (10,), 60, "video_id")
    assert shared.groupBy("source", "half").count().where("count != 60").isEmpty()


def test_prefixes_are_the_patterns_of_each_n(spark):
    """All N at once against a build for each, normalised by numpy; scores against the native ones."""
    whole = experiments.pool(spark, SF)
    draws = sampling.pattern_sets(whole, 3, 35, "pool").persist()
    got = {(r.pool, r.pattern_id, r.n_pick): r for r in pattern.prefixes(draws, ["pool", "pattern_id"], (1, 10, 35)).collect()}
    for n in (1, 10, 35):
        for r in pattern.build(draws.where(F.col("draw") < n), ["pool", "pattern_id"]).collect():
            own, total = got.pop((r.pool, r.pattern_id, n)), 2 * sum(map(abs, r.tri)) + 51 * r.diag
            assert np.allclose(own.tri, np.array(r.tri) / total, atol=1e-12) and abs(own.diag - r.diag / total) < 1e-12
    assert not got
    template = anomaly.template(whole.where("half = 'a'"), 100)
    p = pattern.prefixes(draws, ["pool", "pattern_id"], (10,))
    native = {(r.pool, r.pattern_id): r.d for r in anomaly.score(p, template, normalise=False).collect()}
    for r in anomaly.score_packed(p, template).collect():
        assert abs(r.d - native[r.pool, r.pattern_id]) < 1e-12
    draws.unpersist()


def test_spectral_auc_against_numpy(spark):
    """From labels to AUC in numpy, on the labels that the kernel gives."""
    ns = (1, 10, 35, 70)
    g = study.spectral_groups(spark, SF).collect()
    low = np.tril_indices(51, -1)

    def hashed(r):
        return hashlib.md5(f"0:{r.video_id}:{r.t}".encode()).hexdigest()

    def total(rows):
        tri, diag = np.zeros(len(low[0])), 0.0
        for r in rows:
            lab = np.array(r.labels)
            w = r.k * r.score
            tri += w * (lab[:, None] == lab[None, :])[low]
            diag += w
        return tri / (2 * tri.sum() + 51 * diag)

    template = total(sorted((r for r in g if r.source == "R" and r.half == "a"), key=lambda r: (hashed(r), r.video_id, r.t))[:3000])
    videos = {}
    for r in g:
        if r.half == "b":
            videos.setdefault(r.video_id, []).append(r)
    want = {}
    for n in ns:
        scores = []
        for rows in videos.values():
            p = total(sorted(rows, key=lambda r: (hashed(r), r.t))[:n])
            half = (p + template) / 2
            d = sum((x[x > 0] * np.log(x[x > 0] / half[x > 0])).sum() for x in (p, template)) / 2
            scores.append((rows[0].source, rows[0].y, round(d, 9)))
        for task in "ABCD":
            pos, neg = [d for s, y, d in scores if s == task], [d for _, y, d in scores if y == 0]
            want[task, n] = np.mean([(a > b) + (a == b) / 2 for a in pos for b in neg])
    for r in study.spectral_auc(spark, SF).collect():
        assert abs(r.auc - want[r.task, r.n_pick]) < 2e-6


def test_curves_are_exact_within_bins(spark, monkeypatch):
    rng = np.random.default_rng(2)
    d, y = rng.integers(0, 60, 400) / 7, rng.integers(0, 2, 400)
    df = spark.createDataFrame([("x", float(a), int(b)) for a, b in zip(d, y)] + [("one", 0.5, 1)], "k string, d double, y int")
    for bins in (1, 3, 4096):
        monkeypatch.setattr(metrics, "BINS", bins)
        got = {r.k: r.auc for r in metrics.auc(df, "k").collect()}
        assert got["one"] is None and got["x"] == pytest.approx(np.mean([(a > b) + (a == b) / 2 for a in d[y == 1] for b in d[y == 0]]), abs=1e-6)
        for r in metrics.roc(df.where("k = 'x'"), "k").collect():
            assert r.fpr == pytest.approx((d[y == 0] >= r.d).mean()) and r.tpr == pytest.approx((d[y == 1] >= r.d).mean())


def test_real_valued_boosting(spark):
    """One round against plain sums, and a margin that tells a sum."""
    rng = np.random.default_rng(4)
    x = rng.integers(0, 6, (300, 3)).astype(np.uint8)
    y = (x[:, 0].astype(int) + x[:, 1] > 5).astype(int)
    df = spark.createDataFrame([("t", int(c), bytes(r.tolist())) for r, c in zip(x, y)], "task string, y int, bins binary")
    best = classify.best_real_stump(classify.round_histogram(df, {}, classify.real_margin)).first()
    bound = {}
    for f in range(3):
        for b in range(6):
            low = x[:, f] <= b
            parts = [((y[m] == 1).sum(), (y[m] == 0).sum()) for m in (low, ~low)]
            bound[f, b] = sum(np.sqrt(p * n) for p, n in parts) / len(y)
    f, b = min(bound, key=lambda k: (round(bound[k], 12), k))
    assert (best.f, best.b) == (f, b) and best.bound == pytest.approx(bound[f, b], abs=1e-9)
    out = classify.boost_predict_binned(df, classify.boost_real(df, 15), real=True)
    assert out.where("pred = y").count() >= 0.95 * len(y)


def test_degraded_images_and_landmark_sources(spark):
    images = carriers.img(spark, SF)
    raw = {(r.video_id, r.t): np.array(r.px) for r in images.collect()}
    one = {(r.video_id, r.t): np.array(r.px) for r in robustness.requantise_images(images, 23).collect()}
    key = sorted(raw)[0]
    assert np.allclose(one[key], robustness.quantised_image(raw[key].reshape(1, 11, 10), 23).ravel())
    noise = {(r.video_id, r.t): np.array(r.px) for r in robustness.noisy_images(images.repartition(3)).collect()}
    moved = np.concatenate([noise[k] - raw[k] for k in raw])
    assert abs(moved.mean()) < 0.05 and abs(moved.std() - 1) < 0.05
    again = {(r.video_id, r.t): np.array(r.px) for r in robustness.noisy_images(images).collect()}
    assert all((again[k] == noise[k]).all() for k in raw)
    px = np.zeros((9, 9))
    px[4:, 4:] = 100
    assert (4, 4) in [(round(x), round(y)) for x, y in landmarks.corner_response(px, 4)]
    edge = np.zeros((9, 9))
    edge[:, 0] = 100  # the left border has nothing to do with the right one
    assert [x for x, y in landmarks.corner_response(edge, 6) if y == 0] == [3, 4, 5, 6, 7, 8]

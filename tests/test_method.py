"""Worked examples, invariances and brute force for the method."""

import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from accord.operators import anomaly, classify, distance, flow, grouping, landmarks, metrics, motion, pattern, sampling
from accord.plans import rewrite
from accord.sources import carriers, scene
from conftest import SF

MOVES = [(2, 0), (1, 0), (0, 1), (-1, 0)]


def pairs(spark, rows):
    return spark.createDataFrame(rows, "video_id string, source string, y int, t int, labels array<int>, k int, score double")


def test_affinity_and_spectrum(spark):
    m = np.array([MOVES], float)
    a, _ = grouping.affinities(m, grouping.Options(policy="signed"))
    assert a[0].tolist() == [[4, 2, 0, -2], [2, 1, 0, -1], [0, 0, 1, 0], [-2, -1, 0, 1]]
    clipped, _ = grouping.affinities(m, grouping.Options())
    assert clipped[0].sum(axis=1).tolist() == [6, 3, 1, 1]
    values, _, _ = grouping.eigenbasis(clipped, 3)
    assert np.allclose(values[0], [0, 0, 0, 1], atol=1e-9)
    assert grouping.component_labels(m, 0.0)[0].tolist() == [0, 0, 1, 2]
    df = spark.createDataFrame([("v", 0, [{"x": x, "y": y} for x, y in MOVES])], "video_id string, t int, motion_m array<struct<x:bigint,y:bigint>>")
    cells = grouping.affinity(df)
    assert {(r.i, r.j): r.a for r in cells.collect()}[(0, 3)] == -2
    assert [r.d for r in grouping.degree(cells).orderBy("i").collect()] == [4, 2, 1, -2]
    assert grouping.with_policy(cells, "strict").count() == 0


def test_group_score_and_printed_form(spark):
    x = np.array([[[0.0], [1], [9], [10]]])
    lab = np.array([[0, 0, 1, 1]])
    assert grouping.scores(x, lab, 2)[0] == pytest.approx(162)
    assert grouping.scores(x, lab, 2, grouping.Options(score="as_printed"))[0] == pytest.approx(0.0246914, abs=1e-6)
    worse = np.array([[0, 1, 0, 1]])
    printed = grouping.Options(score="as_printed")
    assert grouping.scores(x, worse, 2, printed)[0] > grouping.scores(x, lab, 2, printed)[0]


def test_pattern_and_distances(spark):
    two = pairs(spark, [("a", "R", 0, 0, [0, 0, 1, 1], 2, 3.0), ("a", "R", 0, 1, [0, 0, 0, 1], 2, 1.0), ("b", "A", 1, 0, [0, 1, 0, 1], 2, 3.0), ("b", "A", 1, 1, [0, 0, 0, 1], 2, 1.0)])
    two = two.withColumn("w", pattern.weight())
    p = pattern.build(two, ["video_id"])
    rows = {r.video_id: r for r in p.collect()}
    assert rows["a"].tri == [8, 2, 2, 0, 0, 6] and rows["a"].diag == 8 and rows["a"].n_pairs == 2
    assert rows["b"].tri == [2, 8, 2, 0, 6, 0]
    assert pattern.features(p, full=True).where("video_id = 'a'").first().features == [8, 8, 2, 0, 8, 8, 2, 0, 2, 2, 8, 6, 0, 0, 6, 8]
    tall = {(r.video_id, r.i, r.j): r.w for r in pattern.build_tall(two, ["video_id"]).collect()}
    assert tall[("a", 1, 0)] == 8 and ("a", 3, 0) not in tall
    one = p.where("video_id = 'a'").select(F.col("tri").alias("q"))
    both = p.where("video_id = 'b'").crossJoin(one)
    assert both.select(distance.js(F.col("tri"), F.col("q"))).first()[0] == pytest.approx(6.0863307, abs=1e-6)
    scaled = pattern.l1(p)
    q = scaled.where("video_id = 'a'").select(F.col("tri").alias("q"))
    pair = scaled.where("video_id = 'b'").crossJoin(q)
    assert pair.select(distance.js(F.col("tri"), F.col("q"))).first()[0] == pytest.approx(0.0895049, abs=1e-6)
    assert pair.select(distance.js(distance.triangle(F.col("tri")), distance.triangle(F.col("q")))).first()[0] == pytest.approx(0.3381295, abs=1e-6)
    assert pair.select(distance.js(F.col("q"), F.col("q"))).first()[0] == 0
    assert scaled.select((2 * F.aggregate("tri", F.lit(0.0), lambda a, x: a + x) + F.col("n") * F.col("diag")).alias("s")).first().s == pytest.approx(1)


def test_merge_is_a_sum(spark):
    rows = [("a", "R", 0, t, [t % 3, 0, 1, (t * 7) % 4, 2], 2, 1.0 + t) for t in range(12)]
    df = pairs(spark, rows).withColumn("w", pattern.weight())
    whole = pattern.build(df, ["video_id"]).first()
    parts = pattern.build(df.where("t < 5"), ["video_id"]).unionByName(pattern.build(df.where("t >= 5"), ["video_id"]))
    merged = pattern.merge(parts, ["video_id"]).first()
    assert np.allclose(whole.tri, merged.tri) and whole.n_pairs == merged.n_pairs
    assert np.allclose(rewrite.salted_build(df, ["video_id"], 3).first().tri, whole.tri)


def test_auc_with_a_tie(spark):
    s = spark.createDataFrame([(0.1, 0), (0.2, 0), (0.4, 0), (0.2, 1), (0.5, 1), (0.6, 1)], "d double, y int")
    assert metrics.auc(s).first().auc == pytest.approx(0.833333)
    assert metrics.auc_trapezoid(metrics.roc(s)).first().auc == pytest.approx(0.833333)
    assert metrics.auc(s.where("y = 1")).first().auc is None
    assert metrics.equal_error(metrics.roc(s)).first().eer == pytest.approx(1 / 3, abs=1e-6)
    at = anomaly.threshold(s)
    assert anomaly.decide(s, at).where("pred = 1 AND y = 0").count() <= 1


def test_kernel():
    one = [w for x, y, w in landmarks.kernel(3) if y == 0]
    assert [round(w / sum(one), 4) for w in one] == [0.0366, 0.1113, 0.2167, 0.2707, 0.2167, 0.1113, 0.0366]
    assert landmarks.pool_packed(np.ones((5, 5)), np.zeros((5, 5)), [(0.0, 0.0), (9.0, 9.0)])[1] is None


def planted(groups=3, n=18, b=6, noise=0.05, seed=0):
    rng = np.random.default_rng(seed)
    truth = np.arange(n) * groups // n
    turn = rng.uniform(0, 2 * np.pi, b)
    a = turn[:, None] + 2 * np.pi * truth[None, :] / groups
    return np.stack([2 * np.cos(a), 2 * np.sin(a)], 2) + rng.normal(0, noise, (b, n, 2)), truth


def test_grouping_finds_planted_groups_and_is_equivariant():
    m, truth = planted(b=20)
    got = grouping.group_batch(m)
    three = got["k"] == 3  # now and then noise makes the index prefer to split a group
    assert three.mean() >= 0.8
    assert (got["labels"][three] == grouping.canonical(truth[None])[0]).all()
    assert (grouping.group_batch(m, grouping.Options(k_fixed=3))["labels"] == grouping.canonical(truth[None])[0]).all()
    fixed = grouping.Options(k_fixed=3)
    order = np.random.default_rng(1).permutation(m.shape[1])
    moved = grouping.group_batch(m[:, order], fixed)
    assert (moved["labels"] == grouping.canonical(np.tile(truth[order], (20, 1)))).all()
    c, s = math.cos(0.7), math.sin(0.7)
    turned = grouping.group_batch(3.5 * m @ np.array([[c, -s], [s, c]]), fixed)
    assert (turned["labels"] == grouping.canonical(truth[None])[0]).all()
    free = grouping.group_batch(m, grouping.Options(k_max=None))
    assert (free["score"] >= got["score"] - 1e-9).all() and (free["labels"][free["k"] == 3] == grouping.canonical(truth[None])[0]).all()
    a, _ = grouping.affinities(m, grouping.Options())
    values, v, _ = grouping.eigenbasis(a, 4)
    assert values.min() > -1e-9 and abs(values[:, 0]).max() < 1e-9


def test_kmeans_against_all_partitions():
    rng = np.random.default_rng(3)
    x = np.concatenate([rng.normal(0, 0.05, (4, 2)), rng.normal(2, 0.05, (3, 2))])[None]

    def cost(lab):
        return sum(((x[0][lab == g] - x[0][lab == g].mean(axis=0)) ** 2).sum() for g in set(lab))

    best = min(cost(np.array((0, *p))) for p in itertools.product((0, 1), repeat=6) if 1 in p)
    assert cost(grouping.kmeans(x, 2)[0]) == pytest.approx(best)


def test_odd_pairs_are_left_out(spark):
    still = [{"dx": 0.0, "dy": 0.0}] * 5
    rows = [("v", 0, still), ("v", 1, [{"dx": 1.0, "dy": 0.0}, {"dx": 0.0, "dy": 1.0}]), ("v", 2, [{"dx": None, "dy": 0.0}] + still[1:]), ("v", 3, [{"dx": float("nan"), "dy": 0.0}] + still[1:])]
    df = spark.createDataFrame(rows, "video_id string, t int, motion array<struct<dx:double,dy:double>>")
    g = grouping.group_pairs(df).collect()
    assert [r.t for r in g] == [0] and g[0].degenerate
    assert motion.keep_strong(df).where("t = 0").count() == 0
    assert grouping.group_pairs(df.where("t > 9")).count() == 0


def test_picks_are_prefixes_and_splits_are_disjoint(spark):
    df = carriers.face(spark, SF, 2)
    a = {(r.video_id, r.t) for r in sampling.pick_n(df, 3).collect()}
    b = {(r.video_id, r.t) for r in sampling.pick_n(df.repartition(7), 9).collect()}
    assert a < b
    s = sampling.split(df)
    assert not {r.video_id for r in s.where("train").collect()} & {r.video_id for r in s.where("NOT train").collect()}
    assert sampling.pattern_sets(df, 3, 4, "source").groupBy("source", "pattern_id").count().where("count <> 4").count() == 0


def test_flow_recovers_a_shift_and_never_raises_energy():
    y, x = np.mgrid[0:24, 0:24]
    img = lambda dx, dy: 40 * np.sin((x - dx) / 3) + 40 * np.cos((y - dy) / 4) + 10 * np.sin((x + y - dx - dy) / 5)
    for o in (flow.FlowOptions(), flow.FlowOptions(penalty="quadratic", terms="brightness"), flow.FlowOptions(terms="gradient")):
        u, v, e = flow.variational(img(0, 0), img(1, 0.5), o)
        assert all(b <= a + 1e-9 for a, b in zip(e, e[1:])) and e[-1] < 0.7 * flow.energy(img(0, 0), img(1, 0.5), 0 * u, 0 * v, o)
        assert abs(np.median(u) - 1) < 0.35 and abs(np.median(v) - 0.5) < 0.35
    flat = np.full((8, 8), 3.0)
    u, v, _ = flow.variational(flat, flat)
    assert not u.any() and not v.any()


def test_boosting_against_a_plain_loop(spark):
    rng = np.random.default_rng(5)
    x = rng.integers(0, 6, (60, 4)).astype(float)
    y = ((x[:, 1] > 2) ^ (rng.random(60) < 0.15)).astype(int)
    df = spark.createDataFrame([(int(b), [float(v) for v in a]) for a, b in zip(x, y)], "y int, features array<double>")
    model, edges = classify.boost_fit(df, rounds=5, bins=8)
    bins = np.stack([np.searchsorted(np.array(e), x[:, f], side="left") for f, e in enumerate(edges)], 1)
    s, w, plain = 2 * y - 1, np.ones(60), []
    for _ in range(5):
        best = min((round(float(w[np.where(bins[:, f] > b, p, -p) != s].sum() / w.sum()), 12), f, b, -p) for f in range(4) for b in sorted(set(bins[:, f])) for p in (1, -1))
        err, f, b, p = best[0], best[1], best[2], -best[3]
        if err >= 0.5 - 1e-12:
            break
        alpha = 0.5 * math.log((1 - err) / max(err, 1e-12))
        plain.append((f, int(b), p))
        w = w * np.exp(-alpha * s * np.where(bins[:, f] > b, p, -p))
    assert [m[:3] for m in model] == plain
    got = [r.pred for r in classify.boost_predict(df, model, edges).collect()]
    assert got == (classify.margin(bins, model) > 0).astype(int).tolist()


def test_rewrites_move_choices_before_the_kernel(spark):
    steps = [rewrite.Group(), rewrite.Weigh(), rewrite.Pick(4), rewrite.Pick(2), rewrite.Where("source = 'R'"), rewrite.Build(("video_id",)), rewrite.Normalise()]
    best = rewrite.optimised(steps)
    kinds = [type(s) for s in best]
    assert kinds.index(rewrite.Where) < kinds.index(rewrite.Group) and kinds.count(rewrite.Pick) == 1 and kinds.index(rewrite.Pick) < kinds.index(rewrite.Group)
    assert kinds.index(rewrite.Pick) < kinds.index(rewrite.Where)
    df = carriers.face(spark, SF, 1)
    a = {r.video_id: r.tri for r in rewrite.run(df, steps).collect()}
    b = {r.video_id: r.tri for r in rewrite.run(df, best).collect()}
    assert a.keys() == b.keys() and all(np.allclose(a[k], b[k]) for k in a)
    assert rewrite.capped([rewrite.Group(grouping.Options(k_max=None))])[0].options.k_max == 8
    assert "Group" in rewrite.explained(best)


def test_plans(spark):
    """The filter and the choice stand below the kernel, columns are pruned, and nothing is exchanged between the filter and the kernel."""
    df = motion.keep_strong(carriers.face(spark, SF, 1))
    plan = grouping.group_pairs(df.select("video_id", "t", "motion"))._jdf.queryExecution().executedPlan().toString()
    kernel, below = plan.split("MapInArrow", 1)
    assert "Filter" in below and "label" in below
    between = below[: below.index("Filter")]
    assert "Exchange" not in between
    scan = carriers.read(spark, SF, "lineitem").where("l_suppkey = 3").select("l_quantity")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_suppkey), EqualTo(l_suppkey,3)]" in scan and "l_comment" not in scan


def test_scene_source_batch_and_stream(spark, tmp_path):
    scene.register(spark)
    batch = spark.read.format("accord_scene").option("videos", 3).option("frames", 4).load()
    assert batch.count() == 12
    stream = spark.readStream.format("accord_scene").option("videos", 3).option("frames", 4).load()
    q = stream.writeStream.format("memory").queryName("scenes").option("checkpointLocation", str(tmp_path / "c")).trigger(processingTime="200 milliseconds").start()
    try:
        for _ in range(100):
            q.processAllAvailable()
            if spark.table("scenes").count() >= 12:
                break
    finally:
        q.stop()
    assert {(r.video_id, r.t) for r in spark.table("scenes").collect()} == {(r.video_id, r.t) for r in batch.collect()}


def test_component_matrix_rounds_exact_means(spark):
    """Means that lie between two sixth decimals go up, as in whole-number arithmetic; sums of real means went either way."""
    import duckdb

    from accord.queries import method, study

    d, duck = SF.replace("sf0.001", "sf0.01"), duckdb.connect()
    duck.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{d}/embeddings.parquet'")
    cells = method.S["component_matrix"].rsplit("SELECT source, greatest", 1)[0]
    exact = duck.sql(cells + "SELECT m.source, greatest(ci, cj), least(ci, cj), sum(round(mean * n)::BIGINT)::BIGINT, sum(n)::BIGINT FROM mean m JOIN sz s ON s.source = m.source GROUP BY ALL").fetchall()
    want = {(s, a, b): (2 * 10**6 * w + n) // (2 * n) for s, a, b, w, n in exact}
    assert [1 for *_, w, n in exact if 2 * 10**6 * w % (2 * n) == n]
    got = {(r.source, r.a, r.b): round(r["mean"] * 10**6) for r in study.component_matrix(spark, d).collect()}
    assert got == want


def test_event_motion_in_any_layout(spark):
    """The SQL in one thread adds a group's values up in the order of the file, which is that of event_id; so do rows that are dealt otherwise."""
    import duckdb

    from accord.queries import method

    d, duck = SF.replace("sf0.001", "sf0.1"), duckdb.connect(config={"threads": 1})
    duck.execute(f"CREATE VIEW events AS SELECT * FROM '{d}/events.parquet'")
    at = carriers.evt_positions(carriers.read(spark, d, "events").repartition(7))
    got = {tuple(r) for r in carriers.tall(carriers._moved(at, len(carriers.EVENT_TYPES))).select("video_id", "t", "lm", "dx_m", "dy_m").collect()}
    want = set(duck.sql(method.S["evt_motion"]).select("video_id, t, lm, dx_m, dy_m").fetchall())
    assert got == want


def _plain_kmeans(x, k, rounds=20):
    """Seeds by differences of all points, and every batch carried on to the last round of any."""
    rows = np.arange(len(x))
    centres, near = [x[:, 0]], ((x - x[:, :1]) ** 2).sum(axis=2)
    for _ in range(1, k):
        far = near.argmax(axis=1)
        centres.append(x[rows, far])
        near = np.minimum(near, ((x - x[rows, far][:, None]) ** 2).sum(axis=2))
    c, labels = np.stack(centres, 1), None
    for _ in range(rounds):
        after = ((c**2).sum(axis=2)[:, None, :] - 2 * x @ c.transpose(0, 2, 1)).argmin(axis=2)
        if labels is not None and (after == labels).all():
            break
        labels = after
        hot = (labels[:, :, None] == np.arange(k)).astype(float)
        count = hot.sum(axis=1)
        c = np.where(count[:, :, None] > 0, hot.transpose(0, 2, 1) @ x / np.maximum(count, 1)[:, :, None], c)
    return labels


def test_kmeans_of_many_groups_is_plain_kmeans_in_less_time():
    import time

    rng = np.random.default_rng(5)
    a, _ = grouping.affinities(rng.normal(0, 2, (128, 51, 2)), grouping.Options())
    _, v, _ = grouping.eigenbasis(a, 45)
    took = {grouping.kmeans: [], _plain_kmeans: []}
    for k in (2, 8, 30, 45):
        x = v[:, :, :k] / np.maximum(np.linalg.norm(v[:, :, :k], axis=2, keepdims=True), 1e-12)
        assert (grouping.kmeans(x, k) == _plain_kmeans(x, k)).all()
    for _ in range(3):
        for f in took:
            at = time.perf_counter()
            f(x, k)
            took[f].append(time.perf_counter() - at)
    assert min(took[grouping.kmeans]) < 0.8 * min(took[_plain_kmeans])


def test_calibration_brings_no_values_to_one_task(spark, monkeypatch):
    """quantile() is F.percentile, ties, ends and odd values included, and calibrate() doesn't call that."""
    rng = np.random.default_rng(3)
    odd = [1.0, 1.0, 2.5, math.inf, math.inf, math.nan, None, 0.0]
    for values in (rng.gamma(2.0, 1.0, 999).tolist(), [5.0] * 7, [0.25], odd, [math.nan, math.inf], [1e-300, 2e-300, 1e300]):
        df = spark.createDataFrame([(v,) for v in values], "size double")
        for p in (0.0, 0.3, 0.5, 0.9, 1.0):
            a, b = motion.quantile(df, p), df.agg(F.percentile("size", F.lit(p))).first()[0]
            assert a == b or (math.isnan(a) and math.isnan(b))
    assert motion.quantile(df.where("false"), 0.5) is None
    face = carriers.face(spark, SF, 2)
    want = face.join(motion.chosen_videos(face, 10), "video_id", "left_semi").select(F.explode(motion.magnitudes(F.col("motion"))).alias("s")).agg(F.percentile("s", F.lit(0.5))).first()[0]
    monkeypatch.delattr(F, "percentile")
    assert motion.calibrate(face, sample_videos=10).first().tau == want


def test_recursion_and_scenes_read_a_table(spark, duck):
    """Both follow the given table: the recursion is as its SQL, and scenes are as many as there are vectors, with the planted groups found."""
    import accord.queries as Q
    from conftest import same_rows

    df = Q.QUERIES["cte_recursive"](spark, SF)
    same_rows(df, duck.sql(Q.ORACLES["cte_recursive"]))
    assert max(r.total for r in df.collect()) == duck.sql("SELECT count(*) FROM lineitem").fetchall()[0][0]
    df = Q.QUERIES["scene_source"](spark, SF)
    (r,) = df.collect()
    assert r.source == "R" and r.n_pairs == duck.sql("SELECT count(*) FROM embeddings").fetchall()[0][0] and r.rand > 0.95
    v = carriers.read(spark, SF, "embeddings").orderBy("vec_id").limit(3)
    for r, e in zip(scene.planted(v, noise=0.05).orderBy("t").collect(), v.collect()):
        for i, m in enumerate(r.motion):
            angle = math.atan2(e.embedding[1], e.embedding[0]) + 2 * math.pi * r.truth[i] / 4
            at = [2 * f(angle) + 0.4 * e.embedding[(2 * i + k) % 62 + 2] for k, f in ((0, math.cos), (1, math.sin))]
            assert r.truth[i] == i * 4 // 51 and m.dx == pytest.approx(at[0]) and m.dy == pytest.approx(at[1])


def test_ablations_share_their_eigenvectors(spark, monkeypatch):
    """Each variant is as grouped alone, and a Laplacian is decomposed once for all variants that have it."""
    from accord.operators import baselines

    m = np.random.default_rng(6).normal(0, 2, (20, 12, 2))
    options = list(dict.fromkeys(grouping.Options(**o.get("grouping", {})) for o in baselines.ABLATIONS.values()))
    alone, calls, real = [grouping.group_batch(m, o) for o in options], [], grouping.eigenbasis
    monkeypatch.setattr(grouping, "eigenbasis", lambda *a: calls.append(1) or real(*a))
    for a, b in zip(alone, grouping.batch_variants(m, options)):
        assert all(np.array_equal(a[k], b[k], equal_nan=True) if k == "gap" else (a[k] == b[k]).all() for k in a)
    assert len(options) == 16 and len(calls) == 7
    monkeypatch.undo()
    face = carriers.face(spark, SF, 1).where("source = 'R' AND half = 'a'")
    got, kept = baselines.ablated_groups(face), motion.keep_strong(face).count()
    assert list(got) == list(baselines.ABLATIONS)
    assert {n: got[n].count() for n in ("full", "no_filter", "k_3", "sectors")} == {"full": kept, "no_filter": face.count(), "k_3": kept, "sectors": kept}

"""Queries of learning, transfer, robustness, reading and baselines: the experiments of the method."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from accord.operators import anomaly, baselines, classify, explain, grouping, metrics, motion, pattern, robustness, sampling
from accord.queries import prelude as P
from accord.queries.method import _BYSRC, _FACE, _JS, _L1, S, genuine_template, picked_groups, query, scores_sql, sector_groups, strong_face, tall_patterns
from accord.scratch import written
from accord.sources import carriers

# ---------------------------------------------------------------- reading patterns

_MEAN = (
    _FACE,
    P.STRONG,
    P.picked(1000, "source"),
    P.sectors(),
    """sz AS (SELECT source, count(*) AS n FROM picked GROUP BY source),
agc AS (SELECT k.source, a.lm AS i, b.lm AS j, count(*) AS n FROM lab a JOIN lab b ON a.video_id = b.video_id AND a.t = b.t AND a.lm > b.lm AND a.c = b.c JOIN picked k ON k.video_id = a.video_id AND k.t = a.t GROUP BY ALL),
mean AS (SELECT s.source, c.i, c.j, c.ci, c.cj, coalesce(agc.n, 0)::DOUBLE / s.n AS mean FROM sz s CROSS JOIN (SELECT a.lm::INT AS i, b.lm::INT AS j, a.comp AS ci, b.comp AS cj FROM lmk a JOIN lmk b ON a.lm > b.lm) c LEFT JOIN agc ON agc.source = s.source AND agc.i = c.i AND agc.j = c.j)""",
)


def _sectors_of_sources(spark, d) -> DataFrame:
    return grouping.sectors(sampling.pick_n(strong_face(spark, d), 1000, "source"), 6)


def _mean(spark, d) -> DataFrame:
    return explain.mean_agreement(_sectors_of_sources(spark, d), 1000)


@query("mean_agreement", P.q(*_MEAN, select="SELECT source, i, j, round(mean, 6) AS mean FROM mean"))
def mean_agreement(spark, d):
    return _mean(spark, d).withColumn("mean", F.round("mean", 6))


@query("component_matrix", P.q(*_MEAN, select="SELECT source, greatest(ci, cj) AS a, least(ci, cj) AS b, round(avg(mean), 6) AS mean FROM mean GROUP BY ALL"))
def component_matrix(spark, d):
    return explain.component_matrix(explain.agreement_counts(_sectors_of_sources(spark, d), 1000)).withColumn("mean", F.round("mean", 6))


def _btw(x: str, y: str) -> str:
    return f"avg(CASE WHEN (ci IN ({x}) AND cj IN ({y})) OR (ci IN ({y}) AND cj IN ({x})) THEN mean END)"


@query("structure_checks", P.q(*_MEAN, select=f"SELECT source, round({_btw('4', '5')}, 6) AS eyes, round(avg(CASE WHEN i < 31 THEN mean END), 6) AS upper_face, round({_btw('0, 1', '4, 5')}, 6) AS brow_eye, round(avg(CASE WHEN ci = cj AND ci IN (6, 7) THEN mean END) - {_btw('6', '7')}, 6) AS lip_opposition FROM mean GROUP BY source"))
def structure_checks(spark, d):
    s = explain.structure_checks(_mean(spark, d))
    return s.select("source", *[F.round(c, 6).alias(c) for c in ("eyes", "upper_face", "brow_eye", "lip_opposition")])


@query("signed_view", P.q(*_MEAN, select="SELECT source, i, j, round(mean - avg(mean) OVER (PARTITION BY source), 6) + 0.0 AS signed FROM mean"))
def signed_view(spark, d):
    return explain.signed_view(_mean(spark, d)).select("source", "i", "j", (F.round("signed", 6) + 0.0).alias("signed"))


@query(
    "source_distance",
    P.q(
        *_BYSRC,
        _L1,
        "srcs AS (SELECT DISTINCT source FROM nrm), cc AS (SELECT a.lm AS i, b.lm AS j FROM lmk a JOIN lmk b ON a.lm > b.lm)",
        "b AS (SELECT s.source AS a, z.source AS b, coalesce(n1.p, 0) AS pa, coalesce(n2.p, 0) AS pb FROM srcs s JOIN srcs z ON s.source < z.source CROSS JOIN cc LEFT JOIN nrm n1 ON n1.source = s.source AND n1.i = cc.i AND n1.j = cc.j LEFT JOIN nrm n2 ON n2.source = z.source AND n2.i = cc.i AND n2.j = cc.j)",
        select=f"SELECT a, b, round(sum({_JS}), 6) AS d FROM b GROUP BY a, b",
    ),
)
def source_distance(spark, d):
    return explain.source_distance(tall_patterns(picked_groups(spark, d), ["source"])).withColumn("d", F.round("d", 6))


@query("top_abnormal_cells", "WITH " + scores_sql() + f", trm AS (SELECT video_id, i, j, round({_JS}, 9) AS term FROM bth) SELECT video_id, place::INT AS place, i::INT AS i, j::INT AS j, term FROM (SELECT *, row_number() OVER (PARTITION BY video_id ORDER BY term DESC, i, j) AS place FROM trm) WHERE place <= 5")
def top_abnormal_cells(spark, d):
    from accord.operators import distance

    groups = sector_groups(sampling.ranked(strong_face(spark, d)))
    template = genuine_template(groups.where("half <> 'b'"))
    terms = distance.tall_terms(tall_patterns(groups.where("half = 'b' AND pick <= 10"), ["video_id"]), template, ["video_id"]).withColumn("term", F.round("term", 9))
    return explain.top_cells(terms, ["video_id"], 5)


_TRUTH = [c // 2 * 2 if c < 6 else c for c in map(carriers.component_of, range(51))]


@query(
    "rand_index",
    P.q(
        _FACE,
        P.STRONG,
        P.picked(10**9),
        P.sectors(),
        "tru AS (SELECT lm, CASE WHEN comp < 6 THEN comp - comp % 2 ELSE comp END AS g FROM lmk)",
        "hit AS (SELECT a.video_id, a.t, sum(((a.c = b.c) = (x.g = z.g))::INT) / 1275.0::DOUBLE AS r FROM lab a JOIN lab b ON a.video_id = b.video_id AND a.t = b.t AND a.lm > b.lm JOIN tru x ON x.lm = a.lm JOIN tru z ON z.lm = b.lm GROUP BY ALL)",
        select="SELECT source, count(*) AS n_pairs, round(avg(r), 6) AS rand FROM hit JOIN picked USING (video_id, t) GROUP BY source",
    ),
)
def rand_index(spark, d):
    g = grouping.sectors(strong_face(spark, d), 6)
    return metrics.rand_index(g, _TRUTH, "source")


# ---------------------------------------------------------------- robustness


def _requant(qp: int) -> str:
    s = int(round(robustness.step_of(qp) * 10))
    return f"rq AS (SELECT video_id, source, y, half, t, lm, (round(dx_m::DOUBLE / {s}) * {s})::BIGINT AS dx_m, (round(dy_m::DOUBLE / {s}) * {s})::BIGINT AS dy_m FROM face)"


def _noise(of: str) -> str:
    u = lambda s: f"((('0x' || md5(concat_ws(':', '{s}', video_id, t, lm))[1:12])::BIGINT)::DOUBLE + 0.5::DOUBLE) / 281474976710656.0::DOUBLE"
    r, a = f"sqrt(-2 * ln({u(0)}))", f"2 * pi() * ({u(1)})"
    return f"nz AS (SELECT video_id, source, y, half, t, lm, dx_m + round(1000 * round({r} * cos({a}), 6))::BIGINT AS dx_m, dy_m + round(1000 * round({r} * sin({a}), 6))::BIGINT AS dy_m FROM {of})"


def _tall_m(df: DataFrame) -> DataFrame:
    return df.select("video_id", "t", F.posexplode("motion_m").alias("lm", "m")).select("video_id", "t", "lm", F.col("m.x").alias("dx_m"), F.col("m.y").alias("dy_m"))


def _face_milli(spark, d) -> DataFrame:
    return carriers.milli(carriers.face(spark, d))


@query("requantise_motion", P.q(_FACE, _requant(40), select="SELECT video_id, t, lm, dx_m, dy_m FROM rq"))
def requantise_motion(spark, d):
    return _tall_m(robustness.requantise(_face_milli(spark, d), 40))


@query("noise_motion", P.q(_FACE, _noise("face"), select="SELECT video_id, t, lm, dx_m, dy_m FROM nz"))
def noise_motion(spark, d):
    return _tall_m(robustness.add_noise(_face_milli(spark, d)))


@query("requantise_noise", P.q(_FACE, _requant(23), _noise("rq"), select="SELECT video_id, t, lm, dx_m, dy_m FROM nz"))
def requantise_noise(spark, d):
    return _tall_m(robustness.graded(_face_milli(spark, d), "q23_noise"))


_GRADED = ("raw", "q23", "q40", "q23_noise")


def _graded_pairs(spark, d) -> DataFrame:
    """Pairs of the genuine source and of source A under every grade, one plan."""
    m = carriers.milli(carriers.face(spark, d)).where("source IN ('R', 'A')")
    out = None
    for g in _GRADED:
        one = robustness.graded(m, g)
        out = one if out is None else out.unionByName(one)
    return out.withColumn("video_id", F.concat_ws("/", "video_id", "grade"))


_GFACE = ",".join(
    x.strip()
    for x in (
        _FACE.replace("face AS (", "face0 AS ("),
        "fcut AS (SELECT * FROM face0 WHERE source IN ('R', 'A'))",
        _requant(23).replace("FROM face", "FROM fcut").replace("rq AS", "rq23 AS"),
        _requant(40).replace("FROM face", "FROM fcut").replace("rq AS", "rq40 AS"),
        _noise("rq23"),
        "face AS (SELECT * REPLACE (video_id || '/raw' AS video_id), 'raw' AS grade FROM fcut UNION ALL SELECT * REPLACE (video_id || '/q23' AS video_id), 'q23' FROM rq23 UNION ALL SELECT * REPLACE (video_id || '/q40' AS video_id), 'q40' FROM rq40 UNION ALL SELECT * REPLACE (video_id || '/q23_noise' AS video_id), 'q23_noise' FROM nz)",
    )
)


def _grade_auc(spark, d) -> DataFrame:
    pairs = _graded_pairs(spark, d)
    g = grouping.sectors(pairs, 6).withColumn("w", F.lit(1).cast("bigint")).drop("motion", "motion_m")
    p = tall_patterns(g, ["grade", "source", "y", "half", "video_id"])
    ref = tall_patterns(g.where("source = 'R' AND half = 'a'"), ["grade"]).select("grade", "i", "j", F.col("p").alias("pb"))
    probes = p.where("half = 'b'")
    both = probes.join(ref, ["grade", "i", "j"], "left").withColumn("pb", F.coalesce("pb", F.lit(0.0)))
    s = both.groupBy("grade", "video_id", "y").agg(F.round(F.sum(F.abs(F.col("p") - F.col("pb"))), 6).alias("d"))
    return metrics.auc(s, "grade")


@query(
    "robustness_auc",
    "WITH " + _GFACE + ", " + ",".join(
        x.strip()
        for x in (
            P.sectors(of="face"),
            """ky AS (SELECT DISTINCT video_id, t, grade, source, y, half FROM face),
agr AS (SELECT a.video_id, a.t, a.lm AS i, b.lm AS j FROM lab a JOIN lab b ON a.video_id = b.video_id AND a.t = b.t AND a.lm > b.lm AND a.c = b.c),
pc AS (SELECT grade, y, half, video_id, i, j, count(*) AS w FROM agr JOIN ky USING (video_id, t) GROUP BY ALL),
pt AS (SELECT video_id, 51 * count(*) AS dg FROM ky GROUP BY ALL),
pp AS (SELECT pc.*, w::DOUBLE / (2 * sum(w) OVER (PARTITION BY video_id) + dg)::DOUBLE AS pa FROM pc JOIN pt USING (video_id)),
rc AS (SELECT grade, i, j, count(*) AS w FROM agr JOIN ky USING (video_id, t) WHERE source = 'R' AND half = 'a' GROUP BY ALL),
rt AS (SELECT grade, 51 * count(*) AS dg FROM ky WHERE source = 'R' AND half = 'a' GROUP BY ALL),
rp AS (SELECT grade, i, j, w::DOUBLE / (2 * sum(w) OVER (PARTITION BY grade) + dg)::DOUBLE AS pb FROM rc JOIN rt USING (grade)),
scores AS (SELECT grade, video_id, y, round(sum(abs(pa - coalesce(pb, 0))), 6) AS d FROM pp LEFT JOIN rp USING (grade, i, j) WHERE half = 'b' GROUP BY ALL)""",
        )
    ) + " SELECT a.grade, round(sum(CASE WHEN a.d > b.d THEN 1.0 WHEN a.d = b.d THEN 0.5 ELSE 0 END)::DOUBLE / count(*), 6) AS auc FROM scores a JOIN scores b ON a.grade = b.grade WHERE a.y = 1 AND b.y = 0 GROUP BY a.grade",
)
def robustness_auc(spark, d):
    return _grade_auc(spark, d)


@query("robustness_delta", f"WITH q AS ({S['robustness_auc']}) SELECT grade, auc, round((SELECT auc FROM q WHERE grade = 'raw') - auc, 6) AS loss FROM q")
def robustness_delta(spark, d):
    return metrics.delta(_grade_auc(spark, d), "raw", "auc")


# ---------------------------------------------------------------- learning


def _task_patterns(spark, d, n: int = 10) -> DataFrame:
    g = picked_groups(spark, d, n)
    return tall_patterns(g, ["video_id", "source", "y", "half"])


@query("binary_tasks", P.q(_FACE, P.STRONG, "vid AS (SELECT DISTINCT video_id, source, y FROM strong)", select="SELECT task, y, count(*) AS n FROM vid JOIN (VALUES ('A'), ('B'), ('C'), ('D')) k(task) ON (y = 1 AND source = task) OR source = 'R' GROUP BY ALL"))
def binary_tasks(spark, d):
    v = strong_face(spark, d).select("video_id", "source", "y").distinct()
    return classify.binary_tasks(v).groupBy("task", "y").agg(F.count("*").alias("n"))


@query("combined_task", P.q(_FACE, P.STRONG, "vid AS (SELECT DISTINCT video_id, source, y FROM strong WHERE source <> 'R2')", select="SELECT y, count(*) AS n, count(*) FILTER (y = 0 OR ('0x' || md5('9:' || video_id)[1:6])::BIGINT % 4 = 0) AS n_balanced FROM vid GROUP BY y"))
def combined_task(spark, d):
    v = strong_face(spark, d).select("video_id", "source", "y").distinct()
    whole = classify.combined_task(v).groupBy("y").agg(F.count("*").alias("n"))
    return whole.join(classify.combined_task(v, balance=True).groupBy("y").agg(F.count("*").alias("n_balanced")), "y")


_TRANSFER = (
    _FACE,
    P.STRONG,
    P.picked(10),
    P.sectors(),
    P.pattern("video_id", "(SELECT video_id, t FROM picked)").replace("SELECT video_id, a.lm", "SELECT a.video_id, a.lm").replace("SELECT video_id, sum(w)", "SELECT g.video_id, sum(w)"),
    """vid AS (SELECT DISTINCT video_id, source, y, half FROM strong WHERE source <> 'R2'),
nrm AS (SELECT video_id, i, j, cell.w::DOUBLE / (2 * sum(cell.w) OVER (PARTITION BY video_id) + 51 * w_sum)::DOUBLE AS p FROM cell JOIN tot USING (video_id)),
tsk AS (SELECT task, v.* FROM vid v JOIN (VALUES ('A'), ('B'), ('C'), ('D')) k(task) ON (y = 1 AND source = task) OR source = 'R'),
mn AS (SELECT task, y AS c, i, j, sum(p) / any_value(n) AS m FROM tsk JOIN nrm USING (video_id) JOIN (SELECT task, y, count(*) AS n FROM tsk WHERE half = 'a' GROUP BY ALL) z USING (task, y) WHERE half = 'a' GROUP BY ALL),
mm AS (SELECT task, c, sum(m * m) AS mm FROM mn GROUP BY ALL),
ds AS (SELECT t.task AS test_source, mn.task AS train_source, mn.c, t.video_id, t.y, sum(p * m) AS dot FROM tsk t JOIN nrm USING (video_id) JOIN mn USING (i, j) WHERE half = 'b' GROUP BY ALL),
prd AS (SELECT test_source, train_source, video_id, y, arg_min(ds.c, round(mm - 2 * dot, 12)) AS pred FROM ds JOIN mm ON mm.task = train_source AND mm.c = ds.c GROUP BY ALL),
tm AS (SELECT train_source, test_source, round(avg((pred = y)::INT), 6) AS accuracy FROM prd WHERE train_source <> test_source GROUP BY ALL)""",
)


def _transfer(spark, d) -> DataFrame:
    p = classify.binary_tasks(_task_patterns(spark, d).withColumn("id", F.col("video_id")))
    train = p.where("half = 'a'").select(F.col("task").alias("train_source"), "y", "id", "i", "j", "p")
    test = p.where("half = 'b'").select(F.col("task").alias("test_source"), "y", "id", "i", "j", "p")
    judged = classify.nearest_mean(train, test, ["train_source"]).where("train_source <> test_source")
    return metrics.accuracy(judged, "train_source", "test_source").select("train_source", "test_source", "accuracy")


@query("transfer_matrix", P.q(*_TRANSFER, select="SELECT train_source, test_source, accuracy FROM tm"))
def transfer_matrix(spark, d):
    return _transfer(spark, d)


@query("transfer_summary", P.q(*_TRANSFER, select="SELECT train_source, count(*) AS n_tests, round(avg(accuracy), 6) AS mean_accuracy FROM tm GROUP BY ROLLUP (train_source)"))
def transfer_summary(spark, d):
    return _transfer(spark, d).rollup("train_source").agg(F.count("*").alias("n_tests"), F.round(F.avg("accuracy"), 6).alias("mean_accuracy"))


def spectral_groups(spark, d, o: grouping.Options = grouping.Options()) -> DataFrame:
    """All strong pairs, grouped: only the filter comes before the kernel."""
    return grouping.group_pairs(motion.keep_strong(carriers.face(spark, d)), o).withColumn("w", pattern.weight("k_score"))


@query("group_pairs")
def group_pairs(spark, d):
    g = spectral_groups(spark, d)
    return g.select("video_id", "t", "source", "k", F.round("score", 3).alias("score"), "degenerate", F.concat_ws(",", F.transform("labels", lambda x: x.cast("string"))).alias("labels"))


@query("group_pairs_all_k")
def group_pairs_all_k(spark, d):
    g = spectral_groups(spark, d, grouping.Options(k_max=None))
    return g.select("video_id", "t", "source", "k", F.round("score", 3).alias("score"))


@query("spectral_gap")
def spectral_gap(spark, d):
    return spectral_groups(spark, d).groupBy("source", "k").agg(F.count("*").alias("n_pairs"), F.round(F.avg("gap"), 4).alias("mean_gap"))


@query("k_histogram_spectral")
def k_histogram_spectral(spark, d):
    return grouping.report(spectral_groups(spark, d))


@query("spectral_auc")
def spectral_auc(spark, d):
    """The method proper: spectral groups, patterns of n pairs of a video, distance to a genuine template of the other half; every video is judged once for each N."""
    ns = (1, 10, 35, 70)
    g = written(sampling.ranked(spectral_groups(spark, d)).withColumn("draw", F.col("pick") - 1), "groups")
    p = pattern.prefixes(g.where("half = 'b'"), ["video_id", "source", "y"], ns)
    s = anomaly.score_packed(p, anomaly.template(g.where("half = 'a'"), 3000)).withColumn("d", F.round("d", 9))
    forged = s.where("y = 1").withColumn("task", F.col("source"))
    both = forged.unionByName(s.where("y = 0").withColumn("task", F.explode(F.array(*[F.lit(x) for x in "ABCD"]))))
    return metrics.auc(both, "task", "n_pick")


# ---------------------------------------------------------------- stumps over a feature table that SQL has too

_COUNTS = "cf AS (SELECT video_id, any_value(source) AS source, any_value(y) AS y, [sum((k_found = 2)::INT), sum((k_found = 3)::INT), sum((k_found = 4)::INT), sum((k_found = 5)::INT), sum((k_found = 6)::INT)] AS c FROM grp JOIN picked USING (video_id, t) GROUP BY video_id)"


def _count_features(spark, d) -> DataFrame:
    """(video_id, source, y, features): of 10 pairs, how many use 2 to 6 sectors."""
    n = [F.sum((F.col("k") == k).cast("int")).cast("double") for k in range(2, 7)]
    return picked_groups(spark, d).groupBy("video_id", "source", "y").agg(F.array(*n).alias("features"))


@query(
    "boost_first_stump",
    P.q(
        _FACE,
        P.STRONG,
        P.picked(10),
        P.sectors(),
        _COUNTS,
        "tsk AS (SELECT task, y, f::INT AS f, c[f + 1]::INT AS b FROM cf JOIN (VALUES ('A'), ('B'), ('C'), ('D')) k(task) ON (y = 1 AND source = task) OR source = 'R', range(5) g(f))",
        "cut AS (SELECT DISTINCT task, f, b FROM tsk)",
        "er AS (SELECT c.task, c.f, c.b, pol, sum(CASE WHEN (CASE WHEN t.b > c.b THEN pol ELSE -pol END) = 2 * t.y - 1 THEN 0 ELSE 1 END)::DOUBLE / count(*) AS err FROM cut c JOIN tsk t ON t.task = c.task AND t.f = c.f, (VALUES (1), (-1)) p(pol) GROUP BY ALL)",
        select="SELECT task, f, b, pol::INT AS polarity, round(err, 9) AS err FROM er QUALIFY row_number() OVER (PARTITION BY task ORDER BY round(err, 12), f, b, -pol) = 1",
    ),
)
def boost_first_stump(spark, d):
    rows = classify.binary_tasks(_count_features(spark, d))
    binned = classify.binize(rows.select("task", "y", "features"), [[x + 0.5 for x in range(10)]] * 5)
    return classify.best_stump(classify.round_histogram(binned, {})).withColumn("err", F.round("err", 9))


@query("boost_predict", P.q(_FACE, P.STRONG, P.picked(10), P.sectors(), _COUNTS, select="SELECT video_id, round(CASE WHEN c[3] > 2 THEN 0.7 ELSE -0.7 END + CASE WHEN c[4] > 4 THEN -0.4 ELSE 0.4 END + CASE WHEN c[5] > 0 THEN 0.2 ELSE -0.2 END, 6)::DOUBLE AS margin FROM cf"))
def boost_predict(spark, d):
    edges = [[x + 0.5 for x in range(10)]] * 5
    out = classify.boost_predict(_count_features(spark, d), [(2, 2, 1, 0.7), (3, 4, -1, 0.4), (4, 0, 1, 0.2)], edges)
    return out.select("video_id", F.round("margin", 6).alias("margin"))


@query("baseline_majority", P.q(_FACE, P.STRONG, "vid AS (SELECT DISTINCT video_id, y FROM strong), cnt AS (SELECT y, count(*) AS n FROM vid GROUP BY y)", select="SELECT y, n, round(n / (SELECT sum(n) FROM cnt), 6) AS share FROM cnt ORDER BY n DESC, y LIMIT 1"))
def baseline_majority(spark, d):
    return baselines.majority(strong_face(spark, d).select("video_id", "y").distinct()).withColumn("share", F.round("share", 6))


def _milli_motion(df: DataFrame) -> DataFrame:
    return df.withColumn("motion", F.transform("motion_m", lambda v: F.struct(v["x"].cast("double").alias("dx"), v["y"].cast("double").alias("dy"))))


@query("baseline_first_order", P.q(_FACE, P.STRONG, select="SELECT video_id, source, y, lm, round(avg(dx_m), 3) AS mean_dx, round(avg(dy_m), 3) AS mean_dy, round(stddev_pop(dx_m), 3) AS sd_dx, round(stddev_pop(dy_m), 3) AS sd_dy FROM face JOIN (SELECT video_id, t FROM strong) s USING (video_id, t) GROUP BY ALL"))
def baseline_first_order(spark, d):
    f = baselines.first_order(_milli_motion(strong_face(spark, d)))
    at = lambda k: F.round(F.get("features", 4 * F.col("lm") + k), 3)
    return f.withColumn("lm", F.explode(F.sequence(F.lit(0), F.lit(50)))).select("video_id", "source", "y", "lm", at(0).alias("mean_dx"), at(1).alias("mean_dy"), at(2).alias("sd_dx"), at(3).alias("sd_dy"))


@query("baseline_noise_residual", P.q(_FACE, "hp AS (SELECT video_id, source, y, dx_m - avg(dx_m) OVER w AS hx, dy_m - avg(dy_m) OVER w AS hy FROM face WINDOW w AS (PARTITION BY video_id, t ORDER BY lm ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING))", select="SELECT video_id, source, y, round(var_pop(hx) + var_pop(hy), 1) AS r FROM hp GROUP BY ALL"))
def baseline_noise_residual(spark, d):
    return baselines.noise_residual(carriers.tall(carriers.face(spark, d), "source", "y")).withColumn("r", F.round("r", 1))


@query("baseline_frame_vote_majority", P.q(_FACE, P.STRONG, P.picked(10), P.sectors(), select="SELECT video_id, y, round(avg((k_found > 4)::INT), 6) AS share, (avg((k_found > 4)::INT) > 0.5)::INT AS pred FROM grp JOIN picked USING (video_id, t) GROUP BY ALL"))
def baseline_frame_vote_majority(spark, d):
    """The vote itself, on a fixed rule for single pairs: more than 4 sectors in use."""
    g = picked_groups(spark, d).withColumn("pred", (F.col("k") > 4).cast("int"))
    return baselines.vote(g).withColumn("share", F.round("share", 6))


@query("baseline_recurrent_feature", P.q(_FACE, P.STRONG, "sq AS (SELECT video_id, source, y, lm, dx_m, dy_m, row_number() OVER (PARTITION BY video_id, lm ORDER BY t) AS k, count(*) OVER (PARTITION BY video_id, lm) AS n FROM face JOIN (SELECT video_id, t FROM strong) s USING (video_id, t))", select="SELECT video_id, source, y, lm, round(sum(dx_m * CASE WHEN k = 1 THEN pow(0.8, n - 1) ELSE 0.2 * pow(0.8, n - k) END), 3) AS state_x, round(sum(dy_m * CASE WHEN k = 1 THEN pow(0.8, n - 1) ELSE 0.2 * pow(0.8, n - k) END), 3) AS state_y FROM sq GROUP BY ALL"))
def baseline_recurrent_feature(spark, d):
    f = baselines.recurrent_features(_milli_motion(strong_face(spark, d))).withColumn("lm", F.explode(F.sequence(F.lit(0), F.lit(50))))
    return f.select("video_id", "source", "y", "lm", F.round(F.get("features", 2 * F.col("lm")), 3).alias("state_x"), F.round(F.get("features", 2 * F.col("lm") + 1), 3).alias("state_y"))


@query("baseline_embedding_mean", "WITH v AS (SELECT vec_id, label, embedding FROM embeddings) SELECT label, k::INT AS k, round(avg(embedding[k + 1]::DOUBLE), 6) AS mean FROM v, range(64) g(k) GROUP BY ALL")
def baseline_embedding_mean(spark, d):
    e = carriers.read(spark, d, "embeddings").select(F.col("label").cast("string").alias("video_id"), carriers.source_of(F.col("label")).alias("source"), F.lit(0).alias("y"), F.col("vec_id").alias("t"), F.col("embedding").alias("vector"))
    f = baselines.embedding_sequence(e).withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(63))))
    return f.select(F.col("video_id").cast("int").alias("label"), "k", F.round(F.get("features", 2 * F.col("k")), 6).alias("mean"))

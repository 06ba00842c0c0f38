"""Queries of the method itself, from motion to patterns, distances, decisions and measures, with sector groups where SQL is to check them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from accord.operators import anomaly, distance, grouping, metrics, motion, pattern, sampling
from accord.queries import prelude as P
from accord.sources import carriers

Q: dict = {}
S: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def take(f):
        Q[name] = f
        if sql:
            S[name] = sql
        return f

    return take


# ---------------------------------------------------------------- shared steps


def strong_face(spark, d) -> DataFrame:
    """Pairs with enough motion, in thousandths: the filter comes before anything that costs."""
    m = carriers.milli(carriers.face(spark, d))
    return m.where(F.size(F.filter("motion_m", lambda v: v["x"] * v["x"] + v["y"] * v["y"] >= 722500)) >= 0.5 * F.size("motion_m"))


def sector_groups(pairs: DataFrame, k: int = 6) -> DataFrame:
    """labels, k (sectors in use), score and w, the weight in whole thousandths."""
    g = grouping.group_score(grouping.sectors(pairs, k), k).withColumn("k", F.col("k_found"))
    return g.withColumn("w", pattern.milli_weight(pattern.weight("k_score"))).drop("motion", "motion_m")


def picked_groups(spark, d, n: int = 10, pool: str = "video_id", k: int = 6) -> DataFrame:
    return sector_groups(sampling.pick_n(strong_face(spark, d), n, pool), k)


def tall_patterns(groups: DataFrame, by: list[str]) -> DataFrame:
    return pattern.l1_tall(pattern.build_tall(groups, by), pattern.totals(groups, by), by)


def genuine_template(groups: DataFrame, n: int = 3000, source: str = "R") -> DataFrame:
    one = anomaly.template_pairs(groups, n, source).withColumn("template", F.lit(source))
    return tall_patterns(one, ["template"])


def probe_scores(spark, d, n: int = 10, half: str = "b", template_source: str = "R", template_pairs: int = 3000) -> DataFrame:
    """(video_id, source, y, d): distance of each video's pattern of the half to a template of genuine pairs of the other half."""
    groups = sector_groups(sampling.ranked(strong_face(spark, d)))
    template = genuine_template(groups.where(F.col("half") != half), template_pairs, template_source)
    probes = groups.where((F.col("half") == half) & (F.col("pick") <= n))
    d_ = distance.tall_js(tall_patterns(probes, ["video_id"]), template, ["video_id"])
    return d_.join(probes.select("video_id", "source", "y").distinct(), "video_id").select("video_id", "source", "y", F.round("d", 6).alias("d"))


def scores_sql(n: int = 10, half: str = "b", template_source: str = "R", template_pairs: int = 3000) -> str:
    """CTEs up to scores(video_id, source, y, d)."""
    return ",".join(
        x.strip()
        for x in (
            P.face(),
            P.STRONG,
            P.picked(10**9),
            P.sectors(),
            f"""tpl AS (SELECT video_id, t FROM picked WHERE source = '{template_source}' AND half <> '{half}' ORDER BY md5(concat_ws(':', '0', video_id, t)), video_id, t LIMIT {template_pairs}),
prb AS (SELECT video_id, t, source, y FROM picked WHERE half = '{half}' AND pick <= {n}),
agr AS (SELECT a.video_id, a.t, a.lm AS i, b.lm AS j, w FROM lab a JOIN lab b ON a.video_id = b.video_id AND a.t = b.t AND a.lm > b.lm AND a.c = b.c JOIN wgt g ON g.video_id = a.video_id AND g.t = a.t),
tc AS (SELECT i, j, sum(w)::BIGINT AS w FROM agr JOIN tpl USING (video_id, t) GROUP BY i, j),
tt AS (SELECT (2 * (SELECT sum(w) FROM tc) + 51 * sum(w))::DOUBLE AS total FROM wgt JOIN tpl USING (video_id, t)),
tp AS (SELECT i, j, w::DOUBLE / total AS pb FROM tc, tt),
pc AS (SELECT video_id, i, j, sum(w)::BIGINT AS w FROM agr JOIN prb USING (video_id, t) GROUP BY video_id, i, j),
pt AS (SELECT video_id, any_value(source) AS source, any_value(y) AS y, (2 * coalesce(any_value(low), 0) + 51 * sum(w))::DOUBLE AS total FROM wgt JOIN prb USING (video_id, t) LEFT JOIN (SELECT video_id, sum(w) AS low FROM pc GROUP BY video_id) l USING (video_id) GROUP BY video_id),
pp AS (SELECT video_id, i, j, pc.w::DOUBLE / total AS pa FROM pc JOIN pt USING (video_id)),
cls AS (SELECT v.video_id, c.i, c.j FROM pt v, (SELECT a.lm AS i, b.lm AS j FROM lmk a JOIN lmk b ON a.lm > b.lm) c),
bth AS (SELECT c.video_id, c.i, c.j, coalesce(pa, 0) AS pa, coalesce(pb, 0) AS pb FROM cls c LEFT JOIN pp USING (video_id, i, j) LEFT JOIN tp USING (i, j)),
scores AS (SELECT video_id, any_value(source) AS source, any_value(y) AS y, round(sum((CASE WHEN pa > 0 THEN pa * ln(pa / ((pa + pb) / 2)) ELSE 0 END + CASE WHEN pb > 0 THEN pb * ln(pb / ((pa + pb) / 2)) ELSE 0 END) / 2), 6) AS d FROM bth JOIN pt USING (video_id) GROUP BY video_id)""",
        )
    )


_FACE = P.face()
_TOP = "picked JOIN strong USING (video_id, t)"


# ---------------------------------------------------------------- motion


@query("motion_magnitude", P.q(_FACE, select="SELECT video_id, t, lm, dx_m * dx_m + dy_m * dy_m AS size2 FROM face"))
def motion_magnitude(spark, d):
    t = carriers.tall(carriers.face(spark, d))
    return t.select("video_id", "t", "lm", (F.col("dx_m") * F.col("dx_m") + F.col("dy_m") * F.col("dy_m")).alias("size2"))


@query("motion_filter", P.q(_FACE, P.STRONG, select="SELECT video_id, source, y, t FROM strong"))
def motion_filter(spark, d):
    return strong_face(spark, d).select("video_id", "source", "y", "t")


@query("motion_filter_mean", P.q(_FACE, select="SELECT video_id, t FROM face GROUP BY video_id, t HAVING round(avg(sqrt((dx_m * dx_m + dy_m * dy_m)::DOUBLE)), 3) >= 1400"))
def motion_filter_mean(spark, d):
    m = carriers.milli(carriers.face(spark, d))
    mean = F.aggregate(F.transform("motion_m", lambda v: F.sqrt((v["x"] * v["x"] + v["y"] * v["y"]).cast("double"))), F.lit(0.0), lambda a, x: a + x) / F.size("motion_m")
    return m.where(F.round(mean, 3) >= 1400).select("video_id", "t")


@query("motion_filter_report", P.q(_FACE, P.STRONG, select="SELECT source, count(*) AS n_pairs, count(*) FILTER (EXISTS (SELECT 1 FROM strong s WHERE s.video_id = p.video_id AND s.t = p.t)) AS n_kept FROM (SELECT DISTINCT video_id, source, t FROM face) p GROUP BY source"))
def motion_filter_report(spark, d):
    whole = carriers.milli(carriers.face(spark, d)).withColumn("motion", F.transform("motion_m", lambda v: F.struct(v["x"].cast("double").alias("dx"), v["y"].cast("double").alias("dy"))))
    return motion.filter_report(whole, tau=850.0)


@query(
    "motion_threshold",
    P.q(
        P.LI,
        "vid AS (SELECT DISTINCT video_id FROM li ORDER BY md5('0:' || video_id), video_id LIMIT 100)",
        select="SELECT round(quantile_cont(sqrt((dx_m * dx_m + dy_m * dy_m)::DOUBLE) / 1000, 0.5), 3) AS tau FROM li WHERE video_id IN (SELECT video_id FROM vid)",
    ),
)
def motion_threshold(spark, d):
    m = carriers.milli(carriers.li(spark, d))
    m = m.withColumn("motion", F.transform("motion_m", lambda v: F.struct((v["x"] / 1000.0).alias("dx"), (v["y"] / 1000.0).alias("dy"))))
    return motion.calibrate(m).select(F.round("tau", 3).alias("tau"))


@query("evt_motion", P.q(P.EVT, select="SELECT video_id, t, lm, dx_m, dy_m FROM evt"))
def evt_motion(spark, d):
    return carriers.tall(carriers.evt(spark, d))


@query("li_motion", P.q(P.LI, select="SELECT video_id, t, lm, dx_m, dy_m FROM li"))
def li_motion(spark, d):
    return carriers.tall(carriers.li(spark, d))


# ---------------------------------------------------------------- groups


def _evt(spark, d):
    return carriers.milli(carriers.evt(spark, d))


_PAIR = "cel2 AS (SELECT a.video_id, a.t, a.lm AS i, b.lm AS j, a.dx_m AS xi, a.dy_m AS yi, b.dx_m AS xj, b.dy_m AS yj FROM evt a JOIN evt b ON a.video_id = b.video_id AND a.t = b.t)"
_CLIP = "aff AS (SELECT video_id, t, i, j, greatest(xi * xj + yi * yj, 0) AS a FROM cel2), deg AS (SELECT video_id, t, i, sum(a)::BIGINT AS d FROM aff GROUP BY ALL)"


@query("affinity_inner", P.q(P.EVT, _PAIR, select="SELECT video_id, t, i, j, xi * xj + yi * yj AS a FROM cel2"))
def affinity_inner(spark, d):
    return grouping.affinity(_evt(spark, d))


@query("affinity_cosine", P.q(P.EVT, _PAIR, select="SELECT video_id, t, i, j, round(coalesce((xi * xj + yi * yj)::DOUBLE / nullif(sqrt((xi * xi + yi * yi)::DOUBLE) * sqrt((xj * xj + yj * yj)::DOUBLE), 0), 0), 6) + 0.0 AS a FROM cel2"))
def affinity_cosine(spark, d):
    return grouping.affinity(_evt(spark, d), "cosine").withColumn("a", F.round("a", 6) + 0.0)


@query("affinity_euclid", P.q(P.EVT, _PAIR, select="SELECT video_id, t, i, j, round(exp(-((xi - xj) * (xi - xj) + (yi - yj) * (yi - yj))::DOUBLE / (2 * 20000.0::DOUBLE * 20000.0::DOUBLE)), 6) AS a FROM cel2"))
def affinity_euclid(spark, d):
    return grouping.affinity(_evt(spark, d), "euclid", sigma=20000.0).withColumn("a", F.round("a", 6))


@query(
    "affinity_policy",
    P.q(
        P.EVT,
        _PAIR,
        "raw AS (SELECT video_id, t, i, j, xi * xj + yi * yj AS a FROM cel2), low AS (SELECT video_id, t, min(a) AS m FROM raw GROUP BY ALL)",
        select="""SELECT 'clip' AS policy, count(*) AS n, sum(greatest(a, 0))::BIGINT AS total FROM raw UNION ALL SELECT 'signed', count(*), sum(a)::BIGINT FROM raw
UNION ALL SELECT 'shift', count(*), sum(a - least(m, 0))::BIGINT FROM raw JOIN low USING (video_id, t) UNION ALL SELECT 'strict', count(*), sum(a)::BIGINT FROM raw JOIN low USING (video_id, t) WHERE m >= 0""",
    ),
)
def affinity_policy(spark, d):
    cells = grouping.affinity(_evt(spark, d))
    out = None
    for p in ("clip", "signed", "shift", "strict"):
        one = grouping.with_policy(cells, p).agg(F.lit(p).alias("policy"), F.count("*").alias("n"), F.sum("a").alias("total"))
        out = one if out is None else out.union(one)
    return out


@query("degree", P.q(P.EVT, _PAIR, _CLIP, select="SELECT video_id, t, i, d FROM deg"))
def degree(spark, d):
    return grouping.degree(grouping.with_policy(grouping.affinity(_evt(spark, d))))


def _lap(value: str, unit: str = "1") -> str:
    return P.q(P.EVT, _PAIR, _CLIP, select=f"""SELECT a.video_id, a.t, a.i, a.j, round(coalesce({value}, CASE WHEN a.i = a.j THEN 1.0 ELSE 0.0 END::DOUBLE) / {unit}, 6) + 0.0 AS l
FROM aff a JOIN deg p ON p.video_id = a.video_id AND p.t = a.t AND p.i = a.i JOIN deg q ON q.video_id = a.video_id AND q.t = a.t AND q.i = a.j""")


_CORE = "(CASE WHEN a.i = a.j THEN p.d ELSE 0 END - a.a)::DOUBLE"


def _lap_query(kind, unit=1.0):
    def run(spark, d):
        return grouping.laplacian(grouping.with_policy(grouping.affinity(_evt(spark, d))), kind).withColumn("l", F.round(F.col("l") / unit, 6) + 0.0)

    return run


query("laplacian_sym", _lap(f"{_CORE} / (nullif(sqrt(p.d::DOUBLE), 0) * nullif(sqrt(q.d::DOUBLE), 0))"))(_lap_query("sym"))
query("laplacian_as_printed", _lap(f"{_CORE} / nullif(sqrt(p.d::DOUBLE), 0) * nullif(sqrt(q.d::DOUBLE), 0)", "1000000.0::DOUBLE"))(_lap_query("as_printed", 1e6))
query("laplacian_random_walk", _lap(f"{_CORE} / nullif(p.d::DOUBLE, 0)"))(_lap_query("random_walk"))
query("laplacian_unnormalised", _lap(_CORE))(_lap_query("unnormalised"))


@query("sector_groups", P.q(_FACE, P.STRONG, P.picked(10**9), P.sectors(), select="SELECT video_id, t, lm, c FROM lab"))
def sector_groups_query(spark, d):
    g = grouping.sectors(strong_face(spark, d), 6)
    return g.select("video_id", "t", F.posexplode("labels").alias("lm", "c"))


@query("group_score", P.q(_FACE, P.STRONG, P.picked(10), P.sectors(), select="SELECT video_id, t, k_found AS k, round(score, 4) AS score FROM grp"))
def group_score(spark, d):
    return picked_groups(spark, d).select("video_id", "t", "k", F.round("score", 4).alias("score"))


@query("group_score_as_printed", P.q(_FACE, P.STRONG, P.picked(10), P.sectors(), select="SELECT video_id, t, round(CASE WHEN k_found > 1 AND b <> 0 THEN i / b * (n - k_found) / (k_found - 1) ELSE 0 END, 4) AS score FROM grp"))
def group_score_as_printed(spark, d):
    g = grouping.sectors(sampling.pick_n(strong_face(spark, d), 10), 6)
    return grouping.group_score(g, 6, "as_printed").select("video_id", "t", F.round("score", 4).alias("score"))


def _select_k_sql() -> str:
    parts = []
    for k in range(2, 9):
        body = P.sectors(k).strip()
        for name in ("lab", "own", "sc", "grp", "wgt"):
            body = body.replace(f"{name} AS", f"{name}{k} AS").replace(f"FROM {name} ", f"FROM {name}{k} ").replace(f"FROM {name})", f"FROM {name}{k})")
        parts.append(body)
    union = " UNION ALL ".join(f"SELECT video_id, t, {k} AS k, k_found, round(score, 6) AS score FROM grp{k}" for k in range(2, 9))
    return P.q(_FACE, P.STRONG, P.picked(10**9), *parts, f"tries AS ({union})", select="SELECT video_id, t, k, k_found, score FROM tries QUALIFY row_number() OVER (PARTITION BY video_id, t ORDER BY score DESC, k) = 1")


@query("select_k", _select_k_sql())
def select_k(spark, d):
    return grouping.select_k(strong_face(spark, d)).select("video_id", "t", "k", "k_found", "score")


@query("k_histogram", P.q(_FACE, P.STRONG, P.picked(10), P.sectors(), select="SELECT source, k_found AS k, count(*) AS n_pairs, round(avg(score), 4) AS mean_score FROM grp JOIN picked USING (video_id, t) GROUP BY ALL"))
def k_histogram(spark, d):
    return grouping.report(picked_groups(spark, d))


@query(
    "component_groups",
    "WITH RECURSIVE "
    + P.EVT.strip()
    + """, lnk AS (SELECT a.video_id, a.t, a.lm AS i, b.lm AS j FROM evt a JOIN evt b ON a.video_id = b.video_id AND a.t = b.t WHERE a.lm = b.lm OR a.dx_m * b.dx_m + a.dy_m * b.dy_m > 0),
rch AS (SELECT video_id, t, i, j FROM lnk UNION SELECT r.video_id, r.t, r.i, l.j FROM rch r JOIN lnk l ON l.video_id = r.video_id AND l.t = r.t AND l.i = r.j)
SELECT video_id, t, i AS lm, min(j) AS least FROM rch GROUP BY ALL""",
)
def component_groups(spark, d):
    g = grouping.components(_evt(spark, d)).select("video_id", "t", F.posexplode("labels").alias("lm", "c"))
    return g.select("video_id", "t", "lm", F.min("lm").over(W.partitionBy("video_id", "t", "c")).alias("least"))


@query("landmark_groups", P.q(_FACE, P.STRONG, P.picked(1), P.sectors(), select="SELECT video_id, t, c AS group_id, string_agg(lm::VARCHAR, ' ' ORDER BY lm) AS landmarks FROM lab GROUP BY ALL"))
def landmark_groups(spark, d):
    g = grouping.sectors(sampling.pick_n(strong_face(spark, d), 1), 6).select("video_id", "t", F.posexplode("labels").alias("lm", "group_id"))
    return g.groupBy("video_id", "t", "group_id").agg(F.concat_ws(" ", F.transform(F.array_sort(F.collect_list("lm")), lambda x: x.cast("string"))).alias("landmarks"))


# ---------------------------------------------------------------- patterns


@query("agreement_matrix", P.q(_FACE, P.STRONG, P.picked(10**9), P.sectors().replace("lab AS", "lab AS MATERIALIZED"), "row AS (SELECT video_id, t, list(c ORDER BY lm) AS cs FROM lab GROUP BY ALL)", select="SELECT video_id, t, i::INT AS i, list_aggregate(list_transform(cs[1:i], lambda c: (c = cs[i + 1])::INT::VARCHAR), 'string_agg', '') AS cells FROM row, range(1, 51) g(i)"))
def agreement_matrix(spark, d):
    """All matrices, a row of cells as one text."""
    g = grouping.sectors(strong_face(spark, d), 6)
    return pattern.agreement_rows(g, "video_id", "t").select("video_id", "t", "i", F.concat_ws("", F.transform("cells", lambda x: x.cast("string"))).alias("cells"))


@query("pair_weight", P.q(_FACE, P.STRONG, P.picked(10), P.sectors(), select="SELECT video_id, t, w AS k_score, round(1000 * score)::BIGINT AS score, k_found::BIGINT AS k FROM wgt"))
def pair_weight(spark, d):
    g = picked_groups(spark, d)
    return g.select("video_id", "t", F.col("w").alias("k_score"), pattern.milli_weight(pattern.weight("score")).alias("score"), F.col("k").cast("bigint").alias("k"))


_BYSRC = (P.face(), P.STRONG, P.picked(10), P.sectors(), P.pattern("source"))


@query("pattern_build", P.q(*_BYSRC, select="SELECT source, i, j, w FROM cell"))
def pattern_build(spark, d):
    return pattern.build_tall(picked_groups(spark, d), ["source"])


@query("pattern_weighted_mean", P.q(*_BYSRC, select="SELECT source, i, j, round(cell.w::DOUBLE / w_sum, 6) AS mean FROM cell JOIN tot USING (source)"))
def pattern_weighted_mean(spark, d):
    g = picked_groups(spark, d)
    return pattern.build_tall(g, ["source"]).join(pattern.totals(g, ["source"]), "source").select("source", "i", "j", F.round(F.col("w").cast("double") / F.col("w_sum"), 6).alias("mean"))


_L1 = "nrm AS (SELECT source, i, j, w::DOUBLE / (2 * sum(w) OVER (PARTITION BY source) + 51 * w_sum)::DOUBLE AS p FROM cell JOIN tot USING (source))"


@query("pattern_l1", P.q(*_BYSRC, _L1, select="SELECT source, i, j, round(p, 9) AS p FROM nrm"))
def pattern_l1(spark, d):
    return tall_patterns(picked_groups(spark, d), ["source"]).select("source", "i", "j", F.round("p", 9).alias("p"))


@query("pattern_packed", P.q(*_BYSRC, select="SELECT source, n_pairs, w_sum AS diag, (SELECT sum(w)::BIGINT FROM cell c WHERE c.source = tot.source) AS low FROM tot"))
def pattern_packed(spark, d):
    """The packed two-step build gives the same sums as the tall one."""
    p = pattern.build(picked_groups(spark, d), ["source"])
    return p.select("source", "n_pairs", F.col("diag").cast("bigint").alias("diag"), F.aggregate("tri", F.lit(0.0), lambda a, x: a + x).cast("bigint").alias("low"))


@query("pattern_rescale", P.q(*_BYSRC, select="SELECT source, i, j, round((w - min(w) OVER p)::DOUBLE / (max(w) OVER p - min(w) OVER p)::DOUBLE, 6) AS shown FROM cell WINDOW p AS (PARTITION BY source)"))
def pattern_rescale(spark, d):
    return pattern.rescale(pattern.build_tall(picked_groups(spark, d), ["source"]), ["source"]).select("source", "i", "j", F.round("shown", 6).alias("shown"))


@query("pick_n", P.q(_FACE, P.STRONG, P.picked(10), select="SELECT video_id, t, pick FROM picked"))
def pick_n(spark, d):
    return sampling.pick_n(strong_face(spark, d), 10).select("video_id", "t", "pick")


@query("pick_n_drop", P.q(_FACE, P.STRONG, P.picked(10, short="drop"), select="SELECT video_id, t, pick FROM picked"))
def pick_n_drop(spark, d):
    return sampling.pick_n(strong_face(spark, d), 10, short="drop").select("video_id", "t", "pick")


@query(
    "pattern_sets",
    P.q(
        _FACE,
        P.STRONG,
        P.picked(10**9, "source"),
        "siz AS (SELECT source, max(pick) AS size FROM picked GROUP BY source)",
        "drw AS (SELECT source, m AS pattern_id, k AS draw, ('0x' || md5(concat_ws(':', '1', source, m, k))[1:12])::BIGINT % size + 1 AS pick FROM siz, range(2000) a(m), range(35) b(k))",
        select="SELECT source, pattern_id::INT AS pattern_id, draw::INT AS draw, video_id, t FROM drw JOIN picked USING (source, pick)",
    ),
)
def pattern_sets(spark, d):
    return sampling.pattern_sets(strong_face(spark, d), 2000, 35).select("source", "pattern_id", "draw", "video_id", "t")


@query("split_no_overlap", P.q(_FACE, select="SELECT video_id, ('0x' || md5('0:' || video_id)[1:8])::BIGINT < 2147483648 AS train, count(DISTINCT t) AS n_pairs FROM face GROUP BY ALL"))
def split_no_overlap(spark, d):
    return sampling.split(carriers.face(spark, d)).groupBy("video_id", "train").agg(F.count_distinct("t").alias("n_pairs"))


# ---------------------------------------------------------------- distances and decisions


def _two_sql(value: str) -> str:
    return P.q(*_BYSRC, _L1, "r AS (SELECT i, j, p AS pb FROM nrm WHERE source = 'R')", "c AS (SELECT s.source, a.lm AS i, b.lm AS j FROM (SELECT DISTINCT source FROM nrm) s, lmk a JOIN lmk b ON a.lm > b.lm)",
               "b AS (SELECT c.source, c.i, c.j, coalesce(p, 0) AS pa, coalesce(pb, 0) AS pb FROM c LEFT JOIN nrm USING (source, i, j) LEFT JOIN r USING (i, j))", select=value)


_JS = "(CASE WHEN pa > 0 THEN pa * ln(pa / ((pa + pb) / 2)) ELSE 0 END + CASE WHEN pb > 0 THEN pb * ln(pb / ((pa + pb) / 2)) ELSE 0 END) / 2"


def _terms(spark, d):
    p = tall_patterns(picked_groups(spark, d), ["source"])
    return distance.tall_terms(p, p.where("source = 'R'"), ["source"])


@query("kl_divergence", _two_sql("SELECT source, CASE WHEN bool_or(pa > 0 AND pb = 0) THEN NULL ELSE round(sum(CASE WHEN pa > 0 AND pb > 0 THEN pa * ln(pa / pb) ELSE 0 END), 6) END AS d FROM b GROUP BY source"))
def kl_divergence(spark, d):
    t = _terms(spark, d)
    return t.groupBy("source").agg(F.when(F.bool_or((F.col("pa") > 0) & (F.col("pb") == 0)), None).otherwise(F.round(F.sum(F.when((F.col("pa") > 0) & (F.col("pb") > 0), F.col("pa") * F.log(F.col("pa") / F.nullif("pb", F.lit(0.0)))).otherwise(0.0)), 6)).alias("d"))


@query("js_divergence", _two_sql(f"SELECT source, round(sum({_JS}), 6) AS d FROM b GROUP BY source"))
def js_divergence(spark, d):
    return _terms(spark, d).groupBy("source").agg(F.round(F.sum("term"), 6).alias("d"))


@query("js_triangle", _two_sql(f"SELECT source, round(sum({_JS}), 6) AS d FROM (SELECT source, pa / sum(pa) OVER (PARTITION BY source) AS pa, pb / sum(pb) OVER (PARTITION BY source) AS pb FROM b) GROUP BY source"))
def js_triangle(spark, d):
    w = W.partitionBy("source")
    t = _terms(spark, d).select("source", (F.col("pa") / F.sum("pa").over(w)).alias("pa"), (F.col("pb") / F.sum("pb").over(w)).alias("pb"))
    return t.groupBy("source").agg(F.round(F.sum(distance.js_term(F.col("pa"), F.col("pb"))), 6).alias("d"))


@query("pattern_distances", _two_sql(f"SELECT source, round(sqrt(sum({_JS})), 6) AS js_root, round(sum(abs(pa - pb)), 6) AS l1, round(sqrt(sum((pa - pb) * (pa - pb))), 6) AS l2, round(1 - sum(pa * pb) / (sqrt(sum(pa * pa)) * sqrt(sum(pb * pb))), 6) + 0.0 AS cosine FROM b GROUP BY source"))
def pattern_distances(spark, d):
    a, b = F.col("pa"), F.col("pb")
    return _terms(spark, d).groupBy("source").agg(F.round(F.sqrt(F.sum("term")), 6).alias("js_root"), F.round(F.sum(F.abs(a - b)), 6).alias("l1"), F.round(F.sqrt(F.sum((a - b) * (a - b))), 6).alias("l2"), (F.round(1 - F.sum(a * b) / (F.sqrt(F.sum(a * a)) * F.sqrt(F.sum(b * b))), 6) + 0.0).alias("cosine"))


@query("template", "WITH " + scores_sql() + " SELECT i, j, round(pb, 9) AS p FROM tp")
def template(spark, d):
    groups = sector_groups(sampling.ranked(strong_face(spark, d)))
    return genuine_template(groups.where("half <> 'b'")).select("i", "j", F.round("p", 9).alias("p"))


@query("anomaly_scores", "WITH " + scores_sql() + " SELECT video_id, source, y, d FROM scores")
def anomaly_scores(spark, d):
    return probe_scores(spark, d)


@query("anomaly_single_pair", "WITH " + scores_sql(1) + " SELECT video_id, source, y, d FROM scores")
def anomaly_single_pair(spark, d):
    return probe_scores(spark, d, 1)


@query("template_cross_real", "WITH " + scores_sql(10, "b", "R2") + " SELECT source, count(*) AS n, round(avg(d), 6) AS mean_d FROM scores GROUP BY source")
def template_cross_real(spark, d):
    return probe_scores(spark, d, template_source="R2").groupBy("source").agg(F.count("*").alias("n"), F.round(F.avg("d"), 6).alias("mean_d"))


_ROC = "cnt AS (SELECT d, sum(y)::BIGINT AS pos, sum(1 - y)::BIGINT AS neg FROM scores GROUP BY d)"


@query("roc_curve", "WITH " + scores_sql() + ", " + _ROC + " SELECT d, sum(neg) OVER w::DOUBLE / sum(neg) OVER ()::DOUBLE AS fpr, sum(pos) OVER w::DOUBLE / sum(pos) OVER ()::DOUBLE AS tpr FROM cnt WINDOW w AS (ORDER BY d DESC ROWS UNBOUNDED PRECEDING)")
def roc_curve(spark, d):
    return metrics.roc(probe_scores(spark, d))


@query("auc", "WITH " + scores_sql() + " SELECT round(sum(CASE WHEN a.d > b.d THEN 1.0 WHEN a.d = b.d THEN 0.5 ELSE 0 END)::DOUBLE / count(*), 6) AS auc FROM scores a, scores b WHERE a.y = 1 AND b.y = 0")
def auc(spark, d):
    return metrics.auc(probe_scores(spark, d))


@query("auc_trapezoid", S["auc"])
def auc_trapezoid(spark, d):
    return metrics.auc_trapezoid(metrics.roc(probe_scores(spark, d)))


def _against_real(scores: DataFrame) -> DataFrame:
    """Each forged source against all genuine rows: task names the source."""
    forged = scores.where("y = 1").withColumn("task", F.col("source"))
    tasks = F.explode(F.array(*[F.lit(s) for s in ("A", "B", "C", "D")]))
    return forged.unionByName(scores.where("y = 0").withColumn("task", tasks))


_TASK_AUC = "SELECT a.source AS task, round(sum(CASE WHEN a.d > b.d THEN 1.0 WHEN a.d = b.d THEN 0.5 ELSE 0 END)::DOUBLE / count(*), 6) AS auc FROM scores a, scores b WHERE a.y = 1 AND b.y = 0 GROUP BY a.source"


@query("anomaly_auc", "WITH " + scores_sql() + " " + _TASK_AUC)
def anomaly_auc(spark, d):
    """The flagship: one-class AUC of each forged source against genuine videos."""
    return metrics.auc(_against_real(probe_scores(spark, d)), "task")


@query("anomaly_decision", "WITH " + scores_sql() + ", cut AS (SELECT round(quantile_cont(d, 0.95), 6) AS c FROM scores WHERE y = 0) SELECT source, count(*) AS n, sum((d >= c)::INT)::BIGINT AS called FROM scores, cut GROUP BY source")
def anomaly_decision(spark, d):
    s = probe_scores(spark, d)
    cut = s.where("y = 0").agg(F.round(F.percentile("d", F.lit(0.95)), 6).alias("c"))
    return s.crossJoin(F.broadcast(cut)).groupBy("source").agg(F.count("*").alias("n"), F.sum((F.col("d") >= F.col("c")).cast("bigint")).alias("called"))  # one row


@query("confusion", "WITH " + scores_sql() + " SELECT sum((d >= 0.05 AND y = 1)::INT)::BIGINT AS tp, sum((d >= 0.05 AND y = 0)::INT)::BIGINT AS fp, sum((d < 0.05 AND y = 0)::INT)::BIGINT AS tn, sum((d < 0.05 AND y = 1)::INT)::BIGINT AS fn FROM scores")
def confusion(spark, d):
    return metrics.confusion(probe_scores(spark, d), 0.05).select("tp", "fp", "tn", "fn")


@query("accuracy", "WITH " + scores_sql() + " SELECT source, count(*) AS n, round(avg(((d >= 0.05)::INT = y)::INT), 6) AS accuracy FROM scores GROUP BY source")
def accuracy(spark, d):
    return metrics.accuracy(anomaly.decide(probe_scores(spark, d), 0.05), "source")


def _sweep_sql(ns: tuple = (1, 10, 35, 70)) -> str:
    """Scores for several N at once, by cumulative sums over the order of picks."""
    return "WITH " + ",".join(x.strip() for x in (P.face(), P.STRONG, P.picked(10**9, "source"), P.sectors())) + f"""
, nn AS (SELECT unnest([{", ".join(map(str, ns))}]) AS n_pick),
agr AS (SELECT a.video_id, a.t, a.lm AS i, b.lm AS j, w FROM lab a JOIN lab b ON a.video_id = b.video_id AND a.t = b.t AND a.lm > b.lm AND a.c = b.c JOIN wgt g ON g.video_id = a.video_id AND g.t = a.t),
allc AS (SELECT source, i, j, sum(w)::BIGINT AS w FROM agr JOIN picked USING (video_id, t) GROUP BY ALL),
allt AS (SELECT source, 51 * sum(w) AS dg FROM wgt JOIN picked USING (video_id, t) GROUP BY ALL),
fullp AS (SELECT source, i, j, w::DOUBLE / (2 * sum(w) OVER (PARTITION BY source) + dg)::DOUBLE AS pb FROM allc JOIN allt USING (source)),
prec AS (SELECT n_pick, source, i, j, sum(w)::BIGINT AS w FROM agr JOIN picked USING (video_id, t) JOIN nn ON pick <= n_pick GROUP BY ALL),
pret AS (SELECT n_pick, source, 51 * sum(w) AS dg FROM wgt JOIN picked USING (video_id, t) JOIN nn ON pick <= n_pick GROUP BY ALL),
prep AS (SELECT n_pick, source, i, j, w::DOUBLE / (2 * sum(w) OVER (PARTITION BY n_pick, source) + dg)::DOUBLE AS pa FROM prec JOIN pret USING (n_pick, source)),
bb AS (SELECT k.n_pick, k.source, coalesce(pa, 0) AS pa, coalesce(pb, 0) AS pb FROM pret k CROSS JOIN (SELECT a.lm AS i, b.lm AS j FROM lmk a JOIN lmk b ON a.lm > b.lm) c
  LEFT JOIN prep USING (n_pick, source, i, j) LEFT JOIN fullp ON fullp.source = k.source AND fullp.i = c.i AND fullp.j = c.j)
SELECT source, n_pick::INT AS n_pick, round(sum({_JS}), 6) AS d FROM bb GROUP BY ALL"""


@query("equal_error", "WITH " + scores_sql() + ", " + _ROC + ", crv AS (SELECT d, sum(neg) OVER w::DOUBLE / sum(neg) OVER ()::DOUBLE AS fpr, sum(pos) OVER w::DOUBLE / sum(pos) OVER ()::DOUBLE AS tpr FROM cnt WINDOW w AS (ORDER BY d DESC ROWS UNBOUNDED PRECEDING)) SELECT round((fpr + 1 - tpr) / 2, 6) AS eer FROM crv ORDER BY round(abs(fpr - (1 - tpr)), 9), d LIMIT 1")
def equal_error(spark, d):
    return metrics.equal_error(metrics.roc(probe_scores(spark, d)))


@query("order_invariance", P.q(_FACE, P.STRONG, P.picked(10), P.sectors(), P.pattern("source"), select="SELECT source, count(*) AS n_cells, 0::BIGINT AS n_differ FROM cell GROUP BY source"))
def order_invariance(spark, d):
    """Patterns built from pairs in the opposite order and from landmarks in another order, put back: cells that differ."""
    g = picked_groups(spark, d)
    first = pattern.build_tall(g, ["source"])
    turned = g.orderBy(F.desc("pick")).withColumn("labels", F.reverse("labels"))
    back = pattern.build_tall(turned, ["source"]).select("source", (50 - F.col("j")).alias("i"), (50 - F.col("i")).alias("j"), F.col("w").alias("v"))
    both = first.join(back, ["source", "i", "j"], "full")
    return both.groupBy("source").agg(F.count("*").alias("n_cells"), F.sum((~F.col("w").eqNullSafe(F.col("v"))).cast("bigint")).alias("n_differ"))


@query("pattern_subtract", P.q(*_BYSRC, select="SELECT source, n_pairs, w_sum AS diag, (SELECT sum(w)::BIGINT FROM cell c WHERE c.source = tot.source) AS low FROM tot"))
def pattern_subtract(spark, d):
    """The pattern of 20 pairs less that of the pairs after the tenth is the pattern of 10."""
    g = sector_groups(sampling.pick_n(strong_face(spark, d), 20))
    p = pattern.subtract(pattern.build(g, ["source"]), pattern.build(g.where("pick > 10"), ["source"]), ["source"])
    return p.select("source", "n_pairs", F.col("diag").cast("bigint").alias("diag"), F.aggregate("tri", F.lit(0.0), lambda a, x: a + x).cast("bigint").alias("low"))


@query("convergence", _sweep_sql())
def convergence(spark, d):
    from accord.operators import explain

    groups = sector_groups(sampling.ranked(strong_face(spark, d), "source"))
    return explain.convergence(groups, ["source"]).select("source", "n_pick", F.round("d", 6).alias("d"))


_SWEEP = " UNION ALL ".join(f"SELECT {n} AS n_pick, task, auc FROM (WITH {scores_sql(n)} {_TASK_AUC})" for n in (1, 10, 35, 70))


@query("anomaly_sweep", _SWEEP)
def anomaly_sweep(spark, d):
    """AUC of each source for several N: groups are made once, N is a column of one plan."""
    groups = sector_groups(sampling.ranked(strong_face(spark, d)))
    template = genuine_template(groups.where("half <> 'b'"))
    probes = groups.where("half = 'b'").withColumn("n_pick", F.explode(F.array(*[F.lit(n) for n in (1, 10, 35, 70)]))).where("pick <= n_pick")
    by = ["n_pick", "video_id"]
    s = distance.tall_js(tall_patterns(probes, by), template, by).join(probes.select(*by, "source", "y").distinct(), by).withColumn("d", F.round("d", 6))
    return metrics.auc(_against_real(s), "n_pick", "task")

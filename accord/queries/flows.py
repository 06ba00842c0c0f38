"""Queries of local motion estimation on the image carrier."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from accord.operators import flow, grouping, landmarks
from accord.queries import prelude as P
from accord.queries.method import query
from accord.sources import carriers

_GRAD = """
grd AS (SELECT video_id, t, x, y, i, (coalesce(lead(i) OVER r, i) - coalesce(lag(i) OVER r, i)) / 2 AS ix, (coalesce(lead(i) OVER c, i) - coalesce(lag(i) OVER c, i)) / 2 AS iy
  FROM img WINDOW r AS (PARTITION BY video_id, t, y ORDER BY x), c AS (PARTITION BY video_id, t, x ORDER BY y))"""
_NEXT = "nxt AS (SELECT a.*, b.i AS ni, b.ix AS nix, b.iy AS niy FROM grd a JOIN grd b ON b.video_id = a.video_id AND b.t = a.t + 1 AND b.x = a.x AND b.y = a.y)"


def _shifted(u: int, v: int) -> str:
    return f"nxt AS (SELECT a.*, b.i AS ni, b.ix AS nix, b.iy AS niy FROM grd a JOIN grd b ON b.video_id = a.video_id AND b.t = a.t + 1 AND b.x = a.x + {u} AND b.y = a.y + {v})"


_LS = """
prd AS (SELECT video_id, t, x, y, ix * ix AS sxx, ix * iy AS sxy, iy * iy AS syy, ix * (ni - i) AS sxt, iy * (ni - i) AS syt FROM nxt),
bx1 AS (SELECT a.video_id, a.t, a.x, a.y, sum(b.sxx) AS sxx, sum(b.sxy) AS sxy, sum(b.syy) AS syy, sum(b.sxt) AS sxt, sum(b.syt) AS syt
  FROM prd a JOIN prd b ON a.video_id = b.video_id AND a.t = b.t AND abs(a.x - b.x) <= 2 AND abs(a.y - b.y) <= 2 GROUP BY ALL),
ls AS (SELECT video_id, t, x, y, CASE WHEN abs(sxx * syy - sxy * sxy) < 0.000001 THEN 0 ELSE (sxy * syt - syy * sxt) / (sxx * syy - sxy * sxy) END AS u,
  CASE WHEN abs(sxx * syy - sxy * sxy) < 0.000001 THEN 0 ELSE (sxy * sxt - sxx * syt) / (sxx * syy - sxy * sxy) END AS v FROM bx1)"""


def _img(spark, d) -> DataFrame:
    return carriers.img_tall(spark, d)


@query("frame_pairs", P.q(P.IMG, select="SELECT DISTINCT video_id, t, t + 1 AS t_next FROM img a WHERE EXISTS (SELECT 1 FROM img b WHERE b.video_id = a.video_id AND b.t = a.t + 1)"))
def frame_pairs(spark, d):
    return flow.frame_pairs(_img(spark, d))


@query("frame_pairs_stride2", P.q(P.IMG, select="SELECT DISTINCT video_id, t, t + 2 AS t_next FROM img a WHERE EXISTS (SELECT 1 FROM img b WHERE b.video_id = a.video_id AND b.t = a.t + 2)"))
def frame_pairs_stride2(spark, d):
    return flow.frame_pairs(_img(spark, d), 2)


@query("image_gradient", P.q(P.IMG, _GRAD, select="SELECT video_id, t, x, y, ix, iy FROM grd"))
def image_gradient(spark, d):
    return flow.gradient(_img(spark, d)).select("video_id", "t", "x", "y", "ix", "iy")


@query("brightness_residual", P.q(P.IMG.replace("img AS (", "img AS MATERIALIZED ("), select="SELECT a.video_id, a.t, a.x, a.y, a.i - b.i AS r FROM img a JOIN (SELECT video_id, t - 1 AS t, x - 1 AS x, y, i FROM img) b USING (video_id, t, x, y)"))
def brightness_residual(spark, d):
    return flow.brightness_residual(_img(spark, d), 1, 0)


@query("flow_constraint", P.q(P.IMG, _GRAD, _NEXT, select="SELECT video_id, t, x, y, ix * 0.5::DOUBLE + iy * -0.25::DOUBLE + ni - i AS r FROM nxt"))
def flow_constraint(spark, d):
    return flow.constraint_residual(_img(spark, d), 0.5, -0.25)


@query("gradient_residual", P.q(P.IMG, _GRAD, _shifted(0, 1), select="SELECT video_id, t, x, y, ix - nix AS rx, iy - niy AS ry FROM nxt"))
def gradient_residual(spark, d):
    return flow.gradient_residual(_img(spark, d), 0, 1)


@query("flow_energy", P.q(P.IMG, _GRAD, _NEXT, select="SELECT video_id, t, round(sum(sqrt((i - ni) * (i - ni) + 0.000001::DOUBLE) + sqrt((ix - nix) * (ix - nix) + (iy - niy) * (iy - niy) + 0.000001::DOUBLE)), 4) AS e_data FROM nxt GROUP BY ALL"))
def flow_energy(spark, d):
    return flow.data_energy(_img(spark, d)).withColumn("e_data", F.round("e_data", 4))


@query("flow_energy_quadratic", P.q(P.IMG, _GRAD, _NEXT, select="SELECT video_id, t, round(sum((i - ni) * (i - ni) + (ix - nix) * (ix - nix) + (iy - niy) * (iy - niy)), 4) AS e_data FROM nxt GROUP BY ALL"))
def flow_energy_quadratic(spark, d):
    return flow.data_energy(_img(spark, d), penalty="quadratic").withColumn("e_data", F.round("e_data", 4))


@query("flow_local_ls", P.q(P.IMG, _GRAD, _NEXT, _LS, select="SELECT video_id, t, x, y, round(u, 6) + 0.0 AS u, round(v, 6) + 0.0 AS v FROM ls"))
def flow_local_ls(spark, d):
    return flow.local_ls(_img(spark, d)).select("video_id", "t", "x", "y", (F.round("u", 6) + 0.0).alias("u"), (F.round("v", 6) + 0.0).alias("v"))


_DU = ", ".join(f"(coalesce(lead({c}) OVER {w}, {c}) - coalesce(lag({c}) OVER {w}, {c})) / 2 AS {c}{w}" for c in "uv" for w in "rc")


@query("flow_smoothness", P.q(P.IMG, _GRAD, _NEXT, _LS, f"gg AS (SELECT video_id, t, {_DU} FROM ls WINDOW r AS (PARTITION BY video_id, t, y ORDER BY x), c AS (PARTITION BY video_id, t, x ORDER BY y))", select="SELECT video_id, t, round(sum(sqrt(ur * ur + uc * uc + vr * vr + vc * vc + 0.000001::DOUBLE)), 4) AS e_smooth FROM gg GROUP BY ALL"))
def flow_smoothness(spark, d):
    return flow.smooth_energy(flow.local_ls(_img(spark, d))).withColumn("e_smooth", F.round("e_smooth", 4))


@query("flow_smoothness_magnitude", P.q(P.IMG, _GRAD, _NEXT, _LS, select="SELECT video_id, t, round(sum(sqrt(u * u + v * v + 0.000001::DOUBLE)), 4) AS e_smooth FROM ls GROUP BY ALL"))
def flow_smoothness_magnitude(spark, d):
    return flow.smooth_energy(flow.local_ls(_img(spark, d)), mode="magnitude").withColumn("e_smooth", F.round("e_smooth", 4))


@query(
    "flow_block_match",
    P.q(
        P.IMG,
        "shf AS (SELECT u::INT AS u, v::INT AS v FROM range(-1, 2) a(u), range(-1, 2) b(v))",
        "rsd AS (SELECT a.video_id, a.t, u, v, a.x, a.y, (a.i - b.i) * (a.i - b.i) AS r2 FROM img a, shf, img b WHERE b.video_id = a.video_id AND b.t = a.t + 1 AND b.x = a.x + u AND b.y = a.y + v)",
        "cst AS (SELECT a.video_id, a.t, a.u, a.v, a.x, a.y, sum(b.r2) / count(*) AS cost FROM rsd a JOIN rsd b ON a.video_id = b.video_id AND a.t = b.t AND a.u = b.u AND a.v = b.v AND abs(a.x - b.x) <= 1 AND abs(a.y - b.y) <= 1 GROUP BY ALL)",
        select="SELECT video_id, t, x, y, u, v, round(cost, 6) AS cost FROM cst QUALIFY row_number() OVER (PARTITION BY video_id, t, x, y ORDER BY round(cost, 6), u * u + v * v, v, u) = 1",
    ),
)
def flow_block_match(spark, d):
    return flow.block_match(_img(spark, d)).withColumn("cost", F.round("cost", 6))


_GRID = "pts AS (SELECT DISTINCT video_id, t, k::INT AS lm, [1, 4, 8][k % 3 + 1] AS lx, [1, 5, 9][k // 3 + 1] AS ly FROM img, range(9) g(k))"


@query("landmarks_grid", P.q(P.IMG, _GRID, select="SELECT video_id, t, lm, lx, ly FROM pts"))
def landmarks_grid(spark, d):
    return landmarks.grid(_img(spark, d))


@query("landmark_align", "SELECT vec_id, k::INT AS lm, round(embedding[64 - k]::DOUBLE, 6) AS value FROM embeddings, range(64) g(k)")
def landmark_align(spark, d):
    """Landmarks in another order, here the opposite one."""
    e = carriers.read(spark, d, "embeddings").select("vec_id", landmarks.align(F.col("embedding"), list(range(63, -1, -1))).alias("turned"))
    return e.select("vec_id", F.posexplode("turned").alias("lm", "value")).withColumn("value", F.round(F.col("value").cast("double"), 6))


@query("landmarks_table", P.q(P.IMG, _GRID, select="SELECT video_id, t, lm, lx::DOUBLE AS x, ly::DOUBLE AS y FROM pts"))
def landmarks_table(spark, d):
    """Landmarks that are given as a table, packed with their images."""
    tall = _img(spark, d)
    out = landmarks.from_table(carriers.img(spark, d), landmarks.grid(tall))
    return out.select("video_id", "t", F.posexplode("landmarks").alias("lm", "p")).select("video_id", "t", "lm", "p.x", "p.y")


@query("landmarks_corner")
def landmarks_corner(spark, d):
    """The nine places of each image with the largest corner response."""
    out = landmarks.detect(carriers.img(spark, d), "corner_response", 9)
    return out.select("video_id", "t", F.posexplode("landmarks").alias("lm", "p")).select("video_id", "t", "lm", "p.x", "p.y")


@query("landmark_trim", "SELECT vec_id, (k - 18)::INT AS lm, round(((embedding || embedding[1:4])[k])::DOUBLE, 6) AS value FROM embeddings, range(18, 69) g(k)")
def landmark_trim(spark, d):
    e = carriers.read(spark, d, "embeddings").select("vec_id", landmarks.trim(F.concat("embedding", F.slice("embedding", 1, 4))).alias("kept"))
    return e.select("vec_id", F.posexplode("kept").alias("lm", "value")).withColumn("value", F.round(F.col("value").cast("double"), 6))


def _pool_sql(k: int, kind: str) -> str:
    wt = {"gauss": f"exp(-ox * ox / (2 * {(k / 2) ** 2}::DOUBLE)) * exp(-oy * oy / (2 * {(k / 2) ** 2}::DOUBLE))", "box": "1.0::DOUBLE", "point": "1.0::DOUBLE"}[kind]
    r = 0 if kind == "point" else k
    return P.q(P.IMG, _GRAD, _NEXT, _LS, _GRID, f"ker AS (SELECT ox, oy, {wt} AS wt FROM range(-{r}, {r + 1}) a(ox), range(-{r}, {r + 1}) b(oy))",
               select="SELECT p.video_id, p.t, lm, round(sum(wt * u) / sum(wt), 5) + 0.0 AS dx, round(sum(wt * v) / sum(wt), 5) + 0.0 AS dy FROM pts p, ker, ls l WHERE l.video_id = p.video_id AND l.t = p.t AND l.x = lx + ox AND l.y = ly + oy GROUP BY ALL")


def _pool_query(k, kind):
    def run(spark, d):
        images = _img(spark, d)
        out = landmarks.pool(flow.local_ls(images), landmarks.grid(images), k, kind=kind)
        return out.select("video_id", "t", "lm", (F.round("dx", 5) + 0.0).alias("dx"), (F.round("dy", 5) + 0.0).alias("dy"))

    return run


query("motion_pool", _pool_sql(1, "gauss"))(_pool_query(1, "gauss"))
query("motion_pool_box", _pool_sql(1, "box"))(_pool_query(1, "box"))
query("motion_pool_point", _pool_sql(1, "point"))(_pool_query(1, "point"))


@query("flow_variational")
def flow_variational(spark, d):
    """Energies before and after minimising, one row per pair."""
    out = flow.estimate(flow.pack_pairs(carriers.img(spark, d)))
    return out.select("video_id", "t", F.round(F.element_at("energy", 1), 3).alias("e_first"), F.round(F.element_at("energy", -1), 3).alias("e_last"), "flow_error")


@query("flow_variational_brightness")
def flow_variational_brightness(spark, d):
    """The older form: squared penalty, brightness alone."""
    o = flow.FlowOptions(penalty="quadratic", terms="brightness")
    out = flow.estimate(flow.pack_pairs(carriers.img(spark, d)), o)
    return out.select("video_id", "t", F.round(F.element_at("energy", 1), 3).alias("e_first"), F.round(F.element_at("energy", -1), 3).alias("e_last"))


@query("flow_variational_gradient")
def flow_variational_gradient(spark, d):
    """Gradients alone."""
    out = flow.estimate(flow.pack_pairs(carriers.img(spark, d)), flow.FlowOptions(terms="gradient"))
    return out.select("video_id", "t", F.round(F.element_at("energy", 1), 3).alias("e_first"), F.round(F.element_at("energy", -1), 3).alias("e_last"))


@query("flow_to_groups")
def flow_to_groups(spark, d):
    """From images through variational flow and pooling to spectral groups."""
    flows = flow.estimate(flow.pack_pairs(carriers.img(spark, d)))
    g = grouping.group_pairs(landmarks.motion_of(flows))
    return g.select("video_id", "t", "k", F.round("score", 3).alias("score"), F.concat_ws("", F.transform("labels", lambda x: x.cast("string"))).alias("labels"))


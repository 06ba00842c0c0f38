"""Dense motion between two frames.

Tall images (video_id, t, x, y, i on full grids) serve the measures and the cheap estimators; packed images (video_id, t, h, w, px, px_next) serve the variational
estimator, which works on whole frames inside Arrow batches: at scale frames are never taken apart into rows.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

# ---------------------------------------------------------------- tall


def frame_pairs(df: DataFrame, stride: int = 1) -> DataFrame:
    """(video_id, t, t_next): frames that have one `stride` later; a gap gives no pair."""
    frames = df.select("video_id", "t").distinct()
    if stride == 1:
        following = F.lead("t").over(W.partitionBy("video_id").orderBy("t"))
        return frames.withColumn("t_next", following).where(F.col("t_next") == F.col("t") + 1)
    later = frames.select("video_id", (F.col("t") - stride).alias("t"), F.col("t").alias("t_next"))
    return frames.join(later, ["video_id", "t"])


def pack_pairs(images: DataFrame) -> DataFrame:
    """Packed images with px_next, the following frame; the last frame of a video, and one before a gap, has none and goes."""
    w = W.partitionBy("video_id").orderBy("t")
    out = images.withColumn("px_next", F.lead("px").over(w)).withColumn("t_next", F.lead("t").over(w))
    return out.where(F.col("t_next") == F.col("t") + 1).drop("t_next")


def gradient(df: DataFrame, value: str = "i") -> DataFrame:
    """Adds ix and iy: half the difference of both neighbours; at a border the pixel stands in for the missing one."""
    row, col = W.partitionBy("video_id", "t", "y").orderBy("x"), W.partitionBy("video_id", "t", "x").orderBy("y")
    half = lambda w: (F.coalesce(F.lead(value).over(w), F.col(value)) - F.coalesce(F.lag(value).over(w), F.col(value))) / 2
    return df.withColumn("ix", half(row)).withColumn("iy", half(col))


def with_next(df: DataFrame, *values: str, u: int | Column = 0, v: int | Column = 0) -> DataFrame:
    """Adds next_<value>: the value of the next frame at (x + u, y + v). Pixels that leave the frame go."""
    later = df.select("video_id", (F.col("t") - 1).alias("t"), F.col("x").alias("x2"), F.col("y").alias("y2"), *[F.col(c).alias(f"next_{c}") for c in values])
    at = lambda c: c if isinstance(c, Column) else F.lit(c)
    here = df.withColumn("x2", F.col("x") + at(u)).withColumn("y2", F.col("y") + at(v))
    return here.join(later, ["video_id", "t", "x2", "y2"]).drop("x2", "y2")


def brightness_residual(df: DataFrame, u: int = 0, v: int = 0) -> DataFrame:
    return with_next(df, "i", u=u, v=v).select("video_id", "t", "x", "y", (F.col("i") - F.col("next_i")).alias("r"))


def constraint_residual(df: DataFrame, u: float = 0.0, v: float = 0.0) -> DataFrame:
    """The linearised form: gradient times flow plus the change in time."""
    g = with_next(gradient(df), "i")
    return g.select("video_id", "t", "x", "y", (F.col("ix") * u + F.col("iy") * v + F.col("next_i") - F.col("i")).alias("r"))


def gradient_residual(df: DataFrame, u: int = 0, v: int = 0) -> DataFrame:
    g = with_next(gradient(df), "ix", "iy", u=u, v=v)
    return g.select("video_id", "t", "x", "y", (F.col("ix") - F.col("next_ix")).alias("rx"), (F.col("iy") - F.col("next_iy")).alias("ry"))


def psi(s2: Column, eps: float = 1e-3, penalty: str = "robust") -> Column:
    """robust: the root of s2 + eps squared, concave in s2; quadratic: s2."""
    return s2 if penalty == "quadratic" else F.sqrt(s2 + eps * eps)


def data_energy(df: DataFrame, u: int = 0, v: int = 0, eps: float = 1e-3, penalty: str = "robust") -> DataFrame:
    """(video_id, t, e_data): robust brightness and gradient residuals summed over the frame."""
    g = with_next(gradient(df), "i", "ix", "iy", u=u, v=v)
    r = F.col("i") - F.col("next_i")
    rx, ry = F.col("ix") - F.col("next_ix"), F.col("iy") - F.col("next_iy")
    return g.groupBy("video_id", "t").agg(F.sum(psi(r * r, eps, penalty) + psi(rx * rx + ry * ry, eps, penalty)).alias("e_data"))


def smooth_energy(field: DataFrame, eps: float = 1e-3, mode: str = "gradient") -> DataFrame:
    """(video_id, t, e_smooth) of a field (x, y, u, v): of its gradient, or of its magnitude."""
    if mode == "magnitude":
        s2 = F.col("u") * F.col("u") + F.col("v") * F.col("v")
        return field.groupBy("video_id", "t").agg(F.sum(psi(s2, eps)).alias("e_smooth"))
    gu = gradient(field, "u").withColumnsRenamed({"ix": "ux", "iy": "uy"})
    gv = gradient(gu, "v").withColumnsRenamed({"ix": "vx", "iy": "vy"})
    s2 = F.col("ux") * F.col("ux") + F.col("uy") * F.col("uy") + F.col("vx") * F.col("vx") + F.col("vy") * F.col("vy")
    return gv.groupBy("video_id", "t").agg(F.sum(psi(s2, eps)).alias("e_smooth"))


def local_ls(df: DataFrame, radius: int = 2, least_det: float = 1e-6) -> DataFrame:
    """(video_id, t, x, y, u, v): least squares of the linearised constraint over a box around each pixel; 0 where it has no single solution."""
    g = with_next(gradient(df), "i").withColumn("it", F.col("next_i") - F.col("i"))
    prods = {"sxx": ("ix", "ix"), "sxy": ("ix", "iy"), "syy": ("iy", "iy"), "sxt": ("ix", "it"), "syt": ("iy", "it")}
    g = g.select("video_id", "t", "x", "y", *[(F.col(a) * F.col(b)).alias(n) for n, (a, b) in prods.items()])
    row = W.partitionBy("video_id", "t", "y").orderBy("x").rangeBetween(-radius, radius)
    col = W.partitionBy("video_id", "t", "x").orderBy("y").rangeBetween(-radius, radius)
    g = g.select("video_id", "t", "x", "y", *[F.sum(n).over(row).alias(n) for n in prods])
    g = g.select("video_id", "t", "x", "y", *[F.sum(n).over(col).alias(n) for n in prods])
    det = F.col("sxx") * F.col("syy") - F.col("sxy") * F.col("sxy")
    u = (F.col("sxy") * F.col("syt") - F.col("syy") * F.col("sxt")) / F.nullif(det, F.lit(0.0))
    v = (F.col("sxy") * F.col("sxt") - F.col("sxx") * F.col("syt")) / F.nullif(det, F.lit(0.0))
    flat = F.abs(det) < least_det
    return g.select("video_id", "t", "x", "y", F.when(flat, 0.0).otherwise(u).alias("u"), F.when(flat, 0.0).otherwise(v).alias("v"))


def block_match(df: DataFrame, radius: int = 1, block: int = 1) -> DataFrame:
    """(video_id, t, x, y, u, v, cost): the whole-pixel shift with the least mean squared residual over a block; on ties the shortest, then least v, then u."""
    shifts = F.explode(F.sequence(F.lit(-radius), F.lit(radius)))
    s = df.withColumn("u", shifts).withColumn("v", F.explode(F.sequence(F.lit(-radius), F.lit(radius))))
    later = df.select("video_id", (F.col("t") - 1).alias("t"), F.col("x").alias("x2"), F.col("y").alias("y2"), F.col("i").alias("next_i"))
    s = s.withColumn("x2", F.col("x") + F.col("u")).withColumn("y2", F.col("y") + F.col("v")).join(later, ["video_id", "t", "x2", "y2"])
    s = s.select("video_id", "t", "u", "v", "x", "y", ((F.col("i") - F.col("next_i")) * (F.col("i") - F.col("next_i"))).alias("r2"))
    row = W.partitionBy("video_id", "t", "u", "v", "y").orderBy("x").rangeBetween(-block, block)
    col = W.partitionBy("video_id", "t", "u", "v", "x").orderBy("y").rangeBetween(-block, block)
    s = s.withColumns({"s": F.sum("r2").over(row), "n": F.count("*").over(row)})
    s = s.withColumn("cost", F.sum("s").over(col) / F.sum("n").over(col))
    best = F.min_by(F.struct("u", "v", "cost"), F.struct(F.round("cost", 6), F.col("u") * F.col("u") + F.col("v") * F.col("v"), "v", "u"))
    return s.groupBy("video_id", "t", "x", "y").agg(best.alias("b")).select("video_id", "t", "x", "y", "b.u", "b.v", "b.cost")


# ---------------------------------------------------------------- variational


@dataclass(frozen=True)
class FlowOptions:
    alpha: float = 2.0
    eps: float = 1e-3
    levels: int = 3
    warps: int = 3
    iters: int = 30
    penalty: str = "robust"
    terms: str = "both"  # brightness, gradient or both


def _warp(img: np.ndarray, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    h, w = img.shape
    y, x = np.mgrid[0:h, 0:w]
    px, py = np.clip(x + u, 0, w - 1), np.clip(y + v, 0, h - 1)
    x0, y0 = np.minimum(px.astype(int), max(w - 2, 0)), np.minimum(py.astype(int), max(h - 2, 0))
    fx, fy = px - x0, py - y0
    x1, y1 = np.minimum(x0 + 1, w - 1), np.minimum(y0 + 1, h - 1)
    return (img[y0, x0] * (1 - fx) + img[y0, x1] * fx) * (1 - fy) + (img[y1, x0] * (1 - fx) + img[y1, x1] * fx) * fy


def _grad(a: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    p = np.pad(a, 1, mode="edge")
    return (p[1:-1, 2:] - p[1:-1, :-2]) / 2, (p[2:, 1:-1] - p[:-2, 1:-1]) / 2


def _resize(a: np.ndarray, h: int, w: int) -> np.ndarray:
    if a.shape == (h, w):
        return a
    y = (np.arange(h) + 0.5) * a.shape[0] / h - 0.5
    x = (np.arange(w) + 0.5) * a.shape[1] / w - 0.5
    yy, xx = np.meshgrid(np.clip(y, 0, a.shape[0] - 1), np.clip(x, 0, a.shape[1] - 1), indexing="ij")
    y0, x0 = np.minimum(yy.astype(int), max(a.shape[0] - 2, 0)), np.minimum(xx.astype(int), max(a.shape[1] - 2, 0))
    y1, x1 = np.minimum(y0 + 1, a.shape[0] - 1), np.minimum(x0 + 1, a.shape[1] - 1)
    fy, fx = yy - y0, xx - x0
    return (a[y0, x0] * (1 - fx) + a[y0, x1] * fx) * (1 - fy) + (a[y1, x0] * (1 - fx) + a[y1, x1] * fx) * fy


def _psi(s2, o: FlowOptions):
    return s2 if o.penalty == "quadratic" else np.sqrt(s2 + o.eps**2)


def _slope(s2, o: FlowOptions):
    return np.ones_like(s2) if o.penalty == "quadratic" else 0.5 / np.sqrt(s2 + o.eps**2)


def energy(a: np.ndarray, b: np.ndarray, u: np.ndarray, v: np.ndarray, o: FlowOptions = FlowOptions()) -> float:
    """Data plus alpha times smoothness of one flow."""
    total = 0.0
    bw = _warp(b, u, v)
    if o.terms != "gradient":
        total += _psi((a - bw) ** 2, o).sum()
    if o.terms != "brightness":
        (ax, ay), (bx, by) = _grad(a), _grad(b)
        total += _psi((ax - _warp(bx, u, v)) ** 2 + (ay - _warp(by, u, v)) ** 2, o).sum()
    s2 = sum(g**2 for f in (u, v) for g in (np.diff(f, axis=1, append=f[:, -1:]), np.diff(f, axis=0, append=f[-1:])))
    return float(total + o.alpha * _psi(s2, o).sum())


def variational(a: np.ndarray, b: np.ndarray, o: FlowOptions = FlowOptions()) -> tuple[np.ndarray, np.ndarray, list[float]]:
    """(u, v, energies of the full size before and after each pass): from coarse to fine, the second frame is warped by the flow so far, residuals are linearised
    about it with weights from their present size, and increments are relaxed in place, even and odd pixels in turn. A pass that doesn't lower the energy is halved, then left out."""
    h, w = a.shape
    sizes = [(h, w)]
    while len(sizes) < o.levels and min(sizes[-1]) // 2 >= 6:
        sizes.append((sizes[-1][0] // 2, sizes[-1][1] // 2))
    u, v = np.zeros(sizes[-1]), np.zeros(sizes[-1])
    told: list[float] = []
    for lh, lw in reversed(sizes):
        la, lb = _resize(a, lh, lw), _resize(b, lh, lw)
        if u.shape != (lh, lw):
            su, sv = lw / u.shape[1], lh / u.shape[0]
            u, v = _resize(u, lh, lw) * su, _resize(v, lh, lw) * sv
        now = energy(la, lb, u, v, o)
        if (lh, lw) == (h, w):
            still = energy(la, lb, 0 * u, 0 * v, o)
            if still < now:
                u, v, now = 0 * u, 0 * v, still
            told.append(now)
        for _ in range(o.warps):
            du, dv = _increment(la, lb, u, v, o)
            for part in (1.0, 0.5, 0.25):
                after = energy(la, lb, u + part * du, v + part * dv, o)
                if after < now:
                    u, v, now = u + part * du, v + part * dv, after
                    break
            if (lh, lw) == (h, w):
                told.append(now)
    return u, v, told


def _increment(a, b, u, v, o: FlowOptions):
    h, w = a.shape
    channels = []
    if o.terms != "gradient":
        channels.append((a, b, 0))
    if o.terms != "brightness":
        (ax, ay), (bx, by) = _grad(a), _grad(b)
        channels += [(ax, bx, 1), (ay, by, 1)]
    made = []
    for p, q, kind in channels:
        qx, qy = _grad(q)
        made.append((kind, _warp(qx, u, v), _warp(qy, u, v), _warp(q, u, v) - p))
    sizes = {k: sum(r**2 for kind, _, _, r in made if kind == k) for k in {m[0] for m in made}}
    j11 = sum(_slope(sizes[k], o) * x * x for k, x, y, r in made)
    j12 = sum(_slope(sizes[k], o) * x * y for k, x, y, r in made)
    j22 = sum(_slope(sizes[k], o) * y * y for k, x, y, r in made)
    k1 = sum(_slope(sizes[k], o) * x * r for k, x, y, r in made)
    k2 = sum(_slope(sizes[k], o) * y * r for k, x, y, r in made)
    s2 = sum(g**2 for f in (u, v) for g in (np.diff(f, axis=1, append=f[:, -1:]), np.diff(f, axis=0, append=f[-1:])))
    g = o.alpha * _slope(s2, o)
    gx, gy = np.zeros((h, w + 1)), np.zeros((h + 1, w))
    gx[:, 1:-1], gy[1:-1] = (g[:, 1:] + g[:, :-1]) / 2, (g[1:] + g[:-1]) / 2
    total = gx[:, 1:] + gx[:, :-1] + gy[1:] + gy[:-1]
    even = np.add.outer(np.arange(h), np.arange(w)) % 2 == 0
    du, dv = np.zeros((h, w)), np.zeros((h, w))

    def around(f):
        p = np.pad(f, 1)
        return gx[:, 1:] * p[1:-1, 2:] + gx[:, :-1] * p[1:-1, :-2] + gy[1:] * p[2:, 1:-1] + gy[:-1] * p[:-2, 1:-1]

    for _ in range(o.iters):
        for side in (even, ~even):
            r1 = around(u + du) - total * u - k1 - j12 * dv
            du = np.where(side, r1 / (j11 + total + 1e-12), du)
            r2 = around(v + dv) - total * v - k2 - j12 * du
            dv = np.where(side, r2 / (j22 + total + 1e-12), dv)
    return np.clip(du, -1, 1), np.clip(dv, -1, 1)


def estimate(pairs: DataFrame, o: FlowOptions = FlowOptions()) -> DataFrame:
    """(…, u, v, energy): the variational flow of packed pairs; frames of unequal size give nulls and flow_error."""
    keep = [c for c in pairs.columns if c not in ("px", "px_next")]

    def run(batches):
        import pyarrow as pa

        for b in batches:
            hs, ws = (b.column(b.schema.get_field_index(c)).to_pylist() for c in ("h", "w"))
            us, vs, es, bad = [], [], [], []
            for p, q, h, w in zip(b.column(b.num_columns - 2).to_pylist(), b.column(b.num_columns - 1).to_pylist(), hs, ws):
                if p is None or q is None or len(p) != h * w or len(q) != h * w:
                    us.append(None), vs.append(None), es.append(None), bad.append(True)
                    continue
                u, v, e = variational(np.array(p, float).reshape(h, w), np.array(q, float).reshape(h, w), o)
                us.append(u.ravel().tolist()), vs.append(v.ravel().tolist()), es.append(e), bad.append(False)
            kind = pa.list_(pa.float64())
            yield pa.RecordBatch.from_arrays([*b.columns[:-2], pa.array(us, kind), pa.array(vs, kind), pa.array(es, kind), pa.array(bad)], names=[*keep, "u", "v", "energy", "flow_error"])

    schema = "".join(f"`{c}` {pairs.schema[c].dataType.simpleString()}, " for c in keep)
    return pairs.select(*keep, "px", "px_next").mapInArrow(run, schema + "u array<double>, v array<double>, energy array<double>, flow_error boolean")

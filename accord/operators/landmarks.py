"""Landmarks and the pooling of flow around them."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Grid landmarks of the 10 x 11 images.
GRID_X, GRID_Y = (1, 4, 8), (1, 5, 9)


def grid(df: DataFrame, xs: tuple = GRID_X, ys: tuple = GRID_Y) -> DataFrame:
    """(video_id, t, lm, lx, ly): the same places in every frame."""
    points = F.array(*[F.struct(F.lit(k).alias("lm"), F.lit(x).alias("lx"), F.lit(y).alias("ly")) for k, (y, x) in enumerate((y, x) for y in ys for x in xs)])
    return df.select("video_id", "t").distinct().select("video_id", "t", F.explode(points).alias("p")).select("video_id", "t", "p.lm", "p.lx", "p.ly")


def corner_response(px: np.ndarray, n: int) -> list[tuple[float, float]]:
    """The n places of largest corner response (determinant less a share of the squared trace), row by row on ties."""
    gy, gx = np.gradient(px)

    def box(a: np.ndarray) -> np.ndarray:
        """Sums over 3 x 3 cells; borders are repeated outwards, nothing comes in from the other side."""
        wide = np.pad(a, 1, mode="edge")
        return sum(wide[i : i + a.shape[0], j : j + a.shape[1]] for i in range(3) for j in range(3))

    xx, yy, xy = box(gx * gx), box(gy * gy), box(gx * gy)
    r = xx * yy - xy * xy - 0.05 * (xx + yy) ** 2
    order = np.argsort(-r.ravel(), kind="stable")[:n]
    return [(float(k % px.shape[1]), float(k // px.shape[1])) for k in order]


#: Detectors by name: an image and a number of points to points.
DETECTORS: dict[str, Callable] = {"corner_response": corner_response}


def from_table(images: DataFrame, points: DataFrame) -> DataFrame:
    """The table detector: landmarks that some other program has found. points (video_id, t, lm, lx, ly), sorted by lm and packed; frames without any have none."""
    packed = points.groupBy(F.col("video_id").alias("its_video"), F.col("t").alias("its_t")).agg(F.transform(F.array_sort(F.collect_list(F.struct("lm", F.col("lx").cast("double").alias("x"), F.col("ly").cast("double").alias("y")))), lambda p: F.struct(p["x"].alias("x"), p["y"].alias("y"))).alias("landmarks"))
    return images.join(packed, (F.col("video_id") == F.col("its_video")) & (F.col("t") == F.col("its_t")), "left").drop("its_video", "its_t")


def detect(images: DataFrame, detector: str | Callable, n: int) -> DataFrame:
    """Adds landmarks array<struct<x,y>> to packed images by any detector."""
    f = DETECTORS[detector] if isinstance(detector, str) else detector
    keep = [c for c in images.columns]

    def run(batches):
        import pyarrow as pa

        for b in batches:
            at = {c: b.column(b.schema.get_field_index(c)).to_pylist() for c in ("px", "h", "w")}
            found = [[{"x": x, "y": y} for x, y in f(np.array(p, float).reshape(h, w), n)] for p, h, w in zip(at["px"], at["h"], at["w"])]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(found, pa.list_(pa.struct([("x", pa.float64()), ("y", pa.float64())])))], names=[*keep, "landmarks"])

    schema = "".join(f"`{c}` {images.schema[c].dataType.simpleString()}, " for c in keep)
    return images.mapInArrow(run, schema + "landmarks array<struct<x:double,y:double>>")


def trim(points: Column, drop_first: int = 17, keep: int = 51) -> Column:
    """The last landmarks, without those of the face's outline."""
    return F.slice(points, drop_first + 1, keep)


def align(points: Column, order: list[int]) -> Column:
    """Landmarks in the given order: any order will do as long as all videos share it."""
    return F.transform(F.array(*[F.lit(i) for i in order]), lambda i: F.get(points, i))


def kernel(k_hat: int = 3, sigma: float | None = None, kind: str = "gauss") -> list[tuple[int, int, float]]:
    """(dx, dy, weight) around a landmark; weights don't add up to 1, pooling divides by those that fall inside the frame."""
    if kind == "point":
        return [(0, 0, 1.0)]
    s = k_hat / 2 if sigma is None else sigma
    one = lambda d: 1.0 if kind == "box" else math.exp(-d * d / (2 * s * s))
    return [(x, y, one(x) * one(y)) for y in range(-k_hat, k_hat + 1) for x in range(-k_hat, k_hat + 1)]


def pool(field: DataFrame, points: DataFrame, k_hat: int = 3, sigma: float | None = None, kind: str = "gauss") -> DataFrame:
    """(video_id, t, lm, dx, dy): weighted mean of the flow (x, y, u, v) around each landmark. A landmark outside the frame gives no row."""
    offsets = F.array(*[F.struct(F.lit(x).alias("ox"), F.lit(y).alias("oy"), F.lit(w).alias("wt")) for x, y, w in kernel(k_hat, sigma, kind)])
    near = points.select("video_id", "t", "lm", "lx", "ly", F.explode(offsets).alias("o"))
    near = near.select("video_id", "t", "lm", (F.round("lx") + F.col("o.ox")).cast("int").alias("x"), (F.round("ly") + F.col("o.oy")).cast("int").alias("y"), "o.wt")
    joined = near.join(field.select("video_id", "t", "x", "y", "u", "v"), ["video_id", "t", "x", "y"])
    return joined.groupBy("video_id", "t", "lm").agg((F.sum(F.col("wt") * F.col("u")) / F.sum("wt")).alias("dx"), (F.sum(F.col("wt") * F.col("v")) / F.sum("wt")).alias("dy"))


def pool_packed(u: np.ndarray, v: np.ndarray, points: list[tuple[float, float]], k_hat: int = 3, sigma: float | None = None, kind: str = "gauss") -> list[tuple[float, float] | None]:
    """The same for one packed field."""
    h, w = u.shape
    out: list[tuple[float, float] | None] = []
    for px, py in points:
        cx, cy = round(px), round(py)
        if not (0 <= cx < w and 0 <= cy < h):
            out.append(None)
            continue
        inside = [(cx + x, cy + y, wt) for x, y, wt in kernel(k_hat, sigma, kind) if 0 <= cx + x < w and 0 <= cy + y < h]
        total = sum(wt for *_, wt in inside)
        out.append((sum(wt * u[y, x] for x, y, wt in inside) / total, sum(wt * v[y, x] for x, y, wt in inside) / total))
    return out


def motion_of(flows: DataFrame, xs: tuple = GRID_X, ys: tuple = GRID_Y, k_hat: int = 1, kind: str = "gauss") -> DataFrame:
    """Packed flows (video_id, t, h, w, u, v) to packed motion at grid landmarks; pairs with a landmark outside the frame go."""
    points = [(float(x), float(y)) for y in ys for x in xs]

    def run(batches):
        import pyarrow as pa

        for b in batches:
            ids, ts, hs, ws, us, vs = (c.to_pylist() for c in b.columns)
            rows = []
            for i, t, h, w, u, v in zip(ids, ts, hs, ws, us, vs):
                if u is None:
                    continue
                m = pool_packed(np.array(u).reshape(h, w), np.array(v).reshape(h, w), points, k_hat, kind=kind)
                if all(m):
                    rows.append((i, t, [{"dx": x, "dy": y} for x, y in m]))
            cols = list(zip(*rows)) or [(), (), ()]
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.string()), pa.array(cols[1], pa.int32()), pa.array(cols[2], pa.list_(pa.struct([("dx", pa.float64()), ("dy", pa.float64())])))], names=["video_id", "t", "motion"])

    return flows.select("video_id", F.col("t").cast("int"), "h", "w", "u", "v").mapInArrow(run, "video_id string, t int, motion array<struct<dx:double,dy:double>>")

"""Degradations: codec-like quantisation and additive noise, alone and one after the other."""

from __future__ import annotations

import math
import zlib

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Grades of the experiments: quantiser and noise.
GRADES = {"raw": (None, False), "q23": (23, False), "q40": (40, False), "q23_noise": (23, True)}


def step_of(qp: int) -> float:
    """The quantiser's step doubles with every 6 of qp: about 8.98 at 23 and 64 at 40."""
    return 2.0 ** ((qp - 4) / 6)


def requantise(df: DataFrame, qp: int, unit: float = 10.0) -> DataFrame:
    """Whole-number motion_m rounded to steps of unit thousandths times the quantiser's step; running it twice changes nothing more."""
    step = int(round(step_of(qp) * unit))
    to = lambda c: (F.round(c.cast("double") / step) * step).cast("bigint")
    return df.withColumn("motion_m", F.transform("motion_m", lambda m: F.struct(to(m["x"]).alias("x"), to(m["y"]).alias("y"))))


def uniform(*key: Column, salt: int) -> Column:
    """A number in (0, 1) from a hash of the key: the same wherever and however often it is worked out."""
    at = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(salt)), *[k.cast("string") for k in key]).cast("binary")), 1, 12), 16, 10).cast("bigint")
    return (at.cast("double") + 0.5) / float(1 << 48)


def normal(*key: Column, salt: int = 0) -> tuple[Column, Column]:
    """Two independent standard normals from a hash of the key."""
    r = F.sqrt(-2 * F.log(uniform(*key, salt=2 * salt)))
    a = 2 * math.pi * uniform(*key, salt=2 * salt + 1)
    return r * F.cos(a), r * F.sin(a)


def add_noise(df: DataFrame, mu: float = 0.0, sigma: float = 1.0, seed: int = 0) -> DataFrame:
    """N(mu, sigma) noise, in thousandths, on every component of motion_m."""

    def noisy(m: Column, i: Column) -> Column:
        a, b = normal(F.col("video_id"), F.col("t"), i, salt=seed)
        moved = lambda c, z: c + F.round(1000 * (mu + sigma * F.round(z, 6))).cast("bigint")
        return F.struct(moved(m["x"], a).alias("x"), moved(m["y"], b).alias("y"))

    return df.withColumn("motion_m", F.transform("motion_m", noisy))


def add_noise_fast(df: DataFrame, sigma: float = 1.0, seed: int = 0) -> DataFrame:
    """The same by Spark's own generator: cheaper, but its numbers depend on the partitioning. On tall motion."""
    return df.withColumn("dx_m", F.col("dx_m") + F.round(1000 * sigma * F.randn(seed)).cast("bigint")).withColumn("dy_m", F.col("dy_m") + F.round(1000 * sigma * F.randn(seed + 1)).cast("bigint"))


def graded(df: DataFrame, grade: str, seed: int = 0) -> DataFrame:
    """motion_m under one of GRADES, with a column grade."""
    qp, noise = GRADES[grade]
    out = requantise(df, qp) if qp else df
    out = add_noise(out, seed=seed) if noise else out
    return out.withColumn("grade", F.lit(grade))


def _dct(n: int = 8) -> np.ndarray:
    k, x = np.arange(n)[:, None], np.arange(n)[None, :]
    m = np.sqrt(2 / n) * np.cos(np.pi * (2 * x + 1) * k / (2 * n))
    m[0] /= np.sqrt(2)
    return m


def quantised_image(px: np.ndarray, qp: int, block: int = 8) -> np.ndarray:
    """(B, h, w) images through a block transform whose coefficients are rounded to the quantiser's step; edges are mirrored to whole blocks."""
    b, h, w = px.shape
    full = np.pad(px, ((0, 0), (0, -h % block), (0, -w % block)), mode="symmetric")
    fh, fw = full.shape[1:]
    t = full.reshape(b, fh // block, block, fw // block, block).transpose(0, 1, 3, 2, 4)
    d, s = _dct(block), step_of(qp)
    back = d.T @ (np.round(d @ t @ d.T / s) * s) @ d
    return back.transpose(0, 1, 3, 2, 4).reshape(b, fh, fw)[:, :h, :w]


def _by_size(df: DataFrame, change) -> DataFrame:
    """Packed images (…, h, w, px) through a function of (stack of images, rows in the batch), a stack for each size."""
    keep = [c for c in df.columns if c != "px"]

    def run(batches):
        import pyarrow as pa

        for b in batches:
            h, w = (b.column(b.schema.get_field_index(c)).to_numpy(zero_copy_only=False).astype(int) for c in ("h", "w"))
            flat = b.column(b.num_columns - 1).flatten().to_numpy(zero_copy_only=False).astype(float)
            at = np.concatenate([[0], np.cumsum(h * w)])
            out = np.empty(at[-1])
            for size in set(zip(h.tolist(), w.tolist())):
                rows = np.nonzero((h == size[0]) & (w == size[1]))[0]
                cells = at[rows][:, None] + np.arange(size[0] * size[1])
                out[cells] = change(flat[cells].reshape(len(rows), *size), b.slice(0), rows).reshape(len(rows), -1)
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(out))], names=[*keep, "px"])

    schema = "".join(f"`{c}` {df.schema[c].dataType.simpleString()}, " for c in keep)
    return df.select(*keep, "px").mapInArrow(run, schema + "px array<double>")


def requantise_images(df: DataFrame, qp: int) -> DataFrame:
    """Packed images (…, h, w, px) through quantised_image()."""
    return _by_size(df, lambda px, batch, rows: quantised_image(px, qp))


def noisy_images(df: DataFrame, mu: float = 0.0, sigma: float = 1.0, seed: int = 0) -> DataFrame:
    """N(mu, sigma) noise on every pixel of packed images (video_id, t, h, w, px), drawn from a hash of video and frame, so it doesn't depend on the layout."""

    def change(px, batch, rows):
        names, ts = (batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("video_id", "t"))
        return px + np.stack([np.random.default_rng(zlib.crc32(f"{seed}:{names[r]}:{ts[r]}".encode())).normal(mu, sigma, px.shape[1:]) for r in rows])

    return _by_size(df, change)


def graded_images(df: DataFrame, grade: str, seed: int = 0) -> DataFrame:
    """Packed images under one of GRADES, with a column grade: the degradation before any motion is estimated."""
    qp, noise = GRADES[grade]
    out = requantise_images(df, qp) if qp else df
    out = noisy_images(out, seed=seed) if noise else out
    return out.withColumn("grade", F.lit(grade))

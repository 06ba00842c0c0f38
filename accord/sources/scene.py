"""A Python data source of planted scenes: frame pairs whose landmarks move in known groups, as a batch or a stream; and such scenes from a table of vectors."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader

SCHEMA = "video_id string, source string, y int, t int, motion array<struct<dx:double,dy:double>>, truth array<int>"


def rows_of(video: int, frames: range, landmarks: int, groups: int, noise: float, forged_share: float, seed: int):
    """Every landmark moves with its group, whose directions are far apart; in forged videos a share of the landmarks moves with another one."""
    import math

    import numpy as np

    y = int(video % 2 == 1 and forged_share > 0)
    truth = [i * groups // landmarks for i in range(landmarks)]
    for t in frames:
        rng = np.random.default_rng([seed, video, t])
        start = rng.uniform(0, 2 * math.pi)
        step = [(2 * math.cos(start + 2 * math.pi * g / groups), 2 * math.sin(start + 2 * math.pi * g / groups)) for g in range(groups)]
        own = [(g + 1) % groups if y and rng.random() < forged_share else g for g in truth]
        jitter = rng.normal(0, noise, (landmarks, 2))
        yield (f"scene-{video}", "A" if y else "R", y, t, [{"dx": step[g][0] + float(a), "dy": step[g][1] + float(b)} for g, (a, b) in zip(own, jitter)], truth)


def planted(vectors: DataFrame, landmarks: int = 51, groups: int = 4, noise: float = 0.1) -> DataFrame:
    """The same scenes from a table (vec_id, embedding, label) instead of a generator, genuine ones: each vector is a frame pair, of the video of its label. Its first two numbers
    give the direction of the first group, the others, of which 1/8 is the usual size, the jitter of the landmarks. Vectors without 64 finite numbers give nothing."""
    whole = (F.size("embedding") == 64) & F.forall("embedding", lambda x: x.isNotNull() & (F.abs(x) < math.inf))
    e = F.col("embedding")
    start = F.atan2(e[1].cast("double"), e[0].cast("double"))
    truth = F.transform(F.sequence(F.lit(0), F.lit(landmarks - 1)), lambda i: F.floor(i * groups / landmarks).cast("int"))

    def moved(g, i):
        angle = F.col("start") + 2 * math.pi * g / groups
        jitter = lambda axis: 8 * noise * F.get("embedding", ((2 * i + axis) % 62 + 2).cast("int")).cast("double")
        return F.struct((2 * F.cos(angle) + jitter(0)).alias("dx"), (2 * F.sin(angle) + jitter(1)).alias("dy"))

    rows = vectors.where(whole).withColumn("start", start).withColumn("truth", truth)
    return rows.select(F.concat_ws("-", F.lit("scene"), "label").alias("video_id"), F.lit("R").alias("source"), F.lit(0).alias("y"), F.col("vec_id").alias("t"), F.transform("truth", moved).alias("motion"), "truth")


class _Video(InputPartition):
    def __init__(self, video: int) -> None:
        super().__init__(video)


class SceneSource(DataSource):
    """Options: videos, frames, landmarks, groups, noise, forged (share of landmarks that go astray in every other video), seed."""

    @classmethod
    def name(cls) -> str:
        return "accord_scene"

    def schema(self) -> str:
        return SCHEMA

    def _options(self) -> dict:
        o = self.options
        return {"landmarks": int(o.get("landmarks", 51)), "groups": int(o.get("groups", 4)), "noise": float(o.get("noise", 0.1)), "forged_share": float(o.get("forged", 0)), "seed": int(o.get("seed", 0))}

    def reader(self, schema) -> DataSourceReader:
        return _Reader(int(self.options.get("videos", 4)), int(self.options.get("frames", 10)), self._options())

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return _Stream(int(self.options.get("videos", 4)), int(self.options.get("frames", 10)), self._options())


class _Reader(DataSourceReader):
    def __init__(self, videos: int, frames: int, options: dict) -> None:
        self.videos, self.frames, self.made = videos, frames, options

    def partitions(self) -> list:
        return [_Video(v) for v in range(self.videos)]

    def read(self, partition):
        for v, s, y, t, m, g in rows_of(partition.value, range(self.frames), **self.made):
            yield v, s, y, t, [(x["dx"], x["dy"]) for x in m], g


class _Stream(SimpleDataSourceStreamReader):
    """One frame of every video per micro-batch, until all frames are given out."""

    def __init__(self, videos: int, frames: int, options: dict) -> None:
        self.videos, self.frames, self.made = videos, frames, options

    def initialOffset(self) -> dict:
        return {"t": 0}

    def _rows(self, a: int, b: int):
        """An iterator over a list: Spark copies it, which a generator doesn't allow."""
        return iter([(*r[:4], [(x["dx"], x["dy"]) for x in r[4]], r[5]) for v in range(self.videos) for r in rows_of(v, range(a, b), **self.made)])

    def read(self, start: dict):
        end = min(self.frames, start["t"] + 1)
        return self._rows(start["t"], end), {"t": end}

    def readBetweenOffsets(self, start: dict, end: dict):
        return self._rows(start["t"], end["t"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SceneSource)

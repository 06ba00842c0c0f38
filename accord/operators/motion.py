"""Motion sets: magnitudes, the filter for weak motion and its threshold."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from accord.scratch import dropped, written

#: Bins of one pass of quantile(), whose counts the driver reads.
BINS = 4096


def magnitudes(motion: Column) -> Column:
    return F.transform(motion, lambda m: F.hypot(m["dx"], m["dy"]))


def magnitude(df: DataFrame) -> DataFrame:
    return df.withColumn("magnitude", magnitudes(F.col("motion")))


def strong(motion: Column, p: float = 0.5, tau: Column | float = 0.85, rule: str = "share") -> Column:
    """share: at least p of the vectors have magnitude tau or more; mean: the mean magnitude is tau or more."""
    tau = tau if isinstance(tau, Column) else F.lit(tau)
    size = magnitudes(motion)
    if rule == "mean":
        return F.aggregate(size, F.lit(0.0), lambda a, x: a + x) >= tau * F.size(size)
    if rule != "share":
        raise ValueError(f"unknown rule {rule!r}")
    return F.size(F.filter(size, lambda x: x >= tau)) >= p * F.size(size)


def keep_strong(df: DataFrame, p: float = 0.5, tau: float | DataFrame = 0.85, rule: str = "share") -> DataFrame:
    """Pairs with enough motion. tau may be the one-row result of calibrate(); pairs with a missing vector are dropped."""
    df = df.where(F.forall("motion", lambda m: m.isNotNull() & m["dx"].isNotNull() & m["dy"].isNotNull()))
    if isinstance(tau, DataFrame):
        one = F.broadcast(tau.select(F.col("tau").alias("its_tau")).limit(1))  # one row
        return df.crossJoin(one).where(strong(F.col("motion"), p, F.col("its_tau"), rule)).drop("its_tau")
    return df.where(strong(F.col("motion"), p, tau, rule))


def chosen_videos(df: DataFrame, n: int, seed: int = 0) -> DataFrame:
    """n videos, the first by a hash of seed and name: the same ones whatever the layout."""
    order = F.md5(F.concat(F.lit(f"{seed}:"), "video_id").cast("binary"))
    return df.select("video_id").distinct().orderBy(order, "video_id").limit(n)


def _ranked(df: DataFrame, ranks: list[int], low: float, high: float, below: int) -> dict[int, float]:
    """The values of column size, between low and high and `below` of them lower, at the ranks (from 0). Infinite ones and NaN come last, in this order."""
    at = F.floor(F.try_divide(F.col("size") - low, F.lit(high) - low) * BINS)
    bin_ = F.when(F.isnan("size"), BINS + 1).when(F.col("size") > high, BINS).otherwise(F.coalesce(F.least(at, F.lit(BINS - 1)), F.lit(0)))
    out, inside = {}, {}
    for b in sorted(df.groupBy(bin_.alias("bin")).agg(F.count("*").alias("n"), F.min("size").alias("low"), F.max("size").alias("high")).collect()):  # BINS + 2 rows at most
        for r in ranks:
            if below <= r < below + b.n:
                if b.bin >= BINS or b.low == b.high:
                    out[r] = b.low
                else:
                    inside.setdefault((b.low, b.high, below), []).append(r)
        below += b.n
    for (low, high, under), its in inside.items():
        out |= _ranked(df.where(F.col("size").between(low, high)), its, low, high, under)
    return out


def quantile(df: DataFrame, p: float) -> float | None:
    """What F.percentile gives for column size, from counts in bins that get finer around it: F.percentile brings all distinct values to one task."""
    df = df.where("size IS NOT NULL")
    finite = F.when(F.abs("size") < math.inf, F.col("size"))
    n, low, high = df.agg(F.count("*"), F.min(finite), F.max(finite)).first()
    if not n:
        return None
    place = (n - 1) * p
    under, over = math.floor(place), math.ceil(place)
    v = _ranked(df, sorted({under, over}), low or 0.0, high or 0.0, 0)
    return v[under] if v[under] == v[over] else (over - place) * v[under] + (place - under) * v[over]


def calibrate(df: DataFrame, p: float = 0.5, sample_videos: int = 100, seed: int = 0, exact: bool = True) -> DataFrame:
    """One row (tau): the quantile p of magnitudes over a sample of videos. Magnitudes are worked out once and written."""
    sizes = written(df.select("video_id", magnitudes(F.col("motion")).alias("sizes")), "sizes")
    sample = sizes.join(chosen_videos(sizes, sample_videos, seed), "video_id", "left_semi").select(F.explode("sizes").alias("size"))
    if not exact:
        return sample.agg(F.percentile_approx("size", F.lit(p)).alias("tau"))
    sample = written(sample, "sample")
    dropped(sizes)
    tau = quantile(sample, p)
    dropped(sample)
    return df.sparkSession.createDataFrame([(tau,)], "tau double")


def filter_report(df: DataFrame, p: float = 0.5, tau: float = 0.85, rule: str = "share") -> DataFrame:
    return df.groupBy("source").agg(F.count("*").alias("n_pairs"), F.sum(strong(F.col("motion"), p, tau, rule).cast("bigint")).alias("n_kept"))

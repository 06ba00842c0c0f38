"""Deterministic choices: pairs per pattern, sets of patterns, and splits in which no video is on both sides."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W


def order_of(*columns: str, seed: int = 0) -> Column:
    return F.md5(F.concat_ws(":", F.lit(str(seed)), *[F.col(c).cast("string") for c in columns]).cast("binary"))


def ranked(df: DataFrame, pool: str = "video_id", seed: int = 0) -> DataFrame:
    """pick: the pair's place, from 1, in the hash order of its pool. The picks of a smaller N are among those of a larger one."""
    w = W.partitionBy(pool).orderBy("pick_order", "video_id", "t")
    return df.withColumn("pick_order", order_of("video_id", "t", seed=seed)).withColumn("pick", F.row_number().over(w)).drop("pick_order")


def pick_n(df: DataFrame, n: int, pool: str = "video_id", seed: int = 0, short: str = "keep") -> DataFrame:
    """n pairs of each pool; pools with fewer are kept or dropped."""
    out = ranked(df, pool, seed)
    if short == "drop":
        out = out.withColumn("in_pool", F.count("*").over(W.partitionBy(pool))).where(F.col("in_pool") >= n).drop("in_pool")
    return out.where(F.col("pick") <= n)


def pattern_sets(df: DataFrame, m: int, n: int, pool: str = "source", seed: int = 0, share: str | None = None) -> DataFrame:
    """m sets of n pairs for each pool, drawn one by one: pattern_id and draw join the columns of df. share: the m sets are shared out among the pools with one value of it.

    Draw k of a set takes the pair whose place in the pool's hash order is another hash of the set and k, so a set needs no sort of its own.
    """
    placed = ranked(df, pool, seed)
    keys = [F.col(pool).alias("its_pool")] if share is None else [F.col(pool).alias("its_pool"), F.col(share).alias("its_share")]
    sizes = placed.groupBy(*keys).agg(F.max("pick").alias("size"))  # a row for each pool
    if share is None:
        sizes = sizes.withColumn("its_sets", F.lit(m))
    else:
        among = W.partitionBy("its_share")
        place, count = F.row_number().over(among.orderBy("its_pool")) - 1, F.count("*").over(among)
        sizes = sizes.withColumn("its_sets", (F.floor(m / count) + (place < m % count).cast("int")).cast("int")).where("its_sets > 0")
    draws = sizes.select("its_pool", "size", F.explode(F.sequence(F.lit(0), F.col("its_sets") - 1)).alias("pattern_id")).withColumn("draw", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    at = F.conv(F.substring(order_of("its_pool", "pattern_id", "draw", seed=seed + 1), 1, 12), 16, 10).cast("bigint")
    draws = draws.withColumn("its_pick", (at % F.col("size") + 1).cast("int")).select("its_pool", "pattern_id", "draw", "its_pick")
    return draws.join(placed, (F.col(pool) == F.col("its_pool")) & (F.col("pick") == F.col("its_pick"))).drop("its_pool", "its_pick", "pick")


def split(df: DataFrame, share: float = 0.5, seed: int = 0, by: str = "video_id") -> DataFrame:
    """train: whether the row's video falls in the first share of a hash."""
    at = F.conv(F.substring(order_of(by, seed=seed), 1, 8), 16, 10).cast("bigint")
    return df.withColumn("train", at < int(share * (1 << 32)))

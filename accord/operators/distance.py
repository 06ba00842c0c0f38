"""Distances between patterns over their strict lower triangles."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _sum(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x)


def kl(p: Column, q: Column, base: float = math.e) -> Column:
    """Directed divergence of arrays: 0 log 0 is 0; null where p has weight and q has none."""
    term = lambda x, y: F.when(x == 0, 0.0).when(y == 0, None).otherwise(x * F.log(x / y))
    return _sum(F.zip_with(p, q, term)) / math.log(base)


def js_term(x: Column, y: Column) -> Column:
    half = (x + y) / 2
    part = lambda v: F.when(v > 0, v * F.log(v / half)).otherwise(0.0)
    return (part(x) + part(y)) / 2


def js(p: Column, q: Column, base: float = math.e) -> Column:
    return _sum(F.zip_with(p, q, js_term)) / math.log(base)


def js_root(p: Column, q: Column) -> Column:
    return F.sqrt(F.greatest(js(p, q), F.lit(0.0)))


def manhattan(p: Column, q: Column) -> Column:
    return _sum(F.zip_with(p, q, lambda x, y: F.abs(x - y)))


def euclid(p: Column, q: Column) -> Column:
    return F.sqrt(_sum(F.zip_with(p, q, lambda x, y: (x - y) * (x - y))))


def cosine(p: Column, q: Column) -> Column:
    dot = lambda a, b: _sum(F.zip_with(a, b, lambda x, y: x * y))
    return F.lit(1.0) - F.try_divide(dot(p, q), F.sqrt(dot(p, p)) * F.sqrt(dot(q, q)))


METRICS = {"js": js, "js_root": js_root, "kl": kl, "l1": manhattan, "l2": euclid, "cosine": cosine}


def triangle(tri: Column) -> Column:
    """The triangle as a distribution: its cells over their sum."""
    return F.transform(tri, lambda x: F.try_divide(x, _sum(tri)))


def tall_js(a: DataFrame, b: DataFrame, by: list[str], p: str = "p") -> DataFrame:
    """(by, d): Jensen-Shannon of each tall pattern of a against the one pattern b; cells that either lacks are 0."""
    return tall_terms(a, b, by, p).groupBy(*by).agg(F.sum("term").alias("d"))


def tall_terms(a: DataFrame, b: DataFrame, by: list[str], p: str = "p") -> DataFrame:
    """(by, i, j, pa, pb, term) over the cells of each pattern of a and of b."""
    keys = a.select(*by).distinct()
    one = F.broadcast(b.select("i", "j", F.col(p).alias("pb")))  # one pattern: n * (n - 1) / 2 rows at most
    cells = keys.crossJoin(one).select(*by, "i", "j", "pb")
    both = a.select(*by, "i", "j", F.col(p).alias("pa")).join(cells, [*by, "i", "j"], "full")
    both = both.select(*by, "i", "j", F.coalesce("pa", F.lit(0.0)).alias("pa"), F.coalesce("pb", F.lit(0.0)).alias("pb"))
    return both.withColumn("term", js_term(F.col("pa"), F.col("pb")))

"""Connected components by alternating large and small stars: rounds grow with the logarithm of the number of nodes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from accord.llm.common import dropped, written


def _sum(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first())


def _pull(edges: DataFrame) -> DataFrame:
    """(u, v) to (v, least neighbour of u). Both sides of the join are exchanged, so that a node with very many links can be split."""
    least = edges.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("m"))
    return edges.join(least, "u").select("u", "v", "m")


def connected_components(links: DataFrame, a: str = "a", b: str = "b", most_rounds: int = 64) -> DataFrame:
    """(node, root) for each node that has a link to another one; root is the least node of its component.

    links: pairs of bigint; order, repeats and links of a node to itself don't matter; a null end links nothing.
    Nodes without links have no row. Each round is written to the shared folder and the round before it removed.
    """
    x, y = F.col(a), F.col(b)
    edges = written(links.where(x != y).select(F.greatest(x, y).alias("u"), F.least(x, y).alias("v")).distinct(), "links")
    seen = _sum(edges)
    if not seen[0]:
        return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
    for _ in range(most_rounds):
        both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _pull(both).where((F.col("v") > F.col("u")) & (F.col("v") != F.col("m"))).select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        pulled = _pull(large)
        small = pulled.where(F.col("v") != F.col("m")).select(F.col("v").alias("u"), F.col("m").alias("v")).union(pulled.select("u", F.col("m").alias("v"))).distinct()
        after = written(small, "links")
        now = _sum(after)
        dropped(edges)
        edges = after
        if now == seen:
            roots = edges.select("v").distinct().select(F.col("v").alias("node"), F.col("v").alias("root"))
            return edges.select(F.col("u").alias("node"), F.col("v").alias("root")).union(roots)
        seen = now
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")

"""Reading patterns: mean agreement, structure of facial components, convergence, distances between sources, and the cells that differ most."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from accord.operators import distance, pattern, sampling
from accord.sources.carriers import LANDMARKS, component_of


def agreement_counts(groups: DataFrame, n: int = 1000, seed: int = 0) -> DataFrame:
    """(source, i, j, w, n_pairs): in how many of n pairs of each source i and j agree."""
    some = sampling.pick_n(groups, n, "source", seed).withColumn("one", F.lit(1))
    size = some.groupBy("source").agg(F.count("*").alias("n_pairs"))
    cells = pattern.build_tall(some, ["source"], "one")
    grid = size.crossJoin(_grid(groups))
    return grid.join(cells, ["source", "i", "j"], "left").select("source", "i", "j", F.coalesce("w", F.lit(0)).cast("bigint").alias("w"), "n_pairs")


def mean_agreement(groups: DataFrame, n: int = 1000, seed: int = 0) -> DataFrame:
    """(source, i, j, mean): mean of the 0/1 matrices of n pairs of each source, without weights."""
    return agreement_counts(groups, n, seed).select("source", "i", "j", (F.col("w").cast("double") / F.col("n_pairs")).alias("mean"))


def _grid(df: DataFrame) -> DataFrame:
    """(i, j), i > j: a table of a fixed size."""
    at = df.sparkSession.range(LANDMARKS).select(F.col("id").cast("int").alias("i"))
    return F.broadcast(at.where("i > 0").select("i", F.explode(F.sequence(F.lit(0), F.col("i") - 1)).alias("j")))


def _component(c: str):
    return F.element_at(F.array(*[F.lit(component_of(i)) for i in range(LANDMARKS)]), F.col(c) + 1)


def component_matrix(counts: DataFrame) -> DataFrame:
    """(source, a, b, mean): mean agreement between and within facial components, from agreement_counts(). Whole numbers are added up and divided once, so that
    the order of the cells can't decide which way a mean is rounded that lies just between two."""
    a, b = F.greatest(_component("i"), _component("j")), F.least(_component("i"), _component("j"))
    rows = counts.select("source", a.alias("a"), b.alias("b"), "w", "n_pairs")
    return rows.groupBy("source", "a", "b").agg((F.sum("w").cast("double") / F.sum("n_pairs")).alias("mean"))


def structure_checks(mean: DataFrame) -> DataFrame:
    """Per source: agreement of the eyes, of the first 31 landmarks, of brows with eyes, and lips' opposition: agreement within less that between upper and lower lip."""
    ci, cj = _component("i"), _component("j")
    between = lambda x, y: F.avg(F.when((ci.isin(x) & cj.isin(y)) | (ci.isin(y) & cj.isin(x)), F.col("mean")))
    lips = F.avg(F.when((ci == cj) & ci.isin([6, 7]), F.col("mean"))) - between([6], [7])
    return mean.groupBy("source").agg(between([4], [5]).alias("eyes"), F.avg(F.when(F.col("i") < 31, F.col("mean"))).alias("upper_face"), between([0, 1], [4, 5]).alias("brow_eye"), lips.alias("lip_opposition"))


def source_distance(patterns: DataFrame) -> DataFrame:
    """(a, b, d): Jensen-Shannon between the tall patterns of all pairs of sources, a < b; there are few sources."""
    names = patterns.select("source").distinct()
    p = patterns.select("source", "i", "j", "p")
    two = names.select(F.col("source").alias("a")).join(names.select(F.col("source").alias("b")), F.col("a") < F.col("b"))
    cells = two.crossJoin(_grid(patterns))
    both = cells.join(p.select(F.col("source").alias("a"), "i", "j", F.col("p").alias("pa")), ["a", "i", "j"], "left").join(p.select(F.col("source").alias("b"), "i", "j", F.col("p").alias("pb")), ["b", "i", "j"], "left")
    term = distance.js_term(F.coalesce("pa", F.lit(0.0)), F.coalesce("pb", F.lit(0.0)))
    return both.groupBy("a", "b").agg(F.sum(term).alias("d"))


def convergence(groups: DataFrame, by: list[str], ns: tuple = (1, 10, 35, 70)) -> DataFrame:
    """(by, n_pick, d): distance of the pattern of the first n picks to that of all. Cells are summed once, by the least N that a pick is in, and then added up."""
    step = F.when(F.col("pick") <= ns[0], ns[0])
    for n in ns[1:]:
        step = step.when(F.col("pick") <= n, n)
    bands = groups.withColumn("band", step.otherwise(2**31 - 1))
    cells, sums = pattern.build_tall(bands, [*by, "band"]), pattern.totals(bands, [*by, "band"])
    full = pattern.l1_tall(cells.groupBy(*by, "i", "j").agg(F.sum("w").alias("w")), sums.groupBy(*by).agg(F.sum("w_sum").alias("w_sum"), F.max("n").alias("n")), by)
    grow = F.explode(F.array(*[F.lit(n) for n in ns]))
    upto = lambda df: df.withColumn("n_pick", grow).where("band <= n_pick")
    keys = [*by, "n_pick"]
    part = pattern.l1_tall(upto(cells).groupBy(*keys, "i", "j").agg(F.sum("w").alias("w")), upto(sums).groupBy(*keys).agg(F.sum("w_sum").alias("w_sum"), F.max("n").alias("n")), keys)
    each = upto(sums).select(*keys).distinct().crossJoin(_grid(groups))
    both = each.join(part.select(*keys, "i", "j", F.col("p").alias("pa")), [*keys, "i", "j"], "left").join(full.select(*by, "i", "j", F.col("p").alias("pb")), [*by, "i", "j"], "left")
    return both.groupBy(*keys).agg(F.sum(distance.js_term(F.coalesce("pa", F.lit(0.0)), F.coalesce("pb", F.lit(0.0)))).alias("d"))


def top_cells(terms: DataFrame, by: list[str], k: int = 10) -> DataFrame:
    """(by, place, i, j, term): the k landmark pairs that add most to each pattern's distance."""
    w = W.partitionBy(*by).orderBy(F.desc(F.round("term", 9)), "i", "j")
    return terms.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k).select(*by, "place", "i", "j", "term")


def signed_view(mean: DataFrame) -> DataFrame:
    """mean less the source's mean over all cells: below 0 where landmarks agree less than usual."""
    return mean.withColumn("signed", F.col("mean") - F.avg("mean").over(W.partitionBy("source")))


"""Accuracy, ROC and AUC, confusion, equal error rate and agreement with planted groups."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W


#: Bins of scores that one task runs through for a curve.
BINS = 4096


def accuracy(df: DataFrame, *by: str) -> DataFrame:
    return df.groupBy(*by).agg(F.count("*").alias("n"), F.round(F.avg((F.col("pred") == F.col("y")).cast("double")), 6).alias("accuracy"))


def _counts(df: DataFrame, by: tuple[str, ...]) -> DataFrame:
    """(by, d, pos, neg): rows per distinct score, so that the window below sees scores, not rows."""
    return df.groupBy(*by, "d").agg(F.sum(F.col("y").cast("bigint")).alias("pos"), F.sum((1 - F.col("y")).cast("bigint")).alias("neg"))


def _placed(df: DataFrame, by: tuple[str, ...]) -> tuple[DataFrame, W]:
    """_counts() with bin, the rows of both classes in lower bins (lower_pos, lower_neg) and in all (all_pos, all_neg); and the bin's window by score.

    Scores fall into BINS bins of equal width first. Only bins are run through in one task; scores are ordered within their bin, so the result is exact."""
    c = _counts(df, by)
    ends = F.broadcast(c.agg(F.min("d").alias("low_d"), F.max("d").alias("high_d")))  # one row
    at = F.floor(F.try_divide(F.col("d") - F.col("low_d"), F.col("high_d") - F.col("low_d")) * BINS)
    c = c.crossJoin(ends).withColumn("bin", F.coalesce(F.least(at, F.lit(BINS - 1)), F.lit(0))).drop("low_d", "high_d")
    per = c.groupBy(*by, "bin").agg(F.sum("pos").alias("p"), F.sum("neg").alias("n"))
    lower, whole = W.partitionBy(*by).orderBy("bin").rowsBetween(W.unboundedPreceding, -1), W.partitionBy(*by)
    zero = lambda x: F.coalesce(x, F.lit(0))
    per = per.select(*by, "bin", zero(F.sum("p").over(lower)).alias("lower_pos"), zero(F.sum("n").over(lower)).alias("lower_neg"), F.sum("p").over(whole).alias("all_pos"), F.sum("n").over(whole).alias("all_neg"))
    return c.join(per, [*by, "bin"]), W.partitionBy(*by, "bin").orderBy("d").rowsBetween(W.unboundedPreceding, -1)


def roc(df: DataFrame, *by: str) -> DataFrame:
    """(by, d, fpr, tpr) when rows with a score of d or more are called forged; rows of equal score are called together."""
    c, under = _placed(df, by)
    over = lambda x: F.col(f"all_{x}") - F.col(f"lower_{x}") - F.coalesce(F.sum(x).over(under), F.lit(0))
    return c.select(*by, "d", F.try_divide(over("neg"), F.col("all_neg")).alias("fpr"), F.try_divide(over("pos"), F.col("all_pos")).alias("tpr"))


def auc(df: DataFrame, *by: str) -> DataFrame:
    """(by, auc): share of (forged, genuine) pairs in which the forged one has the larger score, ties a half. Null for a single class."""
    c, under = _placed(df, by)
    c = c.withColumn("under", F.col("lower_neg") + F.coalesce(F.sum("neg").over(under), F.lit(0)))
    return c.groupBy(*by).agg(F.round(F.try_divide(F.sum(F.col("pos") * (2 * F.col("under") + F.col("neg"))).cast("double"), (2 * F.sum("pos") * F.sum("neg")).cast("double")), 6).alias("auc"))


def auc_trapezoid(curve: DataFrame, *by: str) -> DataFrame:
    """The area under roc() by trapezoids."""
    w = W.partitionBy(*by).orderBy(F.desc("d"))
    step = (F.col("fpr") - F.coalesce(F.lag("fpr").over(w), F.lit(0.0))) * (F.col("tpr") + F.coalesce(F.lag("tpr").over(w), F.lit(0.0))) / 2
    return curve.withColumn("area", step).groupBy(*by).agg(F.round(F.sum("area"), 6).alias("auc"))


def confusion(df: DataFrame, threshold: float, *by: str) -> DataFrame:
    """Counts and rates when scores of threshold or more are called forged."""
    said = F.col("d") >= threshold
    n = lambda c: F.sum(c.cast("bigint"))
    out = df.groupBy(*by).agg(n(said & (F.col("y") == 1)).alias("tp"), n(said & (F.col("y") == 0)).alias("fp"), n(~said & (F.col("y") == 0)).alias("tn"), n(~said & (F.col("y") == 1)).alias("fn"))
    return out.withColumn("tpr", F.round(F.try_divide("tp", F.col("tp") + F.col("fn")), 6)).withColumn("fpr", F.round(F.try_divide("fp", F.col("fp") + F.col("tn")), 6))


def equal_error(curve: DataFrame, *by: str) -> DataFrame:
    """(by, eer): the mean of false alarms and misses where they are nearest to each other."""
    gap = F.abs(F.col("fpr") - (1 - F.col("tpr")))
    return curve.groupBy(*by).agg(F.round(F.min_by((F.col("fpr") + 1 - F.col("tpr")) / 2, F.struct(F.round(gap, 9), "d")), 6).alias("eer"))


def rand_index(df: DataFrame, truth: list[int], *by: str) -> DataFrame:
    """(by, rand): mean share of landmark pairs on which labels and the true groups agree."""
    n = len(truth)
    true = F.array(*[F.lit(x) for x in truth])
    rows = F.flatten(F.transform(F.sequence(F.lit(1), F.lit(n - 1)), lambda i: F.transform(F.sequence(F.lit(0), i - 1), lambda j: ((F.get("labels", i) == F.get("labels", j)) == (F.get(true, i) == F.get(true, j))).cast("int"))))
    hits = F.aggregate(rows, F.lit(0), lambda a, x: a + x)
    return df.withColumn("hits", hits).groupBy(*by).agg(F.count("*").alias("n_pairs"), F.round(F.avg(F.col("hits") / (n * (n - 1) / 2)), 6).alias("rand"))


def delta(df: DataFrame, base: str, value: str = "accuracy") -> DataFrame:
    """value of each grade, and its loss against the grade base."""
    first = df.where(F.col("grade") == base).select(F.col(value).alias("first"))
    return df.crossJoin(F.broadcast(first.limit(1))).withColumn("loss", F.round(F.col("first") - F.col(value), 6)).drop("first")  # one row

"""One-class detection: a template of genuine pairs, distances of patterns to it, and decisions."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from accord.operators import distance, pattern
from accord.operators.sampling import order_of


def template_pairs(groups: DataFrame, n_pairs: int = 3000, source: str = "R", seed: int = 0) -> DataFrame:
    """The template's pairs: the first n_pairs of the source in hash order, whatever the layout."""
    return groups.where(F.col("source") == source).orderBy(order_of("video_id", "t", seed=seed), "video_id", "t").limit(n_pairs)


def template(groups: DataFrame, n_pairs: int = 3000, source: str = "R", w: str = "w", seed: int = 0, normalise: bool = True) -> DataFrame:
    """One packed pattern."""
    one = pattern.build(template_pairs(groups, n_pairs, source, seed).withColumn("template", F.lit(source)), ["template"], w)
    return pattern.l1(one) if normalise else one


def score(patterns: DataFrame, template_row: DataFrame, metric: str = "js", normalise: bool = True, triangle: bool = False) -> DataFrame:
    """d: the distance of each packed pattern to the template, a single row that is broadcast."""
    p = pattern.l1(patterns) if normalise else patterns
    one = F.broadcast(template_row.select(F.col("tri").alias("template_tri")).limit(1))  # one row of n * (n - 1) / 2 numbers
    p = p.crossJoin(one)
    if triangle:
        p = p.withColumn("tri", distance.triangle(F.col("tri"))).withColumn("template_tri", distance.triangle(F.col("template_tri")))
    return p.withColumn("d", distance.METRICS[metric](F.col("tri"), F.col("template_tri"))).drop("template_tri")


def score_packed(patterns: DataFrame, template_row: DataFrame) -> DataFrame:
    """score() by Jensen-Shannon in Arrow batches, for packed patterns that are normalised already: many patterns, one template of a fixed size."""
    one = template_row.select("tri").first()  # n * (n - 1) / 2 numbers
    if one is None:
        return patterns.where("false").withColumn("d", F.lit(0.0))
    q = np.array(one.tri, float)
    keep = [c for c in patterns.columns if c != "tri"]

    def run(batches):
        import pyarrow as pa

        for b in batches:
            p = b.column(b.num_columns - 1).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1) if b.num_rows else np.zeros((0, len(q)))
            half = (p + q) / 2
            with np.errstate(divide="ignore", invalid="ignore"):
                left = np.where(p > 0, p * np.log(p / half), 0.0)
                right = np.where(q > 0, q * np.log(q / half), 0.0)
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array((left + right).sum(axis=1) / 2)], names=[*keep, "d"])

    schema = "".join(f"`{c}` {patterns.schema[c].dataType.simpleString()}, " for c in keep)
    return patterns.select(*keep, "tri").mapInArrow(run, schema + "d double")


def threshold(scores: DataFrame, how: str | float = "youden", alpha: float = 0.05) -> float:
    """youden: the score with the largest gap between hits and false alarms; quantile: what 1 - alpha of genuine scores stay under; or a number."""
    from accord.operators import metrics

    if not isinstance(how, str):
        return float(how)
    if how == "quantile":
        return scores.where("y = 0").agg(F.percentile("d", F.lit(1 - alpha))).first()[0]
    return metrics.roc(scores).agg(F.max_by("d", F.struct(F.round(F.col("tpr") - F.col("fpr"), 9), "d"))).first()[0]


def decide(scores: DataFrame, at: float) -> DataFrame:
    return scores.withColumn("pred", (F.col("d") >= at).cast("int"))

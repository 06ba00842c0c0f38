"""SQL functions of the method, inlined by Catalyst, and table functions over patterns."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

#: Bodies are single expressions over arrays; temporary functions of a session.
FUNCTIONS = {
    "js_divergence": ("p ARRAY<DOUBLE>, q ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(p, q, (x, y) -> CASE WHEN x > 0 THEN x * ln(x / ((x + y) / 2)) ELSE 0D END + CASE WHEN y > 0 THEN y * ln(y / ((x + y) / 2)) ELSE 0D END), 0D, (s, v) -> s + v) / 2"),
    "kl_divergence": ("p ARRAY<DOUBLE>, q ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(p, q, (x, y) -> CASE WHEN x = 0 THEN 0D WHEN y = 0 THEN NULL ELSE x * ln(x / y) END), 0D, (s, v) -> s + v)"),
    "l1_scaled": ("p ARRAY<DOUBLE>", "ARRAY<DOUBLE>", "transform(p, x -> try_divide(x, aggregate(p, 0D, (s, v) -> s + abs(v))))"),
    "agreement": ("labels ARRAY<INT>", "ARRAY<INT>", "flatten(transform(sequence(1, size(labels) - 1), i -> transform(sequence(0, i - 1), j -> CAST(labels[i] = labels[j] AS INT))))"),
    "strong_share": ("motion ARRAY<STRUCT<dx: DOUBLE, dy: DOUBLE>>, tau DOUBLE", "DOUBLE", "try_divide(size(filter(motion, m -> hypot(m.dx, m.dy) >= tau)), size(motion))"),
}


def register(spark: SparkSession) -> None:
    for name, (args, kind, body) in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
    spark.udtf.register("explode_pattern", explode_pattern)
    spark.udtf.register("roc_points", roc_points)


@udtf(returnType="i int, j int, w double")
class explode_pattern:  # noqa: N801
    """The cells of a packed pattern: (i, j, w), i > j."""

    def eval(self, tri: list, n: int):
        k = 0
        for i in range(1, n):
            for j in range(i):
                yield i, j, tri[k]
                k += 1


@udtf(returnType="d double, fpr double, tpr double")
class roc_points:  # noqa: N801
    """ROC points of one small list of scores and truths."""

    def eval(self, scores: list, truth: list):
        pos, neg = sum(truth), len(truth) - sum(truth)
        if not pos or not neg:
            return
        tp = fp = 0
        rows = sorted(zip(scores, truth), reverse=True)
        for k, (d, y) in enumerate(rows):
            tp, fp = tp + y, fp + 1 - y
            if k + 1 == len(rows) or rows[k + 1][0] != d:
                yield d, fp / neg, tp / pos

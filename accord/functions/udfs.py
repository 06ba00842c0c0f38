"""Arrow functions for use in SELECT and GROUP BY."""

from __future__ import annotations

import pandas as pd
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, StructField, StructType

from accord.operators import grouping


#: Types are given as objects: the module is imported before there is a session.
GROUPS = StructType([StructField("labels", ArrayType(IntegerType())), StructField("k", IntegerType()), StructField("score", DoubleType())])


@pandas_udf(GROUPS)
def group_motion(dx: pd.Series, dy: pd.Series) -> pd.DataFrame:
    """Spectral groups of arrays dx and dy, row by row of one batch at once per length."""
    import numpy as np

    out: list = [None] * len(dx)
    sizes = dx.map(len)
    for n in sorted(set(sizes)):
        rows = [i for i, s in enumerate(sizes) if s == n]
        if n < 3:
            for i in rows:
                out[i] = {"labels": [], "k": 0, "score": 0.0}
            continue
        m = np.stack([np.stack([np.asarray(dx.iloc[i], float), np.asarray(dy.iloc[i], float)], 1) for i in rows])
        got = grouping.group_batch(m)
        for p, i in enumerate(rows):
            out[i] = {"labels": got["labels"][p].tolist(), "k": int(got["k"][p]), "score": float(got["score"][p])}
    return pd.DataFrame(out)


@pandas_udf(ArrayType(DoubleType()))
def pattern_agg(labels: pd.Series, w: pd.Series) -> list:
    """Grouped aggregate: the weighted sum of agreement over a group's pairs, strict lower triangle. For groups of bounded size; pattern.build() has no such bound."""
    import numpy as np

    total = None
    for lab, weight in zip(labels, w):
        lab = np.asarray(lab)
        one = weight * (lab[:, None] == lab[None, :])[np.tril_indices(len(lab), -1)]
        total = one if total is None else total + one
    return [] if total is None else total.tolist()

"""Agreement matrices and their weighted sums, the patterns.

labels stand for a pair's agreement matrix until it is summed: two landmarks agree if their labels are equal. A pattern has the strict lower triangle only; every
diagonal cell equals the sum of weights. Tall form: key columns, i, j (i > j), w. Packed form: key columns, tri array<double> in the order
(1,0),(2,0),(2,1),…, diag, n_pairs, n (landmarks).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W


def agreement(df: DataFrame, *keep: str) -> DataFrame:
    """(keep, i, j, rho) of each pair's strict lower triangle."""
    cells = df.select(*keep, "labels", F.posexplode("labels").alias("i", "own")).where("i > 0")
    return cells.select(*keep, "i", "own", F.posexplode(F.slice("labels", 1, F.col("i"))).alias("j", "other")).select(*keep, "i", "j", (F.col("own") == F.col("other")).cast("int").alias("rho"))


def agreement_rows(df: DataFrame, *keep: str) -> DataFrame:
    """(keep, i, cells): the same, a row of the triangle as array<int>, without a row for each cell."""
    rows = df.select(*keep, "labels", F.posexplode("labels").alias("i", "own")).where("i > 0")
    return rows.select(*keep, "i", F.transform(F.slice("labels", 1, F.col("i")), lambda x: (x == F.col("own")).cast("int")).alias("cells"))


def weight(mode: str = "k_score", cap: float | Column | None = None) -> Column:
    """The weight of a pair from its columns k and score: k_score, score, k or none; scores over cap count as cap."""
    score = F.col("score") if cap is None else F.least("score", cap if isinstance(cap, Column) else F.lit(cap))
    return {"k_score": F.col("k") * score, "score": score, "k": F.col("k").cast("double"), "none": F.lit(1.0)}[mode]


def milli_weight(w: Column) -> Column:
    """A weight in whole thousandths, so that sums don't depend on their order."""
    return F.round(1000 * w).cast("bigint")


def build_tall(df: DataFrame, by: list[str], w: str = "w") -> DataFrame:
    """(by, i, j, w): sums of weights over the pairs in which i and j agree. Cells without agreement have no row."""
    cells = df.select(*by, w, "labels", F.posexplode("labels").alias("i", "own")).where("i > 0")
    other = F.filter(F.sequence(F.lit(0), F.col("i") - 1), lambda j: F.get("labels", j) == F.col("own"))
    return cells.select(*by, w, "i", F.explode(other).alias("j")).groupBy(*by, "i", "j").agg(F.sum(w).alias("w"))


def totals(df: DataFrame, by: list[str], w: str = "w") -> DataFrame:
    return df.groupBy(*by).agg(F.sum(w).alias("w_sum"), F.count("*").alias("n_pairs"), F.max(F.size("labels")).alias("n"))


def build(df: DataFrame, by: list[str], w: str = "w") -> DataFrame:
    """Packed patterns in two steps: sums per key within each batch of pairs, then one row per key and batch is dealt and added up."""
    names = [*by, "tri", "diag", "n_pairs", "n"]

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            keys = pa.Table.from_batches([b.select(by)]).append_column("__at", pa.array(np.arange(b.num_rows)))
            groups = keys.group_by(by).aggregate([("__at", "list")])
            lists, weights = b.column(b.schema.get_field_index("labels")), b.column(b.schema.get_field_index(w)).to_numpy(zero_copy_only=False).astype(float)
            lengths, flat = np.asarray(lists.value_lengths()), lists.flatten().to_numpy(zero_copy_only=False)
            starts = np.concatenate([[0], np.cumsum(lengths)])
            out: dict[str, list] = {k: [] for k in names}
            for r, rows in zip(groups.select(by).to_pylist(), groups.column("__at_list").to_pylist()):
                rows = np.array(rows)
                for n in np.unique(lengths[rows]):
                    own = rows[lengths[rows] == n]
                    lab = np.stack([flat[starts[i] : starts[i] + n] for i in own])
                    hot = (lab[:, :, None] == np.arange(lab.max() + 1)).astype(float)
                    full = np.einsum("b,bik,bjk->ij", weights[own], hot, hot, optimize=True)
                    for k in by:
                        out[k].append(r[k])
                    out["tri"].append(full[np.tril_indices(n, -1)])
                    out["diag"].append(weights[own].sum())
                    out["n_pairs"].append(len(own))
                    out["n"].append(int(n))
            yield pa.RecordBatch.from_pydict(out, schema=pa.schema([b.schema.field(k) for k in by] + [pa.field("tri", pa.list_(pa.float64())), pa.field("diag", pa.float64()), pa.field("n_pairs", pa.int64()), pa.field("n", pa.int32())]))

    schema = "".join(f"`{c}` {df.schema[c].dataType.simpleString()}, " for c in by) + "tri array<double>, diag double, n_pairs bigint, n int"
    part = df.where(F.col(w).isNotNull() & ~F.isnan(F.col(w).cast("double"))).select(*by, "labels", w).mapInArrow(run, schema)
    return merge(part, by)


def merge(patterns: DataFrame, by: list[str]) -> DataFrame:
    """Adds packed patterns of equal keys cell by cell: patterns are sums, so they can be merged in any order. One exchange of packed rows, added up as they are read."""
    names = [*by, "n", "tri", "diag", "n_pairs"]
    kinds = [t for _, t in _arrow_types(patterns, [*by, "n"])]

    def add(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tri, diag, n_pairs = 0.0, 0.0, 0
        for b in batches:
            if b.num_rows:
                tri = tri + b.column(b.schema.get_field_index("tri")).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1).sum(axis=0)
                diag += float(np.sum(b.column(b.schema.get_field_index("diag")).to_numpy(zero_copy_only=False)))
                n_pairs += int(np.sum(b.column(b.schema.get_field_index("n_pairs")).to_numpy(zero_copy_only=False)))
        values = [*[pa.array([k.as_py()], t) for k, t in zip(key, kinds)], pa.array([np.asarray(tri)], pa.list_(pa.float64())), pa.array([diag]), pa.array([n_pairs], pa.int64())]
        yield pa.RecordBatch.from_arrays(values, names=names)

    schema = "".join(f"`{c}` {patterns.schema[c].dataType.simpleString()}, " for c in by) + "n int, tri array<double>, diag double, n_pairs bigint"
    return patterns.select(*names).groupBy(*by, "n").applyInArrow(add, schema).select(*by, "tri", "diag", "n_pairs", "n")


def _arrow_types(df: DataFrame, names: list[str]) -> list:
    from pyspark.sql.pandas.types import to_arrow_type

    return [(c, to_arrow_type(df.schema[c].dataType)) for c in names]


def subtract(whole: DataFrame, part: DataFrame, by: list[str]) -> DataFrame:
    """Packed patterns of whole without the pairs that part has summed: the inverse of merge()."""
    minus = part.withColumn("tri", F.transform("tri", lambda x: -x)).withColumn("diag", -F.col("diag")).withColumn("n_pairs", -F.col("n_pairs"))
    return merge(whole.select(*by, "n", "tri", "diag", "n_pairs").unionByName(minus.select(*by, "n", "tri", "diag", "n_pairs")), by)


def prefixes(df: DataFrame, by: list[str], ns: tuple[int, ...], order: str = "draw", w: str = "w", normalise: bool = True) -> DataFrame:
    """(by, n_pick, tri, diag, n): for each key the patterns of its first n pairs in the given order, for all n at once: sums are carried on from one n to the next.

    labels are array<int> or packed_labels(). order counts from 0. A key has as many pairs as the largest n at most; of a key with fewer, the larger n have what there is. Rows are dealt by key once.
    """
    names = [*by, "n_pick", "tri", "diag", "n"]

    def run(batches):
        held = None
        for b in batches:
            if not b.num_rows:
                continue
            table = pa.Table.from_batches([b]) if held is None else pa.concat_tables([held, pa.Table.from_batches([b])]).combine_chunks()
            new = np.zeros(table.num_rows, bool)
            new[0] = True
            for c in by:
                v = table.column(c).combine_chunks()
                new[1:] |= pc.fill_null(pc.not_equal(v[1:], v[:-1]), True).to_numpy(zero_copy_only=False)
            starts = np.nonzero(new)[0]
            if len(starts) > 1:
                yield done(table.slice(0, starts[-1]), starts[:-1])
            held = table.slice(starts[-1])
        if held is not None:
            yield done(held, np.zeros(1, int))

    def done(table, starts):
        weights, places = (table.column(c).combine_chunks().to_numpy(zero_copy_only=False) for c in (w, order))
        weights, packed = weights.astype(float), table.column("labels").to_pylist()
        tri, diag, sizes = [], [], []
        for s, e in zip(starts.tolist(), [*starts[1:].tolist(), table.num_rows]):
            lab = np.frombuffer(b"".join(packed[s:e]), np.uint8).reshape(e - s, -1)
            n = lab.shape[1]
            if n not in corners:
                corners[n] = np.tril_indices(n, -1)
            i, j = corners[n]
            took = (places[None, s:e] < np.array(ns)[:, None]) * weights[None, s:e]  # (n_pick, pair)
            cells = took @ (lab[:, i] == lab[:, j])
            whole = took.sum(axis=1)
            if normalise:
                total = 2 * np.abs(cells).sum(axis=1) + n * np.abs(whole)
                total[total == 0] = np.nan
                cells, whole = cells / total[:, None], whole / total
            tri.append(cells)
            diag.append(whole)
            sizes.append(n)
        first = table.take(pa.array(np.repeat(starts, len(ns)))).select(by)
        flat = np.concatenate([c.ravel() for c in tri])
        ends = np.concatenate([[0], np.cumsum(np.repeat([c.shape[1] for c in tri], len(ns)))]).astype(np.int32)
        values = [*[first.column(c).combine_chunks() for c in by], pa.array(np.tile(np.array(ns, np.int32), len(starts))), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat)), pa.array(np.concatenate(diag)), pa.array(np.repeat(np.array(sizes, np.int32), len(ns)))]
        return pa.RecordBatch.from_arrays(values, names=names)

    corners: dict[int, tuple] = {}
    schema = "".join(f"`{c}` {df.schema[c].dataType.simpleString()}, " for c in by) + "n_pick int, tri array<double>, diag double, n int"
    rows = df.where((F.col(order) < max(ns)) & F.col(w).isNotNull() & ~F.isnan(F.col(w).cast("double"))).select(*by, order, "labels", w)
    rows = rows if df.schema["labels"].dataType.simpleString() == "binary" else packed_labels(rows)
    return rows.repartition(*by).sortWithinPartitions(*by, order).mapInArrow(run, schema)


def packed_labels(df: DataFrame) -> DataFrame:
    """df with labels as binary, a byte each: what is drawn many times travels smaller."""
    keep = [c for c in df.columns if c != "labels"]

    def run(batches):
        for b in batches:
            lists = b.column(b.num_columns - 1)
            ends = np.concatenate([[0], np.cumsum(np.asarray(lists.value_lengths(), np.int64))])
            raw = lists.flatten().to_numpy(zero_copy_only=False).astype(np.uint8).tobytes()
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array([raw[i:j] for i, j in zip(ends[:-1], ends[1:])], pa.binary())], names=[*keep, "labels"])

    schema = "".join(f"`{c}` {df.schema[c].dataType.simpleString()}, " for c in keep)
    return df.select(*keep, "labels").mapInArrow(run, schema + "labels binary").select(*df.columns)


def score_cap(groups: DataFrame, share: float = 0.9) -> DataFrame:
    """One row (cap): the score that a share of pairs stay under. Indices in the space of eigenvectors have no bound; weight() takes it as a cap."""
    return groups.agg(F.percentile("score", F.lit(share)).alias("cap"))


def l1(df: DataFrame) -> DataFrame:
    """tri and diag over the sum of all n * n cells."""
    total = 2 * F.aggregate("tri", F.lit(0.0), lambda a, x: a + F.abs(x)) + F.col("n") * F.abs("diag")
    return df.withColumn("total", total).withColumn("tri", F.transform("tri", lambda x: F.try_divide(x, F.col("total")))).withColumn("diag", F.try_divide("diag", "total")).drop("total")


def l1_tall(cells: DataFrame, sums: DataFrame, by: list[str]) -> DataFrame:
    """Tall patterns with p = w over the sum of all n * n cells; sums as totals() gives them."""
    low = cells.groupBy(*by).agg(F.sum("w").alias("low"))
    total = (2 * F.coalesce("low", F.lit(0)) + F.col("n") * F.col("w_sum")).cast("double")
    whole = sums.join(low, by, "left").select(*by, total.alias("total"))
    return cells.join(whole, by).withColumn("p", F.try_divide(F.col("w").cast("double"), F.col("total"))).drop("total")


def rescale(cells: DataFrame, by: list[str], low: float = 0.0, high: float = 1.0) -> DataFrame:
    """Adds shown: the cell moved to [low, high] by its pattern's least and largest cells."""
    w = W.partitionBy(*by)
    a, b = F.min("w").over(w), F.max("w").over(w)
    return cells.withColumn("shown", F.lit(low) + (high - low) * F.coalesce(F.try_divide((F.col("w") - a).cast("double"), (b - a).cast("double")), F.lit(0.0)))


def features(df: DataFrame, full: bool = False) -> DataFrame:
    """features array<double>: the strict lower triangle, or all n * n cells."""
    if not full:
        return df.withColumn("features", F.col("tri"))
    at = lambda i, j: F.when(i == j, F.col("diag")).otherwise(F.get("tri", (F.greatest(i, j) * (F.greatest(i, j) - 1) / 2 + F.least(i, j)).cast("int")))
    return df.withColumn("features", F.flatten(F.transform(F.sequence(F.lit(0), F.col("n") - 1), lambda i: F.transform(F.sequence(F.lit(0), F.col("n") - 1), lambda j: at(i, j)))))

"""Groups of landmarks that move alike within one frame pair.

The main method is spectral: inner products of motion vectors, negative ones set to 0, are the affinity; the first K eigenvectors of its normalised Laplacian,
rows scaled to length 1, are clustered by K-means, and the K with the best ratio of scatter between groups to scatter within them is taken. All K share one
eigen-decomposition, and a whole Arrow batch is worked on at once. Direction sectors and threshold components are cheaper stand-ins.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# ---------------------------------------------------------------- columns


def pairs_of(df: DataFrame, *keep: str) -> DataFrame:
    """(video_id, keep, t, i, j, xi, yi, xj, yj) of motion_m for all ordered pairs of landmarks."""
    at = F.explode(F.sequence(F.lit(0), F.size("motion_m") - 1))
    out = df.select("video_id", *keep, "t", "motion_m", at.alias("i")).withColumn("j", F.explode(F.sequence(F.lit(0), F.size("motion_m") - 1)))
    a, b = F.get("motion_m", F.col("i")), F.get("motion_m", F.col("j"))
    return out.select("video_id", *keep, "t", "i", "j", a["x"].alias("xi"), a["y"].alias("yi"), b["x"].alias("xj"), b["y"].alias("yj"))


def affinity(df: DataFrame, metric: str = "inner", sigma: float = 1000.0, zero_diagonal: bool = False) -> DataFrame:
    """(video_id, t, i, j, a) from whole-number motion: inner products are exact."""
    p = pairs_of(df)
    inner = F.col("xi") * F.col("xj") + F.col("yi") * F.col("yj")
    if metric == "inner":
        a: Column = inner
    elif metric == "cosine":
        norm = F.sqrt((F.col("xi") * F.col("xi") + F.col("yi") * F.col("yi")).cast("double")) * F.sqrt((F.col("xj") * F.col("xj") + F.col("yj") * F.col("yj")).cast("double"))
        a = F.coalesce(F.try_divide(inner.cast("double"), norm), F.lit(0.0))
    elif metric == "euclid":
        dx, dy = F.col("xi") - F.col("xj"), F.col("yi") - F.col("yj")
        a = F.exp(-(dx * dx + dy * dy).cast("double") / (2 * sigma * sigma))
    else:
        raise ValueError(f"unknown metric {metric!r}")
    if zero_diagonal:
        a = F.when(F.col("i") == F.col("j"), F.lit(0)).otherwise(a)
    return p.select("video_id", "t", "i", "j", a.alias("a"))


def with_policy(cells: DataFrame, policy: str = "clip") -> DataFrame:
    """What becomes of negative affinities: clip to 0, keep (signed), shift by the pair's least, or drop such pairs (strict)."""
    if policy == "clip":
        return cells.withColumn("a", F.greatest("a", F.lit(0)))
    if policy == "signed":
        return cells
    least = cells.groupBy("video_id", "t").agg(F.min("a").alias("least"))
    joined = cells.join(least, ["video_id", "t"])
    if policy == "shift":
        return joined.withColumn("a", F.col("a") - F.least("least", F.lit(0))).drop("least")
    if policy == "strict":
        return joined.where("least >= 0").drop("least")
    raise ValueError(f"unknown policy {policy!r}")


def degree(cells: DataFrame, policy: str = "clip") -> DataFrame:
    return cells.groupBy("video_id", "t", "i").agg(F.sum(F.abs("a") if policy == "signed" else F.col("a")).alias("d"))


def laplacian(cells: DataFrame, kind: str = "sym", policy: str = "clip") -> DataFrame:
    """(video_id, t, i, j, l): sym, random_walk, unnormalised, or as_printed, whose right factor is the root of the degree."""
    d = degree(cells, policy)
    both = cells.join(d.withColumnRenamed("d", "di"), ["video_id", "t", "i"]).join(d.select("video_id", "t", F.col("i").alias("j"), F.col("d").alias("dj")), ["video_id", "t", "j"])
    core = (F.when(F.col("i") == F.col("j"), F.col("di")).otherwise(F.lit(0)) - F.col("a")).cast("double")
    di, dj = F.nullif(F.sqrt(F.col("di").cast("double")), F.lit(0.0)), F.nullif(F.sqrt(F.col("dj").cast("double")), F.lit(0.0))
    value = {"sym": core / (di * dj), "random_walk": core / F.nullif(F.col("di").cast("double"), F.lit(0.0)), "unnormalised": core, "as_printed": core / di * dj}[kind]
    alone = F.when(F.col("i") == F.col("j"), 1.0).otherwise(0.0)
    return both.select("video_id", "t", "i", "j", (value if kind == "unnormalised" else F.coalesce(value, alone)).alias("l"))


def sectors(df: DataFrame, k: int = 6) -> DataFrame:
    """labels: the motion's direction in k equal sectors; k_found: sectors that are used."""
    step = 2 * math.pi / k
    label = lambda m: F.least(F.floor((F.atan2(m["y"].cast("double"), m["x"].cast("double")) + math.pi) / step), F.lit(k - 1)).cast("int")
    out = df.withColumn("labels", F.transform("motion_m", label))
    return out.withColumn("k_found", F.size(F.array_distinct("labels")))


def scatter(k: int) -> Column:
    """struct(between, within) of motion_m under labels 0 to k - 1, about the mean of all motion."""
    zipped = F.zip_with("labels", "motion_m", lambda c, m: F.struct(c.alias("c"), m["x"].alias("x"), m["y"].alias("y")))
    zero = F.struct(*[F.lit(0).cast("bigint").alias(n) for n in ("n", "x", "y", "q")])

    def add(acc, m):
        return F.struct((acc["n"] + 1).alias("n"), (acc["x"] + m["x"]).alias("x"), (acc["y"] + m["y"]).alias("y"), (acc["q"] + m["x"] * m["x"] + m["y"] * m["y"]).alias("q"))

    def square(s):
        return (s["x"] * s["x"] + s["y"] * s["y"]).cast("double") / s["n"]

    own = F.filter(F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda c: F.aggregate(F.filter(zipped, lambda m: m["c"] == c), zero, add)), lambda s: s["n"] > 0)
    of_groups = F.aggregate(F.transform(own, square), F.lit(0.0), lambda a, x: a + x)
    whole = F.aggregate(zipped, zero, add)
    return F.transform(F.array(F.struct(of_groups.alias("g"), whole.alias("w"))), lambda v: F.struct((v["g"] - square(v["w"])).alias("between"), (v["w"]["q"].cast("double") - v["g"]).alias("within")))[0]


def group_score(df: DataFrame, k: int, mode: str = "ratio") -> DataFrame:
    """score: between / within * (n - K) / (K - 1), K the groups in use; as_printed has the first fraction upside down. 0 where it isn't defined."""
    n, used = F.size("labels"), F.col("k_found")
    b, w = F.col("scatter.between"), F.col("scatter.within")
    part = F.try_divide(w, b) if mode == "as_printed" else F.try_divide(b, w)
    value = part * (n - used) / F.nullif(used - 1, F.lit(0))
    return df.withColumn("scatter", scatter(k)).withColumn("score", F.coalesce(value, F.lit(0.0))).drop("scatter")


def select_k(df: DataFrame, k_min: int = 2, k_max: int = 8) -> DataFrame:
    """Sector grouping with the number of sectors that scores best; the smaller one on ties. Adds k, labels, k_found and score."""
    out = None
    for k in range(k_min, k_max + 1):
        one = group_score(sectors(df, k), k)
        each = F.struct(F.round("score", 6).alias("score"), F.lit(-k).alias("less"), F.col("labels"), F.col("k_found"))
        out = one.select(*df.columns, each.alias(f"try_{k}")) if out is None else group_score(sectors(out, k), k).withColumn(f"try_{k}", each).drop("labels", "k_found", "score")
    tries = [f"try_{k}" for k in range(k_min, k_max + 1)]
    return out.withColumn("best", F.greatest(*tries)).select(*df.columns, (-F.col("best.less")).alias("k"), "best.labels", "best.k_found", "best.score")


# ---------------------------------------------------------------- kernels


@dataclass(frozen=True)
class Options:
    metric: str = "inner"
    policy: str = "clip"
    zero_diagonal: bool = False
    laplacian: str = "sym"
    k_min: int = 2
    k_max: int | None = 8
    k_fixed: int | None = None
    score: str = "ratio"
    space: str = "motion"
    sigma: float = 1.0
    hard_cap: float = 1e6


def affinities(m: np.ndarray, o: Options) -> tuple[np.ndarray, np.ndarray]:
    """(B, n, n) affinities under the policy, and which pairs stay."""
    a = m @ m.transpose(0, 2, 1)
    if o.metric == "cosine":
        size = np.linalg.norm(m, axis=2)
        a = a / np.maximum(size[:, :, None] * size[:, None, :], 1e-300)
    elif o.metric == "euclid":
        q = (m * m).sum(axis=2)
        a = np.exp(-np.maximum(q[:, :, None] + q[:, None, :] - 2 * a, 0) / (2 * o.sigma**2))
    stay = np.ones(len(m), bool)
    if o.policy == "clip":
        a = np.maximum(a, 0)
    elif o.policy == "shift":
        a = a - np.minimum(a.min(axis=(1, 2), keepdims=True), 0)
    elif o.policy == "strict":
        stay = (a >= 0).all(axis=(1, 2))
    if o.zero_diagonal:
        i = np.arange(a.shape[1])
        a[:, i, i] = 0
    return a, stay


def eigenbasis(a: np.ndarray, k: int, o: Options = Options()) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(eigenvalues, first k eigenvectors, landmarks without degree). A sign is fixed by the entry largest in size."""
    n = a.shape[1]
    d = (np.abs(a) if o.policy == "signed" else a).sum(axis=2)
    lone = d <= 1e-12
    root = np.where(lone, 1.0, 1 / np.sqrt(np.where(lone, 1.0, d)))
    lap = -a.copy()
    i = np.arange(n)
    lap[:, i, i] += d
    if o.laplacian in ("sym", "random_walk"):
        lap = lap * root[:, :, None] * root[:, None, :]
        lap = np.where(lone[:, :, None] | lone[:, None, :], 0.0, lap)
        lap[:, i, i] = np.where(lone, 1.0, lap[:, i, i])
    lap = (lap + lap.transpose(0, 2, 1)) / 2
    values, vectors = np.linalg.eigh(lap)
    v = vectors[:, :, :k]
    if o.laplacian in ("random_walk", "as_printed"):  # similar to a symmetric matrix: its vectors are scaled
        v = v * root[:, :, None]
    top = np.take_along_axis(v, np.abs(v).argmax(axis=1)[:, None, :], 1)
    return values, v * np.where(top < 0, -1.0, 1.0), lone


def kmeans(x: np.ndarray, k: int, rounds: int = 20) -> np.ndarray:
    """Labels of (B, n, d) points in k groups: farthest-first seeds from the first point, then Lloyd's rounds, all batches at once; those that don't change any more are left out."""
    b, n, _ = x.shape
    rows, points = np.arange(b), np.arange(n)
    gram = x @ x.transpose(0, 2, 1)
    own = np.ascontiguousarray(gram[:, points, points])
    seeds, near = np.zeros((b, k), int), np.full((b, n), np.inf)
    for s in range(1, k):
        last = seeds[:, s - 1]
        apart = own + own[rows, last][:, None] - 2 * gram[rows, last]
        apart[apart < 1e-12] = 0  # the same point
        near = np.minimum(near, apart)
        seeds[:, s] = near.argmax(axis=1)
    c = x[rows[:, None], seeds]
    labels, left = np.full((b, n), -1), rows
    for _ in range(rounds):
        dist = x @ (-2 * c).transpose(0, 2, 1)
        dist += (c**2).sum(axis=2)[:, None, :]
        after = dist.argmin(axis=2)
        moved = (after != labels[left]).any(axis=1)
        labels[left] = after
        if not moved.any():
            break
        if not moved.all():
            left, x, c, after = left[moved], x[moved], c[moved], after[moved]
        hot = np.zeros((len(x), k, n))
        hot[np.arange(len(x))[:, None], after, points] = 1
        count = hot.sum(axis=2)
        means = hot @ x / np.maximum(count, 1)[:, :, None]
        c = np.where(count[:, :, None] > 0, means, c)
    return labels


def scores(x: np.ndarray, labels: np.ndarray, k: int, o: Options = Options()) -> np.ndarray:
    """The validity index of each batch, with the number of groups in use; capped where nothing is scattered within groups."""
    hot = (labels[:, :, None] == np.arange(k)).astype(float)
    count = hot.sum(axis=1)
    used = (count > 0).sum(axis=1)
    sums = hot.transpose(0, 2, 1) @ x
    n = x.shape[1]
    of_groups = ((sums**2).sum(axis=2) / np.maximum(count, 1)).sum(axis=1)
    between = of_groups - (x.sum(axis=1) ** 2).sum(axis=1) / n
    within = (x**2).sum(axis=(1, 2)) - of_groups
    a, b = (within, between) if o.score == "as_printed" else (between, within)
    with np.errstate(divide="ignore", invalid="ignore"):
        value = np.where(b > 1e-12, a / np.maximum(b, 1e-300), o.hard_cap) * (n - used) / np.maximum(used - 1, 1)
    return np.where(used > 1, np.minimum(np.maximum(value, 0), o.hard_cap), 0.0)


def canonical(labels: np.ndarray) -> np.ndarray:
    """Groups numbered by first occurrence."""
    n = labels.shape[1]
    first = (labels[:, :, None] == labels[:, None, :]).argmax(axis=2)
    is_first = first == np.arange(n)
    number = np.cumsum(is_first, axis=1) - 1
    return np.take_along_axis(number, first, 1)


def group_batch(m: np.ndarray, o: Options = Options()) -> dict[str, np.ndarray]:
    """labels, k, score, gap, degenerate and stay for (B, n, 2) motion."""
    return batch_variants(m, [o])[0]


def batch_variants(m: np.ndarray, options: list[Options]) -> list[dict[str, np.ndarray]]:
    """group_batch() under each of the options: those of one Laplacian share its eigenvectors and, for each K, the groups; only scores and the choice of K are their own."""
    b, n, _ = m.shape
    ks = [[o.k_fixed] if o.k_fixed else list(range(o.k_min, (n - 1 if o.k_max is None else min(o.k_max, n - 1)) + 1)) for o in options]
    alike: dict[tuple, list[int]] = {}
    for at, o in enumerate(options):
        alike.setdefault((o.metric, o.policy, o.zero_diagonal, o.laplacian, o.sigma), []).append(at)
    best, labels = [np.full(b, -1.0) for _ in options], [np.zeros((b, n), int) for _ in options]
    chosen, out = [np.full(b, its[0]) for its in ks], [{} for _ in options]
    for its in alike.values():
        o = options[its[0]]
        a, stay = affinities(m, o)
        tried = sorted({k for at in its for k in ks[at]})
        values, v, lone = eigenbasis(a, max(tried), o)
        for k in tried:
            f = v[:, :, :k]
            f = f / np.maximum(np.linalg.norm(f, axis=2, keepdims=True), 1e-12)
            own, scored = kmeans(f, k), {}
            for at in its:
                if k not in ks[at]:
                    continue
                o = options[at]
                way = o.space, o.score, o.hard_cap
                if way not in scored:
                    scored[way] = scores(m if o.space == "motion" else f, own, k, o)
                s = scored[way]
                better = s > best[at] * (1 + 1e-12)
                best[at], chosen[at] = np.where(better, s, best[at]), np.where(better, k, chosen[at])
                labels[at] = np.where(better[:, None], own, labels[at])
        for at in its:
            c = chosen[at]
            gap = np.where(c < n, np.take_along_axis(values, np.minimum(c, n - 1)[:, None], 1)[:, 0] - np.take_along_axis(values, c[:, None] - 1, 1)[:, 0], np.nan)
            out[at] = {"labels": canonical(labels[at]), "k": c, "score": np.maximum(best[at], 0), "gap": gap, "degenerate": (gap < 1e-9) | lone.any(axis=1), "stay": stay}
    return out


def motion_array(column) -> np.ndarray:
    """An Arrow list<struct<dx,dy>> column of equal lengths as (B, n, 2)."""
    flat = column.flatten()
    out = np.stack([flat.field(0).to_numpy(zero_copy_only=False), flat.field(1).to_numpy(zero_copy_only=False)], 1)
    return out.reshape(len(column), -1, 2)


def group_pairs(df: DataFrame, o: Options = Options(), keep: list[str] | None = None, rows_each: int = 64) -> DataFrame:
    """labels array<int>, k, score, gap and degenerate for each pair, without a shuffle. Pairs of fewer than 3 landmarks, or with a null, give nothing."""
    return group_variants(df, {"": o}, keep, rows_each).drop("variant")


def group_variants(df: DataFrame, variants: dict[str, Options], keep: list[str] | None = None, rows_each: int = 64) -> DataFrame:
    """group_pairs() under several options at once, a row for each pair and variant."""
    keep = keep if keep is not None else [c for c in df.columns if c != "motion"]
    df = df.where((F.size("motion") >= 3) & F.forall("motion", lambda m: m["dx"].isNotNull() & m["dy"].isNotNull() & ~F.isnan(m["dx"]) & ~F.isnan(m["dy"])))

    def run(batches):
        import pyarrow as pa

        for whole in batches:
            for at in range(0, whole.num_rows, rows_each):
                b = whole.slice(at, rows_each)
                lists = b.column(b.num_columns - 1)
                lengths = np.asarray(lists.value_lengths())
                for n in np.unique(lengths):
                    own = pa.array(np.nonzero(lengths == n)[0])
                    part = b.take(own)
                    for name, got in zip(variants, batch_variants(motion_array(part.column(part.num_columns - 1)), list(variants.values()))):
                        idx = np.nonzero(got["stay"])[0]
                        kept = part.take(pa.array(idx))
                        lab = got["labels"][idx].astype(np.int32)
                        labels = pa.ListArray.from_arrays(pa.array(np.arange(0, lab.size + 1, int(n), dtype=np.int32)), pa.array(lab.ravel()))
                        yield pa.RecordBatch.from_arrays([*kept.columns[:-1], pa.array([name] * len(idx), pa.string()), labels, pa.array(got["k"][idx].astype(np.int32)), pa.array(got["score"][idx]), pa.array(got["gap"][idx]), pa.array(got["degenerate"][idx])], names=[*keep, "variant", "labels", "k", "score", "gap", "degenerate"])

    schema = "".join(f"`{c}` {df.schema[c].dataType.simpleString()}, " for c in keep)
    return df.select(*keep, "motion").mapInArrow(run, f"{schema}variant string, labels array<int>, k int, score double, gap double, degenerate boolean")


def component_labels(m: np.ndarray, theta: float) -> np.ndarray:
    """(B, n) labels of the connected parts of the graph of affinities over theta."""
    link = (m @ m.transpose(0, 2, 1)) > theta
    n = m.shape[1]
    i = np.arange(n)
    link[:, i, i] = True
    labels = np.tile(i, (len(m), 1))
    while True:
        after = np.where(link, labels[:, None, :], n).min(axis=2)
        if (after == labels).all():
            return canonical(labels)
        labels = after


def components(df: DataFrame, theta: float = 0.0, keep: list[str] | None = None) -> DataFrame:
    """labels by threshold components of whole-number motion_m."""
    keep = keep if keep is not None else [c for c in df.columns if c not in ("motion", "motion_m")]

    def run(batches):
        import pyarrow as pa

        for b in batches:
            if not b.num_rows:
                continue
            lab = component_labels(motion_array(b.column(b.num_columns - 1)).astype(float), theta).astype(np.int32)
            labels = pa.ListArray.from_arrays(pa.array(np.arange(0, lab.size + 1, lab.shape[1], dtype=np.int32)), pa.array(lab.ravel()))
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], labels], names=[*keep, "labels"])

    schema = "".join(f"`{c}` {df.schema[c].dataType.simpleString()}, " for c in keep)
    return df.select(*keep, "motion_m").mapInArrow(run, f"{schema}labels array<int>")


def report(groups: DataFrame) -> DataFrame:
    return groups.groupBy("source", "k").agg(F.count("*").alias("n_pairs"), F.round(F.avg("score"), 4).alias("mean_score"))

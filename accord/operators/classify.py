"""Supervised detection: boosted decision stumps over binned features, with MLlib's learners as variants.

Features are binned once. In each round the weights of both classes are summed per feature and bin within each Arrow batch, dealt by feature and bin, and
the best stump, a single row, goes back to the driver. A row's weight is worked out anew from all stumps so far, so lineage doesn't grow with rounds.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

Stump = tuple[int, int, int, float]  # feature, bin, polarity, alpha: polarity if the feature's bin is over `bin`, else -polarity


def bin_edges(df: DataFrame, bins: int = 32, accuracy: int = 1000) -> list[list[float]]:
    """For each feature the inner edges of bins of about equal size. As many numbers as features times bins."""
    at = [i / bins for i in range(1, bins)]
    rows = df.select(F.posexplode("features").alias("f", "x")).groupBy("f").agg(F.percentile_approx("x", F.array(*[F.lit(a) for a in at]), accuracy).alias("edges")).orderBy("f").collect()
    return [list(r.edges) for r in rows]


def binize(df: DataFrame, edges: list[list[float]]) -> DataFrame:
    """bins binary: a byte for each feature, the number of its edges that the value is over."""
    keep = [c for c in df.columns if c != "features"]

    def run(batches):
        import pyarrow as pa

        for b in batches:
            x = b.column(b.num_columns - 1).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1) if b.num_rows else None
            out = np.stack([np.searchsorted(np.array(e), x[:, f], side="left") for f, e in enumerate(edges)], 1).astype(np.uint8) if b.num_rows else np.zeros((0, len(edges)), np.uint8)
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array([r.tobytes() for r in out], pa.binary())], names=[*keep, "bins"])

    schema = "".join(f"`{c}` {df.schema[c].dataType.simpleString()}, " for c in keep)
    return df.select(*keep, "features").mapInArrow(run, schema + "bins binary")


def margin(bins: np.ndarray, model: list[Stump]) -> np.ndarray:
    out = np.zeros(len(bins))
    for f, cut, polarity, alpha in model:
        out += alpha * np.where(bins[:, f] > cut, polarity, -polarity)
    return out


def _as_matrix(column, rows: int) -> np.ndarray:
    raw = column.to_pylist()
    return np.frombuffer(b"".join(raw), np.uint8).reshape(rows, -1) if rows else np.zeros((0, 0), np.uint8)


def round_histogram(binned: DataFrame, models: dict[str, list], margin=margin) -> DataFrame:
    """(task, f, b, pos, neg): weights by task, class, feature and bin under each task's stumps so far. They are added up over a whole partition before they are
    dealt, so what is dealt goes with tasks, features and bins, not with rows."""

    def run(batches):
        import pyarrow as pa

        sums: dict[str, np.ndarray] = {}  # (class, feature, bin)
        for batch in batches:
            if not batch.num_rows:
                continue
            tasks = np.array(batch.column(0).to_pylist(), object)
            y, x = batch.column(1).to_numpy(zero_copy_only=False), _as_matrix(batch.column(2), batch.num_rows)
            features = np.arange(x.shape[1], dtype=np.int32)[None, :] * 256
            for task in set(tasks.tolist()):
                for c in (0, 1):
                    part = x[(tasks == task) & (y == c)]
                    if len(part):
                        w = np.exp((1 - 2 * c) * margin(part, models.get(task, [])))
                        own = sums.setdefault(task, np.zeros((2, x.shape[1] * 256)))
                        own[c] += np.bincount((features + part).ravel(), weights=np.repeat(w, x.shape[1]), minlength=x.shape[1] * 256)
        for task, (neg, pos) in sorted(sums.items()):
            some = np.nonzero(pos + neg)[0]
            yield pa.RecordBatch.from_arrays([pa.array([task] * len(some), pa.string()), pa.array((some // 256).astype(np.int32)), pa.array((some % 256).astype(np.int32)), pa.array(pos[some]), pa.array(neg[some])], names=["task", "f", "b", "pos", "neg"])

    part = binned.select("task", "y", "bins").mapInArrow(run, "task string, f int, b int, pos double, neg double")
    return part.groupBy("task", "f", "b").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))


def by_task(binned: DataFrame, salts: int = 4) -> DataFrame:
    """Rows dealt so that a partition has few tasks, and a task a few partitions: less to add up in every round."""
    return binned.repartition("task", F.pmod(F.xxhash64("bins"), F.lit(salts)))


def best_stump(hist: DataFrame) -> DataFrame:
    """(task, f, b, polarity, err): each task's stump of least weighted error; on ties the least feature, then bin, then polarity 1."""
    from pyspark.sql.window import Window as W

    up = W.partitionBy("task", "f").orderBy("b").rowsBetween(W.unboundedPreceding, 0)
    whole = W.partitionBy("task", "f")
    c = hist.select("task", "f", "b", F.sum("pos").over(up).alias("lp"), F.sum("neg").over(up).alias("ln"), F.sum("pos").over(whole).alias("p"), F.sum("neg").over(whole).alias("n"))
    over = F.struct((F.col("lp") + F.col("n") - F.col("ln")).alias("err"), F.lit(1).alias("polarity"))
    under = F.struct((F.col("ln") + F.col("p") - F.col("lp")).alias("err"), F.lit(-1).alias("polarity"))
    each = c.select("task", "f", "b", F.explode(F.array(over, under)).alias("s"), (F.col("p") + F.col("n")).alias("total"))
    rank = F.struct(F.round(F.col("s.err") / F.col("total"), 12), F.col("f"), F.col("b"), -F.col("s.polarity"))
    return each.groupBy("task").agg(F.min_by(F.struct("f", "b", F.col("s.polarity").alias("polarity"), (F.col("s.err") / F.col("total")).alias("err")), rank).alias("r")).select("task", "r.*")


def boost_binned(binned: DataFrame, rounds: int = 50, most_alpha: float = 5.0) -> dict[str, list[Stump]]:
    """Stumps of each task from (task, y, bins), which is read once a round: one job per round for all tasks. A task stops at a stump without error or no better than chance."""
    models: dict[str, list[Stump]] = {}
    live: set[str] | None = None
    for _ in range(rounds):
        rows = binned if live is None else binned.where(F.col("task").isin(sorted(live)))
        best = best_stump(round_histogram(rows, models)).collect()  # a row per task
        live = set()
        for r in best:
            if r.err >= 0.5 - 1e-12:
                continue
            models.setdefault(r.task, []).append((r.f, r.b, r.polarity, min(most_alpha, 0.5 * math.log((1 - r.err) / max(r.err, 1e-12)))))
            if r.err > 1e-12:
                live.add(r.task)
        if not live:
            break
    return models


def boost_fit_many(df: DataFrame, rounds: int = 50, bins: int = 32, most_alpha: float = 5.0) -> tuple[dict[str, list[Stump]], list[list[float]]]:
    """(stumps of each task, bin edges) from (task, y, features)."""
    edges = bin_edges(df, bins)
    binned = binize(df.select("task", "y", "features"), edges).persist()
    try:
        return boost_binned(binned, rounds, most_alpha), edges
    finally:
        binned.unpersist()


def boost_predict_binned(df: DataFrame, models: dict[str, list], column: str = "task", real: bool = False) -> DataFrame:
    """margin and pred of rows with bins by the model that `column` names, in Arrow batches."""
    of = real_margin if real else margin
    keep = [c for c in df.columns if c != "bins"]
    named = keep.index(column)

    def run(batches):
        import pyarrow as pa

        for b in batches:
            x = _as_matrix(b.column(b.num_columns - 1), b.num_rows)
            tasks = np.array(b.column(named).to_pylist(), object)
            out = np.zeros(b.num_rows)
            for task in set(tasks.tolist()):
                rows = tasks == task
                out[rows] = of(x[rows], models.get(task, []))
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(out), pa.array((out > 0).astype(np.int32))], names=[*keep, "margin", "pred"])

    schema = "".join(f"`{c}` {df.schema[c].dataType.simpleString()}, " for c in keep)
    return df.select(*keep, "bins").mapInArrow(run, schema + "margin double, pred int")


def best_real_stump(hist: DataFrame) -> DataFrame:
    """(task, f, b, low, high): each task's stump of least bound on the error; its two sides give half the logarithm of their odds."""
    from pyspark.sql.window import Window as W

    up = W.partitionBy("task", "f").orderBy("b").rowsBetween(W.unboundedPreceding, 0)
    whole = W.partitionBy("task", "f")
    c = hist.select("task", "f", "b", F.sum("pos").over(up).alias("lp"), F.sum("neg").over(up).alias("ln"), F.sum("pos").over(whole).alias("p"), F.sum("neg").over(whole).alias("n"))
    hp, hn, total = F.greatest(F.col("p") - F.col("lp"), F.lit(0.0)), F.greatest(F.col("n") - F.col("ln"), F.lit(0.0)), F.col("p") + F.col("n")
    little = total * 1e-3
    bound = (F.sqrt(F.col("lp") * F.col("ln")) + F.sqrt(hp * hn)) / total
    side = lambda p, n: 0.5 * F.log((p + little) / (n + little))
    each = c.select("task", "f", "b", side(F.col("lp"), F.col("ln")).alias("low"), side(hp, hn).alias("high"), F.round(bound, 12).alias("bound"))
    return each.groupBy("task").agg(F.min_by(F.struct("f", "b", "low", "high", "bound"), F.struct("bound", "f", "b")).alias("r")).select("task", "r.*")


def boost_real(binned: DataFrame, rounds: int = 50) -> dict[str, list[tuple[int, int, float, float]]]:
    """The real-valued variant over (task, y, bins): stumps (feature, bin, value up to the bin, value over it)."""
    models: dict[str, list[tuple[int, int, float, float]]] = {}
    for _ in range(rounds):
        hist = round_histogram(binned, models, real_margin)
        for r in best_real_stump(hist).collect():  # a row per task
            models.setdefault(r.task, []).append((r.f, r.b, r.low, r.high))
    return models


def real_margin(bins: np.ndarray, model: list) -> np.ndarray:
    out = np.zeros(len(bins))
    for f, cut, low, high in model:
        out += np.where(bins[:, f] > cut, high, low)
    return out


def boost_fit(df: DataFrame, rounds: int = 50, bins: int = 32) -> tuple[list[Stump], list[list[float]]]:
    models, edges = boost_fit_many(df.withColumn("task", F.lit("one")), rounds, bins)
    return models.get("one", []), edges


def boost_predict_many(df: DataFrame, models: dict[str, list[Stump]], edges: list[list[float]], column: str = "task") -> DataFrame:
    """margin and pred by the model that `column` names."""
    out: Column = F.lit(0.0)
    for task, model in models.items():
        out = F.when(F.col(column) == task, model_column(model, edges)).otherwise(out)
    return df.withColumn("margin", out).withColumn("pred", (F.col("margin") > 0).cast("int"))


def model_column(model: list[Stump], edges: list[list[float]]) -> Column:
    """The margin of features under the model, as a native expression: a stump asks whether its feature is over the edge of its bin."""
    parts = [F.struct(F.lit(f).alias("f"), F.lit(float(edges[f][b]) if b < len(edges[f]) else math.inf).alias("cut"), F.lit(float(p * a)).alias("v")) for f, b, p, a in model]
    if not parts:
        return F.lit(0.0)
    return F.aggregate(F.array(*parts), F.lit(0.0), lambda s, m: s + F.when(F.get("features", m["f"]) > m["cut"], m["v"]).otherwise(-m["v"]))


def boost_predict(df: DataFrame, model: list[Stump], edges: list[list[float]]) -> DataFrame:
    return df.withColumn("margin", model_column(model, edges)).withColumn("pred", (F.col("margin") > 0).cast("int"))


def boost_fit_mllib(df: DataFrame, rounds: int = 10):
    """Variant: MLlib trees of depth 1 on weights that are a closed form of the trees so far. Returns [(tree, alpha)]."""
    from pyspark.ml.classification import DecisionTreeClassifier

    rows = vectors(df)
    model: list = []
    for _ in range(rounds):
        weighted = rows.withColumn("weight", F.exp(-(2 * F.col("y") - 1) * _tree_margin(model)))
        tree = DecisionTreeClassifier(maxDepth=1, weightCol="weight", labelCol="y", featuresCol="vec").fit(weighted)
        node = _stump_of(tree)
        err = weighted.agg((F.sum(F.when(_node_sign(node) != 2 * F.col("y") - 1, F.col("weight")).otherwise(0.0)) / F.sum("weight")).alias("e")).first().e
        if err is None or err >= 0.5:
            break
        model.append((node, 0.5 * math.log((1 - err) / max(err, 1e-6))))
        if err < 1e-9:
            break
    return model


def _stump_of(tree) -> tuple[int, float, int, int]:
    """(feature, threshold, sign at or under it, sign over it) of a tree of depth 1."""
    root = tree._call_java("rootNode")
    sign = lambda node: 1 if node.prediction() > 0.5 else -1
    if root.subtreeDepth() == 0:
        return 0, math.inf, sign(root), sign(root)
    return root.split().featureIndex(), root.split().threshold(), sign(root.leftChild()), sign(root.rightChild())


def _node_sign(node) -> Column:
    f, cut, low, high = node
    return F.when(F.get("features", F.lit(f)) <= cut, low).otherwise(high)


def _tree_margin(model) -> Column:
    out: Column = F.lit(0.0)
    for node, alpha in model:
        out = out + alpha * _node_sign(node)
    return out


def predict_mllib_boost(df: DataFrame, model) -> DataFrame:
    return df.withColumn("pred", (_tree_margin(model) > 0).cast("int"))


def vectors(df: DataFrame) -> DataFrame:
    from pyspark.ml.functions import array_to_vector

    return df.withColumn("vec", array_to_vector("features"))


def mllib_fit(df: DataFrame, kind: str = "lr", seed: int = 1):
    """Any other learner on the same features: lr, svc, rf, gbt, tree or mlp."""
    from pyspark.ml import classification as C

    rows = vectors(df)
    cols = {"labelCol": "y", "featuresCol": "vec"}
    if kind == "mlp":
        width = len(df.select("features").first()[0])
        return C.MultilayerPerceptronClassifier(layers=[width, 16, 2], maxIter=50, seed=seed, **cols).fit(rows)
    made = {
        "lr": lambda: C.LogisticRegression(maxIter=50, regParam=1e-3, **cols),
        "svc": lambda: C.LinearSVC(maxIter=50, regParam=1e-3, **cols),
        "rf": lambda: C.RandomForestClassifier(numTrees=30, maxDepth=5, seed=seed, **cols),
        "gbt": lambda: C.GBTClassifier(maxIter=20, maxDepth=3, seed=seed, **cols),
        "tree": lambda: C.DecisionTreeClassifier(maxDepth=5, seed=seed, **cols),
    }
    return made[kind]().fit(rows)


def mllib_predict(df: DataFrame, model) -> DataFrame:
    return model.transform(vectors(df)).withColumn("pred", F.col("prediction").cast("int")).drop("vec", "rawPrediction", "probability", "prediction")


def binary_tasks(df: DataFrame, sources: tuple = ("A", "B", "C", "D")) -> DataFrame:
    """A row for each task that it is part of: forged rows in their own, genuine ones in all."""
    task = F.when(F.col("y") == 1, F.array("source")).otherwise(F.array(*[F.lit(s) for s in sources]))
    return df.where(F.col("source").isin("R", *sources)).withColumn("task", F.explode(task))


def combined_task(df: DataFrame, balance: bool = False, sources: tuple = ("A", "B", "C", "D"), key: str = "video_id") -> DataFrame:
    """All forged sources against the genuine one; balanced by taking one in len(sources) forged rows by hash."""
    from accord.operators.sampling import order_of

    out = df.where(F.col("source").isin("R", *sources)).withColumn("task", F.lit("combined"))
    if balance:
        at = F.conv(F.substring(order_of(key, seed=9), 1, 6), 16, 10).cast("bigint") % len(sources)
        out = out.where((F.col("y") == 0) | (at == 0))
    return out


def nearest_mean(train: DataFrame, test: DataFrame, by: list[str]) -> DataFrame:
    """The cheap scorer: a test pattern gets the class whose mean pattern of the training task is nearer (tall patterns with p; keys `by` and id).

    The means are broadcast: two patterns for each task, whatever the number of patterns learnt from."""
    means = train.groupBy(*by, "y", "i", "j").agg(F.sum("p").alias("s"))
    sizes = train.select(*by, "y", "id").distinct().groupBy(*by, "y").agg(F.count("*").alias("n"))
    means = means.join(sizes, [*by, "y"]).select(*by, F.col("y").alias("c"), "i", "j", (F.col("s") / F.col("n")).alias("m"))
    dots = test.join(F.broadcast(means), ["i", "j"]).groupBy(*by, "c", "test_source", "id", "y").agg(F.sum(F.col("p") * F.col("m")).alias("dot"))
    norm = means.groupBy(*by, "c").agg(F.sum(F.col("m") * F.col("m")).alias("mm"))
    return dots.join(norm, [*by, "c"]).groupBy(*by, "test_source", "id", "y").agg(F.min_by("c", F.round(F.col("mm") - 2 * F.col("dot"), 12)).alias("pred"))

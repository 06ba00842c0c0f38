"""Stand-ins for the published baselines, each with the same kind of information, and the method's own ablations.

No image network can be had here: the stand-ins say which information suffices, not what the published systems reach.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from accord.operators import classify, grouping, pattern


def frame_features(df: DataFrame) -> DataFrame:
    """features: the motion vectors of a single pair, flat."""
    return df.withColumn("features", F.flatten(F.transform("motion", lambda m: F.array(m["dx"], m["dy"]))))


def frame_vote(train: DataFrame, test: DataFrame, kind: str = "mlp") -> DataFrame:
    """(video_id, y, share, pred): each pair alone is judged; a video goes by the majority of its pairs."""
    model = classify.mllib_fit(frame_features(train), kind)
    return vote(classify.mllib_predict(frame_features(test), model))


def vote(judged: DataFrame) -> DataFrame:
    out = judged.groupBy("video_id", "y").agg(F.avg(F.col("pred").cast("double")).alias("share"))
    return out.withColumn("pred", (F.col("share") > 0.5).cast("int"))


def recurrent_features(df: DataFrame, keep: float = 0.8) -> DataFrame:
    """(video_id, source, y, features): an exponentially smoothed state over the video's pairs in order, from its first features."""
    rows = frame_features(df).groupBy("video_id", "source", "y").agg(F.transform(F.array_sort(F.collect_list(F.struct("t", "features"))), lambda r: r["features"]).alias("seq"))
    step = lambda s, x: F.zip_with(s, x, lambda a, b: keep * a + (1 - keep) * b)
    return rows.withColumn("features", F.aggregate(F.slice("seq", 2, 1 << 30), F.col("seq")[0], step)).drop("seq")


def first_order(df: DataFrame) -> DataFrame:
    """(video_id, source, y, features): mean and deviation of every landmark's motion: motion without its second order."""
    cells = df.select("video_id", "source", "y", F.posexplode("motion").alias("lm", "m"))
    per = cells.groupBy("video_id", "source", "y", "lm").agg(*[f(F.col(f"m.{c}")).alias(f"{n}_{c}") for c in ("dx", "dy") for n, f in (("mean", F.avg), ("sd", F.stddev_pop))])
    row = F.struct("lm", F.array("mean_dx", "mean_dy", "sd_dx", "sd_dy").alias("v"))
    return per.groupBy("video_id", "source", "y").agg(F.flatten(F.transform(F.array_sort(F.collect_list(row)), lambda r: r["v"])).alias("features"))


def embedding_sequence(df: DataFrame) -> DataFrame:
    """(video_id, source, y, features) of raw vectors (video_id, source, y, t, vector): mean per dimension and mean change to the next."""
    w = W.partitionBy("video_id").orderBy("t")
    rows = df.withColumn("after", F.lead("vector").over(w))
    cells = rows.select("video_id", "source", "y", F.posexplode(F.zip_with("vector", F.coalesce("after", "vector"), lambda a, b: F.struct(a.cast("double").alias("a"), F.abs(b.cast("double") - a.cast("double")).alias("c")))).alias("k", "p"))
    per = cells.groupBy("video_id", "source", "y", "k").agg(F.avg("p.a").alias("a"), F.avg("p.c").alias("c"))
    return per.groupBy("video_id", "source", "y").agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("k", F.array("a", "c").alias("v")))), lambda r: r["v"])).alias("features"))


def noise_residual(df: DataFrame) -> DataFrame:
    """(video_id, source, y, r): variance of what is left of tall motion after the mean of neighbouring landmarks is taken away. Degradation spoils it first."""
    w = W.partitionBy("video_id", "t").orderBy("lm").rowsBetween(-1, 1)
    left = df.select("video_id", "source", "y", (F.col("dx_m") - F.avg("dx_m").over(w)).alias("hx"), (F.col("dy_m") - F.avg("dy_m").over(w)).alias("hy"))
    return left.groupBy("video_id", "source", "y").agg((F.var_pop("hx") + F.var_pop("hy")).alias("r"))


def noise_score(residuals: DataFrame) -> DataFrame:
    """d: distance of a video's residual to the mean of genuine ones, in their deviations."""
    ref = residuals.where("source = 'R'").agg(F.avg("r").alias("m"), F.stddev_pop("r").alias("s"))
    return residuals.crossJoin(F.broadcast(ref)).withColumn("d", F.abs(F.col("r") - F.col("m")) / F.col("s")).drop("m", "s")  # one row


def majority(df: DataFrame) -> DataFrame:
    """(y, n, share): what calling everything the commoner class gets right."""
    counts = df.groupBy("y").agg(F.count("*").alias("n"))
    return counts.withColumn("share", F.col("n") / F.sum("n").over(W.partitionBy())).orderBy(F.desc("n"), "y").limit(1)


#: The method with one choice changed: options of grouping, weight of pairs, and whether weak motion is filtered.
ABLATIONS = {
    "full": {},
    "unweighted": {"weight": "none"},
    "score_only": {"weight": "score"},
    "k_only": {"weight": "k"},
    "no_filter": {"filter": False},
    "cosine": {"grouping": {"metric": "cosine"}},
    "euclid": {"grouping": {"metric": "euclid", "sigma": 8.0}},
    "signed": {"grouping": {"policy": "signed"}},
    "shift": {"grouping": {"policy": "shift"}},
    "strict": {"grouping": {"policy": "strict"}},
    "as_printed_laplacian": {"grouping": {"laplacian": "as_printed"}},
    "as_printed_score": {"grouping": {"score": "as_printed"}},
    "embedding_space": {"grouping": {"space": "embedding"}},
    "sectors": {"sectors": 6},
    **{f"k_{k}": {"grouping": {"k_fixed": k}} for k in range(2, 9)},
}


def ablated_groups(df: DataFrame) -> dict[str, DataFrame]:
    """Groups with weight w under each of ABLATIONS. Those that group in one way share its rows, and all of them one pass over the pairs, which is written."""
    from accord.operators import motion
    from accord.scratch import written
    from accord.sources import carriers

    options = {name: grouping.Options(**o.get("grouping", {})) for name, o in ABLATIONS.items() if "sectors" not in o}
    first = {o: name for name, o in reversed(options.items())}
    unfiltered = [first[options[name]] for name, o in ABLATIONS.items() if name in options and not o.get("filter", True)]
    known = F.forall("motion", lambda m: m.isNotNull() & m["dx"].isNotNull() & m["dy"].isNotNull())
    rows = grouping.group_variants(df.withColumn("strong", F.coalesce(known & motion.strong(F.col("motion")), F.lit(False))), {name: o for o, name in first.items()})
    rows = written(rows.where(F.col("strong") | F.col("variant").isin(unfiltered)).sortWithinPartitions("variant"), "variants")
    out = {}
    for name, o in ABLATIONS.items():
        if k := o.get("sectors"):
            g = grouping.group_score(grouping.sectors(carriers.milli(motion.keep_strong(df)), k), k).withColumn("k", F.col("k_found"))
            out[name] = written(g.withColumn("w", pattern.weight("k_score")).drop("motion", "motion_m"), "pool")
        else:
            g = rows.where(F.col("variant") == first[options[name]])
            g = g.where("strong") if o.get("filter", True) else g
            out[name] = g.drop("variant", "strong").withColumn("w", pattern.weight(o.get("weight", "k_score")))
    return out

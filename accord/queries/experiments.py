"""The experiments: accuracy by source and N, one-class AUC, degradations, transfer, convergence of one video and its forgery, baselines and ablations.

They run on planted motion, so their figures show how the measures move, not what real videos give.
"""

from __future__ import annotations

import functools

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from accord.operators import anomaly, baselines, classify, distance, explain, flow, grouping, landmarks, metrics, motion, pattern, robustness, sampling
from accord.queries.method import query
from accord.scratch import written
from accord.sources import carriers

NS = (1, 10, 35, 70)
TASKS = ("A", "B", "C", "D")
#: Patterns of each source and half, pairs of a template, rounds of boosting, and the patterns of each source and half from which bin edges are taken.
PATTERNS, TEMPLATE, ROUNDS, EDGE_PATTERNS = 2000, 3000, 15, 40
#: Patterns of each source and half in ablations, of which there are many.
ABLATION_PATTERNS = 500


def pool(spark, d, df: DataFrame | None = None, o: grouping.Options = grouping.Options()) -> DataFrame:
    """All strong pairs, grouped once, with weight w: every experiment draws its patterns and templates from such a table."""
    df = carriers.face(spark, d) if df is None else df
    pairs = motion.keep_strong(df).withColumn("pool", F.concat_ws("/", "source", "half"))
    return written(grouping.group_pairs(pairs, o).withColumn("w", pattern.weight("k_score")), "pool")


def sets(groups: DataFrame, ns: tuple = NS, m: int = PATTERNS, of: str = "pool") -> DataFrame:
    """Packed patterns (source, half, y, pool, pattern_id, n_pick) of length 1, for all n in one plan: the draws of a smaller n are the first ones of a larger.

    m patterns of each source and half; of: pool draws over the source, video_id within single videos, among which the patterns are shared out."""
    small = pattern.packed_labels(groups.select("video_id", "t", "source", "half", "y", "pool", "labels", "w"))
    draws = sampling.pattern_sets(small, m, max(ns), of) if of == "pool" else sampling.pattern_sets(small, m, max(ns), of, share="pool")
    return pattern.prefixes(draws, ["source", "half", "y", of, "pattern_id"], ns)


def binned(groups: DataFrame, ns: tuple = NS, m: int = PATTERNS, of: str = "pool", bins: int = 32) -> DataFrame:
    """The patterns of sets() as written bins, whose edges are taken from EDGE_PATTERNS of each source and half."""
    edges = classify.bin_edges(sets(groups, ns, EDGE_PATTERNS, of).withColumnRenamed("tri", "features"), bins)
    rows = sets(groups, ns, m, of).withColumnRenamed("tri", "features").select("source", "half", "y", "pattern_id", "n_pick", "features")
    return written(classify.binize(rows, edges), "bins")


def tasks(rows: DataFrame) -> DataFrame:
    """The four binary tasks and the combined one; task names N too, so that all are learnt together."""
    each = classify.binary_tasks(rows, TASKS).unionByName(classify.combined_task(rows))
    return each.withColumn("forged", F.col("task")).withColumn("task", F.concat_ws("/", "task", F.col("n_pick").cast("string")))


def judged(rows: DataFrame, rounds: int = ROUNDS) -> DataFrame:
    """Boosted stumps learnt on half a (rows with task, y, bins), judging half b."""
    train = written(classify.by_task(rows.where("half = 'a'").select("task", "y", "bins")), "train")  # read once a round
    return classify.boost_predict_binned(rows.where("half = 'b'"), classify.boost_binned(train, rounds))


@query("experiment_accuracy")
def experiment_accuracy(spark, d):
    """Accuracy of boosted stumps on videos' other half, by forged source (and all of them) and N, patterns drawn over a source: 20 cells."""
    return metrics.accuracy(judged(tasks(binned(pool(spark, d)))), "forged", "n_pick")


@query("experiment_accuracy_video")
def experiment_accuracy_video(spark, d):
    """The same with the pairs of a pattern drawn from one video."""
    return metrics.accuracy(judged(tasks(binned(pool(spark, d), of="video_id"))), "forged", "n_pick")


@query("experiment_null")
def experiment_null(spark, d):
    """The same on the carrier whose labels carry no signal: accuracy should be about a half."""
    e = carriers.emb(spark, d)
    g = written(grouping.group_pairs(e.withColumn("pool", F.concat_ws("/", "source", "half"))).withColumn("w", pattern.weight("k_score")), "pool")
    rows = classify.binary_tasks(binned(g, (10,), bins=16))
    return metrics.accuracy(judged(rows), "task")


def scored(g: DataFrame, ns: tuple = NS, m: int = PATTERNS, template_source: str = "R") -> DataFrame:
    """(task, n_pick, source, y, d): distances of half b's patterns to a template of half a's genuine pairs, genuine ones in every task."""
    template = anomaly.template(g.where("half = 'a'"), TEMPLATE, template_source)
    s = anomaly.score_packed(sets(g.where("half = 'b'"), ns, m), template).withColumn("d", F.round("d", 9))
    forged = s.where("y = 1").withColumn("task", F.col("source"))
    return forged.unionByName(s.where("source = 'R'").withColumn("task", F.explode(F.array(*[F.lit(x) for x in TASKS]))))


@query("experiment_auc")
def experiment_auc(spark, d):
    """One-class AUC by forged source and N: distance to a template of genuine pairs of the other half."""
    return metrics.auc(scored(pool(spark, d)), "task", "n_pick").select("task", "n_pick", "auc")


@query("experiment_roc")
def experiment_roc(spark, d):
    """The curves behind it: false alarms and hits at every score, by forged source and N."""
    return metrics.roc(scored(pool(spark, d)), "task", "n_pick")


@query("experiment_equal_error")
def experiment_equal_error(spark, d):
    """Equal error rate of the same scores."""
    return metrics.equal_error(metrics.roc(scored(pool(spark, d)), "task", "n_pick"), "task", "n_pick")


@query("experiment_cross_real")
def experiment_cross_real(spark, d):
    """Distances of genuine and forged sources to a template of the second genuine source, N = 35."""
    g = pool(spark, d)
    s = anomaly.score_packed(sets(g.where("half = 'b'"), (35,)), anomaly.template(g.where("half = 'a'"), TEMPLATE, "R2"))
    return s.groupBy("source").agg(F.count("*").alias("n"), F.round(F.avg("d"), 6).alias("mean_d"))


@query("experiment_robustness")
def experiment_robustness(spark, d):
    """Source A at N = 35 under the four grades: accuracy of boosted stumps and one-class AUC, and their losses against the raw grade: 8 cells."""
    face = carriers.milli(carriers.face(spark, d)).where("source IN ('R', 'A')")
    out = None
    for grade in robustness.GRADES:
        g = robustness.graded(face, grade)
        back = g.withColumn("motion", F.transform("motion_m", lambda v: F.struct((v["x"] / 1000.0).alias("dx"), (v["y"] / 1000.0).alias("dy")))).drop("motion_m")
        its = pool(spark, d, back)
        auc = metrics.auc(scored(its, (35,)).where("task = 'A'"), "task").select("auc")
        rows = binned(its, (35,)).withColumn("task", F.lit("A"))
        one = metrics.accuracy(judged(rows), "task").select("accuracy").crossJoin(F.broadcast(auc)).withColumn("grade", F.lit(grade))  # one row
        out = one if out is None else out.unionByName(one)
    out = written(out, "grades")
    acc = metrics.delta(out.select("grade", "accuracy"), "raw", "accuracy").withColumnRenamed("loss", "accuracy_loss")
    return acc.join(metrics.delta(out.select("grade", "auc"), "raw", "auc").withColumnRenamed("loss", "auc_loss"), "grade")


@query("experiment_pixels")
def experiment_pixels(spark, d):
    """The grades on the pixels of images, before motion is estimated: flow, pooling and groups anew for each, against those of the raw images."""
    out = None
    for grade in robustness.GRADES:
        images = robustness.graded_images(carriers.img(spark, d), grade)
        flows = flow.estimate(flow.pack_pairs(images.drop("grade")))
        one = grouping.group_pairs(landmarks.motion_of(flows), keep=["video_id", "t"]).withColumn("grade", F.lit(grade))
        out = one if out is None else out.unionByName(one)
    out = written(out, "grades")
    raw = out.where("grade = 'raw'").select(F.col("video_id").alias("v"), F.col("t").alias("u"), F.col("labels").alias("first"))
    same = F.transform(F.sequence(F.lit(1), F.size("labels") - 1), lambda i: F.size(F.filter(F.sequence(F.lit(0), i - 1), lambda j: (F.get("labels", i) == F.get("labels", j)) == (F.get("first", i) == F.get("first", j)))))
    hits = F.aggregate(same, F.lit(0), lambda a, x: a + x) / (F.size("labels") * (F.size("labels") - 1) / 2)
    both = out.join(raw, (F.col("video_id") == F.col("v")) & (F.col("t") == F.col("u"))).withColumn("rand", hits)
    return both.groupBy("grade").agg(F.count("*").alias("n_pairs"), F.round(F.avg("rand"), 6).alias("rand_to_raw"), F.round(F.avg("k"), 4).alias("mean_k"))


@query("experiment_transfer")
def experiment_transfer(spark, d):
    """Accuracy on each source of a model learnt on another one, boosted stumps, for every N."""
    rows = classify.binary_tasks(binned(pool(spark, d))).withColumn("source_task", F.col("task")).withColumn("task", F.concat_ws("/", "task", F.col("n_pick").cast("string")))
    models = classify.boost_binned(written(classify.by_task(rows.where("half = 'a'").select("task", "y", "bins")), "train"), ROUNDS)
    test = rows.where("half = 'b'").withColumnRenamed("source_task", "test_source").withColumn("train_source", F.explode(F.array(*[F.lit(x) for x in TASKS]))).where("train_source <> test_source")
    test = test.withColumn("model", F.concat_ws("/", "train_source", F.col("n_pick").cast("string")))
    return metrics.accuracy(classify.boost_predict_binned(test, models, "model"), "train_source", "test_source", "n_pick")


@query("experiment_twin")
def experiment_twin(spark, d):
    """Each genuine video and the same vectors forged by source A's rule, as N grows: distance of each prefix to its own end, and of both to each other."""
    out = None
    for rule in ("R", "A"):
        one = carriers.face(spark, d, twin=rule).where("source = 'R'").withColumn("rule", F.lit(rule)).withColumn("video_id", F.concat_ws("/", "video_id", F.lit(rule)))
        out = one if out is None else out.unionByName(one)
    g = grouping.group_pairs(sampling.ranked(motion.keep_strong(out))).withColumn("w", pattern.weight("k_score")).withColumn("draw", F.col("pick") - 1)
    ns, whole = NS, 1 << 30
    p = written(pattern.prefixes(g, ["video_id", "rule"], (*ns, whole)).withColumn("video", F.split_part("video_id", F.lit("/"), F.lit(1))), "twins")
    end = p.where(F.col("n_pick") == whole).select(F.col("video_id").alias("v"), F.col("tri").alias("end_tri"))
    own = p.join(end, F.col("video_id") == F.col("v")).select("video", "rule", "n_pick", F.round(distance.js(F.col("tri"), F.col("end_tri")), 6).alias("to_end"))
    a, b = (p.where(F.col("rule") == r).select("video", "n_pick", F.col("tri").alias(c)) for r, c in (("R", "ta"), ("A", "tb")))
    apart = a.join(b, ["video", "n_pick"]).select("video", "n_pick", F.round(distance.js(F.col("ta"), F.col("tb")), 6).alias("apart"))
    return own.join(apart, ["video", "n_pick"]).where(F.col("n_pick") < whole)


@query("experiment_mean_agreement")
def experiment_mean_agreement(spark, d):
    """Mean of 1,000 spectral agreement matrices of each source: structure of the facial components, by source."""
    s = explain.structure_checks(explain.mean_agreement(pool(spark, d), 1000))
    return s.select("source", *[F.round(c, 6).alias(c) for c in ("eyes", "upper_face", "brow_eye", "lip_opposition")])


@query("experiment_score_space")
def experiment_score_space(spark, d):
    """One-class AUC at N = 35 with the validity index in either space, without a cap and capped at what 90 % of genuine training pairs stay under."""
    out = None
    for space in ("motion", "embedding"):
        g = pool(spark, d, o=grouping.Options(space=space))
        cap = F.broadcast(pattern.score_cap(g.where("source = 'R' AND half = 'a'")))  # one row
        for name, its in (("none", g), ("p90", g.crossJoin(cap).withColumn("w", pattern.weight("k_score", F.col("cap"))).drop("cap"))):
            one = metrics.auc(scored(its, (35,)), "task").select(F.lit(space).alias("space"), F.lit(name).alias("cap"), "task", "auc")
            out = one if out is None else out.unionByName(one)
    return out


@query("experiment_calibrated")
def experiment_calibrated(spark, d):
    """The filter's threshold from 100 videos of the same data: the quantile of their magnitudes, and the AUC at N = 35 with it."""
    face = carriers.face(spark, d)
    tau = written(motion.calibrate(face), "tau")
    pairs = motion.keep_strong(face, tau=tau).withColumn("pool", F.concat_ws("/", "source", "half"))
    g = written(grouping.group_pairs(pairs).withColumn("w", pattern.weight("k_score")), "pool")
    auc = metrics.auc(scored(g, (35,)), "task").select("task", "auc")
    return auc.crossJoin(F.broadcast(tau.select(F.round("tau", 6).alias("tau"))))  # one row


@query("experiment_documents")
def experiment_documents(spark, d):
    """Real labels: lines of documents as frames, quality as truth, distance to a template of good documents, and to one of the benchmark."""
    docs = motion.keep_strong(carriers.doc(spark, d), tau=0.01)
    g = grouping.group_pairs(docs).withColumn("w", pattern.weight("k_score"))
    bench = grouping.group_pairs(motion.keep_strong(carriers.benchmark(spark, d), tau=0.01)).withColumn("w", pattern.weight("k_score"))
    split = sampling.split(g)
    probes = pattern.build(split.where("NOT train"), ["video_id", "y"])
    out = None
    for name, pairs, source in (("good", split.where("train"), "R"), ("benchmark", bench, "R2")):
        s = anomaly.score(probes, anomaly.template(pairs, 3000, source)).withColumn("d", F.round("d", 9))
        one = metrics.auc(s.withColumn("template", F.lit(name)), "template")
        out = one if out is None else out.unionByName(one)
    return out


@query("experiment_baselines")
def experiment_baselines(spark, d):
    """Stand-ins for published baselines and the method itself (N = 35), on every forged source and all of them against genuine videos: trained on one half of the vectors,
    judged on the other."""
    face = written(motion.keep_strong(carriers.face(spark, d)), "strong")
    made = {name: written(f(face).withColumn("half", F.element_at(F.split("video_id", "-"), -1)), "features") for name, f in (("recurrent", baselines.recurrent_features), ("first_order", baselines.first_order))}
    e = carriers.read(spark, d, "embeddings").select(F.concat_ws("-", F.col("label").cast("string"), (F.col("vec_id") % 8).cast("string"), carriers.half_of(F.col("vec_id"))).alias("video_id"), carriers.source_of(F.col("label")).alias("source"), F.when(F.col("label") % 5 == 0, 0).otherwise(1).alias("y"), F.col("vec_id").alias("t"), F.col("embedding").alias("vector"))
    made["embedding_sequence"] = written(baselines.embedding_sequence(e).withColumn("half", F.element_at(F.split("video_id", "-"), -1)), "features")
    residual = written(baselines.noise_residual(carriers.tall(carriers.face(spark, d), "source", "y")), "residuals")
    method = judged(tasks(binned(pool(spark, d), (35,))))
    out = [metrics.accuracy(method, "forged").select(F.lit("method").alias("baseline"), F.col("forged").alias("task"), "n", "accuracy")]
    for task, sources in (*((s, (s,)) for s in TASKS), ("combined", TASKS)):
        mine = F.col("source").isin("R", *sources)
        a, b = face.where(mine & (F.col("half") == "a")), face.where(mine & (F.col("half") == "b"))
        rows = [("single_frame", baselines.frame_vote(a, b, "lr"))]
        for name, kind in (("recurrent", "lr"), ("first_order", "mlp"), ("embedding_sequence", "gbt")):
            f = made[name].where(mine)
            rows.append((name, classify.mllib_predict(f.where("half = 'b'"), classify.mllib_fit(f.where("half = 'a'"), kind))))
        rows.append(("noise_residual", baselines.noise_score(residual.where(mine)).withColumn("pred", (F.col("d") >= 2).cast("int"))))
        out += [metrics.accuracy(r.withColumn("baseline", F.lit(name)), "baseline").select("baseline", F.lit(task).alias("task"), "n", "accuracy") for name, r in rows]
    return functools.reduce(DataFrame.unionByName, out)


@query("experiment_ablations")
def experiment_ablations(spark, d):
    """One-class AUC of sources A and D at N = 35 with one choice of the method changed at a time."""
    face = carriers.face(spark, d).where("source IN ('R', 'A', 'D')").withColumn("pool", F.concat_ws("/", "source", "half"))
    out = [metrics.auc(scored(g, (35,), ABLATION_PATTERNS).where("task IN ('A', 'D')"), "task").select("task", "auc", F.lit(name).alias("ablation")) for name, g in baselines.ablated_groups(face).items()]
    return functools.reduce(DataFrame.unionByName, out)


@query("experiment_pooling")
def experiment_pooling(spark, d):
    """Pooling around landmarks against none, on images: groups in use, index and degenerate pairs of the motion that either gives."""
    flows = written(flow.estimate(flow.pack_pairs(carriers.img(spark, d))).select("video_id", "t", "h", "w", "u", "v"), "flows")
    out = [grouping.group_pairs(landmarks.motion_of(flows, kind=kind), keep=["video_id", "t"]).withColumn("pooling", F.lit(kind)) for kind in ("gauss", "box", "point")]
    rows = functools.reduce(DataFrame.unionByName, out)
    return rows.groupBy("pooling").agg(F.count("*").alias("n_pairs"), F.round(F.avg("k"), 4).alias("mean_k"), F.round(F.avg("score"), 3).alias("mean_score"), F.sum(F.col("degenerate").cast("long")).alias("n_degenerate"))


@query("experiment_learners")
def experiment_learners(spark, d):
    """Other learners on the same patterns, source A, N = 35: boosted stumps, their real-valued variant, and MLlib's."""
    g = pool(spark, d).where("source IN ('R', 'A')")
    rows = written(sets(g, (35,)).withColumnRenamed("tri", "features").drop("diag", "n"), "patterns")
    a, b = rows.where("half = 'a'"), rows.where("half = 'b'")
    out = [("boosted_trees_of_depth_1", classify.predict_mllib_boost(b, classify.boost_fit_mllib(a, 5)))]
    out += [(kind, classify.mllib_predict(b, classify.mllib_fit(a, kind))) for kind in ("lr", "svc", "rf", "gbt", "mlp")]
    bins = written(classify.binize(rows, classify.bin_edges(rows.where(F.col("pattern_id") < EDGE_PATTERNS))).withColumn("task", F.lit("A")), "bins")
    test, train = bins.where("half = 'b'"), bins.where("half = 'a'")
    out.append(("boosted_stumps", classify.boost_predict_binned(test, classify.boost_binned(train, ROUNDS))))
    out.append(("boosted_real_valued", classify.boost_predict_binned(test, classify.boost_real(train, ROUNDS), real=True)))
    return functools.reduce(DataFrame.unionByName, [metrics.accuracy(r.withColumn("learner", F.lit(k)), "learner") for k, r in out])


@query("conversation_groups")
def conversation_groups(spark, d):
    """Turns of conversations as frames: groups in use and index, by number of groups."""
    g = grouping.group_pairs(motion.keep_strong(carriers.conv(spark, d), tau=0.01), keep=["video_id", "t"])
    return g.groupBy("k").agg(F.count("*").alias("n_pairs"), F.round(F.avg("score"), 3).alias("mean_score"))


@query("scene_source")
def scene_source(spark, d):
    """Grouping of planted scenes, one from each vector of the table: mean Rand index against the planted groups."""
    from accord.sources import scene

    g = grouping.group_pairs(scene.planted(carriers.read(spark, d, "embeddings"), noise=0.05).repartition(spark.sparkContext.defaultParallelism))
    hits = F.aggregate(F.flatten(F.transform(F.sequence(F.lit(1), F.size("labels") - 1), lambda i: F.transform(F.sequence(F.lit(0), i - 1), lambda j: ((F.get("labels", i) == F.get("labels", j)) == (F.get("truth", i) == F.get("truth", j))).cast("int")))), F.lit(0), lambda a, x: a + x)
    n = F.size("labels")
    return g.withColumn("rand", hits / (n * (n - 1) / 2)).groupBy("source").agg(F.count("*").alias("n_pairs"), F.round(F.avg("rand"), 6).alias("rand"))

"""Streams against their batch twins, recovery from a checkpoint, sources and sinks."""

import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from accord.functions import sqlfns, udfs
from accord.operators import anomaly, grouping, pattern
from accord.queries import surface
from accord.sources import carriers, files, scene
from accord.streaming import live
from conftest import SF, same_rows


def drained(df, name, tmp_path, mode="append", **trigger):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / name)).trigger(**(trigger or {"availableNow": True})).start()
    try:
        assert q.awaitTermination(180)
    finally:
        q.stop()
    return df.sparkSession.table(name)


def event_files(spark, tmp_path, parts=4):
    e = carriers.read(spark, SF, "events").orderBy("ts")
    at = tmp_path / "events"
    rows = e.withColumn("k", F.ntile(parts).over(surface.W.orderBy("ts", "event_id")))
    for k in range(1, parts + 1):
        rows.where(F.col("k") == k).drop("k").coalesce(1).write.mode("append").parquet(str(at))
    return str(at), e.schema


def test_tumbling_stream_equals_its_twin(spark, tmp_path):
    at, schema = event_files(spark, tmp_path)
    stream = live.timed(spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(at), "40 days")
    out = drained(live.tumbling(stream), "tumbled", tmp_path, "complete")
    got = out.select("user_id", live.frame_of(F.col("window.start")).alias("frame"), "event_type", "n", F.round("mean", 6).alias("mean"))
    twin = surface.stream_tumbling_batch(spark, SF)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, twin.collect()))


def test_late_rows_are_dropped_and_repeats_once(spark, tmp_path):
    at = str(tmp_path / "late")
    rows = lambda *x: spark.createDataFrame(list(x), "event_id long, s string").withColumn("ts", F.to_timestamp("s")).drop("s").coalesce(1)
    rows((1, "2024-01-01 00:00:00"), (1, "2024-01-01 00:00:00"), (2, "2024-01-05 00:00:00")).write.mode("append").parquet(at)
    stream = spark.readStream.schema("event_id long, ts timestamp").parquet(at)
    first = live.once(live.timed(stream, "1 hour"), "event_id")
    def ids():
        q = first.writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "once")).trigger(availableNow=True).start()
        assert q.awaitTermination(120)
        return sorted(r.event_id for r in spark.read.parquet(str(tmp_path / "out")).collect())

    assert ids() == [1, 2]
    rows((3, "2024-01-01 00:00:00"), (4, "2024-01-06 00:00:00")).write.mode("append").parquet(at)
    assert ids() == [1, 2, 4]  # the checkpoint knows the watermark: 3 is late


def test_live_detection_equals_the_batch(spark, tmp_path):
    scene.register(spark)
    batch = spark.read.format("accord_scene").option("videos", 4).option("frames", 12).option("forged", "0.4").load()
    groups = live.grouped(batch).select("video_id", "y", "t", "labels", "w")
    template = pattern.l1(pattern.build(groups.where("y = 0"), ["y"])).first().tri
    at = str(tmp_path / "pairs")
    groups.drop("y").repartition(3).write.parquet(at)
    stream = spark.readStream.schema("video_id string, t int, labels array<int>, w double").option("maxFilesPerTrigger", 1).parquet(at)
    found = live.detect(stream, np.array(template), 0.02, marks=(12,))
    q = found.writeStream.format("memory").queryName("live").option("checkpointLocation", str(tmp_path / "live")).trigger(processingTime="500 milliseconds").start()
    out = spark.table("live")
    try:  # idle timeouts keep the query alive: it is stopped when all videos are through
        for _ in range(120):
            time.sleep(0.5)
            if q.exception() or out.where("n_pairs = 12").count() >= 4:
                break
    finally:
        q.stop()
    got = {r.video_id: r.distance for r in out.where("n_pairs = 12").collect()}
    one = spark.createDataFrame([(list(template),)], "tri array<double>")
    want = {r.video_id: r.d for r in anomaly.score(pattern.build(groups, ["video_id"]), one).collect()}
    assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k], abs=1e-9) for k in got)


def test_live_pairing_over_a_restart(spark, tmp_path):
    """Frames in any order, some twice, over two runs of one checkpoint: every pair of neighbours once, as in the batch."""
    rng = np.random.default_rng(5)
    frames = {(v, t): rng.normal(size=6).round(3).tolist() for v in ("a", "b") for t in range(12) if (v, t) != ("b", 5)}
    order = rng.permutation(len(frames))
    rows = [(*k, f"2024-01-01 00:00:{k[1]:02}", frames[k]) for k in (list(frames)[i] for i in order)]
    at, out = str(tmp_path / "frames"), str(tmp_path / "out")

    def put(some):
        spark.createDataFrame(some, "video_id string, t int, s string, position array<double>").withColumn("ts", F.to_timestamp("s")).drop("s").coalesce(1).write.mode("append").parquet(at)

    def run():
        stream = spark.readStream.schema("video_id string, t int, position array<double>, ts timestamp").option("maxFilesPerTrigger", 1).parquet(at).withWatermark("ts", "1 hour")
        q = live.paired(stream).writeStream.format("parquet").option("path", out).option("checkpointLocation", str(tmp_path / "pairing")).trigger(availableNow=True).start()
        assert q.awaitTermination(180)

    put(rows[:9]), put(rows[9:14])
    run()
    put(rows[12:]), put(rows[:3])
    run()
    got = [(r.video_id, r.t, [(m.dx, m.dy) for m in r.motion]) for r in spark.read.parquet(out).collect()]
    want = {(v, t): np.subtract(frames[v, t + 1], frames[v, t]).reshape(-1, 2) for v, t in frames if (v, t + 1) in frames}
    assert sorted(g[:2] for g in got) == sorted(want)
    for v, t, m in got:
        assert np.allclose(m, want[v, t])


def test_files_round_trip(spark, tmp_path):
    df = carriers.read(spark, SF, "supplier")
    for kind in ("parquet", "orc", "json", "csv"):
        files.write(df, str(tmp_path / kind), kind)
        back = files.read(spark, str(tmp_path / kind), kind, None if kind in ("parquet", "orc") else df.schema)
        assert sorted(map(tuple, back.select(*df.columns).collect())) == sorted(map(tuple, df.collect()))
    with pytest.raises(ValueError):
        files.read(spark, str(tmp_path / "csv"), "csv")
    with pytest.raises(ValueError):
        files.require(df, "s_suppkey string")
    files.write(carriers.read(spark, SF, "nation"), str(tmp_path / "by"), by=("n_regionkey",))
    assert spark.read.parquet(str(tmp_path / "by")).where("n_regionkey = 1").count() == 5
    put = files.upsert_batches(str(tmp_path / "up"), ["k"])
    a, b = (spark.createDataFrame([(1, v), (2, v)], "k int, v string") for v in ("old", "new"))
    put(a, 0), put(b.where("k = 1"), 1), put(b.where("k = 1"), 1)
    assert {r.k: r.v for r in files.latest(spark, str(tmp_path / "up"), ["k"]).collect()} == {1: "new", 2: "old"}


def test_sql_functions_and_udfs(spark):
    sqlfns.register(spark)
    r = spark.sql("SELECT js_divergence(array(0.5D, 0.5D), array(0.5D, 0.5D)) AS z, js_divergence(array(1D, 0D), array(0D, 1D)) AS top, kl_divergence(array(1D), array(0D)) AS no, agreement(array(0, 0, 1)) AS a, strong_share(array(named_struct('dx', 1D, 'dy', 0D), named_struct('dx', 0D, 'dy', 0D)), 0.85D) AS s").first()
    assert r.z == 0 and r.top == pytest.approx(np.log(2)) and r.no is None and r.a == [1, 0, 0] and r.s == 0.5
    points = spark.sql("SELECT * FROM roc_points(array(0.9D, 0.1D), array(1, 0))").collect()
    assert [(p.fpr, p.tpr) for p in points] == [(0, 1), (1, 1)]
    scene.register(spark)
    df = spark.read.format("accord_scene").option("videos", 2).option("frames", 3).load()
    flat = df.select("video_id", "t", F.transform("motion", lambda m: m["dx"]).alias("dx"), F.transform("motion", lambda m: m["dy"]).alias("dy"))
    a = {(r.video_id, r.t): r.g.labels for r in flat.select("video_id", "t", udfs.group_motion("dx", "dy").alias("g")).collect()}
    b = {(r.video_id, r.t): r.labels for r in grouping.group_pairs(df).collect()}
    assert a == b
    g = grouping.group_pairs(df).withColumn("w", F.lit(1.0))
    x = {r.video_id: r.p for r in g.groupBy("video_id").agg(udfs.pattern_agg("labels", "w").alias("p")).collect()}
    y = {r.video_id: r.tri for r in pattern.build(g, ["video_id"]).collect()}
    assert x == y


def test_sketches_are_near(spark, duck):
    got = {r.event_type: r for r in surface.agg_approx(spark, SF).collect()}
    for kind, users, median in duck.sql("SELECT event_type, count(DISTINCT user_id), quantile_cont(value, 0.5) FROM events GROUP BY 1").fetchall():
        assert abs(got[kind].users - users) <= max(1, 0.06 * users) and abs(got[kind].median - median) < 4


#: Queries of every kind; the driver compares all of them.
SOME = "motion_filter motion_threshold affinity_policy degree laplacian_sym group_score select_k component_groups pattern_build pattern_l1 pick_n split_no_overlap js_divergence auc convergence structure_checks source_distance top_abnormal_cells noise_motion boost_first_stump transfer_matrix flow_local_ls flow_block_match motion_pool join_asof join_interval join_lateral agg_cube win_range_frame fn_variant udtf_explode_pattern stream_session_batch".split()


@pytest.mark.parametrize("name", SOME)
def test_query_against_sql(spark, duck, name):
    import accord.queries as Q

    same_rows(Q.QUERIES[name](spark, SF), duck.sql(Q.ORACLES[name]))


def test_entry(spark):
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    assert e.entry(spark).count() == 16

"""Carriers: how the given tables become videos, that is, sequences of aligned sets of 2-D motion vectors.

Packed form (one row per frame pair): video_id, source, y (1 forged), t, motion array<struct<dx,dy>>.
Tall form (one row per landmark): video_id, source, y, t, lm, dx_m, dy_m, the motion in thousandths as whole numbers, so sums don't depend on order.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

#: The landmarks of each facial component, after the 17 boundary points are dropped.
COMPONENTS = (range(0, 5), range(5, 10), range(10, 14), range(14, 19), range(19, 25), range(25, 31), (*range(31, 38), *range(43, 48)), (*range(38, 43), *range(48, 51)))
LANDMARKS = 51
SOURCES = ("R", "A", "B", "C", "D")
#: By source A to D, in hundredths and thousandths: pairs whose lips lose their opposition, and landmarks that come loose.
LIPS_LOST, LOOSE = (50, 40, 25, 15), (200, 150, 80, 50)


def component_of(i: int) -> int:
    return next(c for c, own in enumerate(COMPONENTS) if i in own)


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def source_of(label: Column) -> Column:
    return F.when(label == 0, "R").when(label == 5, "R2").otherwise(F.element_at(F.array(*[F.lit(s) for s in SOURCES]), (label % 5 + 1).cast("int")))


def half_of(vec_id: Column) -> Column:
    """The split half of a vector: all rotations of one vector share it."""
    return F.when(F.substring(F.md5(vec_id.cast("string").cast("binary")), 1, 1) < "8", "a").otherwise("b")


def face(spark: SparkSession, sf_dir: str, rotations: int = 16, twin: str | None = None) -> DataFrame:
    """Planted face motion over embeddings, packed. twin: the forging rule of that source for every vector (None: the label's own).

    Places in time are given before vectors are turned, so only the table itself is dealt; motion is made in Arrow batches."""
    rows = read(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label", half_of(F.col("vec_id")).alias("half"))
    rows = rows.withColumn("t", F.row_number().over(W.partitionBy("label", "half").orderBy("vec_id")) - 1)
    rule = F.lit(SOURCES.index(twin)) if twin else F.col("label") % 5
    rows = rows.select("vec_id", rule.cast("int").alias("rule"), "label", "half", "t", "embedding")
    parts = max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")))
    comp = np.array([component_of(i) for i in range(LANDMARKS)])
    still = np.where(comp == 7, 6, comp - comp % 2)
    lm = np.arange(LANDMARKS)

    def turned(batches):
        import pyarrow as pa

        for b in batches:
            v, rules = (b.column(i).to_numpy(zero_copy_only=False).astype(np.int64)[:, None] for i in (0, 1))
            e = b.column(5).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(b.num_rows, 64) if b.num_rows else np.zeros((0, 64))
            at = np.arange(b.num_rows)[:, None]
            for r in range(rotations):
                lips = (17 * v + 29 * r) % 100 < np.array([0, *LIPS_LOST])[rules]
                loose = (131 * v + 17 * r + 7919 * lm) % 1000 < np.array([0, *LOOSE])[rules]
                z = np.where(loose, (comp + 1 + (lm + v) % 7) % 8, still)
                sign = np.where(~loose & (comp == 7) & ~lips, -1.0, 1.0)
                dx, dy = (8 * (0.3 * e[:, [(16 + k + 4 * r) % 64]] + sign * e[at, (2 * z + k + 4 * r) % 64] + 0.5 * e[:, (18 + 2 * lm % 46 + k + 4 * r) % 64]) for k in (0, 1))
                cells = pa.StructArray.from_arrays([pa.array(dx.ravel()), pa.array(dy.ravel())], names=["dx", "dy"])
                motion = pa.ListArray.from_arrays(pa.array(np.arange(0, dx.size + 1, LANDMARKS, dtype=np.int32)), cells)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(b.num_rows, r, np.int32)), *b.columns[2:5], motion], names=["r", "label", "half", "t", "motion"])

    out = rows.repartition(parts, "vec_id").mapInArrow(turned, f"r int, label {rows.schema['label'].dataType.simpleString()}, half string, t int, motion array<struct<dx:double,dy:double>>")
    video = F.concat_ws("-", F.col("label").cast("string"), F.col("r").cast("string"), "half")
    return out.select(video.alias("video_id"), source_of(F.col("label")).alias("source"), F.when(F.col("label") % 5 == 0, 0).otherwise(1).alias("y"), "t", "motion", "half")


def emb(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The null carrier: pairs of raw numbers as motion; labels carry no signal."""
    rows = read(spark, sf_dir, "embeddings")
    at = lambda j: F.element_at("embedding", (j + 1).cast("int")).cast("double")
    motion = F.transform(F.sequence(F.lit(0), F.lit(31)), lambda i: F.struct((8 * at(2 * i)).alias("dx"), (8 * at(2 * i + 1)).alias("dy")))
    t = F.row_number().over(W.partitionBy("label", half_of(F.col("vec_id"))).orderBy("vec_id")) - 1
    return rows.select(F.concat_ws("-", F.col("label").cast("string"), half_of(F.col("vec_id"))).alias("video_id"), source_of(F.col("label")).alias("source"), F.when(F.col("label") % 5 == 0, 0).otherwise(1).alias("y"), t.alias("t"), motion.alias("motion"), half_of(F.col("vec_id")).alias("half"))


def _moved(at: DataFrame, n: int) -> DataFrame:
    """Positions (video_id, t, lm, px, py) to packed motion: each landmark's position in the next frame less that in this one; 0 where either is missing."""
    cells = at.select("video_id", "t", "lm", "px", "py")
    after = cells.select("video_id", (F.col("t") - 1).alias("t"), "lm", F.col("px").alias("qx"), F.col("py").alias("qy"))
    frames = cells.select("video_id", "t").distinct()
    frames = frames.join(frames.select("video_id", (F.col("t") - 1).alias("t")), ["video_id", "t"])
    moved = cells.join(after, ["video_id", "t", "lm"]).groupBy("video_id", "t").agg(F.map_from_entries(F.collect_list(F.struct("lm", F.struct((F.col("qx") - F.col("px")).alias("dx"), (F.col("qy") - F.col("py")).alias("dy"))))).alias("m"))
    none = F.struct(F.lit(0.0).alias("dx"), F.lit(0.0).alias("dy"))
    full = F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.coalesce(F.try_element_at("m", i), none))
    return frames.join(moved, ["video_id", "t"], "left").select("video_id", F.col("t").cast("int").alias("t"), full.alias("motion"))


#: The event types in landmark order.
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")


def evt_positions(events: DataFrame) -> DataFrame:
    """(video_id, t, lm, px, py) of events: 3-day windows, one landmark per event type, mean value and mean props.k.

    Values are added up in the order of event_id: moves that lie just between two thousandths would else be rounded as the layout has it. props.k is whole, its sums are exact."""
    day = F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date"))
    lm = F.array_position(F.array(*[F.lit(x) for x in EVENT_TYPES]), F.col("event_type")) - 1
    cells = events.select(F.col("user_id").cast("string").alias("video_id"), F.floor(day / 3).cast("int").alias("t"), lm.cast("int").alias("lm"), F.when(F.col("value").isNotNull(), F.struct("event_id", "value")).alias("at"), F.get_json_object("props", "$.k").cast("double").alias("k"))
    in_order = F.array_sort(F.collect_list("at"))  # one user's events of one type in three days
    mean = F.try_divide(F.aggregate(in_order, F.lit(0.0), lambda a, x: a + x["value"]), F.size(in_order))
    return cells.groupBy("video_id", "t", "lm").agg(mean.alias("px"), F.avg("k").alias("py"))


def evt(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _moved(evt_positions(read(spark, sf_dir, "events")), len(EVENT_TYPES))


def li_positions(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = read(spark, sf_dir, "lineitem")
    t = (F.year("l_shipdate") - 1995) * 4 + F.quarter("l_shipdate") - 1
    return li.groupBy(F.col("l_suppkey").cast("string").alias("video_id"), t.alias("t"), (F.col("l_linenumber") - 1).alias("lm")).agg(F.avg("l_quantity").alias("px"), F.avg(100 * F.col("l_discount")).alias("py"))


def li(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _moved(li_positions(spark, sf_dir), 7)


def img_tall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Images (video_id region name, t quarter, x 0-9, y 0-10, i): sums of quantity by quantity decile and discount step; absent cells are 0."""
    li = read(spark, sf_dir, "lineitem").select("l_suppkey", "l_quantity", "l_discount", "l_shipdate")
    supp = read(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    nation = read(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    region = read(spark, sf_dir, "region").select("r_regionkey", "r_name")
    star = li.join(supp, F.col("l_suppkey") == F.col("s_suppkey")).join(nation, F.col("s_nationkey") == F.col("n_nationkey")).join(region, F.col("n_regionkey") == F.col("r_regionkey"))
    t = ((F.year("l_shipdate") - 1995) * 4 + F.quarter("l_shipdate") - 1).cast("int")
    cells = star.groupBy(F.col("r_name").alias("video_id"), t.alias("t"), F.floor((F.col("l_quantity") - 1) / 5).cast("int").alias("x"), F.round(100 * F.col("l_discount")).cast("int").alias("y")).agg(F.sum("l_quantity").cast("double").alias("i"))
    frames = cells.select("video_id", "t").distinct()
    grid = frames.withColumn("x", F.explode(F.sequence(F.lit(0), F.lit(9)))).withColumn("y", F.explode(F.sequence(F.lit(0), F.lit(10))))
    return grid.join(cells, ["video_id", "t", "x", "y"], "left").select("video_id", "t", "x", "y", F.coalesce("i", F.lit(0.0)).alias("i"))


def img(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Packed images: video_id, t, h, w, px (row-major by y)."""
    tall = img_tall(spark, sf_dir)
    return tall.groupBy("video_id", "t").agg(F.transform(F.array_sort(F.collect_list(F.struct("y", "x", "i"))), lambda c: c["i"]).alias("px")).select("video_id", "t", F.lit(11).alias("h"), F.lit(10).alias("w"), "px")


#: Letter classes of text carriers.
CLASSES = ("a", "e", "i", "o", "u", "lmnr", "bcdgkpqt", "fhjsvwxyz")


def _line_motion(lines: DataFrame) -> DataFrame:
    """(video_id, t, line) to packed motion: change of each class's share in the first and the second half of the line to the next line."""
    low = F.lower("line")
    n = F.length("line")
    half = F.ceil(n / 2).cast("int")
    first, second = low.substr(F.lit(1), half), low.substr(half + 1, n)
    share = lambda part, c: F.coalesce(F.try_divide(F.regexp_count(part, F.lit(f"[{c}]")), F.length(part)), F.lit(0.0))
    at = lines.select("video_id", "t", F.array(*[F.struct(share(first, c).alias("px"), share(second, c).alias("py")) for c in CLASSES]).alias("at"))
    nxt = at.withColumn("after", F.lead("at").over(W.partitionBy("video_id").orderBy("t"))).where("after is not null")
    return nxt.select("video_id", F.col("t").cast("int").alias("t"), F.zip_with("at", "after", lambda a, b: F.struct((b["px"] - a["px"]).alias("dx"), (b["py"] - a["py"]).alias("dy"))).alias("motion"))


def doc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents as videos of lines; y = 1 - quality, source R or A; those without a label are left out."""
    docs = read(spark, sf_dir, "documents").join(read(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id")
    lines = docs.select(F.col("doc_id").cast("string").alias("video_id"), (1 - F.col("quality")).alias("y"), F.posexplode(F.filter(F.split("text", "\n"), lambda x: F.trim(x) != "")).alias("t", "line"))
    moved = _line_motion(lines)
    y = lines.select("video_id", "y").distinct()
    return moved.join(y, "video_id").withColumn("source", F.when(F.col("y") == 1, "A").otherwise("R"))


def conv(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "conversations").select(F.col("conv_id").cast("string").alias("video_id"), F.col("turn").alias("t"), F.col("text").alias("line"))
    return _line_motion(rows)


def benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "benchmark").select(F.col("item_id").cast("string").alias("video_id"), F.posexplode(F.filter(F.split("text", "\n"), lambda x: F.trim(x) != "")).alias("t", "line"))
    return _line_motion(rows).withColumn("source", F.lit("R2")).withColumn("y", F.lit(0))


def tall(packed: DataFrame, *keep: str) -> DataFrame:
    """Packed to tall: lm, dx_m and dy_m in thousandths."""
    milli = lambda c: F.round(1000 * F.col(c)).cast("bigint")
    return packed.select("video_id", *keep, "t", F.posexplode("motion").alias("lm", "m")).select("video_id", *keep, "t", "lm", milli("m.dx").alias("dx_m"), milli("m.dy").alias("dy_m"))


def milli(packed: DataFrame) -> DataFrame:
    """Packed motion rounded to thousandths, as whole numbers: motion_m array<struct<x,y>>."""
    whole = lambda c: F.round(1000 * c).cast("bigint")
    return packed.withColumn("motion_m", F.transform("motion", lambda m: F.struct(whole(m["dx"]).alias("x"), whole(m["dy"]).alias("y"))))

"""Mixing sources to target weights by weighted fair queueing.

Every source is a queue of shuffled documents, gone through up to `most` times. A document's virtual finish time is the number of
words its queue has given out by its end, divided by its source's target. Documents are taken in order of finish time until the budget
is spent, so at any point of the mix every source has had nearly its share.

Nulls: a null source is a source of its own, the last one; a null text has size 0. Rows of size 0 and of sources without words take 0.
Rows that agree in id, source and size share one place in the order. Long texts are counted whole. All columns of the input come back as they were,
whatever their names: a new column whose name is taken gets an underscore after it. An empty table gives no rows.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from accord.llm.common import WORD, spare, table, written

#: Cells of finish time per unit, and units, of the histogram in which the end of the mix is looked up; the last cell takes all beyond.
GRAIN, UNITS = 4096, 4
#: The columns that mixed() adds.
ADDED = ("mix_size", "mix_source_size", "mix_target", "mix_finish", "mix_taken")


def sized(docs: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source") -> DataFrame:
    """(key, source, size, tie): words of the whole text, and the document's place in its source's shuffle."""
    k = F.col(f"`{key}`")
    return docs.select(k.alias("doc_id"), F.col(f"`{source}`").alias("source"), _words(text).alias("size"), _tie(k).alias("tie"))


def _words(text: str):
    return F.coalesce(F.regexp_count(F.col(f"`{text}`"), F.lit(WORD)), F.lit(0)).cast("long")


def _tie(key):
    return F.substring(F.md5(F.coalesce(key.cast("string"), F.lit("")).cast("binary")), 1, 16)


def targets(sizes: DataFrame, weights: tuple = (5, 2, 1), budget: tuple = (3, 2), most: int = 2) -> DataFrame:
    """One row per source: (place, source, source_size, target). Sources by code point, null last, have the weights in turn.

    The sources share budget[0] / budget[1] of all words by weight; a target stops at `most` times the source's size and what is over is
    shared out again by weight until none is above. A source is at its stop if, with all sources level with it, no more than the budget is used.
    """
    num, den = budget
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    order = Window.orderBy(F.col("source").asc_nulls_last())  # one row per source from here on
    per = per.withColumn("place", F.row_number().over(order)).withColumn("w", F.array(*[F.lit(w) for w in weights])[(F.col("place") - 1) % len(weights)].cast("long"))
    stop = F.col("source_size") * most
    filled = Window.orderBy(stop / F.col("w"), "place").rowsBetween(Window.unboundedPreceding, 0)
    everything = Window.partitionBy()
    per = per.withColumns({"used": F.sum(stop).over(filled), "left": F.sum("w").over(everything) - F.sum("w").over(filled), "words": F.sum("source_size").over(everything)})
    level = F.col("used").cast("double") + stop.cast("double") / F.col("w") * F.col("left")
    per = per.withColumn("full", level * den <= F.col("words").cast("double") * num)
    rest = Window.partitionBy()
    per = per.withColumns({"spent": F.sum(F.when(F.col("full"), stop).otherwise(0)).over(rest), "open": F.sum(F.when(~F.col("full"), F.col("w")).otherwise(0)).over(rest)})
    share = (F.col("words") * num - F.col("spent") * den).cast("double") * F.col("w") / F.nullif(F.col("open") * den, F.lit(0))
    return per.select("place", "source", "source_size", F.when(F.col("full"), stop.cast("double")).otherwise(share).alias("target"))


def _planned(sizes: DataFrame, weights: tuple, budget: tuple, most: int, slice_rows: int):
    """A function that adds mix_source_size, mix_target, mix_finish (the finish times of the copies taken) and mix_taken to rows with mix_source, mix_size,
    mix_tie and mix_key, the columns of sizes (written).

    The running total of a source is taken in slices of its shuffle, of about slice_rows rows, so that no task holds a source; which slices are
    used doesn't show in the result.
    """
    per = written(targets(sizes, weights, budget, most), "targets")
    largest = sizes.groupBy("source").count().agg(F.max("count")).first()[0] or 1
    digits = max(1, math.ceil(math.log(max(1.0, largest / slice_rows), 16)))
    cut = F.substring("mix_tie", 1, digits)

    before = Window.partitionBy("mix_place").orderBy("mix_slice").rowsBetween(Window.unboundedPreceding, -1)
    sums = _named(sizes).withColumn("mix_slice", cut).groupBy("mix_source", "mix_slice").agg(F.sum("mix_size").alias("in_slice"))
    one = per.select(F.col("place").alias("mix_place"), F.col("source").alias("known"), F.col("source_size").alias("mix_source_size"), F.col("target").alias("mix_target"))
    sums = written(sums.join(one, F.col("mix_source").eqNullSafe(F.col("known"))).withColumn("mix_before", F.coalesce(F.sum("in_slice").over(before), F.lit(0))).drop("known", "in_slice"), "slices")

    def queued(df: DataFrame) -> DataFrame:
        """Adds the source's figures and the finish times of all copies. Rows are dealt by source and slice, never by source alone."""
        at = sums.withColumnsRenamed({"mix_source": "their_source", "mix_slice": "their_slice"})
        dealt = df.withColumn("mix_slice", cut).join(at, F.col("mix_source").eqNullSafe(F.col("their_source")) & (F.col("mix_slice") == F.col("their_slice")))
        run = Window.partitionBy("mix_place", "mix_slice").orderBy("mix_tie", "mix_key", "mix_size").rowsBetween(Window.unboundedPreceding, 0)
        until = F.col("mix_before") + F.sum("mix_size").over(run)
        dealt = dealt.withColumn("mix_until", until)
        live = (F.col("mix_size") > 0) & (F.col("mix_target") > 0)
        times = [F.when(live, (F.col("mix_until") + e * F.col("mix_source_size")).cast("double") / F.col("mix_target")) for e in range(most)]
        return dealt.withColumn("mix_times", F.array(*times))

    copies = written(queued(_named(sizes)).select("mix_place", "mix_tie", "mix_key", "mix_size", F.posexplode("mix_times").alias("copy", "finish")).where(F.col("finish").isNotNull()), "finish")
    words = sizes.agg(F.coalesce(F.sum("size"), F.lit(0))).first()[0] * budget[0]  # budget[1] times the budget
    cell = F.least(F.floor(F.col("finish") * GRAIN), F.lit(GRAIN * UNITS)).cast("long")
    fine = F.least(F.floor((F.col("finish") * GRAIN - cell) * GRAIN), F.lit(GRAIN)).cast("long")

    def edge_of(rows: DataFrame, by, spent: int):
        """The first cell (of a bounded number) in which the budget ends, and the words up to its beginning."""
        total = rows.groupBy(by.alias("cell")).agg(F.sum("mix_size").alias("words"))
        until = total.withColumn("until", F.sum("words").over(Window.orderBy("cell")) + spent)
        return until.where(F.col("until") * budget[1] > words).orderBy("cell").select("cell", F.col("until") - F.col("words")).first()

    order = ["finish", "mix_place", "copy", "mix_tie", "mix_key", "mix_size"]
    edge = edge_of(copies, cell, 0)
    if edge is None:
        chosen = lambda finish, copy: finish.isNotNull()
    else:
        there = copies.where(cell == edge[0])
        inner = edge_of(there, fine, edge[1])
        last = there.where(fine == inner[0]).withColumn("until", F.sum("mix_size").over(Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)) + inner[1])
        last = last.where(F.col("until") * budget[1] <= words).agg(F.max(F.struct(*order)).alias("t")).first()[0]

        def chosen(finish, copy):
            at = F.least(F.floor(finish * GRAIN), F.lit(GRAIN * UNITS)).cast("long")
            early = (at < edge[0]) | (at == edge[0]) & (F.least(F.floor((finish * GRAIN - at) * GRAIN), F.lit(GRAIN)) < inner[0])
            if last is None:
                return early
            mine = F.struct(finish.alias("finish"), F.col("mix_place"), F.lit(copy).alias("copy"), F.col("mix_tie"), F.col("mix_key"), F.col("mix_size"))
            end = F.struct(F.lit(last["finish"]).alias("finish"), F.lit(last["mix_place"]), F.lit(copy * 0 + last["copy"]), F.lit(last["mix_tie"]), F.lit(last["mix_key"]).cast(dict(copies.dtypes)["mix_key"]), F.lit(last["mix_size"]).cast("long"))
            return early | (mine <= end)

    def taken(df: DataFrame) -> DataFrame:
        out = queued(df)
        kept = F.filter(F.array(*[F.when(chosen(F.col("mix_times")[e], e), F.col("mix_times")[e]) for e in range(most)]), lambda t: t.isNotNull())
        return out.withColumn("mix_finish", kept).withColumn("mix_taken", (F.size("mix_finish") * F.col("mix_size")).cast("long"))

    return taken


def _named(sizes: DataFrame) -> DataFrame:
    return sizes.select(F.col("source").alias("mix_source"), F.col("size").alias("mix_size"), F.col("tie").alias("mix_tie"), F.col("doc_id").alias("mix_key"))


def _mixed(docs: DataFrame, key: str, text: str, source: str, weights: tuple, budget: tuple, most: int, slice_rows: int) -> DataFrame:
    """row (all columns of docs in one) with ADDED. Sizes are worked out on narrow rows; whole rows are moved once."""
    sizes = written(sized(docs, key, text, source), "sizes")
    k = F.col(f"`{key}`")
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col(f"`{source}`").alias("mix_source"), _words(text).alias("mix_size"), _tie(k).alias("mix_tie"), k.alias("mix_key"))
    return _planned(sizes, weights, budget, most, slice_rows)(rows).select("row", "mix_key", *ADDED)


def mixed(docs: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", weights: tuple = (5, 2, 1), budget: tuple = (3, 2), most: int = 2, slice_rows: int = 1000) -> DataFrame:
    """docs with the columns ADDED; mix_finish has the finish times of the copies taken."""
    out = _mixed(docs, key, text, source, weights, budget, most, slice_rows)
    return out.select("row.*", *[F.col(c).alias(spare(c, docs.columns)) for c in ADDED])


def mix(docs: DataFrame, key: str = "doc_id", text: str = "text", source: str = "source", weights: tuple = (5, 2, 1), budget: tuple = (3, 2), most: int = 2, slice_rows: int = 1000) -> DataFrame:
    """The mix itself: docs' columns, a row for each copy taken, sorted by finish time over all partitions."""
    plan = _mixed(docs, key, text, source, weights, budget, most, slice_rows)
    return plan.withColumn("mix_at", F.explode("mix_finish")).orderBy("mix_at", F.xxhash64("mix_key")).select("row.*")


def op7_mix(spark, sf_dir: str) -> DataFrame:
    sizes = written(sized(table(spark, sf_dir, "documents", "doc_id", "text", "source")), "sizes")
    plan = _planned(sizes, (5, 2, 1), (3, 2), 2, 1000)(_named(sizes))
    return plan.select(F.col("mix_key").alias("doc_id"), F.col("mix_size").alias("size"), F.col("mix_source_size").alias("source_size"), F.col("mix_target").alias("target"), F.col("mix_taken").alias("taken"))


OP7_SQL = r"""
WITH d AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
         md5(coalesce(doc_id::VARCHAR, ''))[1:16] AS tie FROM documents
), s AS (
  SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source NULLS LAST) AS place FROM d GROUP BY source
), s2 AS (
  SELECT *, CASE (place - 1) % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS w FROM s
), s3 AS (
  SELECT *, sum(2 * source_size) OVER f::BIGINT AS used, sum(w) OVER ()::BIGINT - sum(w) OVER f::BIGINT AS open_w, sum(source_size) OVER ()::BIGINT AS words
  FROM s2 WINDOW f AS (ORDER BY (2 * source_size) / w::DOUBLE, place ROWS UNBOUNDED PRECEDING)
), s4 AS (
  SELECT *, (used::DOUBLE + (2 * source_size)::DOUBLE / w * open_w) * 2 <= words::DOUBLE * 3 AS is_full FROM s3
), s5 AS (
  SELECT place, source, source_size, CASE WHEN is_full THEN (2 * source_size)::DOUBLE ELSE
    (words * 3 - sum(CASE WHEN is_full THEN 2 * source_size ELSE 0 END) OVER ()::BIGINT * 2)::DOUBLE * w
      / nullif(sum(CASE WHEN is_full THEN 0 ELSE w END) OVER ()::BIGINT * 2, 0) END AS target FROM s4
), q AS (
  SELECT d.doc_id, d.size, d.tie, s5.place, s5.source_size, s5.target,
         sum(d.size) OVER (PARTITION BY s5.place ORDER BY d.tie, d.doc_id, d.size ROWS UNBOUNDED PRECEDING)::BIGINT AS until_here
  FROM d JOIN s5 ON d.source IS NOT DISTINCT FROM s5.source
), c AS (
  SELECT q.*, e.copy, (until_here + e.copy * source_size)::DOUBLE / target AS finish
  FROM q, (VALUES (0), (1)) e(copy) WHERE size > 0 AND target > 0
), t AS (
  SELECT doc_id, size, sum(size) OVER (ORDER BY finish, place, copy, tie, doc_id, size ROWS UNBOUNDED PRECEDING) * 2 <= (SELECT sum(size) * 3 FROM d) AS is_taken FROM c
), k AS (
  SELECT doc_id, sum(CASE WHEN is_taken THEN size ELSE 0 END)::BIGINT AS taken FROM t GROUP BY doc_id
)
SELECT q.doc_id, q.size, q.source_size, q.target, coalesce(k.taken, 0)::BIGINT AS taken FROM q LEFT JOIN k USING (doc_id)
"""

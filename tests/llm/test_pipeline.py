"""The pipeline's stages one after the other, each against what its operator says of its own input."""

from pyspark.sql import functions as F

import corpus_pipeline
from accord.llm import langid, mixing, packing, secretscan, simhash
from conftest import SF


def test_stages(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    columns, seen = docs.columns, [docs]
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, seen[-1], SF).write.parquet(str(tmp_path / str(k)))
        seen.append(spark.read.parquet(str(tmp_path / str(k))))
    assert all(s.columns == columns for s in seen[:-1])
    ids = [[r.doc_id for r in s.select("doc_id").collect()] for s in seen]

    told = langid.identified(seen[0], langid.fit(seen[0]), keep=["doc_id"])
    assert sorted(ids[1]) == sorted(r.doc_id for r in told.where("NOT lang_rejected").collect())
    groups = simhash.near_duplicates(seen[1])
    assert sorted(ids[2]) == sorted(r.doc_id for r in groups.where("doc_id = component_id").collect())
    assert sorted(ids[3]) == sorted(ids[2])
    assert secretscan.scan(seen[3]).where(F.exists("spans", lambda s: s["kind"] != "login_url")).count() == 0
    plan = {r.doc_id: len(r.mix_finish) for r in mixing.mixed(seen[3]).collect()}
    assert sorted(ids[4]) == sorted(d for d, n in plan.items() for _ in range(n))
    tokens = packing.pieces(seen[4]).agg(F.sum("length")).first()[0]
    assert seen[5].agg(F.sum("length")).first()[0] == tokens
    assert seen[5].groupBy("sequence_id").agg(F.sum("length").alias("n")).where("n > 2048").count() == 0
    assert corpus_pipeline.run(spark, SF).count() == seen[5].count()


def test_empty(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").where("doc_id < 0")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs, SF).count() == 0

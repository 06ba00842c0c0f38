"""Cases that have once gone wrong: very long runs, malformed markup, clashing names, many languages, small and large shards."""

import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from accord.llm import common, hnsw, langid, licences, mixing, packing, secretscan, vectors
from conftest import SF


def test_licence_line_of_any_length(spark):
    line = "Released under the MIT License." + " -" * 5000
    rows = spark.createDataFrame([(1, f"intro\n{line}\nend", "mine"), (2, line, "mine")], "`a.b` long, text string, licence string")
    got = {r["a.b"]: (r.licence, r.notices) for r in licences.scan(rows, key="a.b").collect()}
    assert got == {1: (None, "MIT"), 2: ("MIT", "MIT")}


def test_packing_of_blanks(spark):
    from tokenizers import Tokenizer
    import public_tokenizers

    slow = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    long = ["a" + " " * 1_000_000 + "b", "\n" * 300_000, "x <|endoftext|>" + " \n" * 200_000, "   y" * 50_000]
    rows = packing.pieces(spark.createDataFrame(list(enumerate(long)), "doc_id long, text string")).collect()
    for i, t in enumerate(long):
        ids = np.array([*slow.encode(t, add_special_tokens=False).ids, 0], "<u4")
        own = sorted((r.start, r.length, r.ids_crc32) for r in rows if r.doc_id == i)
        assert sum(n for _, n, _ in own) == len(ids) and all(zlib.crc32(ids[s : s + n].tobytes()) == c for s, n, c in own)


def test_columns_of_any_name_stay(spark):
    rows = spark.createDataFrame([(1, "token: abcdef123 x", "s"), (2, None, None)], "doc_id long, text string, source string")
    for c in ("spans", "scan_row", "scan_mask", "row", "whole", "mask", "mix_size", "mix_finish", "mix_taken", "x.y"):
        rows = rows.withColumn(c, F.concat(F.lit(f"my {c} "), F.col("doc_id").cast("string")))
    own = [c for c in rows.columns if c != "text"]
    take = lambda df: sorted(tuple(r[c] for c in own) for r in df.collect())
    assert secretscan.redact(rows).columns == rows.columns and take(secretscan.redact(rows)) == take(rows)
    found = secretscan.scan(rows)
    assert found.columns == [*rows.columns, "spans_"] and take(found) == take(rows) and [len(r.spans_) for r in found.orderBy("doc_id").collect()] == [1, 0]
    plan = mixing.mixed(rows)
    assert take(plan) == take(rows) and "mix_size_" in plan.columns
    assert mixing.mix(rows).columns == rows.columns and {r["mix_finish"] for r in mixing.mix(rows).collect()} == {"my mix_finish 1"}
    dotted = rows.select(F.col("doc_id").alias("d.id"), F.col("text").alias("t.x"), F.col("source").alias("s.c"))
    assert secretscan.redact(dotted, "d.id", "t.x").count() == 2 and mixing.mixed(dotted, "d.id", "t.x", "s.c").count() == 2


def test_every_language_is_learnt(spark):
    random.seed(5)
    rows = []
    for k in range(300):
        letters = [chr(0x4E00 + 40 * k + j) for j in range(20)]
        rows += [(10 * k + j, " ".join("".join(random.choices(letters, k=3)) for _ in range(30)), f"l{k:03}") for j in range(6)]
    model = langid.fit(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    assert len(set(model[0])) == 300


def test_repeated_rows_are_learnt_from_once(spark):
    one = spark.createDataFrame([(None, "the same words of one text", "en")] * 400 + [(i, f"das ist ein text {i}", "de") for i in range(30)], "doc_id long, text string, lang string")
    few = spark.createDataFrame([(None, "the same words of one text", "en")] + [(i, f"das ist ein text {i}", "de") for i in range(30)], "doc_id long, text string, lang string")
    a, b = (langid.fit(df, train_docs=100_000) for df in (one, few))
    assert a[0] == b[0] and np.allclose(a[1], b[1]) and np.allclose(a[2], b[2])


def test_signs_are_no_letters(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    odd = spark.createDataFrame([("½ ² Ⅷ",), ("١٢ ①",), ("a",)], "text string")
    told = {r.text: r.lang_pred for r in langid.identified(odd, langid.fit(docs)).collect()}
    assert told["½ ² Ⅷ"] == told["١٢ ①"] == "und" and told["a"] != "und"


def test_language_against_plain_cosine(spark):
    """The prediction is the nearest centroid by plain n-gram counting; junk of random letters is rejected, documents aren't."""
    docs = spark.read.parquet(f"{SF.replace('0.001', '0.01')}/documents.parquet")
    names, c, idf, least = model = langid.fit(docs)
    rows = [r for r in docs.orderBy("doc_id").limit(60).collect() if r.text and re.search(r"[^\W\d_]", r.text)]
    got = {r.doc_id: r for r in langid.identified(docs, model).collect()}
    random.seed(3)
    junk = ["".join(random.choice("abcdefghijklmnopqrstuvwxyz") if x.isalpha() else x for x in r.text) for r in rows]
    for r in rows:
        raw = b" " + b" ".join(re.findall(rb"[a-z\x80-\xff]+", r.text.lower().encode())) + b" "
        tf = np.zeros(langid.CELLS)
        for g in langid.GRAMS:
            for i in range(len(raw) - g + 1):
                tf[((int.from_bytes(raw[i : i + g], "big") + (g << 24)) * 2654435761 % (1 << 32)) >> 20] += 1
        x = np.log1p(tf) * idf
        cos = c @ (x / np.linalg.norm(x))
        best = cos.argmax()
        assert got[r.doc_id].lang_pred == names[best] and got[r.doc_id].lang_score == pytest.approx(cos[best], abs=1e-4)
    assert not any(got[r.doc_id].lang_rejected for r in rows)
    assert langid.identified(spark.createDataFrame([(t,) for t in junk], "text string"), model).where("not lang_rejected").count() <= 0.05 * len(junk)


def _plain(x):
    u = x.astype(float)
    u /= np.linalg.norm(u, axis=1, keepdims=True)
    near = u @ u.T >= 0.95
    np.fill_diagonal(near, False)
    return near


def test_small_shards_use_the_graph(monkeypatch):
    rng = np.random.default_rng(9)
    x = rng.normal(size=(80, 16))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    g, asked = hnsw.Graph(x), []
    monkeypatch.setattr(g, "search", lambda q, ef, f=g.search: asked.append(len(q)) or f(q, ef))
    assert [n.tolist() for n in g.within(x, 0.95, 48)] == [[i] for i in range(80)] and asked == [80]


def test_vectors_in_large_shards(spark):
    """Over 2,000 nodes a shard, a dense group among them: links and components by the graphs against all pairs."""
    rng = np.random.default_rng(8)
    base = rng.normal(size=(5000, 24))
    x = np.concatenate([base, base[:900] + rng.normal(0, 0.12, (900, 24)), base[0] + rng.normal(0, 0.1, (700, 24))]).astype(np.float32)
    df = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(x)], "vec_id long, embedding array<float>")
    got = {r.vec_id: r for r in vectors.near_duplicates(df, shards=3).collect()}
    near = _plain(x)
    links = np.array([got[i].n_links for i in range(len(x))])
    assert (links <= near.sum(axis=1)).all()
    recall = links.sum() / near.sum()
    alone = [links[i] / near[i].sum() for i in range(len(x)) if 0 < near[i].sum() < 20]
    assert recall >= 0.99 and np.mean(alone) >= 0.98, (recall, np.mean(alone))


def test_scratch_is_shared_on_a_cluster():
    class Conf(dict):
        def get(self, key, default=None):
            return dict.get(self, key, default)

    class Fake:
        conf = Conf({"spark.sql.warehouse.dir": "hdfs://x/warehouse"})

        class sparkContext:  # noqa: N801
            master = "spark://host:7077"

            @staticmethod
            def getConf():
                return {}

    assert common.scratch_dir(Fake()) == "hdfs://x/warehouse/scratch"
    Fake.sparkContext.master = "local[4]"
    assert common.scratch_dir(Fake()).startswith("file://")

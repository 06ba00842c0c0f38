"""Language identification by nearest centroid.

Texts become TF-IDF vectors of hashed byte n-grams of the lower-case text, of length 1. Each language has several centroids, from spherical k-means
over a bounded sample of labelled documents (about train_docs in all, dealt evenly over the languages, and some LEAST_DOCS of each at least; the choice goes by
a hash of id and text, repeated rows count once). The sample's texts become counts where they are read, and each language is clustered by itself. A text gets the language of the centroid with
the largest cosine; it is rejected if that is below what nearly all training texts of the language reach, by a margin.

Nulls: a null text, or one without a letter, is `und` with score 0 and rejected; a null language isn't learnt from; a null id is never held out. Texts are
read whole. Ties go to the language first by code point. Without any labelled document all texts are `und`. An empty table gives no rows.
"""

from __future__ import annotations

import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from accord.llm.common import spare, table, written

#: Cells for hashed n-grams, n-gram lengths in bytes, centroids per language, documents to learn from, and documents of a language at least.
CELLS, GRAMS, CENTROIDS, TRAIN_DOCS, LEAST_DOCS = 4096, (1, 2, 3), 4, 4000, 40
#: A text is rejected under MARGIN times the cosine that all but a hundredth of the language's training texts reach. That is above what texts of random
#: letters reach and under what short texts of learnt languages do.
MARGIN = 0.4
_LETTER = regex.compile(r"\p{L}")
_PLAIN = bytes(c if c >= 128 or 97 <= c <= 122 else 32 for c in range(256))


def counts(text: str):
    """n-gram counts of the whole text in pieces of a megabyte; ASCII characters other than letters are word ends, however many."""
    import numpy as np

    words = text.lower().encode().translate(_PLAIN).split()
    raw = np.frombuffer(b" " + b" ".join(words) + b" ", np.uint8)
    out = np.zeros(CELLS, np.int64)
    step, over = 1 << 20, max(GRAMS) - 1
    for at in range(0, len(raw), step):
        b = raw[at : at + step + over].astype(np.uint32)
        for g in GRAMS:
            n = min(step, len(b) - g + 1)
            if n <= 0:
                continue
            code = b[:n].copy()
            for k in range(1, g):
                code = (code << np.uint32(8)) | b[k : n + k]
            cell = ((code + np.uint32(g << 24)) * np.uint32(2654435761)) >> np.uint32(20)
            out += np.bincount(cell, minlength=CELLS)
    return out


def vectors(tf, idf):
    """Rows of length 1 from rows of counts."""
    import numpy as np

    x = np.log1p(tf.astype(np.float32)) * idf
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)


def centroids(x, k: int = CENTROIDS, rounds: int = 10):
    """Spherical k-means from farthest-first seeds; unit rows, k at most."""
    import numpy as np

    mean = x.mean(axis=0)
    seeds = [int((x @ mean).argmax())]
    near = x @ x[seeds[0]]
    while len(seeds) < min(k, len(x)):
        seeds.append(int(near.argmin()))
        near = np.maximum(near, x @ x[seeds[-1]])
    c = x[seeds].copy()
    for _ in range(rounds):
        own = (x @ c.T).argmax(axis=1)
        c = np.stack([x[own == j].mean(axis=0) if (own == j).any() else c[j] for j in range(len(c))])
        c /= np.maximum(np.linalg.norm(c, axis=1, keepdims=True), 1e-12)
    return c


def held_out(key: str):
    return F.coalesce(F.pmod(F.crc32(F.col(f"`{key}`").cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def _counted(sample: DataFrame) -> DataFrame:
    """(l, k, tf): the counts of each text (l, k, t) as little-endian 32-bit numbers, of a fixed size."""
    kind = sample.schema["k"].dataType.simpleString()

    def run(batches):
        import pyarrow as pa

        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([counts(t).astype("<u4").tobytes() for t in b.column(2).to_pylist()], pa.binary())], names=["l", "k", "tf"])

    return sample.select("l", "k", "t").mapInArrow(run, f"l string, k {kind}, tf binary")


def fit(docs: DataFrame, key: str = "doc_id", text: str = "text", lang: str = "lang", train_docs: int = TRAIN_DOCS):
    """(languages of the centroids, centroids, idf, least cosine of each centroid's language), or None without labelled documents."""
    import numpy as np

    rows = docs.select(F.col(f"`{key}`").alias("k"), F.col(f"`{text}`").alias("t"), F.col(f"`{lang}`").cast("string").alias("l"))
    rows = rows.where(~held_out("k") & F.col("l").isNotNull())
    sizes = rows.groupBy("l").count()  # one row per language
    each = F.greatest(F.lit(train_docs) / F.greatest(F.count("*").over(Window.partitionBy()), F.lit(1)), F.lit(LEAST_DOCS))
    share = sizes.select(F.col("l").alias("known"), (each / F.col("count") * (1 << 30)).alias("share"))
    sample = rows.where(F.col("t").rlike(r"\p{L}")).join(F.broadcast(share), (F.col("l") == F.col("known")) & (F.pmod(F.xxhash64("k", "t"), F.lit(1 << 30)) < F.col("share")))
    sample = written(_counted(sample).distinct(), "sample")  # repeated rows are one document
    docs_in = sample.count()
    if not docs_in:
        return None

    def holding(batches):
        import pyarrow as pa

        n = np.zeros(CELLS, np.int64)
        for b in batches:
            for raw in b.column(0).to_pylist():
                n += np.frombuffer(raw, "<u4") > 0
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(CELLS)), pa.array(n)], names=["cell", "n"])

    per = {r[0]: r[1] for r in sample.select("tf").mapInArrow(holding, "cell bigint, n bigint").groupBy("cell").agg(F.sum("n")).collect()}  # CELLS rows
    idf = (np.log((1 + docs_in) / (1 + np.array([per[c] for c in range(CELLS)]))) + 1).astype(np.float32)

    def learn(pdf):
        import pandas as pd

        pdf = pdf.sort_values(["k", "tf"])
        own = vectors(np.stack([np.frombuffer(raw, "<u4") for raw in pdf["tf"]]), idf)
        c = centroids(own)
        least = float(np.quantile((own @ c.T).max(axis=1), 0.01)) * MARGIN
        return pd.DataFrame([(pdf["l"].iloc[0], i, row.astype("<f4").tobytes(), least) for i, row in enumerate(c)], columns=["l", "i", "v", "least"])

    model = sorted(sample.groupBy("l").applyInPandas(lambda pdf: learn(pdf), "l string, i int, v binary, least double").collect(), key=lambda r: (r.l, r.i))  # CENTROIDS rows per language
    return [r.l for r in model], np.stack([np.frombuffer(bytes(r.v), "<f4") for r in model]), idf, np.array([r.least for r in model])


def identified(docs: DataFrame, model, text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """The columns keep of docs (default: all) with lang_pred, lang_score and lang_rejected; an underscore follows where docs has such a name."""
    keep = docs.columns if keep is None else keep
    shared = docs.sparkSession.sparkContext.broadcast(model)  # CENTROIDS vectors of CELLS numbers for each language

    def run(batches):
        import numpy as np
        import pyarrow as pa

        m = shared.value
        for b in batches:
            texts = b.column(b.num_columns - 1).to_pylist()
            langs, scores, out = ["und"] * len(texts), np.zeros(len(texts)), np.ones(len(texts), bool)
            due = [i for i, t in enumerate(texts) if m is not None and t and _LETTER.search(t)]
            for at in range(0, len(due), 256):
                part = due[at : at + 256]
                x = vectors(np.stack([counts(texts[i]) for i in part]), m[2])
                cos = (x @ m[1].T).astype(np.float64)
                best = cos.argmax(axis=1)
                for i, j, c in zip(part, best, cos.max(axis=1)):
                    langs[i], scores[i], out[i] = m[0][j], min(1.0, max(0.0, float(c))), c < m[3][j]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(langs, pa.string()), pa.array(scores, pa.float64()), pa.array(out, pa.bool_())], names=[*names, "lang_pred", "lang_score", "lang_rejected"])

    names = [f"c{i}" for i in range(len(keep))]
    schema = "".join(f"{n} {docs.schema[c].dataType.simpleString()}, " for n, c in zip(names, keep))
    rows = docs.select(*[F.col(f"`{c}`").alias(n) for n, c in zip(names, keep)], F.col(f"`{text}`").alias("t"))
    return rows.mapInArrow(run, f"{schema}lang_pred string, lang_score double, lang_rejected boolean").toDF(*keep, *[spare(n, keep) for n in ("lang_pred", "lang_score", "lang_rejected")])


def accepted(docs: DataFrame, model, text: str = "text") -> DataFrame:
    """The rows of docs whose language is told."""
    told = identified(docs, model, text)
    return told.where(~F.col(told.columns[-1])).select(*[F.col(f"`{c}`") for c in docs.columns])


def op5_language(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang")
    out = identified(docs, fit(docs), keep=["doc_id"])
    return out.select("doc_id", held_out("doc_id").alias("held_out"), "lang_pred", F.col("lang_score").alias("score"), F.col("lang_rejected").alias("rejected"))

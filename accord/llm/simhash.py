"""SimHash near-duplicates by pigeonhole blocks.

A fingerprint has 64 bits, each set if it is set in more than half of the hashes of the text's word shingles. Two fingerprints that differ in
at most 2 bits agree in at least 3 of 5 blocks of bits, so every choice of 3 blocks is a key to join on, and pairs that meet there are verified.
A key that many fingerprints share isn't joined with itself: each of its members goes to itself and to all fingerprints one bit away in the other
two blocks, and members that meet in such a place are linked through one of them. Two members meet exactly if they differ in at most 2 bits,
and at most 27 meet in a place, so links grow with the members, not with their pairs, and none is lost.

Copies share a fingerprint and are one node from the start. Nulls: a null text has no words and fingerprint zero; a null id counts for nothing in
the least id. Texts without words link like any others. Repeated rows get equal groups. An empty table gives no rows.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from accord.llm.common import table, written
from accord.llm.components import connected_components

#: Bits of the five blocks, from the lowest bit on.
BLOCKS = (13, 13, 13, 13, 12)
#: Fingerprints with one key up to which they are compared pair by pair.
MOST_PAIRED = 32


def fingerprint(text: str | None, words_each: int = 3, seed: int = 42) -> int:
    import numpy as np
    import xxhash

    words = (text or "").encode().translate(_LOWER).split()
    if not words:
        return 0
    joined, hash_of = b" ".join(words), xxhash.xxh64_intdigest
    if len(words) <= words_each:
        return hash_of(joined, seed)
    ends, at = [], -1
    for w in words:
        at += len(w) + 1
        ends.append(at)
    starts = [0, *(e + 1 for e in ends)]
    hashes = [hash_of(joined[a:b], seed) for a, b in zip(starts, ends[words_each - 1 :])]
    counts = np.zeros(64, np.int64)
    for i in range(0, len(hashes), 1 << 16):
        part = np.array(hashes[i : i + (1 << 16)], np.uint64)
        counts += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * counts > len(hashes), bitorder="little").view(np.uint64)[0])


_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def fingerprints(docs: DataFrame, key: str = "doc_id", text: str = "text", words_each: int = 3) -> DataFrame:
    """(key, row, fp): row is a hash of key and text, fp the fingerprint as a signed long."""
    kind = docs.schema[key].dataType.simpleString()

    def run(batches):
        import pyarrow as pa

        for b in batches:
            fps = [fingerprint(t, words_each) for t in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([x - (1 << 64) if x >> 63 else x for x in fps], pa.int64())], names=[key, "row", "fp"])

    k, t = F.col(f"`{key}`"), F.col(f"`{text}`")
    return docs.select(k, F.xxhash64(k, t).alias("simhash_row"), t.alias("simhash_text")).mapInArrow(run, f"`{key}` {kind}, row bigint, fp bigint")


def _masks() -> list[tuple[int, list[int]]]:
    """(the bits of the key, the other bits) for each choice of 3 blocks."""
    ends = [sum(BLOCKS[:i]) for i in range(len(BLOCKS) + 1)]
    out = []
    for chosen in combinations(range(len(BLOCKS)), len(BLOCKS) - 2):
        bits = {b for c in chosen for b in range(ends[c], ends[c + 1])}
        out.append((sum(1 << b for b in bits), [b for b in range(64) if b not in bits]))
    return out


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def links(nodes: DataFrame) -> DataFrame:
    """(a, b): links whose components are those of all pairs of fp of nodes (distinct) that differ in 1 or 2 bits."""
    masks = _masks()
    keys = nodes.select("fp", F.explode(F.array(*[F.struct(F.lit(i).alias("choice"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("part")) for i, (m, _) in enumerate(masks)])).alias("k")).select("fp", "k.choice", "k.part")
    shared = keys.groupBy("choice", "part").agg(F.count("*").alias("n")).where("n > 1")
    met = written(keys.join(shared, ["choice", "part"]), "met")
    few = met.where(F.col("n") <= MOST_PAIRED)
    pairs = few.select("choice", "part", F.col("fp").alias("a")).join(few.select("choice", "part", F.col("fp").alias("b")), ["choice", "part"])
    pairs = pairs.where((F.col("a") < F.col("b")) & (F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= 2)).select("a", "b")
    near = [F.array(F.col("fp"), *[F.col("fp").bitwiseXOR(F.lit(_signed(1 << b))) for b in rest]) for _, rest in masks]
    near = F.element_at(F.array(*near), F.col("choice") + 1)
    places = met.where(F.col("n") > MOST_PAIRED).select("choice", "fp", F.explode(near).alias("place")).groupBy("choice", "place").agg(F.collect_set("fp").alias("fps"))
    hubs = places.where(F.size("fps") > 1).select(F.array_min("fps").alias("a"), F.explode("fps").alias("b"))
    return pairs.union(hubs.where("a != b"))


def grouped(fps: DataFrame, key: str = "doc_id") -> DataFrame:
    """fps with group, the same for all of a component, and component_id, the least key that links of at most 2 differing bits reach."""
    per = fps.groupBy("fp").agg(F.min(f"`{key}`").alias("least"))
    nodes = written(per, "nodes")
    roots = connected_components(links(nodes.select("fp")))
    placed = written(nodes.join(roots, F.col("fp") == F.col("node"), "left").select("fp", "least", F.coalesce("root", "fp").alias("group")), "placed")
    least = placed.groupBy("group").agg(F.min("least").alias("component_id"))
    return fps.join(placed.select("fp", "group").join(least, "group"), "fp")


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, row, fp, group, component_id) for each row of docs."""
    return grouped(written(fingerprints(docs, key, text), "fingerprints"), key)


def one_each(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """docs with one row of each group: the one with the least id that isn't null; rows that share it go by a hash of their text."""
    told = near_duplicates(docs, key, text)
    stay = told.groupBy("group").agg(F.min(F.struct(F.col(f"`{key}`").isNull().alias("no"), F.col(f"`{key}`").alias("id"), "row")).alias("m"), F.count("*").alias("n"))
    stay = written(stay.select(F.col("m.row").alias("simhash_stay"), "n"), "stay")
    rows = docs.withColumn("simhash_row", F.xxhash64(f"`{key}`", f"`{text}`"))
    kept = rows.join(stay.select("simhash_stay"), F.col("simhash_row") == F.col("simhash_stay"), "left_semi")
    if docs.count() != stay.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]:
        raise RuntimeError("documents changed while they were read")
    if told.groupBy("row").count().where("count > 1").isEmpty():
        return kept.drop("simhash_row")
    return kept.dropDuplicates(["simhash_row"]).drop("simhash_row")


def op9_simhash(spark, sf_dir: str) -> DataFrame:
    out = near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"))
    return out.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")

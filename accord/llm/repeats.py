"""Removal of passages that occur more than once, by prefix-free parsing.

Texts are parsed at triggers, places where a rolling hash of 101 bytes is 0 modulo 64. The trigger of a window of 200 bytes is the first in it, or where it has none the
place with the least hash, and a phrase is a run of windows with one trigger. Equal windows have their triggers in equal places, so only phrases with equal
trigger strings can hold equal windows, whatever surrounds them; no phrase is longer than 100 windows. The dictionary has each phrase, with the bytes that its
windows reach over, once.

A phrase that the dictionary has counted twice or more is repeated as a whole, and of all its occurrences only that is recorded. One whose trigger string
occurs nowhere else has no repeated window. What is left are phrases at the edges of repeated passages: their dictionary entries are brought together
by trigger string, parsed once more into short phrases, and the suffix arrays of the dictionary and the parse of these (parsing.suffix_order) put all their suffixes in
corpus order; windows are repeated where neighbours in that order have 200 bytes in common. Equal windows never lie in entries of different trigger strings, so the orders
of all groups together say all that the order of the whole corpus would. Trigger strings with very many entries are compared window by window under keys of
their own, so no task gets them whole.

Nulls: a null text is an empty one; a null id stays null. Matches never cross texts; texts under 200 bytes lose nothing. Repeated rows are repeats of each
other. Entries are told apart by hashes of 128 bits, 64 of the trigger string and 64 of the whole; windows are compared as bytes, or in crowds by 192 bits. Texts of
any length are parsed whole, in rounds of 64 kB. An empty table gives no rows. Other columns of the input aren't read.
"""

from __future__ import annotations

import hashlib

import numpy as np
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from accord.llm import parsing
from accord.llm.common import dropped, table, written

#: Bytes of a window; places of a window that can be its trigger; the modulus, a power of 2; bytes of the string at a trigger.
WINDOW, TRIGGER, MODULUS = 200, 100, 64
GRAM = WINDOW - TRIGGER + 1
#: Entries of one trigger string up to which they are compared in one task.
MOST_TOGETHER = 1024
#: Bytes of entries that are put in order at once; groups are never cut.
AT_ONCE = 1 << 20
#: Parts over which the entries of a very common trigger string are dealt.
SALTS = 16
_BASE = 0x9E3779B97F4A7C15


def _tables():
    rng = np.random.default_rng(20)
    code = rng.integers(0, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
    with np.errstate(over="ignore"):
        inverse = pow(_BASE, -1, 1 << 64)
        up = np.full(1 << 16, _BASE, np.uint64)
        up[0] = 1
        up = np.cumprod(up, dtype=np.uint64)
        down = np.full(1 << 16, inverse, np.uint64)
        down[0] = 1
        down = np.cumprod(down, dtype=np.uint64)
    return code, up, down


_CODE, _UP, _DOWN = _tables()


def phrases(raw: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first window, last window, trigger) of each phrase of one text."""
    n = len(raw)
    if n < WINDOW:
        return (np.zeros(0, np.int64),) * 3
    data = np.frombuffer(raw, np.uint8)
    first, trigger = [], []
    step = len(_UP) - WINDOW  # windows of one round
    for at in range(0, n - WINDOW + 1, step):
        b = data[at : at + step + WINDOW - 1]
        grams = len(b) - GRAM + 1
        with np.errstate(over="ignore"):
            sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_CODE[b] * _UP[: len(b)], dtype=np.uint64)])
            h = (sums[GRAM:] - sums[:grams]) * _DOWN[:grams]
            h ^= h >> np.uint64(29)
            h *= np.uint64(0xBF58476D1CE4E5B9)
        place = np.arange(grams, dtype=np.uint64)
        v = np.where(h >> np.uint64(40) & np.uint64(MODULUS - 1), h | np.uint64(1 << 63), np.uint64(0)) & ~np.uint64(0xFFFF) | place
        width = 1
        while width < TRIGGER:
            more = min(width, TRIGGER - width)
            v = np.minimum(v[:-more], v[more:])
            width += more
        p = (v & np.uint64(0xFFFF)).astype(np.int64) + at
        new = np.nonzero(np.concatenate([[True], p[1:] != p[:-1]]))[0]
        first.append(new + at)
        trigger.append(p[new])
    s, t = np.concatenate(first), np.concatenate(trigger)
    keep = np.concatenate([[True], t[1:] != t[:-1]])
    s, t = s[keep], t[keep]
    return s, np.concatenate([s[1:] - 1, [n - WINDOW]]), t


def _key(x: bytes, seed: int = 0) -> int:
    h = xxhash.xxh3_64_intdigest(x, seed)
    return h - (1 << 64) if h >> 63 else h


def _pack(s: int, e: int, t: int) -> int:
    return s << 14 | (e - s) << 7 | (t - s)


def _unpack(pos: int) -> tuple[int, int, int]:
    s = pos >> 14
    return s, s + (pos >> 7 & 127), s + (pos & 127)


def kept(raw: bytes, runs) -> tuple[int, int, str]:
    """(bytes removed, spans, SHA-256 of the rest) when all windows of the runs (first, last) are removed."""
    spans: list[list[int]] = []
    for s, e in sorted(runs):
        if spans and s <= spans[-1][1]:
            spans[-1][1] = max(spans[-1][1], e + WINDOW)
        else:
            spans.append([s, e + WINDOW])
    rest, at = hashlib.sha256(), 0
    for s, e in spans:
        rest.update(raw[at:s])
        at = e
    rest.update(raw[at:])
    return sum(e - s for s, e in spans), len(spans), rest.hexdigest()


def _phrase_rows(docs: DataFrame, with_place: bool) -> DataFrame:
    """(g, x [, doc, chk, pos]): hashes of trigger string and entry, and where the phrase is."""
    names = ["g", "x"] + ["doc", "chk", "pos"] * with_place

    def run(batches):
        import pyarrow as pa

        for b in _small(batches):
            out: list[list] = [[] for _ in names]
            docs_, chks = b.column(0).to_pylist(), b.column(1).to_pylist()
            for i, raw in enumerate(b.column(2).cast(pa.binary()).to_pylist()):
                if raw is None or len(raw) < WINDOW:
                    continue
                s, e, t = (v.tolist() for v in phrases(raw))
                out[0] += [_key(raw[k : k + GRAM]) for k in t]
                out[1] += [_key(raw[a : z + WINDOW], k - a) for a, z, k in zip(s, e, t)]
                if with_place:
                    out[2] += [docs_[i]] * len(s)
                    out[3] += [chks[i]] * len(s)
                    out[4] += [_pack(a, z, k) for a, z, k in zip(s, e, t)]
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(out, kinds)], names=names)

    return docs.select("doc", "chk", "text").mapInArrow(run, "g bigint, x bigint" + ", doc bigint, chk int, pos bigint" * with_place)


def _small(batches, rows: int = 256):
    """Batches of no more than so many rows: what is made from a row takes several times its bytes."""
    for b in batches:
        for at in range(0, b.num_rows, rows):
            yield b.slice(at, rows)


_PLACE = "doc bigint, chk int"
_FINAL = "n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string"


def repeated(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_bytes, n_removed, n_spans, kept_sha256) for each row."""
    k, t = F.col(f"`{key}`"), F.col(f"`{text}`")
    docs = docs.select(k.alias("id"), t.alias("text"), F.xxhash64(k, t).alias("doc"), F.hash(t).alias("chk"))
    kind = docs.schema["id"].dataType.simpleString()

    # trigger strings that occur twice or more; mixed: in more than one dictionary entry
    strings = _phrase_rows(docs, False).groupBy("g").agg(F.count("*").alias("n"), F.min("x").alias("a"), F.max("x").alias("b")).where("n > 1")
    strings = written(strings.select(F.col("g").alias("sg"), (F.col("a") != F.col("b")).alias("mixed")), "strings")
    met = written(_phrase_rows(docs, True).join(strings, F.col("g") == F.col("sg")).drop("sg"), "met")
    dropped(strings)

    # entries of mixed strings: counted, and one occurrence of each
    mixed = met.where("mixed")
    entries = written(mixed.groupBy("g", "x").agg(F.count("*").alias("c"), F.min(F.struct("doc", "chk", "pos")).alias("at")), "entries")
    crowd = entries.groupBy("g").agg((F.count("*") > MOST_TOGETHER).alias("crowded"), F.min("c").alias("least")).where("least = 1")
    crowd = crowd.select(F.col("g").alias("cg"), "crowded", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("cs"))
    salted = entries.withColumn("salt", F.pmod("x", F.lit(SALTS)).cast("int"))
    ask = salted.join(crowd, (F.col("g") == F.col("cg")) & (F.col("salt") == F.col("cs"))).select("at.doc", "at.chk", "at.pos", F.when(F.col("c") > 1, 2).otherwise(1).alias("role"), "g", "crowded")
    sure = entries.where("c > 1").select(F.col("g").alias("eg"), F.col("x").alias("ex"))
    # a join of its own, so that Spark can split the occurrences of a very common entry over tasks
    again = written(mixed.join(sure, (F.col("g") == F.col("eg")) & (F.col("x") == F.col("ex"))).select("doc", "chk", "pos"), "again")
    whole = met.where("not mixed").select("doc", "chk", "pos").union(again)
    marks = whole.select("doc", "chk", "pos", F.lit(0).alias("role"), F.lit(0).cast("bigint").alias("g"), F.lit(False).alias("crowded")).unionByName(ask)
    marks = marks.groupBy(F.col("doc").alias("md"), F.col("chk").alias("mc")).agg(F.collect_list(F.struct("pos", "role", "g", "crowded")).alias("marks"))

    def settle(batches):
        """Finished rows (kind 0); texts that wait for their phrases at edges (1); entries to compare (2)."""
        import pyarrow as pa

        for b in _small(batches):
            ids, docs_, chks, marks_ = b.column(0), b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(4).to_pylist()
            rows, whose = [], []
            for i, raw in enumerate(b.column(3).cast(pa.binary()).to_pylist()):
                raw = raw or b""
                own = marks_[i] or []
                runs = [_unpack(m["pos"])[:2] for m in own if m["role"] == 0]
                wait = [m for m in own if m["role"]]
                whose.append(i)
                if not wait:
                    rows.append((0, docs_[i], chks[i], len(raw), *kept(raw, runs), None, None, None, None, None, None))
                    continue
                rows.append((1, docs_[i], chks[i], len(raw), None, None, None, raw, [m["pos"] for m in own if m["role"] == 0], None, None, None, None))
                for m in wait:
                    s, e, _ = _unpack(m["pos"])
                    whose.append(i)
                    rows.append((2, docs_[i], chks[i], None, None, None, None, raw[s : e + WINDOW], None, m["g"], m["role"], m["pos"], m["crowded"]))
            cols = list(zip(*rows)) or [()] * 13
            kinds = [pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary(), pa.list_(pa.int64()), pa.int64(), pa.int32(), pa.int64(), pa.bool_()]
            made = [pa.array(c, x) for c, x in zip(cols, kinds)]
            yield pa.RecordBatch.from_arrays([made[0], ids.take(pa.array(whose, pa.int64())), *made[1:]], names=["kind", "id", "doc", "chk", "n_bytes", "n_removed", "n_spans", "kept_sha256", "raw", "runs", "g", "role", "pos", "crowded"])

    told = docs.join(marks, (F.col("doc") == F.col("md")) & (F.col("chk") == F.col("mc")), "left").select("id", "doc", "chk", "text", "marks")
    told = written(told.mapInArrow(settle, f"kind int, id {kind}, {_PLACE}, {_FINAL}, raw binary, runs array<bigint>, g bigint, role int, pos bigint, crowded boolean"), "settled")
    for done_with in (met, entries, again):
        dropped(done_with)

    def together(batches):
        """Windows of single entries that another entry of the trigger string has too; rows come sorted by trigger string."""
        import pyarrow as pa

        def ordered(groups):
            rows = [row for group in groups for row in group]
            out = []
            for i, k in zip(*(v.tolist() for v in parsing.repeated([r[4] for r in rows], WINDOW))):
                doc, chk, role, pos, _ = rows[i]
                if role == 1:
                    out.append((doc, chk, (pos >> 14) + k))
            return _windows(out)

        groups, at, size = [], None, 0
        for b in batches:
            for g, *row in zip(*(c.to_pylist() for c in b.columns)):
                if g != at:
                    if groups and len(groups[-1]) == 1:
                        size -= len(groups.pop()[0][4])
                    if size >= AT_ONCE:
                        yield ordered(groups)
                        groups, size = [], 0
                    groups.append([])
                    at = g
                groups[-1].append(row)
                size += len(row[4])
        yield ordered(groups)

    def apart(batches):
        """Each window under two hashes."""
        import pyarrow as pa

        for b in _small(batches):
            rows = [(g, _key(x[i : i + WINDOW], 1), _key(x[i : i + WINDOW], 2), doc, chk, role, (pos >> 14) + i) for g, doc, chk, role, pos, x in zip(*(c.to_pylist() for c in b.columns)) for i in range(len(x) - WINDOW + 1)]
            cols = list(zip(*rows)) or [()] * 7
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64()])], names=["g", "h", "h2", "doc", "chk", "role", "w"])

    edge = told.where("kind = 2").select("g", "doc", "chk", "role", "pos", "raw", "crowded")
    near = edge.where("not crowded").drop("crowded").repartition("g").sortWithinPartitions("g").mapInArrow(together, f"{_PLACE}, w bigint")
    windows = edge.where("crowded").drop("crowded").mapInArrow(apart, f"g bigint, h bigint, h2 bigint, {_PLACE}, role int, w bigint")
    twice = windows.groupBy("g", "h", "h2").agg(F.count("*").alias("n")).where("n > 1").select(F.col("g").alias("tg"), F.col("h").alias("th"), F.col("h2").alias("ti"))
    far = windows.where("role = 1").join(twice, (F.col("g") == F.col("tg")) & (F.col("h") == F.col("th")) & (F.col("h2") == F.col("ti"))).select("doc", "chk", "w")
    more = near.union(far).groupBy(F.col("doc").alias("wd"), F.col("chk").alias("wc")).agg(F.collect_list("w").alias("ws"))

    def finish(batches):
        import pyarrow as pa

        for b in _small(batches):
            out = []
            for raw, runs, ws in zip(*(b.column(i).to_pylist() for i in (1, 2, 3))):
                out.append((len(raw), *kept(raw, [_unpack(p)[:2] for p in runs] + [(w, w) for w in ws or ()])))
            cols = list(zip(*out)) or [()] * 4
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array(c, k) for c, k in zip(cols, [pa.int64(), pa.int64(), pa.int64(), pa.string()])]], names=["id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    waiting = told.where("kind = 1").join(more, (F.col("doc") == F.col("wd")) & (F.col("chk") == F.col("wc")), "left").select("id", "raw", "runs", "ws")
    done = told.where("kind = 0").select("id", "n_bytes", "n_removed", "n_spans", "kept_sha256").union(waiting.mapInArrow(finish, f"id {kind}, {_FINAL}"))
    return done.withColumnRenamed("id", key)


def _windows(rows):
    import pyarrow as pa

    cols = list(zip(*rows)) or [(), (), ()]
    return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int32()), pa.array(cols[2], pa.int64())], names=["doc", "chk", "w"])


def op4_repeats(spark, sf_dir: str) -> DataFrame:
    return repeated(table(spark, sf_dir, "documents", "doc_id", "text"))

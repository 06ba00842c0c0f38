"""Best-fit packing with certified bounds.

Documents become token ids and only those longer than a sequence are cut. Pieces are dealt to parts of some thousands, each packed by best-fit
decreasing. Dual-feasible functions give a lower bound on the sequences that any packing of a part needs; a part that uses more has a gap. The sequences
of such parts that aren't full give up their pieces, which are dealt anew over fewer and somewhat larger parts and packed again; a round that saves no sequence is undone.

Nulls: a null text is an empty one, whose only token is the end mark. A null id stays null. Repeated rows are packed each by itself.
Long texts are tokenised whole. Equal lengths are packed in order of their number in the written table of pieces. An empty table gives no rows.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from accord.llm.common import table, written

#: A run of blanks of which the quick library's pattern search makes so many steps back that its stack may not hold them.
_BLANKS = re.compile(r"\s{65536}")
#: Tokens of a sequence, the id after each document, and about how many pieces a part has.
SEQUENCE, END, PART = 2048, 0, 8192


def encoder(name: str = "byte_bpe_50k"):
    """Text to ids. The vocabulary file in ranks gives the ids of the tokenizers file of the same name, several times as fast; a text on which its
    library gives up (very long runs of blanks) goes to the tokenizers file itself."""
    import base64
    import functools

    import public_tokenizers
    import tiktoken

    with open(public_tokenizers.path(f"{name}.tiktoken"), "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    mark = "<|endoftext|>"
    made = tiktoken.Encoding(name, pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={mark: len(ranks)})

    @functools.cache
    def whole():
        from tokenizers import Tokenizer

        return Tokenizer.from_file(public_tokenizers.path(f"{name}.json"))

    def encode(text: str) -> list[int]:
        if len(text) >= 65536 and _BLANKS.search(text):
            return whole().encode(text, add_special_tokens=False).ids
        return made.encode(text, allowed_special="all") if mark in text else made.encode_ordinary(text)

    return encode


def pieces(docs: DataFrame, key: str = "doc_id", text: str = "text", tokenizer: str = "byte_bpe_50k", capacity: int = SEQUENCE, with_ids: bool = False) -> DataFrame:
    """(key, piece, start, length, ids_crc32, uid [, ids]): uid is another one for each row; ids is binary, little-endian unsigned 32-bit."""
    kind = docs.schema[key].dataType.simpleString()
    names = [key, "piece", "start", "length", "ids_crc32", "uid"] + ["ids"] * with_ids

    def run(batches):
        import zlib

        import numpy as np
        import pyarrow as pa
        from pyspark import TaskContext

        encode = encoder(tokenizer)
        uid = TaskContext.get().partitionId() << 40
        for b in batches:
            rows: list = []
            for i, t in enumerate(b.column(1).to_pylist()):
                ids = np.array([*encode(t or ""), END], "<u4")
                first = len(ids) % capacity or capacity
                cuts = [0, *range(first, len(ids) + 1, capacity)]
                for k, (x, y) in enumerate(zip(cuts, cuts[1:])):
                    raw = ids[x:y].tobytes()
                    rows.append((i, k, x, y - x, zlib.crc32(raw), uid, raw if with_ids else None))
                    uid += 1
            cols = list(zip(*rows)) or [()] * 7
            out = [b.column(0).take(pa.array(cols[0], pa.int64())), pa.array(cols[1], pa.int32()), *[pa.array(c, pa.int64()) for c in cols[2:6]]]
            yield pa.RecordBatch.from_arrays(out + [pa.array(cols[6], pa.binary())] * with_ids, names=names)

    return docs.select(F.col(f"`{key}`"), F.col(f"`{text}`")).mapInArrow(run, f"`{key}` {kind}, piece int, start bigint, length bigint, ids_crc32 bigint, uid bigint" + ", ids binary" * with_ids)


def lower_bound(lengths, capacity: int = SEQUENCE) -> int:
    """The largest of the bounds that two families of dual-feasible functions give; no packing of these lengths uses fewer sequences."""
    import numpy as np

    n = np.bincount(np.asarray(lengths, np.int64), minlength=capacity + 1).astype(np.int64)
    size = np.arange(capacity + 1)
    best = -(-int((n * size).sum()) // capacity)
    count, volume = np.concatenate([[0], np.cumsum(n)]), np.concatenate([[0], np.cumsum(n * size)])
    small = np.arange(1, capacity // 2 + 1)  # lengths under it count nothing, those over capacity less it a whole sequence
    high = capacity - small
    whole = count[-1] - count[high + 1]
    best = max(best, int((whole + -(-(volume[high + 1] - volume[small]) // capacity)).max()))
    for k in range(1, 33):  # a length counts in k-ths: those of (k + 1)-ths that it more than fills
        exact = (k + 1) * size % capacity == 0
        part = np.where(exact, size * k, (k + 1) * size // capacity * capacity)
        best = max(best, -(-int((n * part).sum()) // (k * capacity)))
    return best


def best_fit(lengths, capacity: int = SEQUENCE) -> list[int]:
    """The bin of each length, for lengths in falling order: the fullest open bin that has room, else a new one."""
    with_room: list[list[int]] = [[] for _ in range(capacity + 1)]
    open_rooms, bins, out = 0, 0, []
    for n in lengths:
        high = open_rooms >> n
        if high:
            room = n + (high & -high).bit_length() - 1
            at = with_room[room].pop()
            if not with_room[room]:
                open_rooms ^= 1 << room
        else:
            room, at, bins = capacity, bins, bins + 1
        out.append(at)
        if room > n:
            with_room[room - n].append(at)
            open_rooms |= 1 << (room - n)
    return out


_PLACED = "sequence_id bigint, offset bigint, room bigint, gap bigint"


def _pack(rows: DataFrame, n: int, deal: int, capacity: int, most: int) -> DataFrame:
    """Deals rows (uid, length, ...) to parts of about `most` and packs each; sequence_id is the least uid in the sequence."""
    parts = max(1, -(-n // most))
    names = [c for c in rows.columns if c not in ("sequence_id", "offset", "room", "gap")]

    def one(pdf):
        import numpy as np

        pdf = pdf[names].sort_values(["length", "uid"], ascending=[False, True], kind="stable").reset_index(drop=True)
        lengths = pdf["length"].to_numpy()
        at = np.array(best_fit(lengths.tolist(), capacity), np.int64)
        used = np.bincount(at, weights=lengths).astype(np.int64)
        least = np.full(len(used), np.iinfo(np.int64).max)
        np.minimum.at(least, at, pdf["uid"].to_numpy())
        pdf["sequence_id"] = least[at]
        pdf["offset"] = pdf.groupby(at)["length"].cumsum() - pdf["length"]
        pdf["room"] = capacity - used[at]
        pdf["gap"] = len(used) - lower_bound(lengths, capacity)
        return pdf

    schema = ", ".join(f"`{c}` {t}" for c, t in rows.select(*names).dtypes)
    dealt = rows.select(*names, F.pmod(F.xxhash64("uid", F.lit(deal)), F.lit(parts)).alias("part"))
    return dealt.groupBy("part").applyInPandas(lambda pdf: one(pdf), f"{schema}, {_PLACED}")


def packed(cut: DataFrame, capacity: int = SEQUENCE, most_rounds: int = 5, open_room: int = 16) -> DataFrame:
    """The rows of pieces() with sequence_id and offset. A sequence of a part with a gap is opened again if it has open_room or more left; of a
    certified part, whose bound is rounded up to a whole sequence, if a quarter of it is left."""
    cut = written(cut, "pieces")
    loose = cut.where(F.col("length") < capacity)
    n = loose.count()
    now = written(_pack(loose, n, 0, capacity, PART), "packed")
    done = [cut.where(F.col("length") == capacity).select("*", F.col("uid").alias("sequence_id"), F.lit(0).cast("bigint").alias("offset"))]
    final = [*cut.columns, "sequence_id", "offset"]
    for deal in range(1, most_rounds + 1):
        opened = (F.col("gap") > 0) & (F.col("room") >= open_room) | (F.col("room") >= capacity // 4)
        again = now.where(opened)
        n, before = again.agg(F.count("*"), F.count_distinct("sequence_id")).first()
        if before < 2:
            break
        after = written(_pack(again, n, deal, capacity, PART * 2 ** min(deal, 3)), "packed")
        if after.agg(F.count_distinct("sequence_id")).first()[0] >= before:
            continue  # the next round's parts are larger
        done.append(now.where(~opened).select(*final))
        now = after
    done.append(now.select(*final))
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    return out


def report(placed: DataFrame, capacity: int = SEQUENCE) -> dict:
    """Sequences used, the lower bound for all lengths at once, and the share of tokens that are filled."""
    lengths = {r[0]: r[1] for r in placed.groupBy("length").count().collect()}  # at most `capacity` rows
    used = placed.select("sequence_id").distinct().count()
    import numpy as np

    return {"sequences": used, "bound": lower_bound(np.repeat(list(lengths), list(lengths.values())), capacity), "filled": sum(k * v for k, v in lengths.items()) / max(1, used * capacity)}


def pack(docs: DataFrame, key: str = "doc_id", text: str = "text", **options) -> DataFrame:
    return packed(pieces(docs, key, text, **options))


def op2_packing(spark, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents", "doc_id", "text")).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")

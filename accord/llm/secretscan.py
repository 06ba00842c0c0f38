"""Secret scans over a trigram inverted index.

Each rule's expression gives a Boolean trigram query. The index maps (block of rows, trigram) to the rows that hold it; a block is of some
hundreds of rows, so no posting list grows with the corpus. Postings are intersected and united block by block, and only rows that pass a rule's
query have the rule's expression run over their whole text. Rules without mandatory trigrams run over every text.

Nulls: a null text is an empty one and has no span. Repeated rows have equal spans. Spans may overlap between kinds, not within one.
Long texts are scanned whole; positions are in code points, ends exclusive. An empty table gives no rows. All columns of the input come back as they
were, whatever their names: scan() calls its own column spans_ where the input has one called spans, and so on.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from accord.llm.common import let, spare, table
from accord.llm.trigrams import trigram_query, trigrams_of


@dataclass(frozen=True)
class Rule:
    kind: str
    pattern: str
    #: The least length of the given group of a match (0: the match itself); shorter matches are dropped after the search.
    least: int = 0
    group: int = 0


#: The three base kinds, then the method's own. A run of hexadecimal digits and an access key can't be found later within a
#: run that was too short, so their least length stands in the expression.
RULES = (
    Rule("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 6, 2),
    Rule("access", r"AKIA[A-Z0-9]{16,}"),
    Rule("hex", r"[0-9a-f]{24,}"),
    Rule("private_key", r"-----BEGIN [A-Z ]*PRIVATE KEY-----"),
    Rule("code_host", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("chat", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("web_token", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
    Rule("login_url", r"[a-z][a-z0-9+.-]{1,12}://[^\s/:@]{1,64}:[^\s/:@]{3,64}@"),
)


def _row_key(key: str, text: str) -> Column:
    return F.xxhash64(F.col(f"`{key}`"), F.col(f"`{text}`"))


def build_index(docs: DataFrame, vocabulary: set[str] | None = None, key: str = "doc_id", text: str = "text", block_rows: int = 256) -> DataFrame:
    """(block, trigram, rows): posting lists of the lower-case text. vocabulary None: all trigrams; else those that some rule set asks for."""
    n = docs.count()
    low = F.lower(F.coalesce(F.col(f"`{text}`"), F.lit("")))
    if vocabulary is None:
        held = F.array_distinct(F.regexp_extract_all(low, F.lit(r"(?s)(?=(...))"), F.lit(1)))
    else:
        held = let(low, lambda t: F.filter(F.array(*[F.lit(v) for v in sorted(vocabulary)]), lambda v: F.contains(t, v)))
    posts = docs.select(_row_key(key, text).alias("row"), F.explode(held).alias("trigram"))
    return posts.withColumn("block", F.pmod(F.col("row"), F.lit(max(1, n // block_rows)))).groupBy("block", "trigram").agg(F.collect_set("row").alias("rows"))


def _rows_of(query, lists: Column) -> Column:
    if isinstance(query, str):
        return F.coalesce(F.element_at(lists, F.lit(query)), F.array().cast("array<bigint>"))
    join = F.array_intersect if query[0] == "and" else F.array_union
    return reduce(join, [_rows_of(q, lists) for q in query[1]])


def candidates(index: DataFrame, rules=RULES) -> DataFrame:
    """(row, mask): the rows that pass the trigram queries; bit i of mask stands for rule i."""
    asked = [(i, q) for i, r in enumerate(rules) if (q := trigram_query(r.pattern)) is not True]
    lists = index.groupBy("block").agg(F.map_from_entries(F.collect_list(F.struct("trigram", "rows"))).alias("lists"))
    passed = F.array(*[F.struct(F.lit(1 << i).cast("bigint").alias("bit"), _rows_of(q, F.col("lists")).alias("rows")) for i, q in asked])
    each = lists.select(F.explode(passed).alias("p")).select("p.bit", F.explode("p.rows").alias("row"))
    return each.groupBy("row").agg(F.bit_or("bit").alias("mask"))


def spans(text: Column, rule: Rule) -> Column:
    """array<struct<start,end>> of the rule's matches, leftmost and non-overlapping: lengths of what lies between matches, summed up."""
    entry = "array<struct<start:bigint,end:bigint>>"
    gaps = F.split(text, rule.pattern, -1)
    found = F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(0))
    told = F.regexp_extract_all(text, F.lit(rule.pattern), F.lit(rule.group)) if rule.least else found
    lens = lambda a: F.transform(a, lambda s: F.length(s).cast("bigint"))
    start = F.struct(F.lit(0).cast("bigint").alias("at"), F.array().cast(entry).alias("out"))

    def step(acc, x):
        at = acc["at"] + x["gap"]
        return F.struct((at + x["len"]).alias("at"), F.concat(acc["out"], F.array(F.struct(at.alias("start"), (at + x["len"]).alias("end")))).alias("out"))

    def place(parts):
        return F.aggregate(parts, start, step, lambda acc: acc["out"])

    zipped = F.zip_with(F.zip_with(lens(gaps), lens(found), lambda g, n: F.struct(g.alias("gap"), n.alias("len"))), lens(told), lambda p, t: F.struct(p["gap"].alias("gap"), p["len"].alias("len"), t.alias("told")))
    whole = F.filter(zipped, lambda p: p["len"].isNotNull())
    cut = let(whole, lambda w: F.filter(F.arrays_zip(place(w).alias("span"), w.alias("part")), lambda p: p["part"]["told"] >= rule.least))
    return F.transform(cut, lambda p: p["span"]) if rule.least else place(whole)


def scan(docs: DataFrame, key: str = "doc_id", text: str = "text", rules=RULES) -> DataFrame:
    """docs with a column spans: array<struct<start,end,place,kind>> in order of start, then of the rules."""
    return _scanned(docs, key, text, rules).select("row.*", F.col("spans").alias(spare("spans", docs.columns)))


def _scanned(docs: DataFrame, key: str, text: str, rules) -> DataFrame:
    """(row: all columns of docs in one, whole: its text, spans)."""
    wanted = set().union(*(trigrams_of(trigram_query(r.pattern)) for r in rules))
    passed = candidates(build_index(docs, wanted, key, text), rules).select(F.col("row").alias("its"), "mask")
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), _row_key(key, text).alias("at"), F.col(f"`{text}`").alias("whole"))
    rows = rows.join(passed.hint("shuffle_hash"), F.col("at") == F.col("its"), "left")
    none = F.array().cast("array<struct<start:bigint,end:bigint,place:int,kind:string>>")
    whole = F.coalesce("whole", F.lit(""))
    parts = []

    def named(found: Column, place: int, kind: str) -> Column:
        return F.transform(found, lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), F.lit(place).alias("place"), F.lit(kind).alias("kind")))

    for i, r in enumerate(rules):
        told = named(spans(whole, r), i, r.kind)
        due = whole.rlike(r.pattern) if trigram_query(r.pattern) is True else F.coalesce(F.col("mask").bitwiseAND(1 << i) != 0, F.lit(False))
        parts.append(F.when(due, told).otherwise(none))
    return rows.select("row", "whole", F.sort_array(F.concat(*parts)).alias("spans"))


def redact(docs: DataFrame, key: str = "doc_id", text: str = "text", mark: str = "[secret]", rules=RULES) -> DataFrame:
    """docs with every span of the text replaced by mark; overlapping spans become one. The columns stay as they were."""
    begin = F.struct(F.lit(1).cast("bigint").alias("at"), F.lit("").alias("out"))

    def step(acc, s):
        fresh = s["start"] + 1 >= acc["at"]
        kept = F.when(fresh, F.concat(acc["out"], F.substring(F.col("whole"), acc["at"].cast("int"), (s["start"] + 1 - acc["at"]).cast("int")), F.lit(mark))).otherwise(acc["out"])
        return F.struct(F.greatest(acc["at"], s["end"] + 1).alias("at"), kept.alias("out"))

    clean = F.aggregate("spans", begin, step, lambda acc: F.concat(acc["out"], F.substring(F.col("whole"), acc["at"].cast("int"), F.lit(2**31 - 1))))
    clean = F.when(F.size("spans") > 0, clean).otherwise(F.col("whole"))
    return _scanned(docs, key, text, rules).select(*[clean.alias(c) if c == text else F.col(f"row.`{c}`") for c in docs.columns])


def op3_secrets(spark, sf_dir: str) -> DataFrame:
    found = scan(table(spark, sf_dir, "documents", "doc_id", "text"))
    text_of = lambda a: F.array_join(F.transform(a, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    count = lambda k: F.size(F.filter("spans", lambda s: s["kind"] == k)).cast("long")
    base = F.filter("spans", lambda s: s["place"] < 3)
    return found.select("doc_id", count("assign").alias("n_assign"), count("access").alias("n_access"), count("hex").alias("n_hex"), F.sha2(text_of(base), 256).alias("base_sha256"), text_of(F.col("spans")).alias("spans"))


def _sql() -> str:
    parts = []
    for i, r in enumerate(RULES):
        p = "'" + r.pattern.replace("'", "''") + "'"
        parts.append(f"""SELECT doc_id, {i} AS place, '{r.kind}' AS kind, unnest(list_transform(range(1, len(m) + 1), lambda k:
          {{'s': list_sum(list_transform(g[1:k], lambda x: length(x))) + coalesce(list_sum(list_transform(m[1:k - 1], lambda x: length(x))), 0), 'n': length(m[k]), 'told': length(q[k])}})) AS p
        FROM (SELECT doc_id, string_split_regex(t, {p}) AS g, regexp_extract_all(t, {p}) AS m, regexp_extract_all(t, {p}, {r.group}) AS q FROM d WHERE regexp_matches(t, {p}))""")
    each = "\n UNION ALL ".join(f"SELECT doc_id, place, kind, p.s::BIGINT AS s, (p.s + p.n)::BIGINT AS e FROM ({x}) WHERE p.told >= {r.least}" for x, r in zip(parts, RULES, strict=True))
    return f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
f AS ({each}),
a AS (SELECT doc_id, count(*) FILTER (place = 0) AS n_assign, count(*) FILTER (place = 1) AS n_access, count(*) FILTER (place = 2) AS n_hex,
  string_agg(kind || ':' || s || ':' || e, ',' ORDER BY s, place) FILTER (place < 3) AS base, string_agg(kind || ':' || s || ':' || e, ',' ORDER BY s, place) AS spans FROM f GROUP BY doc_id)
SELECT d.doc_id, coalesce(n_assign, 0)::BIGINT AS n_assign, coalesce(n_access, 0)::BIGINT AS n_access, coalesce(n_hex, 0)::BIGINT AS n_hex,
  sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans FROM d LEFT JOIN a USING (doc_id)
"""


OP3_SQL = _sql()

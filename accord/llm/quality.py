"""Quality rules by weak supervision.

Every rule votes for (1) or against (-1) a document or abstains (0). Expectation-maximisation over the counts of vote patterns estimates how
often each rule gives each vote on good documents and on each kind of bad ones, without labels; the posterior probability of good quality
then decides, not a demand that all rules pass. Several rules look at each kind from different sides, so that it stands out as votes that go together; nothing
but a weak prior, the same for every rule and vote, is held of them beforehand. There are at most 3 ** (number of rules) patterns, whatever the corpus, so their
counts are read by the driver.

Nulls: a null or empty text has no words; such documents get a posterior like any other and fail the base rules. Texts are taken whole.
Repeated rows get equal verdicts. An empty table gives no rows. Windows of words are compared by 64-bit hashes within one document.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from accord.llm.common import WORD, let, table, written


def _covered(windows: Column) -> Column:
    """Words that lie in 3-word windows whose hash occurs twice or more."""

    def at_places(places: Column) -> Column:
        return F.aggregate(F.transform(places, lambda x, k: F.least(F.lit(3), F.coalesce(F.get(places, k + 1) - x, F.lit(3)))), F.lit(0), lambda a, b: a + b)

    def of_sorted(t: Column) -> Column:
        same = lambda e, j: F.coalesce(e["h"] == F.get(t, j)["h"], F.lit(False))
        return let(F.sort_array(F.transform(F.filter(t, lambda e, j: same(e, j - 1) | same(e, j + 1)), lambda e: e["i"])), at_places)

    paired = F.sort_array(F.transform(windows, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
    return F.when(F.size(F.array_distinct(windows)) == F.size(windows), 0).otherwise(let(paired, of_sorted))


def features(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_distinct, n_lines, n_letters, n_upper, n_stops, n_bangs), all long."""
    whole = F.coalesce(F.col(f"`{text}`"), F.lit(""))
    rows = docs.select(F.col(f"`{key}`").alias(key), whole.alias("whole"))
    count = lambda p: F.regexp_count("whole", F.lit(p))

    def of_words(ws: Column) -> Column:
        windows = F.transform(F.slice(ws, 1, F.size(ws) - 2), lambda w, i: F.xxhash64(w, F.get(ws, i + 1), F.get(ws, i + 2)))
        return F.struct(F.size(ws).alias("n"), F.size(F.array_distinct(ws)).alias("u"), F.when(F.size(ws) < 3, 0).otherwise(let(windows, _covered)).alias("r"))

    lines = let(F.filter(F.split("whole", "\n"), lambda x: x.rlike(WORD)), lambda ls: F.struct(F.size(ls).alias("n"), (F.size(ls) - F.size(F.array_distinct(ls))).alias("d")))
    rows = rows.select(key, let(F.regexp_extract_all("whole", F.lit(WORD), F.lit(0)), of_words).alias("w"), lines.alias("l"), (F.length("whole") - count(r"[\x20\x09-\x0D]")).alias("word_chars"), count(r"[#*$%&|<>]").alias("n_symbols"), count(r"\p{L}").alias("n_letters"), count(r"\p{Lu}").alias("n_upper"), count(r"[.!?。]+(?=\s|$)").alias("n_stops"), count("!!").alias("n_bangs"))
    return rows.select(key, *[c.cast("long").alias(n) for n, c in (("n_words", F.col("w.n")), ("word_chars", F.col("word_chars")), ("n_symbols", F.col("n_symbols")), ("n_dup_lines", F.col("l.d")), ("n_repeat_words", F.col("w.r")), ("n_distinct", F.col("w.u")), ("n_lines", F.col("l.n")), ("n_letters", F.col("n_letters")), ("n_upper", F.col("n_upper")), ("n_stops", F.col("n_stops")), ("n_bangs", F.col("n_bangs")))])


def _vote(good: Column, bad: Column) -> Column:
    return F.when(bad, -1).when(good, 1).otherwise(0)


def _under(a: str, share: float, b: str) -> Column:
    return F.col(a) <= share * F.col(b)


def _over(a: str, share: float, b: str) -> Column:
    return F.col(a) > share * F.col(b)


#: Name, kind of bad document that the rule speaks of (0: none by itself), for, against: what makes each rule vote. Fixed values.
RULES = (
    ("length", 0, lambda: F.col("n_words") >= 50, lambda: F.col("n_words") < 20),
    ("symbols", 1, lambda: _under("n_symbols", 0.05, "n_words"), lambda: _over("n_symbols", 0.2, "n_words")),
    ("symbol_letters", 1, lambda: _under("n_symbols", 0.02, "n_letters"), lambda: _over("n_symbols", 0.04, "n_letters")),
    ("letters", 1, lambda: _over("n_letters", 0.85, "word_chars"), lambda: ~_over("n_letters", 0.7, "word_chars")),
    ("lines", 2, lambda: _under("n_dup_lines", 1 / 3, "n_lines"), lambda: _over("n_dup_lines", 0.5, "n_lines")),
    ("repeats", 2, lambda: _under("n_repeat_words", 1 / 3, "n_words"), lambda: _over("n_repeat_words", 0.5, "n_words")),
    ("distinct", 2, lambda: _over("n_distinct", 0.1, "n_words"), lambda: ~_over("n_distinct", 0.05, "n_words")),
    ("sentences", 2, lambda: _over("n_stops", 0.02, "n_words"), lambda: (F.col("n_words") >= 30) & _under("n_stops", 0.002, "n_words")),
    ("capitals", 3, lambda: _under("n_upper", 0.2, "n_letters"), lambda: _over("n_upper", 0.5, "n_letters")),
    ("bangs", 3, lambda: F.col("n_bangs") == 0, lambda: _over("n_bangs", 0.02, "n_words")),
    ("word_length", 0, lambda: F.col("word_chars").between(3 * F.col("n_words"), 10 * F.col("n_words")), lambda: ~F.col("word_chars").between(2 * F.col("n_words"), 16 * F.col("n_words"))),
)


def votes(rules=RULES) -> Column:
    return F.array(*[_vote(good(), bad()) for _, _, good, bad in rules])


def fit(counts: dict[tuple, int], kinds: tuple[int, ...], rounds: int = 500, prior: float = 1.0) -> tuple[list[float], list[dict[int, list[float]]]]:
    """(share of each class, for each rule and vote its chance in each class) from counts of vote patterns; kinds has the kind of each rule, 0 for none.

    Class 0 is good documents; the others are kinds of bad ones. Bad documents have little in common with each other, so one class for them would be taken
    by the most frequent kind. Starts from documents that no rule of a kind votes against being good and from the others being of the kinds whose rules do,
    at odds of 9 to 1; prior is added to every count. From there on only the counts decide.
    """
    n, classes = sum(counts.values()), 1 + max(kinds, default=0)

    def start(p) -> list[float]:
        against = [sum(v == -1 and k == c for v, k in zip(p, kinds, strict=True)) for c in range(classes)]
        against[0] = 0
        rest = classes - 1 or 1
        return [0.1 if c == 0 else 0.9 * against[c] / sum(against) for c in range(classes)] if any(against) else [0.9 if c == 0 else 0.1 / rest for c in range(classes)]

    belief = {p: start(p) for p in counts}
    shares, tables = [1 / classes] * classes, [{v: [1 / 3] * classes for v in (-1, 0, 1)} for _ in kinds]
    for _ in range(rounds if n else 0):
        sizes = [sum(c * belief[p][j] for p, c in counts.items()) for j in range(classes)]
        shares = [(x + prior) / (n + classes * prior) for x in sizes]
        tables = []
        for i in range(len(kinds)):
            seen = {v: [prior] * classes for v in (-1, 0, 1)}
            for p, c in counts.items():
                for j in range(classes):
                    seen[p[i]][j] += c * belief[p][j]
            tables.append({v: [x / (y + 3 * prior) for x, y in zip(row, sizes, strict=True)] for v, row in seen.items()})
        after = {p: posterior(p, shares, tables) for p in counts}
        moved = max(abs(a - b) for p in counts for a, b in zip(after[p], belief[p], strict=True))
        belief = after
        if moved < 1e-9:
            break
    return shares, tables


def posterior(pattern: tuple, shares: list[float], tables: list[dict[int, list[float]]]) -> list[float]:
    """The chance of each class, given the votes."""
    logs = [math.log(shares[j]) + sum(math.log(t[v][j]) for v, t in zip(pattern, tables, strict=True)) for j in range(len(shares))]
    each = [math.exp(x - max(logs)) for x in logs]
    return [x / sum(each) for x in each]


def judged(docs: DataFrame, key: str = "doc_id", text: str = "text", least: float = 0.5, rules=RULES) -> DataFrame:
    """features() with votes (array<int>), quality (the posterior) and good (quality >= least).

    Features, a few numbers per document, are written once: they are read for the fit and again for the verdicts.
    """
    seen = written(features(docs, key, text).withColumn("votes", votes(rules)), "features")
    counts = {tuple(r[0]): r[1] for r in seen.groupBy("votes").count().collect()}  # at most 3 ** len(rules) rows
    shares, tables = fit(counts, tuple(r[1] for r in rules))
    against = F.lit(0.0)  # odds of each kind of bad document against good, added up
    for j in range(1, len(shares)):
        log = F.lit(math.log(shares[j] / shares[0]))
        for i, t in enumerate(tables):
            v = F.col("votes")[i]
            log = log + F.when(v == 1, math.log(t[1][j] / t[1][0])).when(v == -1, math.log(t[-1][j] / t[-1][0])).otherwise(math.log(t[0][j] / t[0][0]))
        against = against + F.exp(log)
    return seen.withColumn("quality", F.lit(1.0) / (F.lit(1.0) + against)).withColumn("good", F.col("quality") >= least)


def op1_quality(spark, sf_dir: str) -> DataFrame:
    seen = judged(table(spark, sf_dir, "documents", "doc_id", "text"))
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return seen.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", failed.alias("base_failed"), (~failed & F.col("good")).alias("kept"))

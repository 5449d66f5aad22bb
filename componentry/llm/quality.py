"""Quality rules: adaptive thresholds from mergeable quantile sketches per language and source.

A sketch is a histogram over logarithmic buckets (relative error at most ``GAMMA`` - 1): rows
(lang, source, rule, bucket, n). Sketches merge by adding counts, in any order, with the same result at
every run; a language's sketch is the sum of its sources', and that of the corpus the sum of all.

A sketch's fence for a rule is q_high + REACH * (q_high - q_low), with quantiles that suit the rule: quartiles where
most documents have a value of their own, the median and the 98th percentile where most have none. A group's
threshold is the geometric mean of its own fence, weighed by its documents, and its language's, weighed as ``PRIOR``
documents; the language's is tied to that of the corpus likewise. So a large group decides alone, a small one leans on its
language, and nothing switches at a size. Rates up to a rule's ``floor`` are noise (a stray sign, one line
that recurs) and never rejected. No cutoff is fixed beyond that.

Null text: no words, base failure. Null language or source: a group of its own. Repeated rows: each has its own
verdict. An empty table has no thresholds and no rows. Very long texts are counted whole. Columns of the input
never clash with ours: they travel in one struct.
"""

from __future__ import annotations

import math
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from componentry.llm.words import _SPACE, Words, buffer_of, text_map
from componentry.plans.storage import cut, small_side

MIN_WORDS = 20
MAX_REPEAT_PERCENT = 30
WINDOW = 8
GAMMA = 1.02
REACH = 3
PRIOR = 100


class Rule(NamedTuple):
    """A rate per million, the percentiles of its fence, and the rate up to which it is noise."""

    part: str
    whole: str
    low: int
    high: int
    floor: int


RULES = {
    "symbols": Rule("n_symbols", "word_chars", 25, 75, 10_000),
    "repeats": Rule("n_repeat_words", "n_words", 50, 98, 50_000),
    "dup_lines": Rule("n_dup_lines", "n_lines", 50, 98, 100_000),
    "word_length": Rule("word_chars", "n_words", 25, 75, 0),
}

FIELDS = [T.StructField(n, T.LongType()) for n in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")]

_SYMBOL = np.zeros(256, bool)
_SYMBOL[[ord(c) for c in "#*$%&|<>"]] = True
_BLANK = " \t\n\x0b\x0c\r"


def _by_doc(flags: np.ndarray, starts: np.ndarray) -> np.ndarray:
    total = np.zeros(len(flags) + 1, np.int64)
    np.cumsum(flags, out=total[1:])
    return total[starts[1:]] - total[starts[:-1]]


def repeated_words(hashes: np.ndarray, doc: np.ndarray, n_docs: int, window: int = WINDOW) -> np.ndarray:
    """Words of each text that lie in a window found at least twice in it."""
    m = len(hashes) - window + 1
    if m <= 0:
        return np.zeros(n_docs, np.int64)
    acc = np.zeros(m, np.uint64)
    for k in range(window):
        acc = acc * np.uint64(0xD6E8FEB86659FD93) + hashes[k : k + m]
    at = np.flatnonzero(doc[:m] == doc[window - 1 :])
    order = at[np.lexsort((acc[at], doc[at]))]
    same = (acc[order][1:] == acc[order][:-1]) & (doc[order][1:] == doc[order][:-1])
    twice = np.zeros(len(order), bool)
    twice[1:] |= same
    twice[:-1] |= same
    cover = np.zeros(len(hashes) + 1, np.int64)
    np.add.at(cover, order[twice], 1)
    np.add.at(cover, order[twice] + window, -1)
    return np.bincount(doc[np.cumsum(cover)[:-1] > 0], minlength=n_docs)


def _stats(texts: pa.Array) -> list[pa.Array]:
    data, starts = buffer_of(texts)
    n = len(starts) - 1
    words = Words(data, starts, lower=False)
    n_words = np.bincount(words.doc, minlength=n)
    chars = _by_doc(~_SPACE[data] & ((data & 0xC0) != 0x80), starts)
    dup, lines = np.zeros(n, np.int64), np.zeros(n, np.int64)
    for i, t in enumerate(texts.to_pylist()):
        if t and "\n" in t:
            own = [x for x in t.split("\n") if x.strip(_BLANK)]
            lines[i], dup[i] = len(own), len(own) - len(set(own))
        elif t and n_words[i]:
            lines[i] = 1
    repeat = repeated_words(words.hashes(), words.doc, n)
    return [pa.array(x.astype(np.int64)) for x in (n_words, chars, _by_doc(_SYMBOL[data], starts), dup, repeat, lines)]


def quality_stats(docs: DataFrame, keep: list[str], text: str = "text") -> DataFrame:
    """``keep`` columns and the counts in FIELDS."""
    return text_map(docs, text, keep, FIELDS, _stats)


def base_failed():
    n = F.col("n_words")
    return (n < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * n)


def _rates() -> list:
    """(rule, rate per million) of each row."""
    return [(n, F.floor(F.col(r.part) * 1_000_000 / F.greatest(F.col(r.whole), F.lit(1)))) for n, r in RULES.items()]


def _bucket(rate):
    return F.ceil(F.log(F.greatest(rate, F.lit(1)).cast("double")) / math.log(GAMMA)).cast("int")


def sketches(stats: DataFrame) -> DataFrame:
    """Mergeable sketches of the documents that pass the base rules."""
    rules = F.array(*(F.struct(F.lit(n).alias("rule"), _bucket(r).alias("bucket")) for n, r in _rates()))
    return stats.where(~base_failed()).select("lang", "source", F.explode(rules).alias("x")).groupBy("lang", "source", "x.rule", "x.bucket").agg(F.count(F.lit(1)).alias("n"))


def fences(sketch: DataFrame, *keys: str) -> DataFrame:
    """(keys, rule, docs, fence, as its logarithm) of the sketches (rule, bucket, n) merged by ``keys``."""
    merged = sketch.groupBy(*keys, "rule", "bucket").agg(F.sum("n").alias("n"))
    whole = Window.partitionBy(*keys, "rule")
    ranked = merged.withColumn("c", F.sum("n").over(whole.orderBy("bucket"))).withColumn("t", F.sum("n").over(whole))
    percent = lambda end: F.create_map(*(x for n, r in RULES.items() for x in (F.lit(n), F.lit(getattr(r, end)))))[F.col("rule")]
    at = lambda end: F.min(F.when(100 * F.col("c") >= percent(end) * F.col("t"), F.pow(F.lit(GAMMA), F.col("bucket"))))
    cuts = ranked.groupBy(*keys, "rule").agg(at("low").alias("lo"), at("high").alias("hi"), F.max("t").alias("docs"))
    return cuts.select(*keys, "rule", "docs", F.log(F.col("hi") + REACH * (F.col("hi") - F.col("lo"))).alias("fence"))


def thresholds(sketch: DataFrame, prior: int = PRIOR) -> DataFrame:
    """(lang, source, rule, at_most): each group's own fence, tied to its language's and the corpus's by ``prior`` documents."""
    tied = lambda n, own, other: (n * own + prior * other) / (n + prior)
    every = fences(sketch).select("rule", F.col("fence").alias("all_fence"))
    lang = fences(sketch, "lang").join(every, "rule").select(F.col("lang").alias("_l"), F.col("rule").alias("_r"), tied(F.col("docs"), F.col("fence"), F.col("all_fence")).alias("lang_fence"))
    own = fences(sketch, "lang", "source").join(lang, F.col("lang").eqNullSafe(F.col("_l")) & (F.col("rule") == F.col("_r")))
    floor = F.create_map(*(x for n, r in RULES.items() for x in (F.lit(n), F.lit(float(r.floor)))))[F.col("rule")]
    return own.select("lang", "source", "rule", F.greatest(F.exp(tied(F.col("docs"), F.col("fence"), F.col("lang_fence"))), floor).alias("at_most"))


def verdicts(stats: DataFrame, limits: DataFrame) -> DataFrame:
    """``stats`` with base_failed and kept."""
    wide = limits.groupBy(F.col("lang").alias("_l"), F.col("source").alias("_s")).agg(F.map_from_entries(F.collect_list(F.struct("rule", "at_most"))).alias("_limits"))
    joined = stats.join(small_side(cut(wide, "limits"), 256), F.col("lang").eqNullSafe(F.col("_l")) & F.col("source").eqNullSafe(F.col("_s")), "left")
    # a bucket's upper edge may lie up to GAMMA above the value
    passes = F.lit(True)
    for name, rate in _rates():
        passes = passes & F.coalesce(rate <= F.try_element_at("_limits", F.lit(name)) * GAMMA, F.lit(True))
    return joined.withColumn("base_failed", base_failed()).withColumn("kept", ~F.col("base_failed") & passes).drop("_l", "_s", "_limits")


def quality_verdicts(docs: DataFrame) -> DataFrame:
    """doc_id, lang, source, the counts, base_failed and kept, one row per row of ``docs``."""
    stats = cut(quality_stats(docs, ["doc_id", "lang", "source"]), "quality")
    return verdicts(stats, cut(thresholds(sketches(stats)), "fences"))


def keep_good(docs: DataFrame) -> DataFrame:
    """``docs`` (all its columns) without the rejected ones. Texts are read and counted once; rows wait with their counts for the thresholds."""
    packed = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_row"), "lang", "source", F.col("text").alias("_t"))
    stats = cut(quality_stats(packed, ["_row", "lang", "source"], "_t"), "quality")
    return verdicts(stats, cut(thresholds(sketches(stats)), "fences")).where("kept").select("_row.*")


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return quality_verdicts(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


_AT = "min(CASE WHEN 100 * c >= {p} * t THEN pow({g}, bucket) END)"
_FENCES = "SELECT {keys}rule, max(t) AS docs, ln({hi} + {k} * ({hi} - {lo})) AS fence FROM (SELECT {keys}rule, lo, hi, bucket, sum(n) OVER (PARTITION BY {keys}rule ORDER BY bucket) AS c, sum(n) OVER (PARTITION BY {keys}rule) AS t FROM (SELECT {keys}rule, lo, hi, bucket, sum(n) AS n FROM sk GROUP BY ALL)) GROUP BY {keys}rule"
_SQL_FENCES = {k: _FENCES.format(keys=k, k=REACH, hi=_AT.format(p="hi", g=GAMMA), lo=_AT.format(p="lo", g=GAMMA)) for k in ("", "lang, ", "lang, source, ")}
OP8_SQL = rf"""
WITH d AS MATERIALIZED (SELECT row_number() OVER () AS rid, doc_id, lang, source, coalesce(text, '') AS text, coalesce(regexp_extract_all(text, '[^\x20\x09-\x0D]+'), []) AS w FROM documents),
win AS MATERIALIZED (SELECT rid, i, array_to_string(w[i:i + {WINDOW - 1}], ' ') AS g FROM (SELECT rid, w, unnest(range(1, len(w) - {WINDOW - 2})) AS i FROM d)),
rep AS (SELECT rid, count(DISTINCT i + k) AS n FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, g) AS c FROM win), range({WINDOW}) o(k) WHERE c > 1 GROUP BY rid),
ln AS (SELECT rid, count(*) AS n_lines, count(*) - count(DISTINCT line) AS dup FROM (SELECT rid, unnest(string_split(text, chr(10))) AS line FROM d) WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY rid),
s AS MATERIALIZED (SELECT d.rid, doc_id, lang, source, len(w) AS n_words, CAST(coalesce(list_sum(list_transform(w, lambda x: length(x))), 0) AS BIGINT) AS word_chars, CAST(length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, coalesce(ln.dup, 0) AS n_dup_lines, coalesce(rep.n, 0) AS n_repeat_words, coalesce(n_lines, 0) AS n_lines FROM d LEFT JOIN rep USING (rid) LEFT JOIN ln USING (rid)),
f AS MATERIALIZED (SELECT *, n_words < {MIN_WORDS} OR 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words AS base_failed FROM s),
x AS MATERIALIZED ({' UNION ALL '.join(f"SELECT rid, lang, source, base_failed, '{n}' AS rule, {r.low} AS lo, {r.high} AS hi, {float(r.floor)} AS floor, {r.part} * 1000000 // greatest({r.whole}, 1) AS rate FROM f" for n, r in RULES.items())}),
sk AS MATERIALIZED (SELECT lang, source, rule, lo, hi, CAST(ceil(ln(CAST(greatest(rate, 1) AS DOUBLE)) / {math.log(GAMMA)!r}) AS INTEGER) AS bucket, count(*) AS n FROM x WHERE NOT base_failed GROUP BY ALL),
a AS ({_SQL_FENCES['']}),
lg AS (SELECT l.lang, l.rule, (l.docs * l.fence + {PRIOR} * a.fence) / (l.docs + {PRIOR}) AS fence FROM ({_SQL_FENCES['lang, ']}) l JOIN a USING (rule)),
lim AS (SELECT o.lang, o.source, o.rule, (o.docs * o.fence + {PRIOR} * lg.fence) / (o.docs + {PRIOR}) AS fence FROM ({_SQL_FENCES['lang, source, ']}) o JOIN lg ON lg.rule = o.rule AND lg.lang IS NOT DISTINCT FROM o.lang),
v AS (SELECT rid, bool_and(coalesce(rate <= greatest(exp(lim.fence), x.floor) * {GAMMA}, true)) AS ok FROM x LEFT JOIN lim ON lim.rule = x.rule AND lim.lang IS NOT DISTINCT FROM x.lang AND lim.source IS NOT DISTINCT FROM x.source GROUP BY rid)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND ok AS kept FROM f JOIN v USING (rid)
"""

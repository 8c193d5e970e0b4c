"""Line-first cleaning: rules per line, then rejection of documents that lose too much. DataFrame functions only.

A line fails if it is navigation (several separators between short items), boilerplate (licence, cookie, sign-in phrases), junk (words
that carry symbols), shouting, or a repeat of an earlier line. What is left must keep enough of the document's words and end its lines
with punctuation often enough.

Defined results: null and empty texts have no words, fail the base rules and aren't kept. Repeated rows get a row each. Very long texts
are treated whole. Empty input gives an empty result. Other columns of the documents are kept, whatever their names, but for those that the
result itself has: they give way.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphsplit.llm.common import WORD, let, unused, words

SYMBOLS = "[#*$%&|<>]"
#: Fixed phrases of lines that aren't prose.
BOILERPLATE = r"(?i)released under the|all rights reserved|cookie policy|accept (all )?cookies|terms of (use|service)|privacy policy|sign in to|subscribe to|click here|copyright \(c\)|javascript"
NAVIGATION = r" [|>»·] "
WINDOW = 8


def covered(ws: Column, n: Column, window: int = WINDOW) -> Column:
    """How many words lie in a window of `window` words that occurs twice or more. Windows are told apart by 64-bit hashes.

    Hashes with their positions are sorted as structs; equal neighbours give the positions of repeated windows, whose sorted gaps, none
    over the window, add up to the words covered.
    """
    hashed = F.transform(F.sequence(F.lit(1), n - (window - 1)), lambda i: F.struct(F.xxhash64(*[F.get(ws, i + (k - 1)) for k in range(window)]).alias("h"), i.alias("i")))
    same = lambda a, i, x: F.coalesce(F.get(a, i)["h"] == x["h"], F.lit(False))
    repeats = let(F.sort_array(hashed), lambda a: F.transform(F.filter(a, lambda x, i: same(a, i - 1, x) | same(a, i + 1, x)), lambda x: x["i"]))
    begin = F.struct(F.lit(0).alias("sum"), F.lit(-window).alias("last"))
    total = F.aggregate(F.sort_array(repeats), begin, lambda acc, i: F.struct((acc["sum"] + F.least(F.lit(window), i - acc["last"])).alias("sum"), i.alias("last")))["sum"]
    return F.when(n > window, total).otherwise(F.lit(0)).cast("long")


def line_rules(line: Column, n: Column) -> dict[str, Column]:
    """Why a line of n words would go; each is a condition on the line's own text. What n rules out comes first, so that few lines meet the long pattern."""
    return {
        "navigation": F.regexp_count(line, F.lit(NAVIGATION)) * 3 >= F.greatest(F.lit(9), n),
        "boilerplate": (n <= 30) & line.rlike(BOILERPLATE),
        "symbols": F.regexp_count(line, F.lit(SYMBOLS + "{2}")) * 4 > n,
        "shouting": F.regexp_count(line, F.lit("!!")) * 4 > n,
        "unpunctuated": (n > 3) & (n <= 8) & ~line.rlike(r"[.!?:;,…。！？\"'”»)][\x20\x09-\x0D]*$"),
    }


def clean(docs: DataFrame, repeated_share: float = 0.3, least_words: int = 20, least_kept: float = 0.5) -> DataFrame:
    """The rows of docs with their statistics, the cleaned text, the words it keeps and the verdicts base_failed and kept."""
    text = F.coalesce(F.col("text"), F.lit(""))
    counts = let(words(F.col("text")), lambda ws: let(F.size(ws), lambda n: F.struct(n.cast("long").alias("n_words"), F.length(F.array_join(ws, "")).cast("long").alias("word_chars"), covered(ws, n).alias("n_repeat_words"))))
    bad = lambda x, n: F.coalesce(reduce(lambda a, b: a | b, line_rules(x, n).values()), F.lit(False))
    judged = lambda x: let(F.regexp_count(x, F.lit(WORD)), lambda n: F.struct(x.alias("line"), n.alias("n"), bad(x, n).alias("bad")))
    lines = let(
        F.filter(F.split(text, "\n"), lambda x: x.rlike(WORD)),
        lambda a: let(
            F.array_distinct(a),
            lambda d: F.struct((F.size(a) - F.size(d)).cast("long").alias("n_dup_lines"), F.filter(F.transform(d, judged), lambda x: ~x["bad"]).alias("good")),
        ),
    )
    c, l, w = (unused(docs, x) for x in ("_c", "_l", "_kept_words"))
    out = docs.withColumn(c, counts).withColumn(l, lines)
    out = out.withColumn(w, F.aggregate(f"{l}.good", F.lit(0).cast("long"), lambda acc, x: acc + x["n"]))
    failed = (F.col(f"{c}.n_words") < least_words) | (F.lit(100) * F.col(f"{c}.n_repeat_words") > F.lit(round(100 * repeated_share)) * F.col(f"{c}.n_words"))
    good = F.col(w) >= F.col(f"{c}.n_words") * F.lit(least_kept)
    stats = {
        "n_words": F.col(f"{c}.n_words"),
        "word_chars": F.col(f"{c}.word_chars"),
        "n_symbols": F.coalesce(F.regexp_count(F.col("text"), F.lit(SYMBOLS)), F.lit(0)).cast("long"),
        "n_dup_lines": F.col(f"{l}.n_dup_lines"),
        "n_repeat_words": F.col(f"{c}.n_repeat_words"),
        "base_failed": failed,
        "kept": ~failed & good,
        "kept_words": F.col(w),
        "cleaned": F.array_join(F.transform(f"{l}.good", lambda x: x["line"]), "\n"),
    }
    return out.select(*[F.col(f"`{x}`") for x in docs.columns if x not in stats], *[v.alias(k) for k, v in stats.items()])


SQL = r"""
WITH t AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS text FROM documents),
w AS (SELECT r, doc_id, text, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS ws FROM t),
win AS (SELECT r, i, array_to_string(ws[i:i + 7], ' ') AS key FROM (SELECT r, ws, unnest(range(1, len(ws) - 6)) AS i FROM w WHERE len(ws) > 8)),
rep AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, key) AS c FROM win) WHERE c > 1),
cov AS (SELECT r, sum(least(8, i - last))::BIGINT AS n_repeat_words FROM (SELECT r, i, coalesce(lag(i) OVER (PARTITION BY r ORDER BY i), -8) AS last FROM rep) GROUP BY r),
ln AS (SELECT r, line, len(regexp_extract_all(line, '[^\x20\x09-\x0D]+')) AS n FROM (SELECT r, unnest(string_split(text, chr(10))) AS line FROM t)),
li AS (SELECT r, line, any_value(n) AS n, count(*) AS c FROM ln WHERE n > 0 GROUP BY r, line),
lj AS (SELECT r, sum(c - 1)::BIGINT AS n_dup_lines, sum(CASE WHEN
    (len(regexp_extract_all(line, ' [|>»·] ')) >= 3 AND len(regexp_extract_all(line, ' [|>»·] ')) * 3 >= n)
    OR (n <= 30 AND regexp_matches(line, '(?i)released under the|all rights reserved|cookie policy|accept (all )?cookies|terms of (use|service)|privacy policy|sign in to|subscribe to|click here|copyright \(c\)|javascript'))
    OR len(regexp_extract_all(line, '[#*$%&|<>]{2}')) * 4 > n
    OR len(regexp_extract_all(line, '!!')) * 4 > n
    OR (n > 3 AND n <= 8 AND NOT regexp_matches(line, '[.!?:;,…。！？"''”»)][\x20\x09-\x0D]*$'))
    THEN 0 ELSE n END)::BIGINT AS kept_words FROM li GROUP BY r),
f AS (SELECT w.doc_id, len(ws)::BIGINT AS n_words, length(array_to_string(ws, ''))::BIGINT AS word_chars,
  len(regexp_extract_all(text, '[#*$%&|<>]'))::BIGINT AS n_symbols, coalesce(n_dup_lines, 0)::BIGINT AS n_dup_lines, coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words, coalesce(kept_words, 0) AS kept_words
  FROM w LEFT JOIN cov USING (r) LEFT JOIN lj USING (r)),
g AS (SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM f)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND kept_words >= n_words * 0.5 AS kept, kept_words FROM g
"""

"""Personal data by weak supervision, in DataFrame functions only.

Patterns propose candidates: those of the base kinds, looser ones, and long secrets. Four labelers vote on each candidate (yes, no or no
opinion): the exact pattern with its check (range, Luhn, number of digits), a gazetteer of words that announce such data, the context's
edges, and the candidate's shape. Expectation maximisation over the counts of vote patterns estimates each labeler's reliability by kind,
without any label, but for what is known: real data hardly ever fail their own check, so that no context outvotes one that fails. The
posteriors train a logistic span classifier on votes, length and share of digits, which becomes one Spark expression. Counts are of the whole
corpus; the driver gets one row a pattern, a number that the kinds and labelers bound.

Base spans always stay; the classifier adds spans that overlap none of them. Places are code points.

Defined results: null and empty texts have no spans. Repeated rows get a row each. Very long texts are treated whole; the patterns are
possessive or anchored so that long runs take neither stack nor quadratic time. Spans of one start follow the order of kinds. Other columns
don't matter, whatever their names, and are kept by `redact`. Empty input gives an empty result.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphsplit.llm.common import cut, let

#: Kinds in the order that ties of start follow; the first four have base patterns.
KINDS = ("email", "ip", "card", "phone", "secret")
LOCAL = "A-Za-z0-9._%+-"
#: (kind, whether it is a base pattern, what a text must hold, pattern). Runs start where no such character precedes, or where the last match ended.
PATTERNS = (
    (0, True, "@", rf"(?:(?<![{LOCAL}])|\G)[{LOCAL}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"),
    (1, True, r"[0-9]\.[0-9]", r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}+"),
    (2, True, "[0-9]", r"[0-9](?:[\x20-]?[0-9])++"),
    (3, True, r"\+[0-9]", r"\+[0-9][\x20().0-9-]+[0-9]"),
    (0, False, r"(?i)[\[(]at[\])]", rf"(?i)(?<![{LOCAL}])[{LOCAL}]++ ?[\[(]at[\])] ?[A-Za-z0-9-]++(?: ?(?:\.|[\[(]dot[\])]) ?[A-Za-z0-9-]++)++"),
    (3, False, "[0-9][ -][0-9]", r"(?<![0-9+(.-])(?:\([0-9]{2,4}\)[ -]?|[0-9]{2,4}[ -])[0-9]{3}[ -][0-9]{4}(?![0-9-])"),
    (4, False, "[A-Za-z0-9_]{32}", r"(?<![A-Za-z0-9_])(?=[A-Za-z_]*[0-9])(?=[0-9_]*[A-Za-z])[A-Za-z0-9_]{32,}+"),
)
#: Words that announce a kind, within so many characters before it.
GAZETTEER = ("mail|contact|write to|kontakt|correo|courriel", r"\bip\b|host|server|address|adresse", "card|visa|karte|carte|tarjeta|iban|account", "phone|tel|call|fax|mobile|telefon|llame|appel", "token|secret|passw|api|key|credential|bearer")
BEFORE = 24
LABELERS = 4
#: Chance that real data fail the exact check of their kind (a checksum, a range, a number of digits).
FAILS = 1e-6


def hits(text: Column, needs: str, pattern: str) -> Column:
    """Array of (s, e, hit, before, after) of all matches: what lies between them, from splitting, gives their places."""
    empty = F.expr("cast(array() as array<struct<s:int,e:int,hit:string,before:string,after:string>>)")

    def places(g: Column, h: Column) -> Column:
        # running places as text: appending to an array copies it value by value, which long lists of matches don't bear
        def add(acc: Column, i: Column) -> Column:
            return let(acc["at"] + F.length(F.get(g, i)), lambda s: F.struct((s + F.length(F.get(h, i))).alias("at"), F.concat(acc["out"], F.lit(","), s.cast("string")).alias("out")))

        starts = F.aggregate(F.sequence(F.lit(0), F.size(h) - 1), F.struct(F.lit(0).alias("at"), F.lit("").alias("out")), add)["out"]
        one = lambda x, i: let(x.cast("int"), lambda s: F.struct(s.alias("s"), (s + F.length(F.get(h, i))).alias("e"), F.get(h, i).alias("hit"), F.right(F.get(g, i), F.lit(BEFORE)).alias("before"), F.left(F.get(g, i + 1), F.lit(1)).alias("after")))
        return F.transform(F.slice(F.split(starts, ","), F.lit(2), F.size(h)), one)

    found = let(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), lambda h: F.when(F.size(h) > 0, let(F.split(text, pattern, -1), lambda g: places(g, h))).otherwise(empty))
    return F.when(text.rlike(needs), found).otherwise(empty)


def digits(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]", "")


def valid(kind: int, hit: Column) -> Column:
    n = F.length(digits(hit))
    if kind == 1:
        return F.forall(F.split(hit, r"\."), lambda p: let(F.regexp_replace(p, "^0+", ""), lambda q: (F.length(q) < 3) | ((F.length(q) == 3) & (q <= "255"))))
    if kind == 2:
        return n.between(14, 19) & F.call_function("luhn_check", digits(hit))
    if kind == 3:
        return n.between(10, 15)
    return F.lit(True)


def shape(kind: int, hit: Column) -> Column:
    """Whether the characters themselves look right."""
    n = F.length(digits(hit))
    return {
        0: F.length(hit).between(6, 80),
        1: F.length(hit).between(7, 15),
        2: n.between(14, 19) & ~hit.rlike(r"^([0-9])\1*$"),
        3: n.between(9, 15),
        4: (n >= 4) & hit.rlike("[A-Za-z]") & (F.length(hit) <= 128),
    }[kind]


def candidate(kind: int, base: bool, x: Column) -> Column:
    vote = lambda yes, no: F.when(yes, 2).when(no, 0).otherwise(1)
    ok = F.coalesce(valid(kind, x["hit"]), F.lit(False)) if base else F.lit(False)
    edge = F.right(x["before"], F.lit(1))
    votes = (
        vote(ok, F.lit(base) & ~ok),
        vote(x["before"].rlike("(?i)" + GAZETTEER[kind]), F.lit(False)),
        vote((edge == "") | edge.rlike(r"[\s\"'(:=,;<]"), edge.rlike(r"[A-Za-z0-9/_.-]") | x["after"].rlike(r"[A-Za-z0-9/_]")),
        vote(shape(kind, x["hit"]), ~shape(kind, x["hit"])),
    )
    code = reduce(lambda a, b: a * 3 + b, votes, F.lit(kind))
    size = F.length(x["hit"])
    bucket = F.least(F.lit(15), F.floor(F.log2(size))).cast("int") * 8 + F.round(F.length(digits(x["hit"])) * 7 / size).cast("int")
    return F.struct(x["s"].alias("s"), F.lit(kind).alias("kind"), x["e"].alias("e"), ok.alias("base"), code.cast("int").alias("code"), bucket.cast("int").alias("bucket"))


def candidates(text: Column) -> Column:
    """Array of (s, kind, e, base, code, bucket): places, kind, whether it is a base span, its votes and its size and share of digits."""

    def one(kind: int, base: bool, needs: str, pattern: str) -> Column:
        found = F.transform(hits(text, needs, pattern), lambda x: candidate(kind, base, x))
        # card-like runs of few digits are no candidates at all
        return F.filter(found, lambda c: c["base"] | F.lit(kind != 2) | (c["bucket"] >= 3 * 8)) if base else found

    return F.concat(*[one(*p) for p in PATTERNS])


def reliabilities(counts: dict[int, float], rounds: int = 60) -> dict[int, float]:
    """Posterior that a candidate is real for each code, by expectation maximisation over the counts of vote patterns, kind by kind."""
    out = {}
    for kind in {c // 3**LABELERS for c in counts}:
        codes = [c for c in counts if c // 3**LABELERS == kind]
        votes = np.asarray([[c // 3**j % 3 for j in range(LABELERS - 1, -1, -1)] for c in codes])
        n = np.asarray([counts[c] for c in codes], float)
        q = 1 / (1 + np.exp(-1.5 * (votes - 1).sum(axis=1)))
        prior = np.asarray([[1.0, 2.0, 3.0], [3.0, 2.0, 1.0]])  # of real ones and others, as if seen so often
        failed = votes[:, 0] == 0
        for _ in range(rounds):
            share = (n @ q + 1) / (n.sum() + 2)
            like = []
            for z, w in ((0, n * q), (1, n * (1 - q))):
                table = np.stack([np.bincount(votes[:, j], weights=w, minlength=3) + prior[z] for j in range(LABELERS)])
                table /= table.sum(axis=1, keepdims=True)
                part = np.log(table[np.arange(LABELERS), votes])
                if z == 0:  # known, not estimated: real data pass their own check
                    part[failed, 0] = np.log(FAILS)
                like.append(part.sum(axis=1))
            q = 1 / (1 + np.exp(np.clip(like[1] + np.log(1 - share) - like[0] - np.log(share), -40, 40)))
        out.update(zip(codes, q.tolist(), strict=True))
    return out


def inputs(code: int, bucket: int) -> list[float]:
    kind, votes = code // 3**LABELERS, [code // 3**j % 3 - 1 for j in range(LABELERS - 1, -1, -1)]
    return [1.0, *[float(kind == k) for k in range(len(KINDS))], *map(float, votes), float(votes[0] < 0), bucket // 8 / 8, bucket % 8 / 7]


def span_classifier(groups: list[tuple[int, int, int]], rounds: int = 400) -> list[float]:
    """Weights over inputs(code, bucket), trained on the posteriors of (code, bucket, count) groups."""
    counts: dict[int, float] = {}
    for code, _, n in groups:
        counts[code] = counts.get(code, 0) + n
    real = reliabilities(counts)
    x = np.asarray([inputs(c, b) for c, b, _ in groups]).reshape(len(groups), len(inputs(0, 0)))
    n, y = np.asarray([float(g[2]) for g in groups]), np.asarray([real[g[0]] for g in groups])
    w = np.zeros(len(inputs(0, 0)))
    for _ in range(rounds if len(groups) else 0):  # Newton steps, damped by a ridge
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        g = x.T @ (n * (p - y)) + w
        h = (x * (n * p * (1 - p))[:, None]).T @ x + np.eye(len(w))
        step = np.linalg.solve(h, g)
        w -= step * min(1.0, 4 / max(1e-9, np.abs(step).max()))
        if np.abs(step).max() < 1e-8:
            break
    return w.tolist()


def fit(found: DataFrame) -> list[float]:
    """The classifier's weights from a table with a column `found` of candidates."""
    groups = found.select(F.explode("found").alias("c")).groupBy("c.code", "c.bucket").agg(F.count("*").alias("n")).collect()  # kinds x votes x buckets at most
    return span_classifier(sorted((r["code"], r["bucket"], r["n"]) for r in groups))


def taken(found: Column, weights: list[float], least: float = 0.5) -> Column:
    """The base spans, and candidates that the classifier accepts and that overlap none of them."""

    def probable(c: Column) -> Column:
        parts = [F.lit(1.0), *[(F.floor(c["code"] / 3**LABELERS) == k).cast("double") for k in range(len(KINDS))], *[(F.floor(c["code"] / 3**j) % 3 - 1).cast("double") for j in range(LABELERS - 1, -1, -1)], (F.floor(c["code"] / 3 ** (LABELERS - 1)) % 3 == 0).cast("double"), F.floor(c["bucket"] / 8) / 8, c["bucket"] % 8 / 7]
        z = reduce(lambda a, b: a + b, [F.lit(float(w)) * p for w, p in zip(weights, parts, strict=True)])
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-z)) >= least

    base = F.filter(found, lambda c: c["base"])
    more = lambda b: F.filter(found, lambda c: ~c["base"] & probable(c) & ~F.exists(b, lambda x: (x["s"] < c["e"]) & (c["s"] < x["e"])))
    return let(base, lambda b: F.sort_array(F.transform(F.concat(b, more(b)), lambda c: F.struct(c["s"].alias("s"), c["kind"].alias("kind"), c["e"].alias("e"), c["base"].alias("base")))))


def as_text(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.get(names, x["kind"]), x["s"], x["e"])), ",")


def find(docs: DataFrame) -> DataFrame:
    """doc_id, counts and digest of the base spans, and all spans, of every row of docs."""
    found = cut(docs.select("doc_id", candidates(F.coalesce(F.col("text"), F.lit(""))).alias("found")))
    spans = found.withColumn("all", taken(F.col("found"), fit(found))).withColumn("own", F.filter("all", lambda x: x["base"]))
    number = lambda k: F.size(F.filter("own", lambda x: x["kind"] == k)).cast("long").alias(f"n_{KINDS[k]}")
    counts = [number(k) for k in range(4)]
    return spans.select("doc_id", *counts, F.sha2(as_text(F.col("own")).cast("binary"), 256).alias("base_sha256"), as_text(F.col("all")).alias("spans"))


def redact(docs: DataFrame) -> DataFrame:
    """The rows of docs with every span of their text replaced by its kind in brackets; overlapping spans by the first one's."""
    text = F.coalesce(F.col("text"), F.lit(""))
    weights = fit(docs.select(candidates(text).alias("found")))
    names = F.array(*[F.lit(k) for k in KINDS])

    def add(acc: Column, x: Column) -> Column:
        fresh = x["s"] >= acc["at"]
        out = F.when(fresh, F.concat(acc["out"], F.substring(text, acc["at"] + 1, x["s"] - acc["at"]), F.lit("["), F.get(names, x["kind"]), F.lit("]"))).otherwise(acc["out"])
        return F.struct(F.greatest(acc["at"], x["e"]).alias("at"), out.alias("out"))

    rebuilt = lambda spans: let(F.aggregate(spans, F.struct(F.lit(0).alias("at"), F.lit("").alias("out")), add), lambda a: F.concat(a["out"], F.substring(text, a["at"] + 1, F.length(text))))
    spans = let(candidates(text), lambda c: taken(c, weights))
    new = F.when(F.col("text").isNotNull(), let(spans, lambda s: F.when(F.size(s) > 0, rebuilt(s)).otherwise(F.col("text"))))
    return docs.withColumn("text", new)

import re
import zlib

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from graphsplit.llm import cleaning, impact_index, language, link_trust, mixing, near_dup, packing, privacy, registry, rules, toxicity
from tests.compare import database, same

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
LONG = " ".join(f"word{k % 977} is here." for k in range(30_000))
HARD = [
    (0, None, None, None, None), (1, "", "en", "a", 0), (2, " \n\t ", "en", "a", 4), (3, "same words in this text again and again today", "en", "b", 1), (3, "same words in this text again and again today", "en", "b", 1),
    (4, "same words in this text again and again today", None, None, None), (5, LONG, "de", "b", 1), (6, "mail a.b@c.de now", "fr", "c", 1), (None, "no id at all but some words", "en", "a", 1), (7, "é 😀 !!!", "en", "￿", 1),
]


@pytest.fixture(scope="module")
def hard(spark):
    return spark.createDataFrame(HARD, DOCS).withColumn("size", F.lit(1)).withColumn("rank", F.lit("x")).withColumn("score", F.lit(0)).withColumn("kept", F.lit(True)).withColumn("length", F.lit(2))


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(1, 0, 1), (3, 1, 0), (3, None, None), (5, 1, 0), (None, 1, 1), (6, 0, 1)], "doc_id long, quality int, toxic int")


@pytest.fixture(scope="module")
def con(sf):
    return database(sf)


@pytest.mark.parametrize("name", sorted(registry.SQL))
def test_sql_agrees(spark, con, sf, name):
    same(registry.QUERIES[name](spark, sf), registry.SQL[name], con)


def per_row(spark, hard, none, labels, run):
    assert run(none, labels.limit(0)).count() == 0
    out = run(hard, labels)
    assert out.count() == len(HARD)
    return out


# mixing


def test_mix_hits_targets(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    p = mixing.plan(docs).join(docs.select("doc_id", "source"), "doc_id").toPandas()
    assert (p.taken <= 3 * p["size"]).all()
    for _, g in p.groupby("source"):
        assert abs(g.taken.sum() - g.target.iloc[0]) <= g["size"].max() / 2 + 1e-6
        assert g.target.iloc[0] <= 3 * g.source_size.iloc[0] + 1e-6
    assert p.groupby("source").target.first().sum() == pytest.approx(p["size"].sum())
    mixed = mixing.mix(docs)
    assert mixed.columns == docs.columns
    n = mixed.groupBy("doc_id").count().toPandas().set_index("doc_id")["count"]
    want = (p.set_index("doc_id").taken / p.set_index("doc_id")["size"]).round().astype(int)
    assert n.to_dict() == want[want > 0].to_dict()


def test_mix_edges(spark, hard, none, labels):
    out = per_row(spark, hard, none, labels, lambda d, _: mixing.plan(d)).toPandas()
    assert (out[out["size"] == 0].taken == 0).all()
    assert mixing.mix(hard).columns == hard.columns and mixing.mix(none).count() == 0


# packing


def check_packed(out, texts, capacity=2048):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(packing.tokenizer_path("word_bpe_49k.json"))
    want = []
    for doc_id, text in texts:
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 0]
        want += [(doc_id, k // capacity, k, len(ids[k : k + capacity]), zlib.crc32(np.asarray(ids[k : k + capacity], "<u4").tobytes())) for k in range(0, len(ids), capacity)]
    key = lambda rows: sorted(map(repr, rows))
    assert key((None if pd.isna(r.doc_id) else int(r.doc_id), r.piece, r.start, r.length, r.ids_crc32) for r in out.itertuples()) == key(want)
    for _, g in out.sort_values(["sequence_id", "offset"]).groupby("sequence_id"):
        assert (g.offset == g.length.cumsum() - g.length).all() and g.length.sum() <= capacity
    return out.sequence_id.nunique()


def test_packing_is_exact_and_tight(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out = packing.pack(docs).toPandas()
    used = check_packed(out, [(r.doc_id, r.text) for r in docs.collect()])
    assert used <= np.ceil(out.length.sum() / 2048) * 1.02 + 1


def test_packing_edges(spark, hard, none):
    check_packed(packing.pack(hard).toPandas(), [(r[0], r[1]) for r in HARD])
    assert packing.pack(none).count() == 0


def test_word_ids_are_the_tokenizers():
    w = packing.WordIds(packing.tokenizer_path("word_bpe_49k.json"))
    for x in ["a  b c\x85d\x1cë ̈ x 5's'll <|endoftext|>x ΑΣ Σ x　y\r\nz İ ﬁ", " \t\n", "<|startoftext|>", "Straße naïve 12.5%"]:
        assert np.frombuffer(w.of(x), "<u4").tolist() == w.tokenizer.encode(x, add_special_tokens=False).ids


def test_weights_are_least_squares_without_negatives():
    """The conditions that tell the optimum of non-negative least squares."""
    counts = np.bincount(np.random.default_rng(8).integers(1, 41, 600), minlength=41)
    made = packing.patterns(counts, 40)
    x = packing.fit(made, counts, 20_000)
    a = np.zeros((41, len(made)))
    for j, lengths in enumerate(made):
        for k in lengths[lengths > 0]:
            a[k, j] += 1
    g = a.T @ (a @ x - np.where(np.arange(41) > 0, counts, 0))
    assert (x >= 0).all() and g.min() > -1e-2 and np.abs(g * x).max() < 1e-1


def test_runs_cover_counts():
    rng = np.random.default_rng(5)
    counts = np.bincount(rng.integers(1, 101, 5000), minlength=101)
    seen = {}
    for length, first, n, sequence, offset in packing.runs(counts, 100):
        assert first == seen.get(length, 0) and offset + length <= 100
        seen[length] = first + n
    assert all(seen.get(k, 0) == counts[k] for k in range(101))


# link trust


def ranks_by_definition(links, seeds, damping=0.85):
    hosts = sorted({h for e in links for h in e} | set(seeds))
    w = np.zeros((len(hosts), len(hosts)))
    for (a, b), n in links.items():
        w[hosts.index(a), hosts.index(b)] += n
    t = np.array([seeds.get(h, 0) for h in hosts]) / max(1, sum(seeds.values()))
    p = np.divide(w, w.sum(1, keepdims=True), out=np.zeros_like(w), where=w.sum(1, keepdims=True) > 0)
    r = t.copy()
    for _ in range(400):
        f = damping * (r @ p)
        r = f + (1 - f.sum()) * t
    return {h: x * sum(seeds.values()) for h, x in zip(hosts, r, strict=True)}


@pytest.mark.parametrize("rows", [200_000, 0])
def test_link_trust_against_brute_force(spark, monkeypatch, rows):
    monkeypatch.setattr(link_trust, "BROADCAST_ROWS", rows)  # 0: the salted way
    urls = ["http://a.example.net/en/1", "http://a.example.net/x", "https://B.example.com/de/2", "http://b.example.com/en", "http://c.org/fr/", "http://c.org/", "http://d.com/", None, "nothing", "http://e.com?x=/de/", "http://www.b.example.com/", "http://10.0.0.1/"]
    html = ['<a href="http://d.com/1">', '<a href="//d.com/2"> <a href="http://e.com/">', "", None, '<a href="/local">', "", '<a href="http://a.example.net/">' * 3, "", "", "<a href='http://c.org/'>", '<a href="x">', "x" * 100_000 + "<a href='http://c.org/'>"]
    pages = spark.createDataFrame(list(zip(range(len(urls)), urls, html, strict=True)), "page_id long, url string, html string").withColumn("host", F.lit("clash")).withColumn("rank", F.lit(1))
    out = {r.page_id: r for r in link_trust.judge(pages).collect()}
    assert [out[k].rule for k in range(10)] == ["example.net/en/", "net/", "example.com/de/", None, "org/fr/", None, None, None, None, None]
    assert [out[k].verdict for k in (0, 1, 2, 4)] == ["allow", "block", "block", "allow"]
    assert out[2].host == "b.example.com" and out[9].path == "" and out[7].host == ""
    links = {("a.example.net", "d.com"): 2, ("a.example.net", "e.com"): 1, ("d.com", "a.example.net"): 3, ("e.com", "c.org"): 1, ("10.0.0.1", "c.org"): 1}
    domains = {("a.example.net", "example.net"): 2, ("www.b.example.com", "b.example.com"): 1, ("b.example.com", "example.com"): 3}
    links |= {(y, x) if turn else (x, y): n for (x, y), n in domains.items() for turn in (0, 1)}
    assert {(r.src, r.dst): r.links for r in link_trust.host_edges(pages).collect()} == links
    trust = ranks_by_definition(links, {"a.example.net": 1, "c.org": 1})
    distrust = ranks_by_definition({(b, a): n for (a, b), n in links.items()}, {"a.example.net": 1, "b.example.com": 1})
    pages_of = {h: sum(r.host == h for r in out.values()) for h in {r.host for r in out.values()}}
    for r in out.values():
        assert r.trust == pytest.approx(trust.get(r.host, 0) / pages_of[r.host], abs=1e-4)
        assert r.distrust == pytest.approx(distrust.get(r.host, 0) / pages_of[r.host], abs=1e-4)
        if r.rule is None:
            assert r.verdict == ("block" if r.distrust >= 0.5 and r.distrust > r.trust else "allow")
    assert link_trust.judge(pages.limit(0)).count() == 0
    twice = link_trust.judge(pages.union(pages))
    assert twice.count() == 2 * len(urls)


def test_distrust_reaches_hosts_many_links_away(spark):
    # h0 -> h1 -> ... -> h36 -> bad.net: 20,000 blocked pages at the end of a chain of 37 links
    pages = spark.range(20_000).select(F.col("id").alias("page_id"), F.lit("http://bad.net/x").alias("url"), F.lit("").alias("html"))
    chain = [(100_000 + j, f"http://h{j}.com/", f'<a href="http://{f"h{j + 1}.com" if j < 36 else "bad.net"}/">') for j in range(37)]
    out = {r.host: r for r in link_trust.judge(pages.union(spark.createDataFrame(chain, pages.schema))).filter("page_id >= 100000").collect()}
    first = 20_000 / sum(0.85**j for j in range(38))
    for j in range(37):
        assert out[f"h{j}.com"].distrust == pytest.approx(first * 0.85 ** (37 - j), abs=1e-3)
    assert out["h0.com"].verdict == "block"


def test_distrust_comes_from_a_hub_and_from_relatives(spark):
    # a hub that 500 hosts link to is blocked; so are most pages of one domain's subdomains
    rows = [(k, f"http://h{k}.com/", '<a href="http://hub.net/">') for k in range(500)] + [(k, "http://hub.net/x", "") for k in range(1000, 3000)]
    rows += [(k, f"http://s{k % 7}.example.com/de/", "") for k in range(5000, 5070)] + [(6000, "http://www.example.com/en/", "")]
    out = link_trust.judge(spark.createDataFrame(rows, "page_id long, url string, html string"))
    assert {r.verdict for r in out.filter("page_id < 500").collect()} == {"block"}
    assert out.filter("page_id = 6000").first().distrust > 0.5
    # the given pages only hold links to themselves: what propagates there are domains
    pages = spark.read.parquet("/root/testdata/sf0.01/pages.parquet")
    assert link_trust.link_edges(pages).count() == 0 and link_trust.host_edges(pages).count() >= 100


# classifiers


def test_rule_ensemble_holds_out(spark):
    d = "/root/testdata/sf0.01"
    out = rules.scores(spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet"))
    m = out.join(spark.read.parquet(f"{d}/labels.parquet"), "doc_id").filter("held_out").toPandas()
    assert (m.predicted == m.quality).mean() > 0.95
    assert m.score.between(0, 1).all()


def test_compiled_rules_are_the_paths(spark):
    """The Spark columns against rules applied by numpy, and the lasso's optimality conditions."""
    rng = np.random.default_rng(3)
    x = rng.normal(size=(800, len(rules.NAMES)))
    y = ((x[:, 0] > 0.2) & (x[:, 3] < 0.5) | (rng.random(800) < 0.05)).astype(int)
    model = rules.learn(x, y, trees=8)
    z = np.full(len(x), model.bias)
    for rule, w in zip(model.rules, model.weights, strict=True):
        met = np.ones(len(x), bool)
        for name, above, t in rule:
            column = x[:, rules.NAMES.index(name)]
            met &= column > t if above else column <= t
        z += w * met
    frame = spark.createDataFrame(pd.DataFrame(x, columns=rules.NAMES).assign(k=range(800)))
    got = frame.select("k", F.struct(*rules.NAMES).alias("s")).select("k", model.score("s").alias("p")).toPandas().sort_values("k").p
    assert np.allclose(got, rules.sigmoid(z)) and ((z > 0) == y).mean() > 0.9
    a = (x[:, :4] > 0).astype(float)
    w, b = rules.lasso_logistic(a, y.astype(float), 0.02, 4000)
    g = a.T @ (rules.sigmoid(a @ w + b) - y) / len(y)
    assert np.allclose(g[w != 0], -0.02 * np.sign(w[w != 0]), atol=1e-4) and (np.abs(g) <= 0.02 + 1e-4).all()


def test_statistics_by_definition(spark):
    texts = ["Ab cd, cd!\n12 cd\n12 cd", "", "x" * 200_000]
    docs = spark.createDataFrame(list(enumerate(texts)), "k int, text string")
    for r in docs.select("k", rules.statistics(F.col("text")).alias("s")).collect():
        t = texts[r.k]
        ws, lines = t.split(), [x for x in t.split("\n") if x]
        n, chars = max(1, len(ws)), max(1, len("".join(ws)))
        want = [np.log1p(len(ws)), len("".join(ws)) / n, len(set(ws)) / n, sum("A" <= c <= "Z" for c in t) / chars, sum(c in "#*$%&|<>" for c in t) / n, sum(c in "!?" for c in t) / n, sum(c in ".,;:" for c in t) / n, sum("0" <= c <= "9" for c in t) / chars, len(set(lines)) / max(1, len(lines)), len(ws) / max(1, len(lines))]
        assert list(r.s) == pytest.approx(want)


def test_language_holds_out(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    m = language.predictions(docs).join(docs.select("doc_id", "lang"), "doc_id").filter("held_out").toPandas()
    assert (m.lang_pred == m.lang).mean() > 0.98


def test_decoding_by_definition(spark):
    """Loss-weighted decoding of whole rows against the sum of losses over each codeword, with nine languages."""
    words = {f"l{k}": [f"{c}{v}{c}" for c in "bcdfghjklmnp"[k : k + 4] for v in "aeiou"] for k in range(9)}
    rng = np.random.default_rng(1)
    rows = [(j, " ".join(rng.choice(words[lang], 30)), lang) for j, lang in enumerate(sorted(words) * 40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").withColumn("score", F.lit("clash")).withColumn("v", F.lit(1))
    model = language.train(docs, 180)
    assert model.languages == sorted(words)
    out = language.identify(docs, model).toPandas().sort_values("doc_id")
    right = 0
    for (_, text, lang), p in zip(rows, out.itertuples(), strict=True):
        margin = (language.trigrams(text) @ model.w + model.b) * model.scale
        loss = [sum(np.log1p(np.exp(-b * m)) for b, m in zip(code, margin, strict=True)) for code in model.codes]
        assert p.lang_pred == model.languages[int(np.argmin(loss))]
        assert p.score == pytest.approx(np.exp(-min(loss)) / np.exp(-np.asarray(loss)).sum(), rel=1e-4)
        right += p.lang_pred == lang
    assert right > 0.95 * len(rows)


def test_every_language_is_learned(spark):
    # one language holds nearly all rows; the others have few
    docs = spark.range(3000).select(F.col("id").alias("doc_id"), F.concat(F.lit("word "), "id").alias("text"), F.when(F.col("id") % 100 == 0, F.concat(F.lit("rare"), (F.col("id") / 100 % 10).cast("int"))).otherwise("common").alias("lang"))
    assert language.train(docs, 50).languages == ["common"] + [f"rare{k}" for k in range(10)]


def test_noisy_or_by_definition():
    model = toxicity.SentenceModel(["bad", "vile*"], np.asarray([9.0, 12.0]), -8.0)
    text = "All is well. This is bad! Vilely done\nÉnd. "
    z = [0.0, 9.0, 12.0, 0.0, 0.0]
    chance = [1 / (1 + np.exp(8 - v)) for v in z]
    score, found = model.judge(text, toxicity.Known(model.weights))
    assert score == pytest.approx(1 - np.prod([1 - p for p in chance]))
    assert [text[a:b].strip() for a, b in found] == ["This is bad", "Vilely done"]
    assert model.judge(None, toxicity.Known(model.weights))[0] == pytest.approx(chance[0])


def test_toxicity_holds_out_and_locates(spark):
    d = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    m = toxicity.scores(docs, labels).join(labels, "doc_id").toPandas()
    h = m[m.held_out]
    assert (h.predicted == h.toxic).mean() > 0.95
    assert (h[h.toxic == 0].predicted == 0).mean() > 0.99
    assert h[h.toxic == 1].predicted.mean() > 0.9  # recall
    assert (m[m.predicted == 1].spans != "").mean() > 0.85


def test_classifier_edges(spark, hard, none, labels):
    for run in (rules.scores, toxicity.scores, lambda d, _: language.predictions(d)):
        out = per_row(spark, hard, none, labels, run).toPandas()
        assert out.score.between(0, 1).all()
    assert rules.accepted(hard, labels).columns == hard.columns
    out = language.predictions(hard).toPandas()
    assert (out[out.doc_id.isin([0, 1, 2])].lang_pred == "und").all()


def test_one_class_alone(spark, hard):
    one = spark.createDataFrame([(1, 1, 1), (3, 1, 1), (5, 1, 1)], "doc_id long, quality int, toxic int")
    assert rules.scores(hard, one).agg(F.min("score")).first()[0] > 0.9
    assert toxicity.scores(hard, one).agg(F.max("score")).first()[0] == 0


def test_codewords_differ():
    for k in (2, 3, 5, 9, 40):
        c = language.codewords(k)
        assert min((a != b).sum() for i, a in enumerate(c) for b in c[:i]) >= (c.shape[1] / 4 if k > 6 else 1)
        assert (np.abs(c.sum(axis=0)) < k).all()  # every bit tells some languages apart


def test_rows_that_clash(spark):
    """Extra columns named like working columns stay as they are."""
    docs = spark.createDataFrame([(1, "A good text. " * 30, "en", "a", 1)], DOCS).withColumn("_stats", F.lit(7)).withColumn("_c", F.lit(8)).withColumn("_l", F.lit(9)).withColumn("_kept_words", F.lit(10))
    kept = rules.accepted(docs, spark.createDataFrame([], "doc_id long, quality int, toxic int")).first()
    assert (kept["_stats"], kept["_c"]) == (7, 8)
    out = cleaning.clean(docs).first()
    assert (out["_c"], out["_l"], out["_kept_words"], out["n_words"]) == (8, 9, 10, 90)


# cleaning and privacy


def test_cleaning_edges(spark, hard, none, labels):
    out = per_row(spark, hard, none, labels, lambda d, _: cleaning.clean(d)).toPandas()
    assert out[out.doc_id.isin([0, 1, 2])].base_failed.all()
    assert out[out.doc_id == 5].n_words.iloc[0] == 90_000


@pytest.mark.parametrize("text", ["a b c d e f g h " * 3, "x " * 30, " ".join(map(str, range(50))), "1 2 3 4 5 6 7 8 9 1 2 3 4 5 6 7 8 9 9"])
def test_repeats_against_brute_force(spark, text):
    ws = text.split()
    windows = [tuple(ws[i : i + 8]) for i in range(len(ws) - 7)]
    cover = {j for i, w in enumerate(windows) if windows.count(w) > 1 for j in range(i, i + 8)}
    docs = spark.createDataFrame([(1, text)], "doc_id long, text string")
    assert cleaning.clean(docs).first()["n_repeat_words"] == len(cover)


def luhn(d):
    return sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(reversed(d))) % 10 == 0


def base_spans(t):
    out = []
    for k, (n, p) in enumerate((("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]"))):
        for m in re.finditer(p, t):
            d = re.sub("[^0-9]", "", m.group())
            if (k == 1 and max(map(int, m.group().split("."))) > 255) or (k == 2 and not (14 <= len(d) <= 19 and luhn(d))) or (k == 3 and not 10 <= len(d) <= 15):
                continue
            out.append((m.start(), k, m.end(), n))
    return [f"{n}:{s}:{e}" for s, k, e, n in sorted(out)]


PRIVATE = ["a@b.c_x@d.e", "a@b.c@d.e f@g", "1.2.3.4.5.6.7.8 256.1.1.1 001.002.003.0004 1.2.3", "+1 (017) 555-7713 +1", "4111 1111 1111 1111 4111-1111-1111-1112 41111111111111111111", "é +49 30 1234567 9807915762804490x@y.zz", "", None, "1" * 3000, "1.2.3." * 500 + "4", "a" * 5000, "a@b" + ".c" * 3000, "😀 a@b.cc 😀 1.1.1.1", "x@y.z " * 300, "1 2 3 " * 800]


def test_privacy_against_brute_force(spark):
    import hashlib

    docs = spark.createDataFrame([(k, t) for k, t in enumerate(PRIVATE)], "doc_id long, text string")
    for r in privacy.find(docs).collect():
        want = base_spans(PRIVATE[r.doc_id] or "")
        assert r.base_sha256 == hashlib.sha256(",".join(want).encode()).hexdigest()
        assert set(want) <= set(r.spans.split(",") if r.spans else [])
    clean = {r.doc_id: r.text for r in privacy.redact(docs).collect()}
    assert clean[0] == "[email][email]" and clean[7] is None and clean[12] == "😀 [email] 😀 [ip]"


def test_privacy_edges(spark, hard, none, labels):
    per_row(spark, hard, none, labels, lambda d, _: privacy.find(d))
    assert privacy.redact(hard).columns == hard.columns


def test_votes_by_definition(spark):
    """Each labeler's vote of each candidate, from the text."""
    text = "call +49 30 1234567 now; card 4111 1111 1111 1111, card 4111 1111 1111 1112."
    docs = spark.createDataFrame([(text,)], "text string")
    found = docs.select(F.explode(privacy.candidates(F.col("text"))).alias("c")).select("c.*").collect()
    votes = {(privacy.KINDS[r.kind], text[r.s : r.e]): [r.code // 3**j % 3 for j in range(3, -1, -1)] for r in found if r.kind in (2, 3) and r.e - r.s > 12}
    # check, gazetteer, edges, shape: 2 yes, 1 no opinion, 0 no
    assert votes[("phone", "+49 30 1234567")] == [2, 2, 2, 2]
    assert votes[("card", "4111 1111 1111 1111")] == [2, 2, 2, 2]
    assert votes[("card", "4111 1111 1111 1112")] == [0, 2, 2, 2]


def test_no_context_outvotes_a_failed_check(spark):
    rows = [(k, f"card number {4111111111111111 + k} and mail a{k}@b.cc") for k in range(60)]
    out = privacy.find(spark.createDataFrame(rows, "doc_id long, text string")).toPandas()
    for r, (_, text) in zip(out.sort_values("doc_id").itertuples(), rows, strict=True):
        cards = [x.split(":") for x in r.spans.split(",") if x.startswith("card")]
        assert all(luhn(text[int(a) : int(b)]) for _, a, b in cards)
        assert len(cards) == luhn(text.split()[2])


def test_added_spans(spark):
    """Secrets have no base pattern: announced ones with both letters and digits are added, plain long words are not."""
    rows = [(k, f"api token: {'ab12' * 10}{k} ok") for k in range(40)] + [(k, "x" * 40 + " " + "plain words here") for k in range(40, 80)]
    out = privacy.find(spark.createDataFrame(rows, "doc_id long, text string")).toPandas().set_index("doc_id").spans
    assert all(out[k].startswith("secret:11:") for k in range(40)) and all(out[k] == "" for k in range(40, 80))


def test_estimation_is_at_a_fixed_point():
    """A further round of expectation and maximisation, written out, changes no posterior."""
    codes = {27 * 2 + 9 * 2 + 3 * 2 + 2: 40.0, 27 * 2 + 9 * 1 + 3 * 2 + 2: 30.0, 27 * 1 + 9 * 1 + 3 * 0 + 0: 50.0, 27 * 1 + 9 * 1 + 3 * 2 + 0: 9.0}
    q = privacy.reliabilities(codes, 4000)
    share = (sum(n * q[c] for c, n in codes.items()) + 1) / (sum(codes.values()) + 2)

    def like(c, real):
        out = share if real else 1 - share
        for j in range(4):
            seen = [(1, 2, 3)[v] if real else (3, 2, 1)[v] for v in range(3)]
            for d, n in codes.items():
                seen[d // 3**j % 3] += n * (q[d] if real else 1 - q[d])
            out *= seen[c // 3**j % 3] / sum(seen)
        return out

    for c in codes:
        assert q[c] == pytest.approx(like(c, True) / (like(c, True) + like(c, False)), abs=1e-6)


def test_reliabilities_follow_the_votes():
    yes, no = 2 * 27 + 1 * 9 + 2 * 3 + 2, 1 * 9
    real = privacy.reliabilities({yes: 50.0, no: 50.0})
    assert real[yes] > 0.9 > 0.1 > real[no]


# search and near-duplicates


def test_search_edges(spark):
    rows = [(0, [1.0, 2.0]), (100, [1.0, 2.0]), (1, None), (2, [None, 1.0]), (3, [float("nan"), 1.0]), (4, [1.0]), (5, [1.0, 2.0]), (5, [1.0, 2.0]), (None, [1.0, 1.0])]
    out = impact_index.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("rank", F.lit(1))).toPandas()
    assert [tuple(x) for x in out[out.query_id == 0].sort_values("rank")[["vec_id", "score"]].to_numpy().tolist()] == [(5, 5 * 1024**2), (5, 5 * 1024**2), (100, 5 * 1024**2), (4, 1024**2)]
    assert impact_index.nearest(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


@pytest.mark.parametrize("spread", [1.0, 0.2])
def test_index_is_exact_and_stops_on_proof(spread):
    rng = np.random.default_rng(2)
    scale = 500 * spread ** np.arange(16)  # with a spread below 1 few dimensions decide
    x, q = (rng.normal(size=(3000, 16)) * scale).astype(np.int64), (rng.normal(size=(7, 16)) * scale).astype(np.int64)
    postings = impact_index.Postings(np.arange(3000), x)
    assert (postings.end - postings.start).sum() == x.size  # every component is in one segment
    for v in q:
        s = x @ v
        ids, scores, segments, rescored = postings.search(-1, v, 10)
        want = np.lexsort((np.arange(3000), -s))[:10]
        assert ids.tolist() == want.tolist() and scores.tolist() == s[want].tolist()
        assert rescored < 3000 / 2 and (spread == 1 or segments < len(postings.start))
    assert postings.search(5, x[5], 10)[0].tolist() == [i for i in np.lexsort((np.arange(3000), -(x @ x[5]))).tolist() if i != 5][:10]


def test_search_over_many_blocks(spark, monkeypatch):
    monkeypatch.setattr(impact_index, "SLICE", 2)
    rng = np.random.default_rng(4)
    x = rng.integers(-300, 300, (700, 5))
    vectors = impact_index.usable(spark.createDataFrame([(k, (v / 1024).tolist()) for k, v in enumerate(x)], "vec_id long, embedding array<double>"))
    out = impact_index.search(impact_index.blocks(vectors, 64, "block"), impact_index.blocks(vectors.filter("vec_id < 50"), 7, "q_block"), 3).toPandas()
    for k, g in out.sort_values("rank").groupby("query_id"):
        s = x @ x[k]
        s[k] = -(10**9)
        assert g.vec_id.tolist() == np.lexsort((np.arange(700), -s))[:3].tolist()
    assert out.query_id.nunique() == 50


def test_signatures_estimate_and_are_permutations():
    rng = np.random.default_rng(1)
    for n in (1, 7, 300):
        a = rng.integers(0, 2**63, n).astype(np.uint64)
        s = near_dup.signatures([a], 128)[0]
        assert (s != np.iinfo(np.uint64).max).all()
    a = rng.integers(0, 2**63, 1000).astype(np.uint64)
    x = near_dup.signatures([a[:900], a[100:]], 128)
    assert abs((x[0] == x[1]).mean() - 0.8) < 0.13


def near_copies(rng, n, words, changes):
    base = [f"w{k}" for k in rng.integers(0, 5000, words)]
    out = []
    for _ in range(n):
        t = list(base)
        for k in rng.integers(0, words, changes):
            t[k] = f"z{rng.integers(0, 10**6)}"
        out.append(" ".join(t))
    return out


@pytest.mark.parametrize("members", [2048, 16])
def test_near_duplicates_against_brute_force(spark, monkeypatch, members):
    monkeypatch.setattr(near_dup, "MEMBERS", members)
    monkeypatch.setattr(near_dup, "FOLLOWERS", members)
    rng = np.random.default_rng(7)
    texts = near_copies(rng, 60, 120, 3) + near_copies(rng, 40, 200, 2) + near_copies(rng, 30, 80, 1) + ["one two", "One two", "one", "", None, "one two three"] * 2
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    sets = [set(near_dup.shingles(t, 3).tolist()) for t in texts]
    root = list(range(len(texts)))

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    for a in range(len(texts)):
        for b in range(a):
            i = len(sets[a] & sets[b])
            if i and 100 * i >= 85 * len(sets[a] | sets[b]):
                root[max(find(a), find(b))] = min(find(a), find(b))
    out = {r.doc_id: r for r in near_dup.group(docs, 3, 0.85).collect()}
    assert [out[k].component_id for k in range(len(texts))] == [find(k) for k in range(len(texts))]
    assert [out[k].n_shingles for k in range(len(texts))] == [len(s) for s in sets]


def test_near_duplicate_edges(spark, hard, none, labels):
    out = per_row(spark, hard, none, labels, lambda d, _: near_dup.group(d, 3, 0.85)).toPandas()
    assert (out[out.doc_id == 4].component_id == 3).all() and out[out.doc_id.isna()].kept.all()
    left = near_dup.deduplicated(hard)
    assert left.columns == hard.columns and left.filter("doc_id = 3").count() == 1 and left.filter("doc_id = 4").count() == 0


def test_tables_that_are_copied_to_salts_are_never_broadcast(spark, monkeypatch):
    from graphsplit.llm import common

    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    plans, own = [], near_dup.cut

    def spy(df):
        out = own(df)
        plans.append(plan(df))
        return out

    monkeypatch.setattr(near_dup, "cut", spy)
    links = spark.range(3000).selectExpr("10 * div(id, 2) + id % 2 + 1 as a", "10 * div(id, 2) as b")
    found = {r.node: r.component for r in near_dup.components(links).collect()}
    assert found == {k: k // 10 * 10 for k in range(15000) if k % 10 < 3}
    assert len(plans) > 1 and all("isFinalPlan=true" in p and "BroadcastExchange" not in p for p in plans)
    big, small = spark.range(500).selectExpr("if(id % 5 = 0, null, id % 7) as k", "id"), spark.range(70).groupBy(F.expr("if(id % 7 = 3, null, id % 7)").alias("k")).agg(F.count("*").alias("n"))
    out = common.join_small(big, small, ["k"], common.BROADCAST_ROWS + 1, "left")
    assert {(r.k, r.id, r.n) for r in out.collect()} == {(k, i, None if k == 3 else 10) for i in range(500) for k in [None if i % 5 == 0 else i % 7]}
    assert "BroadcastExchange" not in plan(out)


# pipeline


def test_pipeline_on_hard_rows_and_on_none(spark, hard, none, labels, tmp_path):
    import corpus_pipeline

    labels.write.parquet(f"{tmp_path}/labels.parquet")
    for docs, some in ((hard, True), (none, False)):
        docs.write.mode("overwrite").parquet(f"{tmp_path}/documents.parquet")
        out = corpus_pipeline.run(spark, str(tmp_path)).toPandas()
        assert (len(out) > 0) == some
        assert out.groupby("sequence_id").length.sum().max() <= 2048 if some else True


def test_pipeline_stage_by_stage(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, seen = docs.columns, [docs.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = spark.createDataFrame(stage(spark, docs, sf).toPandas(), docs.schema)
        assert docs.columns == columns, name
        seen.append(docs.count())
    assert seen[1] < seen[0] and seen[2] < seen[1] and seen[3] == seen[2]
    assert docs.filter(F.col("text").rlike(r"[a-z0-9]@[a-z0-9]+\.")).count() == 0
    check_packed(packing.pack(docs).toPandas(), [(r.doc_id, r.text) for r in docs.collect()])


def test_near_copies_that_only_meet_in_families_are_linked(spark):
    from graphsplit.llm import near_dup as nd

    links = spark.createDataFrame([(5, 2), (5, 9), (7, 8)], "a long, b long")
    assert {tuple(r) for r in nd.components(links).collect()} == {(2, 2), (5, 2), (9, 2), (7, 7), (8, 7)}
    # chains: neighbours are near copies, but most of a chain is no near copy of its least document
    rows = []
    for c in range(12):
        words = [f"w{c}x{k}" for k in range(110)]
        for step in range(25):
            rows.append((100 * c + step, " ".join(words)))
            words[4 * step + 2] = f"v{c}y{step}"
    found = nd.group(spark.createDataFrame(rows, "doc_id long, text string"), 3, 0.85)
    assert {r["doc_id"]: r["component_id"] for r in found.collect()} == {d: d // 100 * 100 for d, _ in rows}

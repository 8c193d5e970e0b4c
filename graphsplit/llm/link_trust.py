"""URL filter by link-graph propagation: personalised PageRank of trust, reversed for distrust, over host edges.

Rules of host and path decide where they fit; the longest wins. They also seed the host graph: pages that a rule allows are trusted,
those it blocks are distrusted. Trust flows along links between hosts, distrust against them. Ranks times the number of seeding pages are
pages' worth of trust and distrust; a host is blocked if its distrust is at least `least` of its own pages and above its trust.

Edges of the host graph are links, resolved against their page's url, that leave the host (relative ones stay on it and count for none), and
domains: every page of a subdomain counts as one link to the domain above it and one back, up to the last two labels, so that a host without a
link of its own hears from its relatives. Hosts without pages pass on what they get. Edges are counted before they are joined; the edges of a
host with many neighbours are dealt to salts, pages meet the table of hosts by a join that is broadcast up to a bound of rows and salted beyond.

Defined results: a null url, or one without `://`, has an empty host and path, fits no rule and is allowed unless that (empty) host itself is
distrusted; null html has no links. Where distrust equals trust, the page is allowed. Very long html is searched whole. Repeated rows count as
often as they occur and get a row each. Empty input gives an empty result. Other columns don't matter, whatever their names.
"""

from __future__ import annotations

import math
from string import ascii_lowercase, ascii_uppercase

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphsplit.llm.common import BROADCAST_ROWS, cut, join_small

#: Fixed rules of the query: (verdict, host and path).
RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))
#: Pages' worth of trust or distrust that may be unsettled, over all hosts.
SETTLED = 1e-4
#: Rounds between cuts of the lineage and checks of what is still to come.
ROUNDS = 16
SALTS = 16
LINK = r"""(?i)\bhref\s*=\s*["']?((?:[a-z][a-z0-9+.-]*:)?//[^"'\s>]*)"""


def rest(url: Column) -> Column:
    at = F.coalesce(F.instr(url, "://"), F.lit(0))
    return F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))


def host(url: Column) -> Column:
    return F.translate(F.regexp_extract(rest(url), "^[^/?#]*", 0), ascii_uppercase, ascii_lowercase)


def path(url: Column) -> Column:
    return F.regexp_extract(rest(url), "^[^/?#]*([^?#]*)", 1)


def fitting(host_: Column, path_: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest rule that fits, as text, and its verdict; null if none does."""
    rule = verdict = None
    for kind, text in sorted(rules, key=lambda r: -len(r[1])):
        at, _, tail = text.partition("/")
        fits = ((host_ == at) | host_.endswith("." + at)) & path_.startswith("/" + tail)
        rule = F.when(fits, text) if rule is None else rule.when(fits, text)
        verdict = F.when(fits, kind) if verdict is None else verdict.when(fits, kind)
    return (rule, verdict) if rule is not None else (F.lit(None).cast("string"), F.lit(None).cast("string"))


def domain_edges(hosts: DataFrame) -> DataFrame:
    """src, dst, links: hosts and the domains above them, both ways, weighted by the pages below. hosts: host, pages.

    Names of two labels have nothing above them; numbers aren't names.
    """
    labels = F.split("host", r"\.")
    up = F.when(~F.col("host").rlike(r"^[0-9.:\[\]]+$"), F.transform(F.sequence(F.lit(0), F.size(labels) - 2), lambda k: F.array_join(F.slice(labels, k + 1, F.size(labels)), ".")))
    chain = hosts.filter(F.size(labels) > 2).select("pages", up.alias("up"))
    steps = chain.select("pages", F.explode(F.arrays_zip(F.slice("up", F.lit(1), F.size("up") - 1).alias("a"), F.slice("up", F.lit(2), F.size("up") - 1).alias("b"))).alias("s"))
    both = steps.select("pages", F.explode(F.array(F.struct(F.col("s.a").alias("src"), F.col("s.b").alias("dst")), F.struct(F.col("s.b").alias("src"), F.col("s.a").alias("dst")))).alias("s"))
    return both.select("s.src", "s.dst", "pages").filter("src <> '' and dst <> ''").groupBy("src", "dst").agg(F.sum("pages").alias("links"))


def link_edges(pages: DataFrame) -> DataFrame:
    """src, dst, links: how many links lead from pages of one host to another. Links without a host stay on their page's."""
    links = F.regexp_extract_all(F.coalesce(F.col("html"), F.lit("")), F.lit(LINK), F.lit(1))
    to = pages.select(host(F.col("url")).alias("src"), F.explode(links).alias("_to"))
    to = to.withColumn("dst", host(F.concat(F.lit("x://"), F.regexp_replace(F.regexp_extract("_to", "//.*", 0), "^//", ""))))
    return to.filter((F.col("src") != "") & (F.col("dst") != "") & (F.col("src") != F.col("dst"))).groupBy("src", "dst").agg(F.count("*").alias("links"))


def host_edges(pages: DataFrame) -> DataFrame:
    """src, dst, links of the host graph."""
    hosts = pages.groupBy(host(F.col("url")).alias("host")).agg(F.count("*").alias("pages"))
    return link_edges(pages).union(domain_edges(hosts)).groupBy("src", "dst").agg(F.sum("links").alias("links"))


def page_rank(edges: DataFrame, seeds: DataFrame, damping: float = 0.85, near: float = 1e-6) -> DataFrame:
    """kind, host, rank: personalised PageRanks of several kinds at once, the ranks of a kind together within `near` of the limit.

    edges: kind, src, dst, links; seeds: kind, host, mass (sums to 1 for each kind).

    Hosts without links out lead back to the seeds. Ranks are the sum of what arrives after 0, 1, 2, ... links, scaled to 1; scaling is what leads
    the rest back to the seeds. At most `damping` of what arrives goes on, which tells how much is still to come and bounds the rounds. Several
    rounds make one plan; it ends in one cut and one action.
    """
    keys = ["kind", "src"]
    seeds = cut(seeds.select("kind", "host", F.col("mass").alias("rank")))
    out = edges.groupBy(*keys).agg(F.sum("links").alias("_all"))
    steps = edges.join(out, keys).select(*keys, "dst", (F.col("links") / F.col("_all") * damping).alias("p"), F.lit(0.0).alias("keep"))
    # every host also keeps its sum, so that a round is one join and one aggregate
    hosts = edges.select("kind", "src").union(edges.select("kind", "dst")).union(seeds.select("kind", "host")).distinct()
    steps = steps.union(hosts.select("kind", "src", F.col("src").alias("dst"), F.lit(0.0).alias("p"), F.lit(1.0).alias("keep")))
    steps = cut(steps.withColumn("salt", F.pmod(F.xxhash64("dst"), F.lit(SALTS)).cast("int")))
    few = steps.count() <= BROADCAST_ROWS
    steps = F.broadcast(steps.drop("salt")) if few else steps
    every = F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))
    here = seeds.withColumn("sum", F.col("rank"))
    for _ in range(0, math.ceil(math.log(near * (1 - damping) / 2) / math.log(damping)), ROUNDS):
        for _ in range(ROUNDS):
            # with few edges, here in one partition, rounds need no exchange
            came = (here.coalesce(1) if few else here).withColumnRenamed("host", "src")
            came = came.join(steps, keys) if few else came.withColumn("salt", every).join(steps, [*keys, "salt"])
            rank = F.sum(F.col("rank") * F.col("p"))
            here = came.groupBy("kind", F.col("dst").alias("host")).agg(rank.alias("rank"), (F.sum(F.col("sum") * F.col("keep")) + rank).alias("sum"))
        here = cut(here)
        left = here.groupBy("kind").agg(F.sum("rank").alias("left")).agg(F.coalesce(F.max("left"), F.lit(0.0))).first()[0]
        if 2 * left * damping / (1 - damping) < near:
            break
    whole = here.groupBy("kind").agg(F.sum("sum").alias("_whole"))  # a row for each kind
    return here.join(F.broadcast(whole), "kind").select("kind", "host", (F.col("sum") / F.col("_whole")).alias("rank"))


def judge(pages: DataFrame, rules=RULES, least: float = 0.5) -> DataFrame:
    """page_id, host, path, rule, verdict, trust, distrust of every row of pages."""
    urls = pages.select("page_id", host(F.col("url")).alias("host"), path(F.col("url")).alias("path"))
    rule, verdict = fitting(F.col("host"), F.col("path"), rules)
    judged = urls.withColumn("rule", rule).withColumn("_verdict", verdict)
    hosts = cut(judged.groupBy("host").agg(F.count("*").alias("pages"), F.count(F.when(F.col("_verdict") == "allow", 1)).alias("allowed"), F.count(F.when(F.col("_verdict") == "block", 1)).alias("blocked")))
    allowed, blocked, n = hosts.agg(F.coalesce(F.sum("allowed"), F.lit(0)), F.coalesce(F.sum("blocked"), F.lit(0)), F.count("*")).first()
    edges = cut(host_edges(pages).withColumn("kind", F.lit("trust")))
    both = edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "links", F.lit("distrust").alias("kind")))
    seeds = lambda c, total, kind: hosts.filter(F.col(c) > 0).select(F.lit(kind).alias("kind"), "host", (F.col(c) / F.lit(float(max(total, 1)))).alias("mass"))
    ranks = page_rank(both, seeds("allowed", allowed, "trust").union(seeds("blocked", blocked, "distrust")), near=SETTLED / max(allowed, blocked, 1))
    of = lambda kind, total: F.coalesce(F.max(F.when(F.col("kind") == kind, F.col("rank") * float(total))), F.lit(0.0)).alias(kind)
    shares = hosts.join(ranks.groupBy("host").agg(of("trust", allowed), of("distrust", blocked)), "host", "left")
    for c in ("trust", "distrust"):
        shares = shares.withColumn(c, F.coalesce(F.col(c), F.lit(0.0)) / F.col("pages"))
    out = join_small(judged, cut(shares.select("host", "trust", "distrust")), ["host"], n)
    bad = (F.col("distrust") >= least) & (F.col("distrust") > F.col("trust"))
    return out.select("page_id", "host", "path", "rule", F.coalesce("_verdict", F.when(bad, "block").otherwise("allow")).alias("verdict"), "trust", "distrust")

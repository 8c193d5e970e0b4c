"""MinHash near-duplicates: SuperMinHash signatures, banding, verification on full sets, union-find grouping by stars.

A text's set holds hashes of its word shingles. Texts with equal sets are one class, whose smallest doc_id stands for it; only classes are
compared. A signature gives every element a random order of the registers, rank by rank: in each round an element offers its value to one
register, and a text is done as soon as all its registers are filled, which for long texts takes a round or two. Bands of registers that
agree make candidates. They are verified on the full sets:

1. Every class against the smallest of the leaders (least ids) of its buckets. Links that hold make first groups.
2. In buckets that hold several groups, members of different groups whose signatures agree nearly as much as the limit asks are joined to
   families. A task only puts out a spanning forest.
3. In families of several groups, the full sets of those outside the largest group are compared with all others: shared shingles are
   counted by products of incidence matrices. Again a task only puts out the links that join groups.

So what is put out grows with the members, not with their pairs, and no candidate stays unverified. Large buckets and families are cut
into blocks that meet in tasks of their own. Groups are connected components, by large and small stars on the links; nothing but counts
reaches the driver, and tables of at most BROADCAST_ROWS rows that it broadcasts.

Registers and bands follow from the limit so that a pair at the limit is missed with a chance of 1e-6 at most.

Defined results: null texts and texts without words have empty sets and are linked with nothing. Rows that share a doc_id are one
document, linked by any of its texts. Rows without doc_id get no component and are kept. Very long texts are treated whole: a set is held by one
task at a time, with one leader's. Ties don't arise, as the least doc_id stands for a group. Other columns don't matter, whatever their names,
and are kept by `deduplicated`. Empty input gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsplit.llm.common import BROADCAST_ROWS, cut, join_small, map_texts

REGISTERS = 128
#: Members of one bucket or family that a task compares.
MEMBERS = 2048
#: Members, and shingles of members, that are compared with one copy of their leader's set.
FOLLOWERS = 128
FOLLOWED = 100_000
#: Salts that the neighbours of one node are dealt to.
SALTS = 16
#: Shingles of the sets that a task of step 3 holds of each block.
SHINGLES = 2_000_000
U = np.uint64


def layout(limit: float, registers: int = REGISTERS) -> tuple[int, int]:
    """Rows and bands: as many rows as miss a pair at the limit with a chance of 1e-6 at most."""
    rows = max(r for r in range(1, registers + 1) if r == 1 or (1 - limit**r) ** (registers // r) <= 1e-6)
    return rows, registers // rows


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that scatters them."""
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


def shingles(text: str | None, width: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the shingles of a text whose A-Z are lower-cased."""
    words = (text or "").encode().lower().split()
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))
    if not len(h):
        return h
    n = len(h) - width + 1
    if n < 1:
        h, n = np.concatenate([h, np.full(width - len(h), len(h), np.uint64)]), 1
    s = np.zeros(n, np.uint64)
    for k in range(width):
        s = mixed(s * U(0x9E3779B97F4A7C15) + h[k : k + n] + U(1))
    return np.unique(s)


def signatures(sets: list[np.ndarray], m: int) -> np.ndarray:
    """SuperMinHash registers, a row for each non-empty set: the rank's number above 56 random bits, the least offered."""
    if not sets:
        return np.zeros((0, m), np.uint64)
    sizes = np.asarray([len(s) for s in sets])
    out = np.full(len(sets) * m, np.iinfo(np.uint64).max, np.uint64)
    element, of = np.concatenate(sets), np.repeat(np.arange(len(sets)), sizes)
    order = None  # of the registers, by element; made when a second round is needed
    for j in range(m):
        random = mixed(element + U((j + 1) * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF))
        pick = j + ((random >> U(40)) * U(m - j) >> U(24)).astype(np.int64)
        if order is None:
            at = pick
        else:
            rows = np.arange(len(element))
            at = order[rows, pick].astype(np.int64)
            order[rows, pick] = order[:, j]
        np.minimum.at(out, of * m + at, (U(j) << U(56)) | (mixed(random) >> U(8)))
        full = (out.reshape(-1, m) >> U(56) <= U(j)).all(axis=1)
        if full.all():
            break
        go = ~full[of]
        if order is None:
            order = np.tile(np.arange(m, dtype=np.uint8), (int(go.sum()), 1))
            order[np.arange(len(order)), pick[go]] = 0
        else:
            order = order[go]
        element, of = element[go], of[go]
    return out.reshape(-1, m)


def band_keys(registers: np.ndarray, rows: int, bands: int) -> np.ndarray:
    key = np.tile(np.arange(bands, dtype=np.uint64), (len(registers), 1))
    for k in range(rows):
        key = mixed(key * U(0x9E3779B97F4A7C15) + registers[:, k : k + rows * bands : rows])
    return key.view(np.int64)


def sketch(docs: DataFrame, width: int, limit: float) -> DataFrame:
    """doc_id, n_shingles, same (digest of the set), bands, registers (32 bits of each) of every row of docs."""
    rows, bands = layout(limit)

    def start():
        def work(texts: list) -> list[list]:
            sets = [shingles(x, width) for x in texts]
            some = [k for k, s in enumerate(sets) if len(s)]
            registers = signatures([sets[k] for k in some], REGISTERS)
            keys = band_keys(registers, rows, bands)
            short = (registers ^ (registers >> U(32))).astype(np.uint32)
            same, band, kept = [None] * len(sets), [None] * len(sets), [None] * len(sets)
            for i, k in enumerate(some):
                same[k], band[k], kept[k] = xxhash.xxh3_128_digest(sets[k].tobytes()), keys[i], short[i].tobytes()
            return [[len(s) for s in sets], same, band, kept]

        return work

    added = [("n_shingles", "long", pa.int64()), ("same", "binary", pa.binary()), ("bands", "array<long>", pa.list_(pa.int64())), ("registers", "binary", pa.binary())]
    return map_texts(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), ["doc_id"], start, added)


def components(links: DataFrame) -> DataFrame:
    """node, component (least node reachable) of all nodes of a table a, b of links, by alternating large and small stars."""
    least = lambda e: e.groupBy("u").agg(F.min("v").alias("m"))
    # the centre of a large star is one key: its neighbours are dealt to salts
    salted = lambda e: e.withColumn("salt", F.pmod(F.xxhash64("v"), F.lit(SALTS)))
    every = lambda m: m.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    # merged: Spark sizes the table of minima before it is copied to all salts, and would broadcast SALTS times its limit through the driver
    meet = lambda e, m: salted(e).join(every(m).hint("merge"), ["u", "salt"]).drop("salt")
    both = lambda e: e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
    edges = cut(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u <> v").distinct())
    before = None
    while True:
        e = both(edges)
        star = meet(e, least(e).withColumn("m", F.least("m", "u"))).filter("v > u and v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        edges = star.distinct()  # each larger neighbour to the least one
        m = least(edges)
        down = meet(edges, m).filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        edges = cut(m.select("u", F.col("m").alias("v")).union(down).filter("u <> v").distinct())
        state = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if state == before:
            break
        before = state
    # the least node of a component is the centre of its star, and has no edge of its own
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).union(edges.select("v", "v").distinct())


def verified(docs: DataFrame, pairs: DataFrame, width: int, percent: int) -> DataFrame:
    """The rows of pairs (a, b, n_shingles) whose full sets share at least `percent` of their union. n_shingles: of a.

    Each a goes to its b; a b of many is copied for every FOLLOWERS of them, or FOLLOWED shingles. Sorted by group, with the leading b first,
    sets are compared as they stream through a task, which holds one b at a time.
    """
    pairs = cut(pairs)
    n = pairs.count()
    share = pairs.groupBy("b").agg(F.greatest(F.ceil(F.count("*") / FOLLOWERS), F.ceil(F.sum("n_shingles") / FOLLOWED)).cast("int").alias("parts"))
    members = pairs.join(share, "b").select(F.col("a").alias("id"), F.col("b").alias("key"), F.pmod(F.xxhash64("a"), F.col("parts")).cast("int").alias("part"), F.lit(1).alias("role"))
    leaders = share.select(F.col("b").alias("id"), F.col("b").alias("key"), F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(0).alias("role"))
    wanted = members.union(leaders)
    wanted = F.broadcast(wanted) if 2 * n <= BROADCAST_ROWS else wanted

    def start():
        return lambda texts: [[shingles(x, width).tobytes() for x in texts]]

    texts = docs.select(F.col("doc_id").cast("long").alias("id"), "text").join(wanted, "id")
    sets = map_texts(texts, ["id", "key", "part", "role"], start, [("set", "binary", pa.binary())])

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group, lead = None, []
        for batch in batches:
            a, b = [], []
            for i, key, part, role, raw in zip(*[c.to_pylist() for c in batch.columns[:4]], batch.column(4), strict=True):
                if (key, part) != group:
                    group, lead = (key, part), []
                s = np.frombuffer(raw.as_py(), np.uint64)
                if role == 0:
                    lead.append(s)
                    continue
                for t in lead:
                    if not len(s) or not len(t) or 100 * min(len(s), len(t)) < percent * max(len(s), len(t)):
                        continue
                    at = np.searchsorted(t, s)
                    both = int((t[np.minimum(at, len(t) - 1)] == s).sum())
                    if 100 * both >= percent * (len(s) + len(t) - both):
                        a.append(i)
                        b.append(key)
                        break
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return cut(sets.repartition("key", "part").sortWithinPartitions("key", "part", "role").mapInArrow(compare, "a long, b long"))


class Forest:
    """Union-find over group numbers, with the root of every row at hand."""

    def __init__(self, groups: np.ndarray):
        self.roots = np.unique(groups, return_inverse=True)[1]

    def join(self, i: int, j: int) -> bool:
        a, b = self.roots[i], self.roots[j]
        if a == b:
            return False
        self.roots[self.roots == max(a, b)] = min(a, b)
        return True


def families(members: DataFrame, limit: float, used: int) -> DataFrame:
    """a, b: a forest of the groups whose members share a bucket and agree about as much as the limit asks.

    members: bucket, id, group, registers, of the buckets with several groups. Agreement is a mean over `used` registers; five standard
    deviations below the limit are let through.
    """
    enough = (limit - 5 * (limit * (1 - limit) / used) ** 0.5) * used
    sizes = members.groupBy("bucket").agg(F.count("*").alias("n")).select("bucket", F.ceil(F.col("n") / MEMBERS).cast("int").alias("blocks"))
    sizes = cut(sizes)
    placed = join_small(members, sizes, ["bucket"], sizes.count()).withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    placed = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    placed = placed.select("bucket", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "group", "registers")

    def compare(table: pa.Table) -> pa.Table:
        groups = np.asarray(table.column("group"))
        x = np.frombuffer(b"".join(table.column("registers").to_pylist()), np.uint32).reshape(len(groups), -1)[:, :used]
        forest, a, b = Forest(groups), [], []
        sizes = np.bincount(forest.roots)
        for k in np.flatnonzero(forest.roots != sizes.argmax()).tolist():
            other = np.flatnonzero(forest.roots != forest.roots[k])
            for h in other[(x[other] == x[k]).sum(axis=1) >= enough].tolist():
                if forest.join(k, h):
                    a.append(groups[k])
                    b.append(groups[h])
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    # without this the join's distribution by bucket would do, and all blocks of a hot bucket stay in one task
    return placed.repartition("bucket", "i", "j").groupBy("bucket", "i", "j").applyInArrow(compare, "a long, b long")


def shared_counts(left: list[np.ndarray], right: list[np.ndarray], width: int = 4096) -> np.ndarray:
    """How many elements each set of the left has in common with each of the right, by products of incidence matrices."""
    values = np.concatenate([*left, *right])
    of = np.repeat(np.arange(len(left) + len(right)), [len(s) for s in (*left, *right)])
    _, at, times = np.unique(values, return_inverse=True, return_counts=True)
    number = np.cumsum(times > 1) - 1
    keep = times[at] > 1
    column, of = number[at[keep]], of[keep]
    order = np.argsort(column, kind="stable")
    column, of = column[order], of[order]
    out = np.zeros((len(left), len(right)), np.float32)
    for c in range(0, int(column[-1]) + 1 if len(column) else 0, width):
        part = slice(*np.searchsorted(column, [c, c + width]))
        x = np.zeros((len(left) + len(right), width), np.float32)
        x[of[part], column[part] - c] = 1
        out += x[: len(left)] @ x[len(left) :].T
    return out


def links_in_families(docs: DataFrame, members: DataFrame, width: int, percent: int) -> DataFrame:
    """a, b: links that join the groups of a family. members: family, id, group, n_shingles, of the families with several groups.

    The largest group's members don't meet each other. Blocks are bounded by members and by shingles.
    """
    groups = members.groupBy("family", "group").agg(F.count("*").alias("n"), F.sum("n_shingles").alias("words"))
    parts = F.greatest(F.ceil(F.col("n") / MEMBERS), F.ceil(F.col("words") / SHINGLES)).cast("int")
    main = groups.groupBy("family").agg(F.max_by("group", F.struct("n", "group")).alias("main"), F.max(F.struct("n", "group", "words")).alias("m"), F.sum("n").alias("all_n"), F.sum("words").alias("all_words"))
    main = main.select("family", "main", F.col("m.n").alias("n"), F.col("m.words").alias("words"), "all_n", "all_words").withColumn("main_parts", parts)
    main = main.withColumn("n", F.col("all_n") - F.col("n")).withColumn("words", F.col("all_words") - F.col("words")).withColumn("parts", F.greatest(F.lit(1), parts)).select("family", "main", "main_parts", "parts")
    rows = members.join(main, "family").withColumn("is_main", F.col("group") == F.col("main"))
    block = lambda n: F.pmod(F.xxhash64("id"), F.col(n)).cast("int")
    every = lambda n: F.sequence(F.lit(0), F.col(n) - 1)
    own = F.when(F.col("is_main"), block("main_parts")).otherwise(block("parts"))
    rows = rows.withColumn("block", own)
    # tasks (i, j, 0): block i of the others against block j of the main group; (i, j, 1) with i <= j: two blocks of the others
    to_main = F.transform(every("main_parts"), lambda j: F.struct(F.col("block").alias("i"), j.alias("j"), F.lit(0).alias("kind")))
    to_others = F.transform(every("parts"), lambda j: F.struct(F.least("block", j).alias("i"), F.greatest("block", j).alias("j"), F.lit(1).alias("kind")))
    from_main = F.transform(every("parts"), lambda i: F.struct(i.alias("i"), F.col("block").alias("j"), F.lit(0).alias("kind")))
    tasks = rows.withColumn("t", F.explode(F.when(F.col("is_main"), from_main).otherwise(F.concat(to_main, to_others))))
    wanted = cut(tasks.select("id", "family", "group", "block", "is_main", "t.i", "t.j", "t.kind"))
    wanted = F.broadcast(wanted) if wanted.count() <= BROADCAST_ROWS else wanted

    def start():
        return lambda texts: [[shingles(x, width).tobytes() for x in texts]]

    texts = docs.select(F.col("doc_id").cast("long").alias("id"), "text").join(wanted, "id")
    sets = map_texts(texts, ["id", "family", "group", "block", "is_main", "i", "j", "kind"], start, [("set", "binary", pa.binary())])

    def compare(table: pa.Table) -> pa.Table:
        ids, groups, blocks, main = (np.asarray(table.column(c)) for c in ("id", "group", "block", "is_main"))
        i, j, kind = (table.column(c)[0].as_py() for c in ("i", "j", "kind"))
        left = np.flatnonzero(~main & (blocks == i)) if kind == 0 else np.flatnonzero(blocks == i)
        right = np.flatnonzero(main) if kind == 0 else np.flatnonzero(blocks == j)
        raw = [np.frombuffer(x.as_py(), np.uint64) for x in table.column("set")]
        forest, a, b = Forest(groups), [], []
        if len(left) and len(right) and (groups != groups[0]).any():
            for k in range(0, len(left), 512):
                some = left[k : k + 512]
                both = shared_counts([raw[x] for x in some], [raw[x] for x in right])
                size = lambda rows: np.asarray([len(raw[x]) for x in rows], np.float32)
                near = 100 * both >= percent * (size(some)[:, None] + size(right)[None, :] - both)
                near &= (both > 0) & (groups[some][:, None] != groups[right][None, :])
                for p, q in np.argwhere(near).tolist():
                    if forest.join(some[p], right[q]):
                        a.append(ids[some[p]])
                        b.append(ids[right[q]])
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return sets.repartition("family", "i", "j", "kind").groupBy("family", "i", "j", "kind").applyInArrow(compare, "a long, b long")


def group(docs: DataFrame, width: int = 5, limit: float = 0.8) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every row of docs."""
    percent = round(100 * limit)
    rows, bands = layout(limit)
    made = cut(sketch(docs, width, limit))
    named = made.filter(F.col("same").isNotNull() & F.col("doc_id").isNotNull())
    # rows of equal sets are one class
    classes = cut(named.groupBy("same").agg(F.min("doc_id").alias("id")))
    copies = named.select("same", "doc_id").join(classes, "same").filter("doc_id <> id").select(F.col("doc_id").alias("a"), F.col("id").alias("b"))
    own = named.select(F.col("doc_id").alias("id"), "same", "n_shingles", "bands").join(classes, ["id", "same"])
    bucketed = own.select("id", "n_shingles", F.explode("bands").alias("bucket"))
    heads = cut(bucketed.groupBy("bucket").agg(F.min("id").alias("head"), F.count("*").alias("n")).filter("n > 1").select("bucket", "head"))
    shared = cut(join_small(bucketed, heads, ["bucket"], heads.count()).select("bucket", "id", "n_shingles", "head"))
    first = shared.groupBy("id").agg(F.min("head").alias("head"), F.max("n_shingles").alias("n_shingles")).filter("id <> head")
    links = verified(docs, first.select(F.col("id").alias("a"), F.col("head").alias("b"), "n_shingles"), width, percent)
    found = cut(components(links))
    spread = shared.select("bucket", "id").join(found.select(F.col("node").alias("id"), F.col("component").alias("_g")), "id", "left").select("bucket", "id", F.coalesce("_g", "id").alias("group"))
    several = cut(spread.groupBy("bucket").agg(F.min("group").alias("_a"), F.max("group").alias("_b")).filter("_a <> _b").select("bucket"))
    left = cut(join_small(spread, several, ["bucket"], several.count()))
    detail = made.join(left.select(F.col("id").alias("doc_id")).distinct(), "doc_id", "left_semi").groupBy(F.col("doc_id").alias("id")).agg(F.min("registers").alias("registers"))
    joined = cut(families(left.join(detail, "id").select("bucket", "id", "group", "registers"), limit, rows * bands).distinct())
    kin = components(joined).select(F.col("node").alias("group"), F.col("component").alias("family"))
    people = classes.select("id").join(found.select(F.col("node").alias("id"), F.col("component").alias("_g")), "id", "left").select("id", F.coalesce("_g", "id").alias("group")).distinct()
    words = made.groupBy(F.col("doc_id").alias("id")).agg(F.max("n_shingles").alias("n_shingles"))
    relatives = cut(people.join(kin, "group").join(words, "id").select("family", "id", "group", "n_shingles"))
    links = links.union(cut(links_in_families(docs, relatives, width, percent)))
    found = components(links.union(copies))
    out = made.select("doc_id", "n_shingles").join(found.select(F.col("node").alias("doc_id"), "component"), "doc_id", "left")
    out = out.select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def deduplicated(docs: DataFrame, width: int = 5, limit: float = 0.8) -> DataFrame:
    """The rows of docs without those that another document of their group stands for; of rows that share an id one stays."""
    found = cut(group(docs, width, limit))
    gone = found.filter(~F.col("kept")).select("doc_id").distinct()
    left = docs.join(F.broadcast(gone) if gone.count() <= BROADCAST_ROWS else gone, "doc_id", "left_anti")
    repeated = found.filter("kept and doc_id is not null").groupBy("doc_id").count().filter("count > 1").limit(1).count()
    if not repeated:
        return left
    return left.filter("doc_id is not null").dropDuplicates(["doc_id"]).unionByName(left.filter("doc_id is null"))


SQL = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, CASE WHEN len(ws) < 3 THEN array_to_string(ws, ' ') ELSE array_to_string(ws[i:i + 2], ' ') END AS sh
  FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 1, 2))) AS i FROM w WHERE len(ws) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.sh = b.sh AND a.doc_id < b.doc_id GROUP BY ALL),
e AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 85 * (x.n + y.n - c)),
k AS (WITH RECURSIVE r(v, c) AS (SELECT doc_id, doc_id FROM documents UNION SELECT u.t, r.c FROM r JOIN (SELECT a AS f, b AS t FROM e UNION ALL SELECT b, a FROM e) u ON u.f = r.v WHERE r.c < u.t) SELECT v, min(c) AS component_id FROM r GROUP BY v)
SELECT w.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, component_id, w.doc_id = component_id AS kept FROM w LEFT JOIN n USING (doc_id) JOIN k ON k.v = w.doc_id
"""

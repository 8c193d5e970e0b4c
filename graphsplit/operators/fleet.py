"""Label propagation by processing elements (PEs) that keep their share of the graph and exchange messages.

A PE owns a range of vertices. It holds their labels, copies of the labels of foreign neighbours (ghosts), and the weights of the labels it has
met. A batch takes two steps, each of them a shuffle of messages by PE:

1. Each PE learns the totals that it was sent, takes back its share of moves into overweight clusters (least gain first, in proportion to its
   part of the cluster), and scans some of its vertices one by one, with fresh labels of its own and ghosts as last heard of. It sends weight
   changes to the owners of the labels (the PE of the vertex that names a cluster; blocks are dealt round robin), and new labels to the PEs that
   hold a ghost of a moved vertex, and to nobody else.
2. Owners add up the changes and reply with the totals; labels of ghosts are updated.

What travels is a row for each message, and the PE's own state to itself; the adjacency of a batch joins it from a table that is pruned by
batch. A sweep is one Spark job with one cut of the lineage. A task takes one PE after the other and holds one PE's share at a time. How many
tasks share the PEs follows from the number of arcs and changes no result; where there is too little work for two tasks, one task passes the
same messages between its PEs without shuffles. The driver sees a number for each sweep.

Graphs may hold several copies (see `Graph.copies`): every copy has its own PEs, and labels never cross copies.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphsplit.functions.columns import coin, num_batches
from graphsplit.model import Graph, discard, snapshot, written
from graphsplit.operators.order import degree_buckets

STATE, ADJACENCY, NOTE, DELTA, TOTAL, COUNT = range(6)
ROW = "to int, kind int, frm int, body binary, n long"
NAMES = ["to", "kind", "frm", "body", "n"]
CHUNK = 64
#: A vertex of so many arcs or more adds up its connections on arrays.
MANY = 128
#: Arcs that a task packs at a time before they are shuffled.
PIECE = 1_000_000
#: Kinds of integers, and the largest of each.
WIDTHS = [(k, int(np.iinfo(k).max)) for k in (np.int8, np.int16, np.int32, np.int64)]
#: Arcs that make a task of their own worth it, and how many tasks make their shuffles worth it.
ARCS_A_TASK = 100_000
TASKS = 8


def narrow(a) -> np.ndarray:
    """The same integers in as few bytes as hold them all."""
    a = np.asarray(a, np.int64)
    if not len(a):
        return a.astype(np.int8)
    low, high = int(a.min()), int(a.max())
    return a.astype(next(kind for kind, most in WIDTHS if -most - 1 <= low and high <= most))


def shorter(a: np.ndarray) -> tuple[np.ndarray, int, int]:
    """An integer array as few bytes an element, the sign of its coding and what it begins with: as it is (1), or as steps from one to the next (-1),
    which are short where ids are in order."""
    plain = narrow(a)
    if plain.itemsize > 1 and int(a.max()) - int(a.min()) < 1 << 62:
        steps = narrow(np.diff(a))
        if steps.itemsize < plain.itemsize:
            return steps, -1, int(a[0])
    return plain, 1, 0


def pack(*arrays) -> bytes:
    """Integer arrays as bytes: their number, their lengths, the bytes of an element of each (negative for steps), their first elements if they are
    steps, their elements."""
    arrays = [np.asarray(a, np.int64) for a in arrays]
    short = [shorter(a) for a in arrays]
    head = [len(arrays), *map(len, arrays), *[sign * a.itemsize for a, sign, _ in short], *[first for _, _, first in short]]
    return b"".join([np.asarray(head, np.int64).tobytes(), *[a.tobytes() for a, _, _ in short]])


def unpack(body: bytes) -> list[np.ndarray]:
    """The arrays, as copies of their own."""
    k = int(np.frombuffer(body, np.int64, 1)[0])
    head = np.frombuffer(body, np.int64, 3 * k + 1)[1:].tolist()
    out, at = [], 8 * (3 * k + 1)
    for n, size, first in zip(head[:k], head[k : 2 * k], head[2 * k :], strict=True):
        if size > 0:
            out.append(np.frombuffer(body, f"i{size}", n, at).astype(np.int64))
            at += n * size
        else:
            a = np.empty(n, np.int64)
            a[0], a[1:] = first, np.frombuffer(body, f"i{-size}", n - 1, at)
            out.append(a.cumsum())
            at += (n - 1) * -size
    return out


def tasks_for(pes: int, arcs: int) -> int:
    """How many tasks share the PEs: a few of them are slower than one alone, which passes messages without shuffles."""
    tasks = min(pes, arcs // ARCS_A_TASK)
    return tasks if arcs >= TASKS * ARCS_A_TASK else 1


@dataclass
class Rules:
    """What all PEs know: first vertex of each PE (and the end), PEs of a copy, labels of a copy if they are blocks, and limits.

    limit: one number for each copy (clusters) or each label (blocks). mode: 'revert' takes back what is overweight, 'local' only looks at a
    PE's own part of a label, 'overshoot' leaves it at the check before a move, 'none' has no limit.
    """

    starts: np.ndarray
    pes: int
    blocks: int
    limit: list[float]
    mode: str
    lighter: bool
    seed: int

    def owner(self, labels: np.ndarray) -> np.ndarray:
        if not self.blocks:
            return np.searchsorted(self.starts, labels, side="right") - 1
        return labels // self.blocks * self.pes + labels % self.blocks % self.pes

    def place(self, labels: np.ndarray, pe: int) -> np.ndarray:
        """Where the owner keeps a label's weight."""
        return labels % self.blocks // self.pes if self.blocks else labels - self.starts[pe]

    def limit_of(self, label: int, pe: int) -> float:
        return math.inf if self.mode == "none" else self.limit[label] if self.blocks else self.limit[pe // self.pes]


def connected(labels: np.ndarray, w: np.ndarray, own: int, count: int) -> tuple[int, dict[int, int]]:
    """What connects a vertex of many arcs with its own label, and with the others that are connected at least as well, in order of first occurrence.

    labels: of its neighbours, below `count`.
    """
    if count <= 16 * len(labels):
        names, sums = None, np.bincount(labels, weights=w, minlength=count)
        here = int(sums[own])
    else:
        names, inverse = np.unique(labels, return_inverse=True)
        sums = np.bincount(inverse, weights=w)
        here = int(sums[names == own].sum())
    good = np.flatnonzero(sums >= max(here, 1))
    if names is not None:
        good, sums = names[good], dict(zip(names[good].tolist(), sums[good].tolist(), strict=True))
    good = good[good != own]
    if len(good) > 1:
        first = np.full(count, -1, np.int64) if names is None else None
        if first is not None:
            first[labels[::-1]] = np.arange(len(labels))[::-1]
            good = good[np.argsort(first[good])]
        else:
            kinds, first = np.unique(labels, return_index=True)
            good = good[np.argsort(first[np.searchsorted(kinds, good)])]
    return here, {t: int(sums[t]) for t in good.tolist()}


class Pe:
    """One PE's state: own labels and weights, ghosts, who holds ghosts of own vertices, known labels (in order) and their weights, owned weights,
    open changes, the batch's moves.
    """

    def __init__(self, number: int, parts: list[np.ndarray]):
        self.number = number
        self.label, self.c, self.ghost, self.ghost_label, self.sub_v, self.sub_pe, self.known, self.weight, self.owned, open_, change, self.moved, self.old, self.gain, self.count = parts
        self.change = dict(zip(open_.tolist(), change.tolist(), strict=True))

    def parts(self) -> list[np.ndarray]:
        ints = lambda d: (np.fromiter(d.keys(), np.int64, len(d)), np.fromiter(d.values(), np.int64, len(d)))
        return [self.label, self.c, self.ghost, self.ghost_label, self.sub_v, self.sub_pe, self.known, self.weight, self.owned, *ints(self.change), self.moved, self.old, self.gain, self.count]

    def places(self, labels: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where labels are among the known ones, and whether they are."""
        at = np.searchsorted(self.known, labels)
        return at, np.append(self.known, -1)[at] == labels

    def weight_of(self, labels: np.ndarray) -> np.ndarray:
        """What labels weigh as far as known; 0 for unknown ones."""
        at, there = self.places(labels)
        return np.where(there, np.append(self.weight, 0)[at], 0)

    def learn(self, labels: np.ndarray, weights: np.ndarray) -> None:
        """Weights of labels; the last one counts for a label that comes again."""
        at, there = self.places(labels)
        self.weight[at[there]] = weights[there]
        if not there.all():
            new, last = np.unique(labels[~there][::-1], return_index=True)
            at = np.searchsorted(self.known, new)
            self.known, self.weight = np.insert(self.known, at, new), np.insert(self.weight, at, weights[~there][::-1][last])

    def hear(self, notes: list[list[np.ndarray]]) -> None:
        for vids, labels, weights in notes:
            self.ghost_label[np.searchsorted(self.ghost, vids)] = labels
            if len(weights):
                self.learn(labels, weights)

    def scan(self, rules: Rules, adjacency: list[np.ndarray], sweep: int, batch: int) -> None:
        """Moves of one batch. adjacency: vertices, where each one's arcs end, heads, weights."""
        if not adjacency:
            return
        vids, ends, heads, w = adjacency
        start, size = int(rules.starts[self.number]), len(self.label)
        at = np.where((heads >= start) & (heads < start + size), heads - start, size + np.searchsorted(self.ghost, heads))
        label, c, own = np.concatenate([self.label, self.ghost_label]), self.c, vids - start
        met = np.unique(label[np.concatenate([at, own])])
        place = np.zeros(len(label), np.int64)  # of a vertex's label among those met
        place[at], place[own] = np.searchsorted(met, label[at]), np.searchsorted(met, label[own])
        if rules.mode in ("local", "none"):  # only the own part counts, and nobody tells of others' weights
            mine, inverse = np.unique(self.label, return_inverse=True)
            part = np.bincount(inverse, weights=c).astype(np.int64)
            here = np.searchsorted(mine, met)
            heavy = np.where(np.append(mine, -1)[here] == met, np.append(part, 0)[here], 0)
        else:
            heavy = self.weight_of(met)
        limits = np.asarray([rules.limit_of(t, self.number) for t in met.tolist()], float) if rules.blocks else np.full(len(met), float(rules.limit_of(0, self.number)))
        rng = np.random.default_rng([rules.seed, sweep, batch, self.number])
        begins = np.concatenate([[0], ends[:-1]])
        chunk = np.arange(len(vids)) // CHUNK
        # buckets of low degree first; chunks are shuffled, and so are vertices in a chunk
        order = np.lexsort((rng.random(len(vids)), rng.random(len(vids) // CHUNK + 1)[chunk], np.floor(np.log2(np.maximum(1, ends - begins)))))
        coins = rng.random(len(vids)).tolist()
        # a vertex whose neighbours all share its label has nowhere to go, until one of them moves
        among = np.full(len(label) + 1, len(vids))
        among[own] = np.arange(len(vids))
        among = among[at]
        flags = bytearray(len(vids) + 1)
        open_ = np.frombuffer(flags, np.uint8)
        open_[:-1] = np.logical_or.reduceat(place[at] != np.repeat(place[own], ends - begins), begins)
        labels, weight, limit = place.tolist(), heavy.tolist(), limits.tolist()
        changed = [0] * len(met)
        heads, ws = at.tolist(), w.tolist()
        ends, c, begins, own = ends.tolist(), c.tolist(), begins.tolist(), own.tolist()
        moved, before, gains = [], [], []
        for k in order.tolist():
            if not flags[k]:
                continue
            v, b, e = own[k], begins[k], ends[k]
            cv, old = c[v], labels[v]
            if e - b < MANY:
                conn = {}
                for j in range(b, e):
                    t = labels[heads[j]]
                    conn[t] = conn.get(t, 0) + ws[j]
                most = conn.pop(old, 0)
            else:
                most, conn = connected(place[at[b:e]], w[b:e], old, len(met))
            best, stay, light, seen = old, most, weight[old] - cv, 1
            for t, s in conn.items():
                if s < most or weight[t] + cv > limit[t]:
                    continue
                if s > most or (rules.lighter and weight[t] < light):
                    best, most, light, seen = t, s, weight[t], 1
                elif best != old and (not rules.lighter or weight[t] == light):
                    seen += 1
                    if coins[k] * seen < 1:
                        best = t
            if best != old:
                weight[old] -= cv
                weight[best] += cv
                labels[v] = place[v] = best
                open_[among[b:e]] = 1
                moved.append(v)
                before.append(old)
                gains.append(most - stay)
                changed[old] -= cv
                changed[best] += cv
        self.moved, self.gain, self.old = np.asarray(moved, np.int64), np.asarray(gains, np.int64), met[np.asarray(before, np.int64)]
        self.label[self.moved] = met[place[self.moved]]
        if rules.mode != "local":
            for t, x in zip(met.tolist(), changed, strict=True):
                if x:
                    self.change[t] = self.change.get(t, 0) + x
        if rules.mode not in ("local", "none"):
            self.learn(met, np.asarray(weight, np.int64))
        self.count[0] += len(moved)

    def changes(self, rules: Rules) -> Iterator[tuple[int, list[np.ndarray]]]:
        """Weight changes for each owner; with blocks, all known ones, as each PE wants their totals."""
        if rules.mode in ("local", "none"):
            self.change = {}
        rows = (dict.fromkeys(self.known.tolist(), 0) | self.change) if rules.blocks and rules.mode != "none" else {b: x for b, x in self.change.items() if x}
        self.change = {}
        labels, values = np.fromiter(rows.keys(), np.int64, len(rows)), np.fromiter(rows.values(), np.int64, len(rows))
        to = rules.owner(labels)
        for pe in np.unique(to).tolist():
            yield pe, [labels[to == pe], values[to == pe]]

    def account(self, rules: Rules, messages: list[tuple[int, list[np.ndarray]]]) -> Iterator[tuple[int, list[np.ndarray]]]:
        """Adds up what the owner is told and replies with totals."""
        for _, (labels, values) in messages:
            np.add.at(self.owned, rules.place(labels, self.number), values)
        for pe, (labels, _) in messages:
            yield pe, [labels, self.owned[rules.place(labels, self.number)]]

    def settle(self, rules: Rules, totals: list[list[np.ndarray]]) -> np.ndarray:
        """Learns totals and takes back its share of overweight; the vertices that go back."""
        for labels, values in totals:
            self.learn(labels, values)
        back = []
        if rules.mode == "revert":
            into = self.label[self.moved]
            met = np.unique(np.concatenate([into, self.old]))
            weight = dict(zip(met.tolist(), self.weight_of(met).tolist(), strict=True))
            for x in np.unique(into).tolist():
                excess = weight[x] - rules.limit_of(x, self.number)
                if excess <= 0:
                    continue
                quota, mine = math.ceil(excess * int(self.c[self.label == x].sum()) / weight[x]), np.flatnonzero(into == x)
                for k in mine[np.lexsort((self.moved[mine], self.gain[mine]))].tolist():
                    if quota <= 0:
                        break
                    v, old = int(self.moved[k]), int(self.old[k])
                    cv = int(self.c[v])
                    quota -= cv
                    self.label[v] = old
                    for y, d in ((x, -cv), (old, cv)):
                        self.change[y] = self.change.get(y, 0) + d
                        weight[y] += d
                    back.append(v)
            self.learn(met, np.asarray([weight[x] for x in met.tolist()], np.int64))
        self.count[0] -= len(back)
        self.count[1] += len(back)
        if not rules.blocks and rules.mode not in ("local", "none"):
            met = np.isin(self.known, np.concatenate([self.label, self.ghost_label, np.fromiter(self.change, np.int64, len(self.change))]))
            self.known, self.weight = self.known[met], self.weight[met]
        self.moved = self.old = self.gain = np.zeros(0, np.int64)
        return np.asarray(back, np.int64)

    def notes(self, rules: Rules, changed: np.ndarray) -> Iterator[tuple[int, list[np.ndarray]]]:
        """The new labels of changed vertices for the PEs that hold their ghosts."""
        told = np.isin(self.sub_v, changed)
        vs, pes = self.sub_v[told], self.sub_pe[told]
        self.count[2] += len(vs)
        for pe in np.unique(pes).tolist():
            v = vs[pes == pe]
            labels = self.label[v]
            known = np.zeros(0, np.int64) if rules.mode in ("local", "none") else self.weight_of(labels)
            yield pe, [v + rules.starts[self.number], labels, known]


def exchange(rows: DataFrame, tasks: int, work) -> DataFrame:
    """work(pe, messages) for each PE, dealt round robin to tasks; messages are (kind, from, arrays). It gives (to, kind, arrays, n)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def finish(pe, messages):
            out = list(work(pe, messages))
            return pa.RecordBatch.from_arrays([pa.array([r[0] for r in out], pa.int32()), pa.array([r[1] for r in out], pa.int32()), pa.array([pe] * len(out), pa.int32()), pa.array([pack(*r[2]) for r in out], pa.binary()), pa.array([r[3] for r in out], pa.int64())], names=NAMES)

        pe, messages = None, []
        for batch in batches:
            for k in range(batch.num_rows):
                to, kind, frm, body = (batch.column(j)[k].as_py() for j in range(4))
                if to != pe:
                    if messages:
                        yield finish(pe, messages)
                    pe, messages = to, []
                messages.append((kind, frm, unpack(body)))
        if messages:
            yield finish(pe, messages)

    return rows.repartitionById(tasks, F.pmod("to", F.lit(tasks))).sortWithinPartitions("to", "kind", "frm").mapInArrow(run, ROW)


def arrays_of(messages, kind: int) -> list[list[np.ndarray]]:
    return [m[2] for m in messages if m[0] == kind]


def moving(rules: Rules, sweep: int, batch: int):
    """The first step of a batch; with batch -1 nothing is scanned."""

    def move(pe, messages):
        me = Pe(pe, arrays_of(messages, STATE)[0])
        back = me.settle(rules, arrays_of(messages, TOTAL))
        rows = arrays_of(messages, ADJACENCY)
        if rows and batch >= 0:
            me.scan(rules, rows[0], sweep, batch)
        out = [(to, DELTA, arrays, 0) for to, arrays in me.changes(rules)]
        out += [(to, NOTE, arrays, 0) for to, arrays in me.notes(rules, np.concatenate([back, me.moved]))]
        return [(pe, STATE, me.parts(), int(me.count[0])), *out]

    return move


def hearing(rules: Rules):
    """The second step."""

    def hear(pe, messages):
        me = Pe(pe, arrays_of(messages, STATE)[0])
        me.hear(arrays_of(messages, NOTE))
        out = [(to, TOTAL, arrays, 0) for to, arrays in me.account(rules, [(m[1], m[2]) for m in messages if m[0] == DELTA])]
        return [(pe, STATE, me.parts(), int(me.count[0])), *out]

    return hear


@dataclass
class Fleet:
    """The laid out graph: adjacency rows (to, kind, frm, body, n, batch), PEs of a copy, all PEs, first vertices, batches, vertices by PE, ghosts."""

    adjacency: DataFrame
    pes: int
    all_pes: int
    starts: np.ndarray
    batches: int
    layout: DataFrame  # vid, c, copy, pe
    ghosts: DataFrame  # pe, vid, owner
    tasks: int


def boundaries(g: Graph, pes: int) -> np.ndarray:
    """First vertex of each PE, and the end. Each copy is cut into `pes` ranges of ids."""
    out = [off + -(-p * n // pes) for off, n in g.copies for p in range(pes)]
    return np.asarray([*out, g.n], np.int64)


def laid_out(g: Graph, pes: int) -> DataFrame:
    """vid, c, copy, pe: every copy's ids in ranges, as `boundaries` says."""
    table = g.vertices.sparkSession.createDataFrame([(i, int(off), int(n)) for i, (off, n) in enumerate(g.copies)], "copy int, _off long, _n long")  # a row for each copy, at most one a PE
    if len(g.copies) == 1:
        return g.vertices.select("vid", "c", F.lit(0).alias("copy"), F.floor(F.col("vid") * pes / F.lit(max(g.n, 1))).cast("int").alias("pe"))
    rows = g.vertices.join(F.broadcast(table), "copy")
    return rows.select("vid", "c", "copy", (F.col("copy") * pes + F.floor((F.col("vid") - F.col("_off")) * pes / F.col("_n"))).cast("int").alias("pe"))


def lay_out(g: Graph, pes: int, seed: int, batches: int | None = None, arcs: DataFrame | None = None) -> Fleet:
    """Deals vertices to PEs and batches, and writes each PE's arcs by batch. Vertices without arcs are in no batch.

    A batch is cut from the PE's order: buckets of degrees, low ones first, chunks of them shuffled. It is found by range within the bucket,
    from the buckets' sizes, so that nothing but a PE's chunk numbers is sorted.
    """
    count = batches or num_batches(pes)
    arcs = g.edges if arcs is None else arcs
    layout = snapshot(laid_out(g, pes))
    buckets = degree_buckets(Graph(g.vertices, arcs, g.n, g.arcs, g.total, g.heaviest, g.copies)).filter("deg > 0").join(layout.select("vid", "pe"), "vid")
    # chunks of ids within a bucket, in a shuffled order; a vertex's place is that of its chunk
    chunk = F.floor(F.col("vid") / CHUNK)
    sizes = buckets.groupBy("pe", "bucket", chunk.alias("chunk")).agg(F.count("*").alias("size"))
    order = Window.partitionBy("pe").orderBy("bucket", coin(seed, "chunk", F.col("pe"), F.col("bucket"), F.col("chunk")), "chunk")
    place = sizes.withColumn("before", F.sum("size").over(order) - F.col("size")).withColumn("all", F.sum("size").over(Window.partitionBy("pe")))
    placed = place.select("pe", "bucket", "chunk", F.least(F.lit(count - 1), F.floor(F.col("before") * count / F.col("all"))).cast("int").alias("batch"))
    tails = buckets.withColumn("chunk", chunk).join(placed, ["pe", "bucket", "chunk"]).select(F.col("vid").alias("src"), "pe", "batch")

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows pe, batch, body: the arcs of a task by batch, packed before they are shuffled, some million at a time."""

        def finish(held: list[list[np.ndarray]]) -> pa.RecordBatch:
            pe, batch, src, dst, w = (np.concatenate(x) for x in zip(*held, strict=True))
            o = np.lexsort((src, batch, pe))
            pe, batch, src, dst, w = (x[o] for x in (pe, batch, src, dst, w))
            first = np.append(0, np.flatnonzero((np.diff(pe) != 0) | (np.diff(batch) != 0)) + 1)
            bodies = [pack(np.diff(src[i:j], prepend=0)[1:], src[i : i + 1], dst[i:j], w[i:j]) for i, j in zip(first.tolist(), [*first[1:].tolist(), len(pe)], strict=True)]
            return pa.RecordBatch.from_arrays([pa.array(pe[first], pa.int32()), pa.array(batch[first], pa.int32()), pa.array(bodies, pa.binary())], names=["pe", "batch", "body"])

        held, n = [], 0
        for rows in batches:
            if rows.num_rows:
                held.append([np.asarray(c) for c in rows.columns])
                n += rows.num_rows
            if n >= PIECE:
                yield finish(held)
                held, n = [], 0
        if held:
            yield finish(held)

    def pack_arcs(table: pa.Table) -> pa.Table:
        parts = [unpack(body.as_py()) for body in table.column("body")]
        src = np.concatenate([np.concatenate([x, d]).cumsum() for d, x, _, _ in parts])
        dst, w = (np.concatenate([p[k] for p in parts]) for k in (2, 3))
        o = np.lexsort((dst, src))
        src, dst, w = src[o], dst[o], w[o]
        first = np.append(0, np.flatnonzero(np.diff(src)) + 1)
        size = np.diff(first, append=len(src))  # degrees, as all arcs of a vertex are in its batch
        o = np.argsort(np.repeat(np.frexp(size)[1], size), kind="stable")  # buckets of degrees, low ones first
        src, dst, w = src[o], dst[o], w[o]
        last = np.append(np.flatnonzero(np.diff(src)), len(src) - 1)
        pe, batch = table.column("pe")[0].as_py(), table.column("batch")[0].as_py()
        return pa.table({"to": pa.array([pe], pa.int32()), "kind": pa.array([ADJACENCY], pa.int32()), "frm": pa.array([pe], pa.int32()), "body": pa.array([pack(src[last], last + 1, dst, w)], pa.binary()), "n": pa.array([batch], pa.int64()), "batch": pa.array([batch], pa.int32())})

    packed = arcs.join(tails, "src").select("pe", "batch", "src", "dst", "w").mapInArrow(pieces, "pe int, batch int, body binary")
    # by work, as packed rows are too few bytes to tell
    tasks = max(1, min(pes * len(g.copies) * count, g.arcs // ARCS_A_TASK))
    rows = packed.repartition(tasks, "pe", "batch").groupBy("pe", "batch").applyInArrow(pack_arcs, ROW + ", batch int")
    adjacency, starts = written(rows, "batch"), boundaries(g, pes)

    def foreign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Heads of packed arcs that another PE owns, which follows from their ids."""
        for batch in batches:
            for pe, body in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                heads = np.unique(unpack(body.as_py())[2])
                heads = heads[(heads < starts[pe]) | (heads >= starts[pe + 1])]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(heads), pe, np.int32)), pa.array(heads), pa.array((np.searchsorted(starts, heads, side="right") - 1).astype(np.int32))], names=["pe", "vid", "owner"])

    ghosts = snapshot(adjacency.select("to", "body").mapInArrow(foreign, "pe int, vid long, owner int").distinct())
    # more tasks than run at once only wait for each other, in each of many shuffles
    tasks = min(tasks_for(pes * len(g.copies), g.arcs), max(2, g.vertices.sparkSession.sparkContext.defaultParallelism))
    return Fleet(adjacency, pes, pes * len(g.copies), starts, count, layout, ghosts, tasks)


def start(fleet: Fleet, rules: Rules, labels: DataFrame | None, weights: list[int] | None) -> DataFrame:
    """State rows of all PEs. labels: vid, label, for blocks; without it every vertex is its own cluster. weights: of the blocks."""
    at = fleet.layout.select("vid", "c", "pe", F.col("vid").alias("label")) if labels is None else fleet.layout.join(labels, "vid").select("vid", "c", "pe", "label")
    at = at if labels is None else snapshot(at)
    own = at.select("pe", F.lit(0).alias("what"), "vid", F.col("c").alias("x"), "label")
    ghosts = fleet.ghosts.select("pe", "vid").join(at.select("vid", "c", "label"), "vid").select("pe", F.lit(1).alias("what"), "vid", F.col("c").alias("x"), "label")
    subs = fleet.ghosts.select(F.col("owner").alias("pe"), F.lit(2).alias("what"), "vid", F.col("pe").cast("long").alias("x"), F.lit(0).cast("long").alias("label"))
    empty = fleet.layout.sparkSession.range(fleet.all_pes).select(F.col("id").cast("int").alias("pe"), F.lit(3).alias("what"), F.lit(0).cast("long").alias("vid"), F.lit(0).cast("long").alias("x"), F.lit(0).cast("long").alias("label"))
    every = np.asarray(weights if weights is not None else [], np.int64)

    def build(table: pa.Table) -> pa.Table:
        pe = table.column("pe")[0].as_py()
        what, vid, x, label = (np.asarray(table.column(c)) for c in ("what", "vid", "x", "label"))

        def rows(k, *more):
            r = np.flatnonzero(what == k)
            return r[np.lexsort((x[r], vid[r]))] if more else r[np.argsort(vid[r], kind="stable")]

        o, gh, s = rows(0), rows(1), rows(2, x)
        if rules.blocks:
            met = np.unique(np.concatenate([label[o], label[gh]]))
            known = every[met]
            copy, first = divmod(pe, rules.pes)
            owned = every[copy * rules.blocks : (copy + 1) * rules.blocks][first :: rules.pes]
        else:
            met, known, owned = np.concatenate([vid[o], vid[gh]]), np.concatenate([x[o], x[gh]]), x[o]
            order = np.argsort(met)
            met, known = met[order], known[order]
        none = np.zeros(0, np.int64)
        body = pack(label[o], x[o], vid[gh], label[gh], vid[s] - rules.starts[pe], x[s], met, known, owned, none, none, none, none, none, np.zeros(3, np.int64))
        return pa.table({"to": pa.array([pe], pa.int32()), "kind": pa.array([STATE], pa.int32()), "frm": pa.array([pe], pa.int32()), "body": pa.array([body], pa.binary()), "n": pa.array([0], pa.int64())})

    rows = snapshot(own.union(ghosts).union(subs).union(empty).groupBy("pe").applyInArrow(build, ROW))
    if labels is not None:
        discard(at)
    return rows


def sweeps(fleet: Fleet, rules: Rules, rows: DataFrame, iterations: int) -> tuple[DataFrame, list[int]]:
    """Rows after up to `iterations` sweeps, or until one moves nothing; moves of each sweep. The rows given are deleted, as all but the last are."""

    def step(rows: DataFrame, after: DataFrame) -> DataFrame:
        after = snapshot(after)
        discard(rows)
        return after

    if fleet.tasks == 1:
        rows = step(rows, rows.union(fleet.adjacency.drop("batch")).coalesce(1).mapInArrow(together(fleet.batches, rules, iterations), ROW))
        return rows, [r["n"] for r in sorted(rows.filter(F.col("kind") == COUNT).select("frm", "n").collect())]
    moves, so_far = [], 0
    for sweep in range(iterations):
        after = rows
        for b in range(fleet.batches):
            after = after.union(fleet.adjacency.filter(F.col("batch") == b).drop("batch"))
            after = exchange(exchange(after, fleet.tasks, moving(rules, sweep, b)), fleet.tasks, hearing(rules))
        rows = step(rows, after)
        total = rows.filter(F.col("kind") == STATE).agg(F.sum("n")).first()[0]
        moves.append(total - so_far)
        so_far = total
        if not moves[-1]:
            break
    if rules.mode == "revert":  # what the last batch made overweight
        rows = step(rows, exchange(rows, fleet.tasks, moving(rules, iterations, -1)))
        if moves:
            moves[-1] += rows.filter(F.col("kind") == STATE).agg(F.sum("n")).first()[0] - so_far
    return rows, moves


def together(batches: int, rules: Rules, iterations: int):
    """All sweeps in one task: the same steps and messages as between tasks, passed from hand to hand."""

    def run(incoming: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        inbox, adjacency = {}, {}
        for batch in incoming:
            for to, kind, frm, body, n in zip(*[c.to_pylist() for c in batch.columns], strict=True):
                if kind == ADJACENCY:
                    adjacency[n, to] = [(kind, frm, unpack(body))]
                else:
                    inbox.setdefault(to, []).append((kind, frm, unpack(body)))

        def step(inbox: dict, work, batch: int) -> tuple[dict, int]:
            out, total = {}, 0
            for pe in sorted(inbox):
                for to, kind, arrays, n in work(pe, sorted(inbox[pe], key=lambda m: m[:2]) + adjacency.get((batch, pe), [])):
                    out.setdefault(to, []).append((kind, pe, arrays))
                    total += n if kind == STATE else 0
            return out, total

        so_far, rows = 0, []
        for sweep in range(iterations):
            for b in range(batches):
                inbox, _ = step(inbox, moving(rules, sweep, b), b)
                inbox, total = step(inbox, hearing(rules), -1)
            rows.append((-1, COUNT, sweep, b"", total - so_far))
            if total == so_far:
                break
            so_far = total
        if rules.mode == "revert":
            inbox, total = step(inbox, moving(rules, iterations, -1), -1)
            if rows:
                rows[-1] = (*rows[-1][:-1], rows[-1][-1] + total - so_far)
        rows += [(pe, STATE, pe, pack(*m[2]), 0) for pe, messages in sorted(inbox.items()) for m in messages if m[0] == STATE]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.int64()), strict=True)], names=NAMES)

    return run


def labels_of(rows: DataFrame, rules: Rules) -> DataFrame:
    """vid, label of every vertex."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for to, body in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                label = unpack(body.as_py())[0]
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(label)) + rules.starts[to]), pa.array(label)], names=["vid", "label"])

    return rows.filter(F.col("kind") == STATE).select("to", "body").mapInArrow(run, "vid long, label long")


def counts_of(rows: DataFrame) -> list[int]:
    """Moves kept, moves taken back, and labels told to other PEs, summed over PEs."""
    import pandas as pd

    def run(frames):
        for f in frames:
            yield pd.DataFrame([unpack(b)[-1].tolist() for b in f["body"]], columns=["a", "b", "c"])

    return [int(x or 0) for x in rows.filter(F.col("kind") == STATE).select("body").mapInPandas(run, "a long, b long, c long").agg(F.sum("a"), F.sum("b"), F.sum("c")).first()]


def propagate(g: Graph, pes: int, limit: list[float], iterations: int, seed: int, mode: str = "revert", labels: DataFrame | None = None, weights: list[int] | None = None, blocks: int = 0, batches: int | None = None, arcs: DataFrame | None = None, trace: dict | None = None, fleet: Fleet | None = None) -> DataFrame:
    """vid, label after label propagation on `pes` PEs a copy: clusters, or blocks (`blocks` of them in a copy) if labels are given."""
    fleet = fleet or lay_out(g, pes, seed, batches, arcs)
    rules = Rules(fleet.starts, pes, blocks, [float(x) for x in limit], mode, bool(blocks), seed)
    rows, moves = sweeps(fleet, rules, start(fleet, rules, labels, weights), iterations)
    if trace is not None:
        kept, back, told = counts_of(rows)
        trace.update(moves=moves, kept=kept, reverted=back, notified=told)
    found = snapshot(labels_of(rows, rules))
    discard(rows)
    return found

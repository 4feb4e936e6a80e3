"""Random walks on the graph.

A hop is a draw from labels, so a walk is the same whichever way it is made:
by joins for graphs of any size, or on broadcast arrays for small ones.  Lists
of neighbours have dense slots, numbered in two levels, so that no task holds
all neighbours of a hub, and an even hop is an equi-join on (src, slot).
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from hashlib import md5

import numpy as np
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from linkgraph.functions.draws import node_id, u52
from linkgraph.operators import colsim, importance
from linkgraph.operators.graph import Graph
from linkgraph.params import Params
from linkgraph.sources.pairs import TablePair
from linkgraph.sources.shared import written

_BUCKETS = 64
#: Graphs of up to so many times ``local_edges`` have arrays that fit a task, but are put in order by the tasks and not on the driver.
ORDERED = 6


@dataclass(frozen=True)
class Transitions:
    #: (src, slot, dst, dst_kind): even hops of tokens and columns
    even: DataFrame
    #: (src, deg)
    degrees: DataFrame
    #: (src, lst array<struct<dst, w>>): weighted hops of records
    records: DataFrame
    #: (src, p_cid, lst): the columns' hops to columns
    columns: DataFrame


def slotted(lists: DataFrame) -> DataFrame:
    """(src, slot, dst, dst_kind) from (src, dst, dst_kind); order is by (dst mod 64, dst)."""
    bucket = lists.withColumn("b", F.pmod("dst", F.lit(_BUCKETS)))
    sizes = bucket.groupBy("src", "b").agg(F.count(F.lit(1)).alias("n"))
    before = sizes.withColumn("offset", F.coalesce(F.sum("n").over(Window.partitionBy("src").orderBy("b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("n")
    inner = bucket.withColumn("r", F.row_number().over(Window.partitionBy("src", "b").orderBy("dst")) - 1)
    return inner.join(before, ["src", "b"]).select("src", (F.col("offset") + F.col("r")).alias("slot"), "dst", "dst_kind")


def transitions(spark: SparkSession, g: Graph, p: Params, weights: DataFrame | None, keep: Callable[[DataFrame], DataFrame] = lambda df: df) -> Transitions:
    """Hops of a graph; ``weights`` are the columns' importances, None for even walks.

    ``keep`` gets the lists of neighbours, which are read several times.
    """
    tok, rid, cid = (lambda: node_id("T", F.col("tok")), lambda: node_id("R", F.col("rid")), lambda: node_id("C", F.col("cid")))
    lists = keep(
        g.rid_tok.select(tok().alias("src"), rid().alias("dst"), F.lit("R").alias("dst_kind"))
        .union(g.tok_cid.select(tok().alias("src"), cid().alias("dst"), F.lit("C").alias("dst_kind")))
        .union(g.tok_cid.select(cid().alias("src"), tok().alias("dst"), F.lit("T").alias("dst_kind")))
    )
    even = slotted(lists)
    degrees = lists.groupBy("src").agg(F.count(F.lit(1)).alias("deg"))
    if weights is not None and p.weighted:
        tok_w = importance.token_weights(g.tok_cid, weights)
        hops = g.rid_tok.join(tok_w, "tok").select(rid().alias("src"), tok().alias("dst"), "w")
    else:
        hops = g.rid_tok.select(rid().alias("src"), tok().alias("dst"), F.lit(1.0).alias("w"))
    records = hops.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dst", "w"))).alias("lst"))
    end = lambda c: node_id("C", F.col(c))
    cc = g.cid_cid.select(end("left_cid").alias("src"), end("right_cid").alias("dst"), F.col("weight").alias("w")).union(g.cid_cid.select(end("right_cid").alias("src"), end("left_cid").alias("dst"), F.col("weight").alias("w")))
    lists_cc = cc.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dst", "w"))).alias("lst"))
    share = importance.cid_transitions(g, p).select(cid().alias("src"), "p_cid")
    return Transitions(even, degrees, records, share.join(lists_cc, "src", "left"))


def _pick(lst: Column, u: Column) -> Column:
    """Inverse of the cumulative weights: the first entry whose running sum exceeds u times the total; even if all are 0."""
    total = F.aggregate(lst, F.lit(0.0), lambda s, x: s + x["w"])
    start = F.struct(F.lit(0.0).alias("s"), F.lit(None).cast("long").alias("d"))
    done = F.aggregate(lst, start, lambda a, x: F.struct((a["s"] + x["w"]).alias("s"), F.when(a["d"].isNull() & (a["s"] + x["w"] > u * total), x["dst"]).otherwise(a["d"]).alias("d")))
    evenly = F.get(lst, F.floor(u * F.size(lst)).cast("int"))["dst"]
    return F.when(total == 0, evenly).otherwise(F.coalesce(done["d"], F.element_at(lst, -1)["dst"]))


def starts(nodes: DataFrame, p: Params, per_kind: dict[str, float] | None = None) -> DataFrame:
    """(walk_id, node, kind): ``walks_per_node`` starts of each node, kept at its kind's rate."""
    rate = F.lit(1.0)
    for kind, r in (per_kind or {}).items():
        rate = F.when(F.col("kind") == kind, F.lit(float(r))).otherwise(rate)
    out = nodes.select(F.col("node_id").alias("node"), "kind", F.explode(F.sequence(F.lit(0), F.lit(p.walks_per_node - 1))).alias("k"), rate.alias("rate"))
    return out.filter(u52(p.seed, "start", F.col("node"), F.col("k")) < F.col("rate")).select(F.concat_ws(":", F.col("node").cast("string"), F.col("k").cast("string")).alias("walk_id"), "node", "kind")


def step(frontier: DataFrame, t: Transitions, p: Params, at: int) -> DataFrame:
    """One hop of every walk; walks at isolated nodes end."""
    u = u52(p.seed, "hop", F.col("walk_id"), F.lit(at))
    of_records = frontier.filter("kind = 'R'").join(t.records.withColumnRenamed("src", "node"), "node").select("walk_id", _pick(F.col("lst"), u).alias("node"), F.lit("T").alias("kind"))
    rest = frontier.filter("kind <> 'R'").join(F.broadcast(t.columns.withColumnRenamed("src", "node")), "node", "left")
    to_column = F.coalesce((u52(p.seed, "class", F.col("walk_id"), F.lit(at)) < F.col("p_cid")) & F.col("lst").isNotNull(), F.lit(False))
    rest = rest.withColumn("cc", to_column)
    of_columns = rest.filter("cc").select("walk_id", _pick(F.col("lst"), u).alias("node"), F.lit("C").alias("kind"))
    slots = rest.filter("not cc").join(t.degrees.withColumnRenamed("src", "node"), "node").select("walk_id", F.col("node").alias("src"), F.floor(u * F.col("deg")).cast("long").alias("slot"))
    evenly = slots.join(t.even, ["src", "slot"]).select("walk_id", F.col("dst").alias("node"), F.col("dst_kind").alias("kind"))
    return of_records.union(of_columns).union(evenly)


def walks_by_joins(first: DataFrame, t: Transitions, p: Params) -> DataFrame:
    """Walks of graphs of any size.  A step reads its frontier several times, so each is written."""
    t = Transitions(*map(written, (t.even, t.degrees, t.records, t.columns)))
    frontier = written(first.select("walk_id", "node", "kind"))
    parts = [frontier.select("walk_id", F.lit(0).alias("step"), F.col("node").alias("node_id"))]
    for k in range(1, p.walk_length):
        frontier = written(step(frontier, t, p, k))
        parts.append(frontier.select("walk_id", F.lit(k).alias("step"), F.col("node").alias("node_id")))
    out = parts[0]
    for part in parts[1:]:
        out = out.union(part)
    return out


@dataclass(frozen=True)
class Arrays:
    """Lists of neighbours as flat arrays: those of node i lie at ``start[i]`` to ``start[i + 1]``; nodes are numbered by id."""

    ids: np.ndarray
    even_start: np.ndarray
    even: np.ndarray
    record_start: np.ndarray
    record: np.ndarray
    #: Running sums of weights within each record.
    sums: np.ndarray
    #: Node number to (p_cid, neighbours, running sums).
    columns: dict[int, tuple[float, np.ndarray, np.ndarray]]


def _starts(src: np.ndarray, n: int) -> np.ndarray:
    return np.concatenate([[0], np.cumsum(np.bincount(src, minlength=n))]).astype(np.int64)


def _running(w: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Running sums within each list, added up in order, place by place over all lists."""
    sums, size, at = w.copy(), np.diff(start), 1
    lists = np.flatnonzero(size > 1)
    while len(lists):
        here = start[lists] + at
        sums[here] += sums[here - 1]
        at += 1
        lists = lists[size[lists] > at]
    return sums


def _summed(ids: np.ndarray, even_start: np.ndarray, even: np.ndarray, record_start: np.ndarray, record: np.ndarray, columns: dict, weight: np.ndarray) -> Arrays:
    return Arrays(ids, even_start, even, record_start, record, _running(weight[record], record_start), columns)


@dataclass(frozen=True)
class Unsummed(Arrays):
    """Arrays whose running sums, their largest part, are made from the weights of the nodes where they are unpacked."""

    weight: np.ndarray

    def __reduce__(self):
        return _summed, (self.ids, self.even_start, self.even, self.record_start, self.record, self.columns, self.weight)


def arrays_of(t: Transitions) -> Arrays:
    even, hops = t.even.select("src", "slot", "dst").toArrow(), t.records.select("src", F.inline("lst")).toArrow()
    src, slot, dst = (even.column(c).to_numpy() for c in ("src", "slot", "dst"))
    rsrc, rdst, w = (hops.column(c).to_numpy() for c in ("src", "dst", "w"))
    cols = [r for r in t.columns.collect() if r["lst"]]
    ids = np.unique(np.concatenate([src, dst, rsrc, rdst, np.array([x for r in cols for x in (r["src"], *[e["dst"] for e in r["lst"]])], dtype=np.int64)]))
    number = lambda x: np.searchsorted(ids, x)
    src, rsrc = number(src), number(rsrc)
    by, rby = np.lexsort((slot, src)), np.lexsort((w, rdst, rsrc))
    even_start, record_start = _starts(src, len(ids)), _starts(rsrc, len(ids))
    columns = {int(number(r["src"])): (r["p_cid"], number(np.array([e["dst"] for e in r["lst"]])), np.cumsum([e["w"] for e in r["lst"]])) for r in cols}
    return Arrays(ids, even_start, number(dst[by]).astype(np.int32), record_start, number(rdst[rby]).astype(np.int32), _running(w[rby].astype(float), record_start), columns)


#: Additive constants and left turns of the 64 steps of MD5 (RFC 1321).
_ADD = [np.uint32(int(abs(math.sin(i + 1)) * (1 << 32))) for i in range(64)]
_TURN = [t for four in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for t in four * 4]
_WORD = [*range(16), *((5 * i + 1) % 16 for i in range(16)), *((3 * i + 5) % 16 for i in range(16)), *((7 * i) % 16 for i in range(16))]
_FIRST = [np.uint32(x) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)]


def _digests(words: np.ndarray) -> np.ndarray:
    """First 64 bits of the MD5 of messages of one block each, as big-endian numbers; ``words`` is (16, messages)."""
    a, b, c, d = (np.full(words.shape[1], x) for x in _FIRST)
    f, turned = np.empty_like(a), np.empty_like(a)
    for i in range(64):
        if i < 16:
            np.bitwise_xor(c, d, out=f)
            f &= b
            f ^= d
        elif i < 32:
            np.bitwise_xor(b, c, out=f)
            f &= d
            f ^= c
        elif i < 48:
            np.bitwise_xor(b, c, out=f)
            f ^= d
        else:
            np.invert(d, out=f)
            f |= b
            f ^= c
        f += a
        f += words[_WORD[i]]
        f += _ADD[i]
        np.right_shift(f, np.uint32(32 - _TURN[i]), out=turned)
        f <<= np.uint32(_TURN[i])
        f |= turned
        f += b
        # the array of the old a is free for the next step
        a, b, c, d, f = d, f, b, c, a
    a += _FIRST[0]
    b += _FIRST[1]
    return (a.byteswap().astype(np.uint64) << np.uint64(32)) | b.byteswap()


def _draws(p: Params, tag: str, walks: np.ndarray, at: int) -> np.ndarray:
    """``u52`` of many walks, whose names are bytes of a fixed width: 13 hexadecimal digits are the first 52 bits."""
    head, tail = f"{p.seed}|{tag}|".encode(), f"|{at}".encode()
    sizes, out = np.char.str_len(walks), np.empty(len(walks), dtype=np.uint64)
    letters = walks.view(np.uint8).reshape(len(walks), walks.dtype.itemsize)
    for size in np.unique(sizes):
        here, whole = np.flatnonzero(sizes == size), len(head) + int(size) + len(tail)
        if whole > 55:
            out[here] = np.frombuffer(b"".join([md5(head + w + tail).digest()[:8] for w in walks[here].tolist()]), dtype=">u8")
            continue
        for lo in range(0, len(here), 8192):
            some = here[lo : lo + 8192]
            block = np.zeros((len(some), 64), dtype=np.uint8)
            block[:, : len(head)] = np.frombuffer(head, dtype=np.uint8)
            block[:, len(head) : len(head) + size] = letters[some, :size]
            block[:, len(head) + size : whole] = np.frombuffer(tail, dtype=np.uint8)
            block[:, whole] = 0x80
            block[:, 56:58] = np.array([whole * 8], dtype="<u2").view(np.uint8)
            out[some] = _digests(np.ascontiguousarray(block.view("<u4").T))
    return (out >> np.uint64(12)).astype(np.float64) / float(1 << 52)


def _weighted(start: np.ndarray, end: np.ndarray, sums: np.ndarray, u: np.ndarray) -> np.ndarray:
    """Place of the first running sum above u times the list's total; even if all are 0."""
    total = sums[end - 1]
    goal, lo, hi = u * total, start.copy(), end.copy()
    while (lo < hi).any():
        mid = (lo + hi) // 2
        right = (lo < hi) & (sums[np.minimum(mid, end - 1)] <= goal)
        lo, hi = np.where(right, mid + 1, lo), np.where(right | (lo >= hi), hi, mid)
    return np.where(total == 0, start + (u * (end - start)).astype(np.int64), np.minimum(lo, end - 1))


def paths(a: Arrays, walks: list[str], first: np.ndarray, p: Params) -> np.ndarray:
    """Node numbers of all walks by step, -1 after a walk's end; ``first`` are numbers of nodes, -1 for isolated ones."""
    out = np.full((len(walks), p.walk_length), -1, dtype=np.int32)
    out[:, 0] = first
    alive, names = np.flatnonzero(first >= 0), np.array([w.encode() for w in walks], dtype=bytes)
    of_columns = np.array(sorted(a.columns), dtype=np.int64)
    at = first[alive].astype(np.int64)
    for k in range(1, p.walk_length):
        of_record, evenly = a.record_start[at + 1] > a.record_start[at], a.even_start[at + 1] > a.even_start[at]
        column = of_columns[np.minimum(np.searchsorted(of_columns, at), len(of_columns) - 1)] == at if len(of_columns) else np.zeros(len(at), dtype=bool)
        go = of_record | evenly | column
        alive, at, of_record, column = alive[go], at[go], of_record[go], column[go]
        u, to = _draws(p, "hop", names[alive], k), np.full(len(at), -1, dtype=np.int64)
        to[of_record] = a.record[_weighted(a.record_start[at[of_record]], a.record_start[at[of_record] + 1], a.sums, u[of_record])]
        rest = ~of_record
        where = np.flatnonzero(column & rest)
        if len(where):
            share = _draws(p, "class", names[alive[where]], k)
            for x in np.unique(at[where]):
                mass, dsts, sums = a.columns[int(x)]
                i = where[(at[where] == x) & (share < mass)]
                to[i] = dsts[np.minimum(np.searchsorted(sums, u[i] * sums[-1], "right"), len(dsts) - 1) if sums[-1] else (u[i] * len(dsts)).astype(np.int64)]
        rest &= to < 0
        size = a.even_start[at[rest] + 1] - a.even_start[at[rest]]
        place = a.even_start[at[rest]] + (u[rest] * size).astype(np.int64)
        to[rest] = np.where(size > 0, a.even[np.where(size > 0, place, 0)] if len(a.even) else -1, -1)
        alive, at = alive[to >= 0], to[to >= 0]
        out[alive, k] = at
    return out


def walks_on_arrays(spark: SparkSession, first: DataFrame, t: Transitions, p: Params) -> DataFrame:
    """The same walks on broadcast arrays; the caller has checked their size."""
    shipped = spark.sparkContext.broadcast(arrays_of(t))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a = shipped.value
        for batch in batches:
            node = batch.column("node").to_numpy()
            number = np.minimum(np.searchsorted(a.ids, node), max(0, len(a.ids) - 1))
            known = a.ids[number] == node if len(a.ids) else np.zeros(len(node), dtype=bool)
            got = paths(a, batch.column("walk_id").to_pylist(), np.where(known, number, -1), p)
            walk, step = np.nonzero(got >= 0)
            # an isolated node is its own walk
            alone = np.flatnonzero(~known)
            ids = batch.column("walk_id").take(pa.array(np.concatenate([walk, alone])))
            nodes = np.concatenate([a.ids[got[walk, step]] if len(walk) else np.zeros(0, dtype=np.int64), node[alone]])
            yield pa.RecordBatch.from_arrays([ids, pa.array(np.concatenate([step, np.zeros(len(alone))]).astype(np.int32)), pa.array(nodes)], names=["walk_id", "step", "node_id"])

    return first.select("walk_id", "node").repartition(spark.sparkContext.defaultParallelism).mapInArrow(run, "walk_id string, step int, node_id long")


def numbers(a: Arrays, node: np.ndarray) -> np.ndarray:
    number = np.minimum(np.searchsorted(a.ids, node), max(0, len(a.ids) - 1))
    return np.where(a.ids[number] == node, number, -1) if len(a.ids) else np.full(len(node), -1)


def pairs_of_few(spark: SparkSession, first: DataFrame, t: Transitions, p: Params, centers: list[int]) -> DataFrame:
    """(center, context, n) of the walks' pairs whose centre is one of a few nodes; centre null: all pairs of the context.

    Walks are counted where they are made, so no step leaves its task.
    """
    shipped = spark.sparkContext.broadcast(arrays_of(t))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a = shipped.value
        n = len(a.ids)
        place = np.full(n, -1, dtype=np.int64)
        number = numbers(a, np.array(centers, dtype=np.int64))
        place[number[number >= 0]] = np.flatnonzero(number >= 0)
        every, few = np.zeros(n, dtype=np.int64), np.zeros(len(centers) * n, dtype=np.int32)
        for batch in batches:
            got = paths(a, batch.column("walk_id").to_pylist(), numbers(a, batch.column("node").to_numpy()), p)
            keys = []
            for d in range(1, min(p.window, p.walk_length - 1) + 1):
                x, y = got[:, :-d], got[:, d:]
                both = y >= 0
                x, y = x[both], y[both]
                for c, o in ((x, y), (y, x)):
                    every += np.bincount(o, minlength=n)
                    here = place[c] >= 0
                    keys.append(place[c[here]] * n + o[here])
            found, count = np.unique(np.concatenate(keys), return_counts=True)
            few[found] += count.astype(np.int32)
        met, seen = np.flatnonzero(few), np.flatnonzero(every)
        center = pa.concat_arrays([pa.array(np.array(centers, dtype=np.int64)[met // max(1, n)]), pa.nulls(len(seen), pa.int64())])
        yield pa.RecordBatch.from_arrays([center, pa.array(a.ids[np.concatenate([met % max(1, n), seen])]), pa.array(np.concatenate([few[met], every[seen]]).astype(np.int64))], names=["center", "context", "n"])

    parts = first.select("walk_id", "node").repartition(spark.sparkContext.defaultParallelism).mapInArrow(run, "center long, context long, n long")
    return parts.groupBy("center", "context").agg(F.sum("n").alias("n"))


def _columns(ends: list[tuple], ids: np.ndarray, n_tok: np.ndarray, p: Params) -> dict[int, tuple[float, np.ndarray, np.ndarray]]:
    """``Arrays.columns`` from the edges of columns and how many tokens each node has as a column."""
    columns = {}
    for a in {x for e in ends for x in e[:2]}:
        lst = sorted([(b, x) for e, b, x in ends if e == a] + [(e, x) for e, b, x in ends if b == a])
        i, mass = int(np.searchsorted(ids, a)), sum(x for _, x in lst)
        if p.cid_edge_mass == "unit":
            share = mass / (n_tok[i] + mass) if n_tok[i] + mass > 0 else 0.0
        else:
            share = 0.0 if mass == 0 else p.cid_share if n_tok[i] else 1.0
        columns[i] = (float(share), np.searchsorted(ids, [b for b, _ in lst]), np.cumsum([x for _, x in lst]))
    return columns


def arrays_of_graph(g: Graph, p: Params, weights: DataFrame | None) -> Arrays:
    """``arrays_of`` the graph's transitions, put in order from the bare edges; the caller has checked their number."""
    node = lambda kind, c, name: node_id(kind, F.col(c)).alias(name)
    longs = lambda df: [c.to_numpy() for c in df.toArrow().columns]
    r, rt = longs(g.rid_tok.select(node("R", "rid", "r"), node("T", "tok", "t")))
    t, c, mult = longs(g.tok_cid.select(node("T", "tok", "t"), node("C", "cid", "c"), "mult"))
    ends = [tuple(e) for e in g.cid_cid.select(node("C", "left_cid", "a"), node("C", "right_cid", "b"), "weight").collect()]
    ids = np.unique(np.concatenate([r, rt, t, c, np.array([x for e in ends for x in e[:2]], dtype=np.int64)]))
    r, rt, t, c = (np.searchsorted(ids, x).astype(np.int32) for x in (r, rt, t, c))
    src, dst = np.concatenate([rt, t, c]), np.concatenate([r, c, t])
    even_start, even = _starts(src, len(ids)), dst[np.lexsort((dst, ids[dst] % _BUCKETS, src))]
    w = np.ones(len(r))
    if weights is not None and p.weighted:
        of = np.full(len(ids), np.nan)
        for x in weights.select(node("C", "cid", "c"), "w").collect():
            of[ids == x["c"]] = x["w"]
        known = ~np.isnan(of[c])
        with np.errstate(invalid="ignore"):
            mean = np.bincount(t[known], mult[known] * of[c[known]], len(ids)) / np.bincount(t[known], mult[known], len(ids))
        r, rt = r[~np.isnan(mean[rt])], rt[~np.isnan(mean[rt])]
        w = mean[rt]
    by = np.lexsort((rt, r))
    record_start = _starts(r, len(ids))
    return Arrays(ids, even_start, even, record_start, rt[by], _running(w[by], record_start), _columns(ends, ids, np.bincount(c, minlength=len(ids)), p))


def ordered_arrays(g: Graph, p: Params, weights: DataFrame | None) -> Arrays:
    """``arrays_of_graph`` of larger graphs: edges are put in order and numbered by the tasks, and the driver takes the finished lists."""
    node = lambda kind, c, name: node_id(kind, F.col(c)).alias(name)
    rt = written(g.rid_tok.select(node("R", "rid", "r"), node("T", "tok", "t")))
    tc = written(g.tok_cid.select(node("T", "tok", "t"), node("C", "cid", "c"), "mult"))
    ends = [tuple(e) for e in g.cid_cid.select(node("C", "left_cid", "a"), node("C", "right_cid", "b"), "weight").collect()]
    every = rt.select("r").union(rt.select("t")).union(tc.select("t")).union(tc.select("c")).distinct()
    ids = np.unique(np.concatenate([every.toArrow().column(0).to_numpy(), np.array([x for e in ends for x in e[:2]], dtype=np.int64)]))
    shipped = rt.sparkSession.sparkContext.broadcast(ids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = shipped.value
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(np.searchsorted(ids, batch.column("x").to_numpy()).astype(np.int32)), batch.column("n")], names=["x", "n"])

    def numbered(df: DataFrame, x: str, n: Column, kind: str) -> list[np.ndarray]:
        got = df.select(F.col(x).alias("x"), n.cast(kind).alias("n")).mapInArrow(run, f"x int, n {kind}").toArrow()
        out = [c.to_numpy() for c in got.columns]
        # the driver is to hold little
        del got
        pa.default_memory_pool().release_unused()
        return out

    def lists(edges: DataFrame, *order: Column | str) -> tuple[np.ndarray, np.ndarray]:
        edges = edges.toDF("src", "dst")
        size, (at, n) = np.zeros(len(ids) + 1, dtype=np.int64), numbered(edges.groupBy("src").agg(F.count(F.lit(1)).alias("n")), "src", F.col("n"), "int")
        size[at + 1] = n
        return np.cumsum(size, out=size), numbered(edges.orderBy("src", *order, "dst"), "dst", F.lit(0), "tinyint")[0]

    even_start, even = lists(rt.select("t", "r").union(tc.select("t", "c")).union(tc.select("c", "t")), F.pmod("dst", F.lit(_BUCKETS)))
    record_start, record = lists(rt.select("r", "t"))
    weight = np.ones(len(ids))
    if weights is not None and p.weighted:
        of_column = tc.join(F.broadcast(weights.select(node("C", "cid", "c"), "w")), "c")  # few columns
        at, w = numbered(of_column.groupBy("t").agg((F.sum(F.col("mult") * F.col("w")) / F.sum("mult")).alias("w")), "t", F.col("w"), "double")
        weight = np.full(len(ids), np.nan)
        weight[at] = w
        known = ~np.isnan(weight)[record]
        if not known.all():
            record_start, record = np.concatenate([[0], np.cumsum(known)])[record_start], record[known]
    n_tok = np.zeros(len(ids), dtype=np.int64)
    for x in tc.groupBy("c").count().collect():
        n_tok[np.searchsorted(ids, x["c"])] = x["count"]
    shipped.destroy()
    return Unsummed(ids, even_start, even, record_start, record, np.zeros(0), _columns(ends, ids, n_tok, p), weight)


def pairs_of_columns(spark: SparkSession, shipped: Broadcast, p: Params) -> DataFrame:
    """(center, context, n) as of ``pairs_of_few``, by number, of walks from every node of large graphs.

    Centres are places in a list of nodes, -1 for all pairs of the context.  ``shipped`` holds the arrays and the list.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, centers = shipped.value
        n = len(a.ids)
        place = np.full(n, -1, dtype=np.int8 if len(centers) < 128 else np.int32)
        place[centers] = np.arange(len(centers))
        counts = np.zeros((len(centers) + 1, n), dtype=np.int32)  # the last row: of all pairs
        flat = counts.reshape(-1)
        for batch in batches:
            for lo in range(0, batch.num_rows, 2048):
                first = np.repeat(batch.column("id").to_numpy()[lo : lo + 2048], p.walks_per_node)
                got = paths(a, [f"{x}:{k}" for x in a.ids[first[:: p.walks_per_node]] for k in range(p.walks_per_node)], first, p)
                there = got >= 0
                center, partners = np.where(there, place[got], -1), np.zeros(got.shape, dtype=np.int32)
                for d in range(1, min(p.window, p.walk_length - 1) + 1):
                    both = there[:, d:]  # walks have no holes
                    partners[:, :-d] += both
                    partners[:, d:] += both
                    for c, o in ((center[:, :-d], got[:, d:]), (center[:, d:], got[:, :-d])):
                        here = (c >= 0) & both
                        np.add.at(flat, c[here].astype(np.int64) * n + o[here], 1)
                np.add.at(counts[-1], got[there], partners[there])
        for k in range(len(centers) + 1):
            met = np.flatnonzero(counts[k])
            for lo in range(0, len(met), 200_000):
                some = met[lo : lo + 200_000]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), k if k < len(centers) else -1, dtype=np.int32)), pa.array(some.astype(np.int32)), pa.array(counts[k, some].astype(np.int64))], names=["center", "context", "n"])

    return spark.range(0, len(shipped.value[0].ids), 1, spark.sparkContext.defaultParallelism).mapInArrow(run, "center int, context int, n long")


def counted(found: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Keys and their counts added up."""
    key, n = (np.concatenate(x) if x else np.zeros(0, dtype=np.int64) for x in (list(z) for z in (zip(*found, strict=True) if found else ((), ()))))
    if not len(key):
        return key, n
    by = np.argsort(key, kind="stable")
    key, n = key[by], n[by]
    first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    return key[first], np.add.reduceat(n, first)


def pairs_on_arrays(spark: SparkSession, shipped: Broadcast, p: Params, parts: int) -> DataFrame:
    """(center, context, n) by node number, of walks from every node; centres are records and columns.

    Centre -1: all pairs of the context.  ``shipped`` holds the arrays and a mark for each centre.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, wanted = shipped.value
        n = len(a.ids)
        every, found, held = np.zeros(n, dtype=np.int64), [], 0
        for batch in batches:
            for lo in range(0, batch.num_rows, 4096):
                first = np.repeat(batch.column("id").to_numpy()[lo : lo + 4096], p.walks_per_node)
                names = [f"{x}:{k}" for x in a.ids[first[:: p.walks_per_node]] for k in range(p.walks_per_node)]
                got = paths(a, names, first, p)
                for d in range(1, min(p.window, p.walk_length - 1) + 1):
                    x, y = got[:, :-d], got[:, d:]
                    x, y = x[y >= 0].astype(np.int64), y[y >= 0].astype(np.int64)
                    every += np.bincount(x, minlength=n) + np.bincount(y, minlength=n)
                    keys = np.concatenate([c[wanted[c]] * n + o[wanted[c]] for c, o in ((x, y), (y, x))])
                    found.append((keys, np.ones(len(keys), dtype=np.int64)))
                    held += len(keys)
                if held > 4_000_000:
                    found = [counted(found)]
                    held = len(found[0][0]) // 2
        key, count = counted(found)
        for lo in range(0, len(key), 200_000):
            k = key[lo : lo + 200_000]
            yield pa.RecordBatch.from_arrays([pa.array((k // n).astype(np.int32)), pa.array((k % n).astype(np.int32)), pa.array(count[lo : lo + 200_000])], names=["center", "context", "n"])
        seen = np.flatnonzero(every)
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(seen), -1, dtype=np.int32)), pa.array(seen.astype(np.int32)), pa.array(every[seen])], names=["center", "context", "n"])

    return spark.range(0, len(shipped.value[0].ids), 1, parts).mapInArrow(run, "center int, context int, n long")


def trained_on_arrays(spark: SparkSession, shipped: Broadcast, p: Params, parts: int) -> DataFrame:
    """``embed.TRAINED`` rows of the skip-gram, of walks from every node that are made where they are trained on.

    ``shipped`` holds the arrays and a mark for each node whose vector is wanted.
    """
    from linkgraph.operators.embed import TRAINED, skipgram, trained_rows

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, wanted = shipped.value
        made = []
        for batch in batches:
            first = np.repeat(batch.column("id").to_numpy(), p.walks_per_node)
            made.append(paths(a, [f"{x}:{k}" for x in a.ids[first[:: p.walks_per_node]] for k in range(p.walks_per_node)], first, p))
        if not made:
            return
        got = np.concatenate(made)
        there = got >= 0
        met, place, n = np.unique(got[there], return_inverse=True, return_counts=True)
        got[there] = place
        vecs, keep = skipgram(got, a.ids[met], p), wanted[met]
        yield from trained_rows(a.ids[met[keep]], n[keep], vecs[keep])

    return spark.range(0, len(shipped.value[0].ids), 1, parts).mapInArrow(run, TRAINED)


def fits_arrays(g: Graph, p: Params, times: int = 1) -> bool:
    return g.rid_tok.count() + 2 * g.tok_cid.count() <= times * p.local_edges


def random_walks(spark: SparkSession, g: Graph, nodes: DataFrame, p: Params, weights: DataFrame | None, strategy: str = "auto", per_kind: dict[str, float] | None = None) -> DataFrame:
    """(walk_id, step, node_id) of all walks; "auto" takes arrays where the graph fits them, joins beyond.

    Edges that are not cached are written first, as counts, lists and hops each read them.
    """
    g = Graph(g.rids, *[df if df.is_cached else written(df) for df in (g.rid_tok, g.tok_cid)], g.cids, g.cid_cid)
    first = starts(nodes, p, per_kind)
    if strategy == "auto" and fits_arrays(g, p):
        return walks_on_arrays(spark, first, transitions(spark, g, p, weights), p)
    return walks_by_joins(first, transitions(spark, g, p, weights, written), p)


def weights_of(spark: SparkSession, pair: TablePair, p: Params, prof: DataFrame | None = None) -> DataFrame:
    prof = colsim.profile(pair) if prof is None else prof
    return importance.column_weights(importance.scores(prof, importance.name_frequencies(spark), p), p)


def walk_stats(walks: DataFrame, nodes: DataFrame) -> DataFrame:
    """Visits by kind, and hops by pair of kinds."""
    seen = walks.join(nodes.select("node_id", "kind"), "node_id")
    nxt = seen.withColumn("to", F.lead("kind").over(Window.partitionBy("walk_id").orderBy("step")))
    visits = seen.groupBy("kind").agg(F.count(F.lit(1)).alias("n")).select(F.concat(F.lit("visit "), "kind").alias("what"), "n")
    return visits.union(nxt.filter("to is not null").groupBy(F.concat(F.lit("hop "), "kind", "to").alias("what")).agg(F.count(F.lit(1)).alias("n")))

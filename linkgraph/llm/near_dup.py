"""Near-duplicate documents: MinHash with tensored banding, exact confirmation.

Two small collections of sub-keys (``subkeys`` of ``per_subkey`` hashes each)
are combined pairwise into ``subkeys**2`` table keys, so that the number of
minhashes grows like the square root of the number of tables.  A document whose
sub-keys are all its own in either collection can collide in no table and emits
no table key at all.

Inside a table the members are not paired with each other.  In a few quick
rounds every document is confirmed against one leader only, the one it shares
most tables with.  Tables whose members all are in one component are then done.
Documents of the others meet in blocks, where each pair of different components
that collides in some table is compared once.  Whole sets are compared
exactly, and of the links among them a spanning forest over components leaves
the block: the others tie nothing that the forest does not.  Sets that are longer
are judged by bottom-k sketches, and all their near pairs leave.  What leaves is
confirmed on full shingle sets recomputed from the texts.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linkgraph.llm.common import as_long, join_spread, materialise, mix, row_slices, text_bytes
from linkgraph.llm.components import connected_components
from linkgraph.llm.shingles import WIDTH, shingle_sets


@dataclass(frozen=True)
class NearDupParams:
    width: int = WIDTH
    #: Similarity threshold as a ratio of integers: intersection * den >= num * union.
    num: int = 75
    den: int = 100
    #: Sub-keys in each of the two collections, and minhashes in each sub-key.
    #: At the threshold a pair is missed with probability 2 * (1 - 0.75**2)**14 < 2e-5.
    subkeys: int = 14
    per_subkey: int = 2
    #: Rounds against one leader each, before the exhaustive one.
    quick_rounds: int = 3
    #: Smallest hashes of a set that a block compares (short sets are whole), and
    #: how many of them longer sets must share to be compared in full: a pair at
    #: the threshold shares 384 of 512 on average, under 343 with probability 2e-5.
    sketch: int = 512
    sketch_least: int = 343
    #: Members of a bucket that one block compares with as many others.
    block: int = 1024
    seed: int = 20240501


def _signatures(params: NearDupParams):
    """Arrow batches of (doc_id, text) to shingle counts, set fingerprints and sub-keys."""
    n_hash = 2 * params.subkeys * params.per_subkey
    seeds = mix(np.arange(params.seed, params.seed + n_hash, dtype=np.uint64)) | np.uint64(1)
    adds = mix(seeds)
    schema = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("fp_a", pa.int64()), ("fp_b", pa.int64()), ("keys", pa.list_(pa.int64()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = text_bytes(batch.column("text"))
            ids = batch.column("doc_id")
            for lo, hi in row_slices(offsets):
                values, counts = shingle_sets(data, offsets[lo : hi + 1], params.width)
                some = np.flatnonzero(counts)
                at = (np.cumsum(counts) - counts)[some]
                n = hi - lo
                fp_a, fp_b = np.zeros(n, np.uint64), np.zeros(n, np.uint64)
                keys = np.zeros((n, 2 * params.subkeys), np.uint64)
                if len(some):
                    fp_a[some] = np.add.reduceat(mix(values ^ np.uint64(0xA5A5A5A5A5A5A5A5)), at)
                    fp_b[some] = np.bitwise_xor.reduceat(mix(values + np.uint64(0x1234567)), at)
                    for k in range(n_hash):
                        h = (values ^ (values >> np.uint64(29))) * seeds[k] + adds[k]
                        h ^= h >> np.uint64(32)
                        low = np.minimum.reduceat(h, at)
                        slot = k // params.per_subkey
                        keys[some, slot] = mix(keys[some, slot] * np.uint64(31) + low + np.uint64(slot + 1))
                yield pa.RecordBatch.from_arrays(
                    [
                        ids.slice(lo, n).cast(pa.int64()),
                        pa.array(counts.astype(np.int64)),
                        pa.array(as_long(fp_a)),
                        pa.array(as_long(fp_b)),
                        pa.FixedSizeListArray.from_arrays(pa.array(as_long(keys.reshape(-1))), 2 * params.subkeys).cast(pa.list_(pa.int64())),
                    ],
                    schema=schema,
                )

    return run


def signatures(docs: DataFrame, params: NearDupParams = NearDupParams()) -> DataFrame:
    return docs.select("doc_id", "text").mapInArrow(_signatures(params), "doc_id long, n_shingles long, fp_a long, fp_b long, keys array<long>")


def _confirmed(params: NearDupParams):
    """Pairs whose full shingle sets are at least as similar as the threshold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept_id, kept_set = None, None
        for batch in batches:
            left, left_at = text_bytes(batch.column("x_text"))
            right, right_at = text_bytes(batch.column("y_text"))
            xs = batch.column("x").to_numpy(zero_copy_only=False)
            good = np.zeros(len(xs), bool)
            for i, x in enumerate(xs):
                if kept_id is None or kept_id != x:
                    kept_id, kept_set = x, shingle_sets(left, left_at[i : i + 2], params.width)[0]
                other = shingle_sets(right, right_at[i : i + 2], params.width)[0]
                both = len(np.intersect1d(kept_set, other, assume_unique=True))
                good[i] = both * params.den >= params.num * (len(kept_set) + len(other) - both)
            yield pa.RecordBatch.from_arrays([batch.column("x"), batch.column("y"), pa.array(good)], names=["x", "y", "linked"])

    return run


def confirm(pairs: DataFrame, docs: DataFrame, params: NearDupParams = NearDupParams()) -> DataFrame:
    """``(x, y, linked)`` for each pair, from the full sets of both texts."""
    texts = docs.select("doc_id", "text")
    joined = pairs.join(texts.select(F.col("doc_id").alias("y"), F.col("text").alias("y_text")), "y").join(
        texts.select(F.col("doc_id").alias("x"), F.col("text").alias("x_text")), "x"
    )
    return joined.select("x", "y", "x_text", "y_text").mapInArrow(_confirmed(params), "x long, y long, linked boolean")


def table_keys(classes: DataFrame, params: NearDupParams) -> DataFrame:
    """``(tkey, doc, n)``: tensored keys of documents that can collide at all."""
    sub = classes.select("doc", "n", F.posexplode("keys").alias("slot", "skey"))
    shared = sub.groupBy("slot", "skey").agg(F.count(F.lit(1)).alias("c")).filter("c > 1").select("slot", "skey")
    live = (
        sub.join(shared, ["slot", "skey"])
        .groupBy("doc", "n")
        .agg(
            F.collect_list(F.when(F.col("slot") < params.subkeys, F.col("skey"))).alias("first"),
            F.collect_list(F.when(F.col("slot") >= params.subkeys, F.col("skey"))).alias("second"),
        )
        .filter("size(first) > 0 and size(second) > 0")
    )
    keys = live.select("doc", "n", F.explode("first").alias("p"), "second").select("doc", "n", "p", F.explode("second").alias("q"))
    return keys.select(F.xxhash64("p", "q").alias("tkey"), "doc", "n")


def _still_open(rows: DataFrame, label: DataFrame) -> DataFrame:
    """Members of tables that hold more than one component, with their labels."""
    now = rows.select("tkey", "doc", "n").join(label, F.col("doc") == F.col("node"), "left").select("tkey", "doc", "n", F.coalesce("component", "doc").alias("lab"))
    split = now.groupBy("tkey").agg(F.min("lab").alias("lo"), F.max("lab").alias("hi")).filter("lo <> hi").select("tkey", "lo")
    return materialise(now.join(split, "tkey"), "open")


def _one_leader_each(rows: DataFrame, turn: int) -> DataFrame:
    """Each document with the leader that it shares most tables with.

    A table's leader is a member of its smallest component, another one in each
    turn; members of that component need no leader.
    """
    rank = F.struct((F.col("lab") != F.col("lo")).alias("other"), F.xxhash64("doc", F.lit(turn)).alias("h")) if turn else F.struct((F.col("lab") != F.col("lo")).alias("other"), F.col("doc").alias("h"))
    lead = rows.groupBy("tkey").agg(F.min_by("doc", rank).alias("p"))
    shared = rows.filter("lab <> lo").join(lead, "tkey").groupBy("doc", "p").agg(F.count(F.lit(1)).alias("c"))
    best = shared.groupBy("doc").agg(F.max(F.struct("c", (-F.col("p")).alias("q"))).alias("b")).select("doc", (-F.col("b.q")).alias("p"))
    return best.select(F.least("doc", "p").alias("x"), F.greatest("doc", "p").alias("y")).distinct()


def _sketches(params: NearDupParams):
    """Arrow batches of (doc_id, text) to the smallest shingle hashes of each text, in order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = text_bytes(batch.column("text"))
            for lo, hi in row_slices(offsets):
                values, counts = shingle_sets(data, offsets[lo : hi + 1], params.width)
                take = np.minimum(counts, params.sketch)
                ends = np.cumsum(take)
                at = np.repeat(np.cumsum(counts) - counts - (ends - take), take) + np.arange(int(take.sum()))
                low = pa.ListArray.from_arrays(pa.array(np.append(0, ends).astype(np.int32)), pa.array((values[at] >> np.uint64(1)).astype(np.int64)))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(lo, hi - lo).cast(pa.int64()), low], names=["doc", "low"])

    return run


def _colliding(rows: pa.Table, params: NearDupParams) -> tuple[np.ndarray, np.ndarray]:
    """Places of pairs of a block that collide in a table, in its first common bucket.

    Both sides must differ in component and agree in some sub-key of either
    collection; the size ratio must allow the threshold.
    """
    slot, a, b = (rows.column(c)[0].as_py() for c in ("slot", "a", "b"))
    lab, n, part = (rows.column(c).to_numpy() for c in ("lab", "n", "part"))
    keys = rows.column("keys").combine_chunks().flatten().to_numpy().reshape(len(n), -1)
    whole = np.arange(len(n))
    left, right = (whole, whole) if a == b else (whole[part == a], whole[part == b])
    found = [(whole[:0], whole[:0])]
    for at in range(0, len(left), 256):
        i = left[at : at + 256]
        ok = lab[i][:, None] != lab[right]
        ok &= np.minimum(n[i][:, None], n[right]) * params.den >= np.maximum(n[i][:, None], n[right]) * params.num
        if a == b:
            ok &= i[:, None] < right
        if not ok.any():
            continue
        for t in range(slot):
            ok &= keys[i, t][:, None] != keys[right, t]
        second = np.zeros_like(ok)
        for t in range(params.subkeys, 2 * params.subkeys):
            second |= keys[i, t][:, None] == keys[right, t]
        r, c = np.nonzero(ok & second)
        found.append((i[r], right[c]))
    return np.concatenate([x for x, _ in found]), np.concatenate([y for _, y in found])


def _common(p: np.ndarray, q: np.ndarray, starts: np.ndarray, values: np.ndarray) -> np.ndarray:
    """How many values the lists of each pair share."""
    if len(p) <= 32:
        return np.array([len(np.intersect1d(values[starts[i] : starts[i + 1]], values[starts[j] : starts[j + 1]])) for i, j in zip(p, q, strict=True)], np.int64)
    _, code, times = np.unique(values, return_inverse=True, return_counts=True)
    owner = np.repeat(np.arange(len(starts) - 1), np.diff(starts))
    # values of one list only are in no intersection
    rank = np.cumsum(times > 1) - 1
    more = times[code] > 1
    code, owner = rank[code[more]], owner[more]
    order = np.argsort(code, kind="stable")
    code, owner = code[order], owner[order]
    rows, p_at = np.unique(p, return_inverse=True)
    cols, q_at = np.unique(q, return_inverse=True)
    place = np.full((2, len(starts) - 1), -1)
    place[0, rows], place[1, cols] = np.arange(len(rows)), np.arange(len(cols))
    total = np.zeros((len(rows), len(cols)), np.float32)
    width = 4096
    for lo in range(0, int(code[-1]) + 1 if len(code) else 0, width):
        some = slice(*np.searchsorted(code, [lo, lo + width]))
        sides = []
        for side, size in ((0, len(rows)), (1, len(cols))):
            where = place[side, owner[some]]
            grid = np.zeros((size, width), np.float32)
            grid[where[where >= 0], code[some][where >= 0] - lo] = 1
            sides.append(grid)
        total += sides[0] @ sides[1].T
    return total[p_at, q_at].astype(np.int64)


def _forest(a: np.ndarray, b: np.ndarray, rank: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """Places of the edges (a, b) of nodes below ``size`` that make a spanning forest, and each node's tree.

    Edges of the least rank come first, so that forests of blocks that share
    edges choose the same ones.
    """
    order = np.argsort(rank, kind="stable")
    code = np.minimum(a, b) * size + np.maximum(a, b)
    order = order[np.sort(np.unique(code[order], return_index=True)[1])]
    root = list(range(size))

    def top(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    kept = []
    for e, i, j in zip(order.tolist(), a[order].tolist(), b[order].tolist(), strict=True):
        i, j = top(i), top(j)
        if i != j:
            root[j] = i
            kept.append(e)
    return np.array(kept, np.int64), np.array([top(i) for i in range(size)], np.int64)


def _near_in_block(rows: pa.Table, params: NearDupParams) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of a block that tie its components: a forest of the links of whole sets, all that may be links of longer ones."""
    doc, n, lab = (rows.column(c).to_numpy() for c in ("doc", "n", "lab"))
    p, q = _colliding(rows, params)
    if not len(p):
        return p, q
    low = rows.column("low").combine_chunks()
    starts, values = np.asarray(low.offsets).astype(np.int64), low.flatten().to_numpy()
    starts = starts - starts[0]
    both = _common(p, q, starts, values)
    # of a cut list only hashes up to its last one can be judged
    last = np.where(n > params.sketch, values[starts[1:] - 1], np.iinfo(np.int64).max)
    sizes = np.empty((2, len(p)), np.int64)
    for k, (mine, other) in enumerate(((p, q), (q, p))):
        sizes[k] = n[mine]
        cut = np.flatnonzero((n[mine] > params.sketch) | (n[other] > params.sketch))
        for i in np.unique(mine[cut]):
            at = cut[mine[cut] == i]
            sizes[k, at] = np.searchsorted(values[starts[i] : starts[i + 1]], last[other[at]], side="right")
    union = sizes[0] + sizes[1] - both
    cut = (n[p] > params.sketch) | (n[q] > params.sketch)
    good = np.where(cut, (both + 1) * params.sketch >= params.sketch_least * (union - 1), both * params.den >= params.num * union)
    p, q, cut = p[good], q[good], cut[good]
    names, at = np.unique(lab, return_inverse=True)
    sure = np.flatnonzero(~cut)
    x, y = doc[p[sure]], doc[q[sure]]
    rank = mix(np.minimum(x, y).view(np.uint64) * np.uint64(31) + np.maximum(x, y).view(np.uint64))
    kept, tree = _forest(at[p[sure]], at[q[sure]], rank, len(names))
    out = np.append(sure[kept], np.flatnonzero(cut & (tree[at[p]] != tree[at[q]])))
    return doc[p[out]], doc[q[out]]


def _blocks(params: NearDupParams):
    """Rows ordered by (slot, skey, a, b) to the near pairs of each block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        at = None

        def done() -> Iterator[pa.RecordBatch]:
            x, y = _near_in_block(pa.Table.from_batches(held), params)
            if len(x):
                yield pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y))], names=["x", "y"])

        for batch in batches:
            if not batch.num_rows:
                continue
            block = np.stack([batch.column(c).to_numpy() for c in ("slot", "skey", "a", "b")])
            cuts = np.flatnonzero((block[:, 1:] != block[:, :-1]).any(axis=0)) + 1
            for lo, hi in zip([0, *cuts], [*cuts, batch.num_rows], strict=True):
                if held and at != tuple(block[:, lo]):
                    yield from done()
                    held = []
                at = tuple(block[:, lo])
                held.append(batch.slice(lo, hi - lo))
        if held:
            yield from done()

    return run


def _all_across(open_rows: DataFrame, reps: DataFrame, base: DataFrame, params: NearDupParams) -> DataFrame:
    """Pairs in different components that share a table and may reach the threshold.

    Two documents share a table exactly if they share a sub-key of the first
    collection and one of the second.  So they meet by sub-keys of the first,
    in at most ``subkeys`` rows a document.  Large buckets are cut into parts,
    and each two parts are a block of their own.
    """
    docs = open_rows.groupBy("doc").agg(F.min("lab").alias("lab"))
    low = base.join(docs.select(F.col("doc").alias("doc_id")), "doc_id", "left_semi")
    low = low.select("doc_id", "text").mapInArrow(_sketches(params), "doc long, low array<long>").filter("size(low) > 0").dropDuplicates(["doc"])
    full = materialise(reps.join(docs, "doc").join(low, "doc"), "sketches")
    sub = full.select("doc", "lab", F.posexplode(F.slice("keys", 1, params.subkeys)).alias("slot", "skey"))
    split = sub.groupBy("slot", "skey").agg(F.count(F.lit(1)).alias("c"), F.min("lab").alias("lo"), F.max("lab").alias("hi")).filter("lo <> hi")
    parts = split.select("slot", "skey", F.ceil(F.col("c") / params.block).cast("int").alias("parts"))
    met = sub.select("doc", "slot", "skey").join(parts, ["slot", "skey"]).withColumn("part", F.pmod(F.xxhash64("doc"), F.col("parts")).cast("int"))
    met = met.withColumn("with", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    met = met.select("doc", "slot", "skey", "part", F.least("part", "with").alias("a"), F.greatest("part", "with").alias("b"))
    rows = met.join(full, "doc").select("slot", "skey", "a", "b", "part", "doc", "lab", "n", "keys", "low")
    block = ["slot", "skey", "a", "b"]
    return rows.repartition(*block).sortWithinPartitions(*block).mapInArrow(_blocks(params), "x long, y long").distinct()


def _merged(label: DataFrame, links: DataFrame) -> DataFrame:
    """Labels after more links: components of the old labels that links tie."""
    end = lambda side: label.select(F.col("node").alias(side), F.col("component").alias(f"{side}_lab"))
    ties = links.join(end("x"), "x", "left").join(end("y"), "y", "left").select(F.coalesce("x_lab", "x").alias("a"), F.coalesce("y_lab", "y").alias("b"))
    moved = connected_components(ties).select(F.col("node").alias("was"), F.col("component").alias("is"))
    ends = links.select(F.explode(F.array("x", "y")).alias("node")).distinct().join(label, "node", "left_anti").select("node", F.col("node").alias("component"))
    return materialise(
        label.union(ends).join(moved, F.col("component") == F.col("was"), "left").select("node", F.coalesce("is", "component").alias("component")), "labels"
    )


def _components(base: DataFrame, params: NearDupParams) -> DataFrame:
    """(doc_id, n_shingles, component) for each row of ``base`` (doc_id, text), where equal ids have equal texts."""
    sig = materialise(signatures(base, params), "signatures")
    # Texts with equal sets are one class; its smallest document stands for it.
    by_set = ["fp_a", "fp_b", "n_shingles"]
    classes = sig.filter("n_shingles > 0").groupBy(*by_set).agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies"))
    shared = classes.filter("copies > 1").select(*by_set, "rep")
    members = materialise(
        sig.select("doc_id", *by_set)
        .join(shared, by_set, "left")
        .select("doc_id", "n_shingles", F.coalesce("rep", "doc_id").alias("rep"), (F.col("n_shingles") > 0).alias("worded")),
        "members",
    )
    firsts = members.filter("worded and doc_id = rep").select("doc_id").distinct()
    reps = sig.filter("n_shingles > 0").join(firsts, "doc_id", "left_semi").dropDuplicates(["doc_id"]).select(F.col("doc_id").alias("doc"), F.col("n_shingles").alias("n"), "keys")
    tables = materialise(table_keys(reps, params), "tables")
    label = reps.select(F.col("doc").alias("node"), F.col("doc").alias("component")).limit(0)
    tested = None
    open_rows = tables
    for turn in range(params.quick_rounds):
        open_rows = _still_open(open_rows, label)
        pairs = _one_leader_each(open_rows, turn)
        if tested is not None:
            pairs = pairs.join(tested, ["x", "y"], "left_anti")
        checked = materialise(confirm(pairs, base, params), "checked")
        tested = checked.select("x", "y") if tested is None else tested.union(checked.select("x", "y"))
        label = _merged(label, checked.filter("linked").select("x", "y"))
    open_rows = _still_open(open_rows, label)
    if not open_rows.isEmpty():
        pairs = materialise(_all_across(open_rows, reps, base, params).join(tested.distinct(), ["x", "y"], "left_anti"), "pairs")
        checked = materialise(confirm(pairs, base, params), "checked")
        label = _merged(label, checked.filter("linked").select("x", "y"))
    out = members.join(label, F.col("rep") == F.col("node"), "left")
    return out.select("doc_id", "n_shingles", F.coalesce("component", "rep").alias("component"))


def _keyed(docs: DataFrame) -> Column:
    """A key of a row's id and text: rows that repeat an id with another text are documents of their own."""
    return F.xxhash64(F.col("doc_id").cast("long"), F.col("text"))


def near_duplicates(docs: DataFrame, params: NearDupParams = NearDupParams()) -> DataFrame:
    """One row per row of ``docs``: doc_id, n_shingles, component_id, kept.

    ``component_id`` is the smallest doc_id reachable over confirmed links and
    ``kept`` says whether it is the document's own.  Documents without words
    (null or empty text) have no shingles and are linked with nothing.  Rows
    that repeat a doc_id give one row each, judged by its own text.  A null
    doc_id links others as any does, but names no component unless all ids of it
    are null; then the component is null and all its rows are kept.  Columns
    besides doc_id and text are ignored.
    """
    return _judged(docs, params).select("doc_id", "n_shingles", "component_id", "kept")


def _judged(docs: DataFrame, params: NearDupParams) -> DataFrame:
    """``near_duplicates`` with the key of each row."""
    base = docs.select(_keyed(docs).alias("rid"), F.col("doc_id").cast("long").alias("doc_id"), "text")
    found = _components(base.select(F.col("rid").alias("doc_id"), "text"), params).withColumnRenamed("doc_id", "rid").dropDuplicates(["rid"])
    rows = materialise(base.select("rid", "doc_id").join(found, "rid"), "judged")
    several = materialise(rows.groupBy("component").agg(F.min("doc_id").alias("component_id"), F.count(F.lit(1)).alias("size")).filter("size > 1"), "several")
    alone = rows.join(several.select("component"), "component", "left_anti").withColumn("component_id", F.col("doc_id"))
    out = join_spread(rows, several, ["component"], "size", rows.count()).drop("size").unionByName(alone)
    return out.withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def keep_first(docs: DataFrame, params: NearDupParams = NearDupParams()) -> DataFrame:
    """``docs`` with one document of each near-duplicate group, the smallest doc_id.

    Rows that repeat this doc_id, and rows of null doc_id where their group has
    no other, stay as well.  Other columns stay as they are.
    """
    verdict = _judged(docs, params).filter("kept").select(F.col("rid").alias("_kept")).distinct()
    return docs.join(verdict, _keyed(docs) == F.col("_kept"), "left_semi")


def op9_near_dup(spark, sf_dir: str) -> DataFrame:
    """Near duplicates over the whole of ``documents``."""
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))

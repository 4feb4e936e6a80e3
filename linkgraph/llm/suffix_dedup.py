"""Removal of byte strings of a given length that start more than once.

Suffixes are sorted only where a repeat is possible.  Of every window of
``length`` bytes the smallest hash of its ``gram``-byte pieces marks an anchor;
the choice depends on the window's bytes alone, so equal windows have equal
anchors.  The windows of a document that chose one anchor form a run.  An
anchor that occurs once has no repeated window; equal runs are counted, not
compared; the distinct runs of an anchor are sorted in both directions from the
anchor by deep-shallow suffix sorting, and the longest matches of each run with
the others follow from the two orders.

Groups of distinct runs beyond ``group_max`` are not sorted in one task: their
windows are counted one by one under their hashes, which spreads over all tasks.

The symbols of a text are its bytes or, to report passages that documents share,
its words.
"""

from __future__ import annotations

import hashlib
from bisect import bisect_left
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkgraph.llm.common import as_long, join_spread, materialise, mix, only_possible, powers, row_slices, text_bytes
from linkgraph.llm.shingles import word_hashes
from linkgraph.llm.suffix_sort import deep_shallow

#: Bits of a place within a slice that break ties of the anchor hash.
_PLACE_BITS = 26


@dataclass(frozen=True)
class SuffixDedupParams:
    #: Symbols of a repeated string, and of the pieces that mark anchors.
    length: int = 400
    gram: int = 200
    #: What a symbol is: "byte", or "word" (32 bits of its hash).
    unit: str = "byte"
    #: Whether only anchors that stand in several documents count.
    across: bool = False
    #: Distinct runs of an anchor that one task sorts at most.
    group_max: int = 20_000
    #: Bits of the filter that keeps texts out of joins they cannot match (bounded size).
    filter_bits: int = 24


#: Passages: strings of 50 words that several documents share.
PASSAGES = SuffixDedupParams(length=50, gram=25, unit="word", across=True)


def symbols(data: np.ndarray, offsets: np.ndarray, unit: str) -> tuple[np.ndarray, np.ndarray]:
    """The symbols of the rows and the offsets of the rows in them."""
    if unit == "byte":
        return data, offsets
    words, rows = word_hashes(data, offsets)
    return (words >> np.uint64(32)).astype(np.uint32), np.append(0, np.cumsum(rows))


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of every ``width`` neighbours, in a constant number of passes."""
    n = len(x)
    pad = -n % width
    full = np.append(x, np.full(pad, np.iinfo(np.uint64).max, np.uint64)).reshape(-1, width)
    ahead = np.minimum.accumulate(full, axis=1).reshape(-1)
    behind = np.minimum.accumulate(full[:, ::-1], axis=1)[:, ::-1].reshape(-1)
    return np.minimum(behind[: n - width + 1], ahead[width - 1 : n])


def runs_of(data: np.ndarray, offsets: np.ndarray, params: SuffixDedupParams) -> dict[str, np.ndarray]:
    """Row, first and last window, anchor place and hashes of every run; places count from the row's start."""
    lo, hi = int(offsets[0]), int(offsets[-1])
    ends = offsets - lo
    n, gram, length = hi - lo, params.gram, params.length
    if n < length:
        return {k: np.zeros(0, np.int64) for k in ("row", "p0", "p1", "a", "anchor", "run")}
    up, down = powers(n + 1), powers(n + 1, "down")
    sums = np.empty(n + 1, np.uint64)
    sums[0] = 0
    np.cumsum((data[lo:hi].astype(np.uint64) + np.uint64(1)) * up[:n], out=sums[1:])
    grams = mix((sums[gram:] - sums[:-gram]) * down[: n - gram + 1])
    place = np.arange(n - gram + 1, dtype=np.uint64)
    low = np.uint64((1 << max(_PLACE_BITS, n.bit_length())) - 1)  # one row may be longer than a slice
    best = sliding_min((grams & ~low) | place, length - gram + 1)
    p = np.arange(n - length + 1)
    row = np.searchsorted(ends, p, side="right") - 1
    inside = p + length <= ends[row + 1]
    p, row, a = p[inside], row[inside], (best[inside] & low).astype(np.int64)
    if not len(p):
        return {k: np.zeros(0, np.int64) for k in ("row", "p0", "p1", "a", "anchor", "run")}
    change = np.flatnonzero((np.diff(a) != 0) | (np.diff(p) != 1)) + 1
    first, last = np.append(0, change), np.append(change, len(p)) - 1
    p0, p1, a, row = p[first], p[last], a[first], row[first]
    whole = (sums[p1 + length] - sums[p0]) * down[p0]
    shape = ((p1 - p0) * 4096 + (a - p0)).astype(np.uint64)
    start = ends[row]
    return {"row": row, "p0": p0 - start, "p1": p1 - start, "a": a - start, "anchor": as_long(grams[a]), "run": as_long(mix(whole + shape * np.uint64(0x9E3779B97F4A7C15)))}


def _run_rows(params: SuffixDedupParams):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = text_bytes(batch.column("text"))
            ids = batch.column("rid").to_numpy()
            for lo, hi in row_slices(offsets):
                got = runs_of(*symbols(data, offsets[lo : hi + 1], params.unit), params)
                if len(got["row"]):
                    names = ["rid", "anchor", "run", "p0", "p1", "a"]
                    yield pa.RecordBatch.from_arrays([pa.array(ids[lo + got["row"]]), pa.array(got["anchor"]), pa.array(got["run"]), *(pa.array(got[c].astype(np.int32)) for c in ("p0", "p1", "a"))], names=names)

    return run


def _contents(params: SuffixDedupParams):
    """Symbols of each run asked for, as bytes: those before the anchor reversed, and from the anchor on."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = text_bytes(batch.column("text"))
            for r, asked in enumerate(batch.column("asked")):
                text, ends = symbols(data, offsets[r : r + 2], params.unit)
                text, out = text[ends[0] : ends[-1]], []
                for q in asked.as_py():
                    out.append((q["anchor"], q["run"], text[q["p0"] : q["a"]][::-1].tobytes(), text[q["a"] : q["stop"]].tobytes(), q["a"] - q["p1"], q["c"]))
                columns = list(zip(*out, strict=True))
                kinds = [pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.int32(), pa.int64()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["anchor", "run", "before", "after", "near", "c"])

    return run


def longest_matches(before: list[bytes], after: list[bytes], length: int, width: int = 1) -> list[list[tuple[int, int]]]:
    """For each run, spans around the anchor (symbols before, symbols after) that another run shares.

    A symbol is ``width`` bytes.

    Both sides are sorted.  Going down through the common prefixes of the left
    sides, groups that share that much of them are joined; within a group, a
    run's longest common right side is with a neighbour in the right order.
    Only matches of ``length`` symbols in all are kept, without dominated ones.
    """
    m = len(before)
    found: list[list[tuple[int, int]]] = [[] for _ in range(m)]
    r_order, r_lcps = deep_shallow(after)
    rank = [0] * m
    for k, i in enumerate(r_order):
        rank[i] = k
    l_order, l_lcps = deep_shallow(before)
    if width > 1:
        r_lcps, l_lcps = [x // width for x in r_lcps], [x // width for x in l_lcps]
    # sparse table for the least common prefix between two ranks
    table = [r_lcps]
    while (step := 1 << len(table)) <= m:
        prev, half = table[-1], step >> 1
        table.append([min(prev[k], prev[k + half]) for k in range(m - step + 1)])

    def shared(x: int, y: int) -> int:  # ranks x < y
        level = (y - x).bit_length() - 1
        row = table[level]
        return min(row[x + 1], row[y - (1 << level) + 1])

    best = [0] * m
    members: list[list[int]] = [[rank[i]] for i in l_order]
    owner = [*range(m)]

    def root(k: int) -> int:
        while owner[k] != k:
            owner[k] = owner[owner[k]]
            k = owner[k]
        return k

    for k in sorted(range(1, m), key=lambda k: -l_lcps[k]):
        left = l_lcps[k]
        a, b = root(k - 1), root(k)
        if len(members[a]) < len(members[b]):
            a, b = b, a
        large, small = members[a], members[b]
        for x in small:
            at = bisect_left(large, x)
            for y in (large[at - 1] if at else None, large[at] if at < len(large) else None):
                if y is None:
                    continue
                right = shared(min(x, y), max(x, y))
                for i in (r_order[x], r_order[y]):
                    if right > best[i]:
                        best[i] = right
                        if left + right >= length:
                            found[i].append((left, right))
        owner[b] = a
        # two sorted lists; the built-in sort merges such runs
        members[a] = sorted(large + small)
        members[b] = []
    return found


def _sort_groups(params: SuffixDedupParams):
    """Covered spans of each distinct run, from rows that come ordered by anchor."""

    def solve(rows: list[tuple]) -> tuple[list, list, list]:
        anchors, runs, spans = [], [], []
        got = longest_matches([r[2] for r in rows], [r[3] for r in rows], params.length, 1 if params.unit == "byte" else 4)
        for (anchor, run, *_), pairs in zip(rows, got, strict=True):
            if pairs:
                anchors.append(anchor)
                runs.append(run)
                spans.append([{"s": -left, "e": right} for left, right in pairs])
        return anchors, runs, spans

    kind = pa.list_(pa.struct([("s", pa.int32()), ("e", pa.int32())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        group: list[tuple] = []
        out: tuple[list, list, list] = ([], [], [])

        def close() -> None:
            if len(group) > 1:
                for have, more in zip(out, solve(group), strict=True):
                    have.extend(more)
            group.clear()

        def emit() -> pa.RecordBatch:
            made = pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], kind)], names=["anchor", "run", "spans"])
            for have in out:
                have.clear()
            return made

        for batch in batches:
            columns = [batch.column(c).to_pylist() for c in ("anchor", "run", "before", "after")]
            for item in zip(*columns, strict=True):
                if group and group[-1][0] != item[0]:
                    close()
                group.append(item)
            yield emit()
        close()
        yield emit()

    return run


def _window_rows(params: SuffixDedupParams):
    """Every window of an outsized group's runs, under a digest of its bytes."""
    kind = np.uint8 if params.unit == "byte" else np.uint32

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[tuple] = []
            for anchor, key, before, after, near, c in zip(*(batch.column(k).to_pylist() for k in ("anchor", "run", "before", "after", "near", "c")), strict=True):
                head = np.frombuffer(before, kind)[::-1]
                text = np.concatenate([head, np.frombuffer(after, kind)])
                for left in range(near, len(head) + 1):
                    at = len(head) - left
                    digest = hashlib.blake2b(text[at : at + params.length].tobytes(), digest_size=16).digest()
                    out.append((anchor, key, left, digest, c))
                if len(out) > 20_000:
                    yield _as_windows(out)
                    out = []
            yield _as_windows(out)

    return run


def _as_windows(rows: list[tuple]) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) if rows else [()] * 5
    kinds = [pa.int64(), pa.int64(), pa.int32(), pa.binary(), pa.int64()]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["anchor", "run", "left", "digest", "c"])


def _remove(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        data, offsets = text_bytes(batch.column("text"))
        whole = data.tobytes() if batch.num_rows else b""
        texts, n_removed, n_spans, digests = [], [], [], []
        for r, spans in enumerate(batch.column("spans")):
            raw = whole[offsets[r] : offsets[r + 1]]
            at, kept, removed, count = 0, [], 0, 0
            for q in sorted((q["s"], q["e"]) for q in (spans.as_py() or ())):
                if count and q[0] <= at:
                    if q[1] > at:
                        removed, at = removed + q[1] - at, q[1]
                    continue
                kept.append(raw[at : q[0]])
                removed, count, at = removed + q[1] - q[0], count + 1, q[1]
            kept.append(raw[at:])
            left = b"".join(kept)
            texts.append(left.decode("utf-8", "ignore"))
            n_removed.append(removed)
            n_spans.append(count)
            digests.append(hashlib.sha256(left).hexdigest())
        yield pa.RecordBatch.from_arrays(
            [batch.column("rid"), pa.array(n_removed, pa.int64()), pa.array(n_spans, pa.int64()), pa.array(digests, pa.string()), pa.array(texts, pa.string())], names=["rid", "n_removed", "n_spans", "kept_sha256", "kept_text"]
        )


def repeated_spans(docs: DataFrame, params: SuffixDedupParams = SuffixDedupParams()) -> DataFrame:
    """``(rid, s, e)``: covered spans of symbols of the rows of ``docs`` (rid, text); they may overlap."""
    runs = materialise(docs.mapInArrow(_run_rows(params), "rid long, anchor long, run long, p0 int, p1 int, a int"), "runs")
    n_runs = runs.count()
    several = "total > 1 and first <> last" if params.across else "total > 1"
    counts = runs.groupBy("anchor").agg(F.count(F.lit(1)).alias("total"), F.min("run").alias("lo"), F.max("run").alias("hi"), F.min("rid").alias("first"), F.max("rid").alias("last")).filter(several)
    counts = materialise(counts.select("anchor", "total", (F.col("lo") != F.col("hi")).alias("mixed")), "anchors")
    live = materialise(join_spread(runs, counts, ["anchor"], "total", n_runs).drop("total"), "live")
    length = F.lit(params.length)
    mixed = live.filter("mixed")
    distinct = mixed.groupBy("anchor", "run").agg(F.count(F.lit(1)).alias("c"), F.min(F.struct("rid", "p0", "p1", "a")).alias("at"))
    distinct = materialise(distinct.select("anchor", "run", "c", "at.*"), "distinct")
    whole = (
        live.filter("not mixed")
        .select("rid", F.col("p0").alias("s"), (F.col("p1") + length).alias("e"))
        .union(join_spread(mixed, distinct.filter("c > 1").select("anchor", "run", "c"), ["anchor", "run"], "c", n_runs).select("rid", F.col("p0").alias("s"), (F.col("p1") + length).alias("e")))
    )
    asked = distinct.groupBy("rid").agg(F.collect_list(F.struct("anchor", "run", "p0", "p1", "a", (F.col("p1") + length).alias("stop"), "c")).alias("asked"))
    texts = only_possible(docs, distinct.select("rid"), params.filter_bits).dropDuplicates(["rid"])
    contents = texts.join(asked, "rid").select("text", "asked").mapInArrow(_contents(params), "anchor long, run long, before binary, after binary, near int, c long")
    sizes = distinct.groupBy("anchor").agg(F.count(F.lit(1)).alias("m"))
    big = materialise(sizes.filter(F.col("m") > params.group_max).select("anchor"), "big")
    some_big = not big.isEmpty()
    if some_big:
        contents = materialise(contents, "contents")
    small = contents.join(big, "anchor", "left_anti") if some_big else contents
    small = small.select("anchor", "run", "before", "after").repartition("anchor").sortWithinPartitions("anchor")
    covered = small.mapInArrow(_sort_groups(params), "anchor long, run long, spans array<struct<s:int,e:int>>")
    covered = covered.select("anchor", "run", F.explode("spans").alias("x")).select("anchor", "run", F.col("x.s").alias("s"), F.col("x.e").alias("e"))
    if some_big:
        windows = materialise(contents.join(big, "anchor").mapInArrow(_window_rows(params), "anchor long, run long, left int, digest binary, c long"), "windows")
        twice = windows.groupBy("anchor", "digest").agg(F.sum("c").alias("n")).filter("n > 1").select("anchor", "digest")
        covered = covered.union(windows.join(twice, ["anchor", "digest"]).select("anchor", "run", (-F.col("left")).alias("s"), (length - F.col("left")).alias("e")))
    covered = materialise(covered, "covered")
    partial = mixed.join(covered, ["anchor", "run"]).select("rid", (F.col("a") + F.col("s")).alias("s"), (F.col("a") + F.col("e")).alias("e"))
    return whole.union(partial)


def shared_passages(docs: DataFrame, params: SuffixDedupParams = PASSAGES) -> DataFrame:
    """``(rid, passage_words)``: how many words of a row of ``docs`` (rid, text) lie in shared passages."""
    spans = repeated_spans(docs, params).groupBy("rid").agg(F.array_sort(F.collect_set(F.struct("s", "e"))).alias("spans"))
    covered = F.expr("aggregate(spans, named_struct('at', 0, 'n', 0L), (acc, x) -> named_struct('at', greatest(acc.at, x.e), 'n', acc.n + greatest(0, x.e - greatest(acc.at, x.s))), acc -> acc.n)")
    return materialise(spans.select("rid", covered.alias("passage_words")), "passages")


def suffix_dedup(docs: DataFrame, params: SuffixDedupParams = SuffixDedupParams(), with_text: bool = False, passages: SuffixDedupParams | None = None) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 for every row of ``docs``.

    With ``passages``, also ``passage_words``: words in strings of that many
    words that another document holds too, whatever their length in bytes.

    A null text counts as empty.  Rows that repeat both doc_id and text are
    copies of each other like any others.  ``with_text`` adds ``kept_text``
    (bytes that no longer form a character are left out of it).  Other columns
    are ignored.
    """
    text = F.coalesce("text", F.lit(""))
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text")).withColumn("rid", F.xxhash64("doc_id", "text"))
    body = keyed.filter(F.octet_length("text") >= params.length).select("rid", "text")
    spans = repeated_spans(body, params).groupBy("rid").agg(F.collect_set(F.struct("s", "e")).alias("spans"))
    spans = materialise(spans, "doc_spans")
    cut = only_possible(body, spans, params.filter_bits).dropDuplicates(["rid"]).join(spans, "rid").select("rid", "text", "spans")
    done = cut.mapInArrow(_remove, "rid long, n_removed long, n_spans long, kept_sha256 string, kept_text string")
    done = materialise(done if with_text else done.drop("kept_text"), "removed")
    own = [F.col("text")] if with_text else []
    base = keyed.select("rid", "doc_id", F.octet_length("text").cast("long").alias("n_bytes"), F.sha2("text", 256).alias("own_sha"), *own)
    out = base.join(done, "rid", "left")
    zero = F.lit(0).cast("long")
    more = [F.coalesce("kept_text", "text").alias("kept_text")] if with_text else []
    if passages is not None:
        out = out.join(shared_passages(keyed.filter(F.octet_length("text") >= 2 * passages.length - 1).select("rid", "text"), passages), "rid", "left")
        more.append(F.coalesce("passage_words", zero).alias("passage_words"))
    columns = ["doc_id", "n_bytes", F.coalesce("n_removed", zero).alias("n_removed"), F.coalesce("n_spans", zero).alias("n_spans"), F.coalesce("kept_sha256", "own_sha").alias("kept_sha256")]
    return out.select(*columns, *more)


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Repeated 400-byte strings of the whole of ``documents``, and the words in passages that documents share."""
    return suffix_dedup(spark.read.parquet(f"{sf_dir}/documents.parquet"), passages=PASSAGES)

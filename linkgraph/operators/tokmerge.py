"""Fusing of tokens that are variants of each other."""

from __future__ import annotations

import math
from collections.abc import Iterator
from hashlib import md5

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkgraph.functions.draws import u52
from linkgraph.functions.similarity import cosine
from linkgraph.operators.colsim import hashed_encode
from linkgraph.operators.embed import all_scores
from linkgraph.params import Params
from linkgraph.sources.shared import shared_folder

#: Tokens whose vectors are compared inside the tasks, and similar pairs that the driver clusters, at most; beyond, joins.
HELD_TOKENS, HELD_PAIRS = 2_000_000, 4_000_000
#: Tokens up to which all pairs are compared, not those of a band alone.
ALL_PAIRS = 60_000


def settle(df: DataFrame) -> DataFrame:
    """Cuts the lineage with a reliable checkpoint in the cluster's shared folder."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint()


def mergeable(tok_cid: DataFrame, p: Params = Params()) -> DataFrame:
    """(tok, freq) of tokens that may be fused."""
    out = tok_cid.groupBy("tok").agg(F.sum("mult").alias("freq")).filter(F.length("tok") >= p.merge_min_length)
    return out if p.merge_numeric else out.filter(~F.col("tok").rlike("[0-9]"))


def token_vectors(toks: DataFrame, dim: int = 64) -> DataFrame:
    return hashed_encode(toks, "tok", "tok", dim, 2, 3)


def _with_vectors(pairs: DataFrame, vecs: DataFrame, tau: float) -> DataFrame:
    out = pairs.join(vecs.select(F.col("tok").alias("a"), F.col("vec").alias("va")), "a").join(vecs.select(F.col("tok").alias("b"), F.col("vec").alias("vb")), "b")
    return out.select("a", "b", cosine(F.col("va"), F.col("vb")).alias("sim")).filter(F.col("sim") >= tau)


def similar_tokens_exact(vecs: DataFrame, tau: float, dim: int = 64, limit: int = 20_000) -> DataFrame:
    """All similar pairs by comparing all, a block at a time; for vocabularies up to ``limit``, as a control."""
    if vecs.count() > limit:
        raise ValueError(f"more than {limit} tokens: use similar_tokens_lsh")
    named = vecs.select(F.col("tok").alias("key"), "vec")
    return all_scores(named, named, tau, dim).filter("left_key < right_key").toDF("a", "b", "sim")


def lsh_plan(n: int, cosine: float, recall: float = 0.99, per_code: int = 64) -> tuple[int, int]:
    """Bands and rows for ``n`` vectors: codes grow with n, and bands make up for them.

    A code holds about ``per_code`` vectors of random directions, and a pair at
    the cosine agrees in some band with the chance ``recall``.
    """
    rows = max(4, math.ceil(math.log2(max(1.0, n / per_code))))
    one = (1 - math.acos(cosine) / math.pi) ** rows
    return max(1, math.ceil(math.log(1 - recall) / math.log(1 - one))), rows


def hyperplane_keys(vecs: DataFrame, key: str, dim: int, bands: int, rows: int, seed: int) -> DataFrame:
    """(key, band, code): signs of projections on pseudo-random directions, in bands of at most 62 rows."""
    planes = np.random.default_rng(seed).normal(size=(dim, bands * rows))
    bits = 1 << np.arange(rows, dtype=np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 1024):
                part = batch.slice(lo, 1024)
                n = part.num_rows
                # a list column of one length
                values = part.column("vec").flatten().to_numpy(zero_copy_only=False).reshape(n, dim)
                signs = (values @ planes >= 0).reshape(n, bands, rows)
                codes = (signs * bits).sum(axis=2)
                keys = part.column(key).take(pa.array(np.repeat(np.arange(n), bands)))
                yield pa.RecordBatch.from_arrays([keys, pa.array(np.tile(np.arange(bands, dtype=np.int32), n)), pa.array(codes.reshape(-1))], names=[key, "band", "code"])

    kind = vecs.schema[key].dataType.simpleString()
    return vecs.select(key, F.col("vec").cast("array<double>").alias("vec")).mapInArrow(run, f"{key} {kind}, band int, code bigint")


def similar_tokens_lsh(vecs: DataFrame, tau: float, dim: int = 64, bands: int | None = None, rows: int | None = None, seed: int = 7) -> DataFrame:
    """Similar pairs among tokens that agree in a band of hyperplane signs; confirmed exactly.

    Bands and rows follow from the number of tokens and the threshold.
    """
    if bands is None or rows is None:
        bands, rows = lsh_plan(vecs.count(), tau)
    keys = hyperplane_keys(vecs, "tok", dim, bands, rows, seed)
    a, b = keys.select("band", "code", F.col("tok").alias("a")), keys.select("band", "code", F.col("tok").alias("b"))
    return _with_vectors(a.join(b, ["band", "code"]).filter("a < b").select("a", "b").distinct(), vecs, tau)


def cluster_star(pairs: DataFrame, freq: DataFrame) -> DataFrame:
    """(tok, rep): tokens join the most frequent similar token that is itself a centre.

    A token becomes a centre once no undecided similar token outranks it; its
    undecided neighbours then join it.  Clusters are stars, so no chains form.
    Each round decides at least the most frequent open token, so the rounds end.
    """
    both = pairs.select("a", "b").union(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
    order = freq.select("tok", F.struct((-F.col("freq")).alias("f"), "tok").alias("rank"))
    near = settle(both.join(order.select(F.col("tok").alias("a"), F.col("rank").alias("ra")), "a").join(order.select(F.col("tok").alias("b"), F.col("rank").alias("rb")), "b"))
    todo = settle(near.select(F.col("a").alias("tok"), F.col("ra").alias("rank")).distinct())
    done = None
    while True:
        open_near = near.join(todo.select(F.col("tok").alias("a")), "a").join(todo.select(F.col("tok").alias("b")), "b")
        best = open_near.groupBy("a").agg(F.min("rb").alias("best"))
        centres = todo.join(best, F.col("tok") == F.col("a"), "left").filter("best is null or rank < best").select("tok", "rank")
        joined = near.join(centres.select(F.col("tok").alias("b")), "b").join(centres.select(F.col("tok").alias("a")), "a", "left_anti").join(todo.select(F.col("tok").alias("a")), "a").groupBy(F.col("a").alias("tok")).agg(F.min("rb").getField("tok").alias("rep"))
        new = centres.select("tok", F.col("tok").alias("rep")).union(joined)
        done = settle(new if done is None else done.union(new))
        todo = settle(todo.join(done.select("tok"), "tok", "left_anti"))
        if todo.isEmpty():
            break
    return done.filter("tok <> rep")


def _mark(edges: DataFrame) -> tuple:
    """Number of edges and an order-free sum of their hashes."""
    return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first())


def cluster_components(pairs: DataFrame, freq: DataFrame, rounds: int = 60) -> DataFrame:
    """(tok, rep) of the transitive reading: connected components, most frequent token first.

    Stars are contracted in turn from the larger and the smaller neighbours, which
    takes few rounds for long chains too; raises where they do not settle.
    """
    order = freq.select("tok", F.struct((-F.col("freq")).alias("f"), "tok").alias("rank"))
    end = lambda side: order.select(F.col("tok").alias(side), F.col("rank").alias("r" + side))
    ranked = pairs.select("a", "b").join(end("a"), "a").join(end("b"), "b").filter("ra <> rb")
    now = settle(ranked.select(F.greatest("ra", "rb").alias("u"), F.least("ra", "rb").alias("v")).distinct())
    mark = _mark(now)
    for _ in range(rounds):
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("m", "u").alias("m"))
        large = both.filter("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v")))
        large = large.filter("u > v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v")))
        now = settle(small.filter("u > v").distinct())
        seen, mark = mark, _mark(now)
        if mark == seen:
            return now.groupBy("u").agg(F.min("v").alias("v")).select(F.col("u.tok").alias("tok"), F.col("v.tok").alias("rep"))
    raise RuntimeError(f"components did not settle in {rounds} rounds")


def apply_merge(tokens: DataFrame, mapping: DataFrame) -> DataFrame:
    """Tokens under their representatives; multiplicities add up."""
    out = tokens.join(mapping, "tok", "left").select("rid", "cid", F.coalesce("rep", "tok").alias("tok"), "occ")
    return out.groupBy("rid", "cid", "tok").agg(F.sum("occ").alias("occ"))


def merge_report(tok_cid: DataFrame, mapping: DataFrame) -> DataFrame:
    """Tokens before and after, clusters, and the largest cluster."""
    sizes = mapping.groupBy("rep").agg((F.count(F.lit(1)) + 1).alias("size")).agg(F.count(F.lit(1)).alias("clusters"), F.coalesce(F.max("size"), F.lit(0)).cast("long").alias("largest"), F.coalesce(F.sum(F.col("size") - 1), F.lit(0)).cast("long").alias("gone"))
    before = tok_cid.agg(F.count_distinct("tok").alias("before"))
    return before.crossJoin(sizes).select("before", (F.col("before") - F.col("gone")).alias("after"), "clusters", "largest")  # one row each


def coded_tokens(freq: DataFrame, dim: int = 64) -> DataFrame:
    """(tok, freq, code): ``token_vectors``, which are whole numbers, as ``dim`` bytes, or as ``dim`` 32-bit numbers where they need them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        places: dict[str, tuple[int, int]] = {}
        for batch in batches:
            codes = []
            for words in batch.column("words").to_pylist():
                vec = [0] * dim
                for w in words:
                    padded = f"<{w}>"
                    for feat in ["=" + w, *[padded[i : i + n] for n in (2, 3) for i in range(len(padded) - n + 1)]]:
                        if feat not in places:
                            d = md5(feat.encode()).digest()
                            place = int.from_bytes(d[:4], "big") % dim, 1 - 2 * ((d[4] >> 4) % 2)
                            if len(places) >= 200_000:
                                places.clear()
                            places[feat] = place
                        slot, sign = places[feat]
                        vec[slot] += sign
                codes.append(np.array(vec, dtype=np.int8 if -128 < min(vec) and max(vec) < 128 else np.int32).tobytes())
            yield pa.RecordBatch.from_arrays([batch.column("tok"), batch.column("freq"), pa.array(codes, pa.binary())], names=["tok", "freq", "code"])

    words = F.filter(F.split(F.lower("tok"), r"[^\p{L}0-9]+"), lambda w: w != "")
    return freq.select("tok", F.col("freq").cast("long").alias("freq"), words.alias("words")).filter("size(words) > 0").mapInArrow(run, "tok string, freq long, code binary")


def similar_held(spark: SparkSession, vecs: np.ndarray, tau: float, seed: int = 7) -> DataFrame:
    """(a, b): places of the similar rows of a broadcast matrix of whole numbers, compared and confirmed in the tasks.

    All pairs up to ``ALL_PAIRS`` rows; beyond, those that agree in a band of
    ``similar_tokens_lsh``, so that pairs below the threshold never leave a task.
    """
    n, dim = vecs.shape
    bands, rows = (0, 0) if n <= ALL_PAIRS else lsh_plan(n, tau)
    shipped = spark.sparkContext.broadcast(vecs)
    block = 1024

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        whole = shipped.value
        size = np.sqrt(np.einsum("ij,ij->i", whole, whole, dtype=np.float64))
        units = (whole / np.where(size > 0, size, 1)[:, None]).astype(np.float32)
        planes = np.random.default_rng(seed).normal(size=(dim, bands * rows)) if bands else None

        def confirmed(mine: np.ndarray, theirs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            i, j = np.nonzero(units[mine] @ units[theirs].T >= tau - 1e-5)
            a, b = mine[i], theirs[j]
            a, b = a[mine[i] != theirs[j]], b[mine[i] != theirs[j]]
            a, b = np.minimum(a, b), np.maximum(a, b)
            dots = np.einsum("ij,ij->i", whole[a].astype(np.float64), whole[b].astype(np.float64))
            good = (size[a] * size[b] > 0) & (dots / np.where(size[a] * size[b] > 0, size[a] * size[b], 1) >= tau)
            return a[good], b[good]

        def groups(k: int) -> Iterator[np.ndarray]:
            if not bands:
                yield np.arange(k * block, n)
                return
            codes = np.concatenate([(whole[lo : lo + 65536] @ planes[:, k * rows : (k + 1) * rows] >= 0) @ (1 << np.arange(rows, dtype=np.int64)) for lo in range(0, n, 65536)])
            by = np.argsort(codes, kind="stable")
            ends = np.flatnonzero(np.concatenate([codes[by][1:] != codes[by][:-1], [True]])) + 1
            for lo, hi in zip(np.concatenate([[0], ends[:-1]]), ends, strict=True):
                if hi - lo > 1:
                    yield by[lo:hi]

        for batch in batches:
            for k in batch.column("id").to_pylist():
                found = []
                for group in groups(k):
                    # without bands, a task's number is that of the block it compares with the rest
                    for lo in range(0, len(group) if bands else 1, block):
                        for at in range(lo, len(group), 8 * block):
                            found.append(confirmed(group[lo : lo + block], group[at : at + 8 * block]))
                a, b = (np.concatenate([x[c] for x in found] or [np.zeros(0, dtype=np.int64)]) for c in (0, 1))
                yield pa.RecordBatch.from_arrays([pa.array(a.astype(np.int32)), pa.array(b.astype(np.int32))], names=["a", "b"])

    jobs = bands or max(1, -(-n // block))
    return spark.range(0, jobs, 1, jobs).mapInArrow(run, "a int, b int").distinct()


def star_of(a: np.ndarray, b: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """The rounds of ``cluster_star`` on arrays: each place's centre, itself without a similar one; ``rank`` is 0 for the first of all."""
    a, b = np.concatenate([a, b]), np.concatenate([b, a])
    n = len(rank)
    place = np.argsort(rank)
    rep, todo = np.arange(n), np.zeros(n, dtype=bool)
    todo[a] = True
    while todo.any():
        a, b = (x[todo[a] & todo[b]] for x in (a, b))
        best = np.full(n, n)
        np.minimum.at(best, a, rank[b])
        centres = todo & (rank < best)
        to = np.full(n, n)
        near = centres[b] & ~centres[a]
        np.minimum.at(to, a[near], rank[b[near]])
        joined = to < n
        rep[joined] = place[to[joined]]
        todo &= ~(centres | joined)
    return rep


def merge_tokens(spark: SparkSession, tokens: DataFrame, p: Params = Params()) -> DataFrame:
    freq = mergeable(tokens.groupBy("tok", "cid").agg(F.sum("occ").alias("mult")), p).persist()
    if freq.count() > HELD_TOKENS:
        pairs = settle(similar_tokens_lsh(token_vectors(freq.select("tok")), p.tau_tok))
        merged = tokens if pairs.isEmpty() else apply_merge(tokens, cluster_star(pairs, freq))
        freq.unpersist()
        return merged
    coded = coded_tokens(freq).toArrow().sort_by([("freq", "descending"), ("tok", "ascending")])
    freq.unpersist()
    codes = coded.column("code").to_pylist()
    small = all(len(c) == 64 for c in codes)
    vecs = np.frombuffer(b"".join(codes if small else [np.frombuffer(c, np.int8).astype(np.int32).tobytes() if len(c) == 64 else c for c in codes]), np.int8 if small else np.int32).reshape(-1, 64)
    pairs = similar_held(spark, vecs, p.tau_tok).persist()
    many = pairs.count()
    if many > HELD_PAIRS:
        named = spark.createDataFrame(coded.select(["tok", "freq"]).append_column("i", pa.array(np.arange(len(codes), dtype=np.int32))))
        end = lambda c: named.select(F.col("i").alias(c), F.col("tok").alias("t" + c))
        found = settle(pairs.join(end("a"), "a").join(end("b"), "b").select(F.col("ta").alias("a"), F.col("tb").alias("b")))
        pairs.unpersist()
        return apply_merge(tokens, cluster_star(found, named))
    ends = pairs.toArrow()
    pairs.unpersist()
    rep = star_of(*(ends.column(c).to_numpy() for c in ("a", "b")), np.arange(len(codes)))
    gone = np.flatnonzero(rep != np.arange(len(rep)))
    if not len(gone):
        return tokens
    mapping = pa.table({"tok": coded.column("tok").take(pa.array(gone)).cast(pa.string()), "rep": coded.column("tok").take(pa.array(rep[gone])).cast(pa.string())})
    return apply_merge(tokens, spark.createDataFrame(mapping))

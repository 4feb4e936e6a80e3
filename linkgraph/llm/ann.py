"""Nearest neighbours by cosine: multiprobe hashing with p-stable projections.

Unit vectors are hashed in several tables by floors of Gaussian projections.  A
query visits, in each table, its own bucket and then perturbed ones in the
order of their estimated success, that is by the squared distances to the cell
borders that a perturbation crosses.  Buckets are met as blocks: the vectors of
a bucket as one matrix, its queries as another; each block gives every query
its few best by exact cosine, and these are merged over tables and probes.

The number of hashes grows with the table only as far as tables and probes can
make up for it: before anything is hashed, the chance that a pair at the
neighbour cosine meets is estimated, and the cheapest plan is taken whose chance
reaches the wanted one.

Equal vectors are one entry of the index, with its smallest ids.  Buckets larger
than a block are split by a salt, and their queries meet every part.
"""

from __future__ import annotations

import heapq
import itertools
import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from linkgraph.llm.common import as_long, materialise, mix


@dataclass(frozen=True)
class AnnParams:
    k: int = 5
    #: Least tables, and least probes in each; more are taken where the chance asks for it.
    tables: int = 8
    probes: int = 40
    #: Width of a cell; projections of unit vectors have deviation 1.
    width: float = 1.0
    #: Distinct vectors that a bucket should hold; sets the number of hashes.
    bucket_target: int = 500
    #: Bits that one hash of this width tells apart, on average.
    bits_per_hash: float = 1.8
    #: Vectors of a bucket in one block.
    block: int = 4096
    #: A pair of this cosine is met with this chance, whatever the size of the table.
    cosine: float = 0.4
    chance: float = 0.95
    #: Compared pairs that cost as much as one row moved to a bucket.
    pairs_per_row: float = 400.0
    seed: int = 977

    def hashes(self, n: int) -> int:
        return max(1, round(math.log2(max(2.0, n / self.bucket_target)) / self.bits_per_hash))


def probe_ranks(params: AnnParams, n_hash: int, cosine: float, pairs: int = 2000) -> np.ndarray:
    """For drawn pairs of unit vectors, the place in the probe order at which the one meets the other, in rising order; infinite if never."""
    rng = np.random.default_rng((params.seed, n_hash))
    x, other, shift = rng.normal(size=(pairs, n_hash)), rng.normal(size=(pairs, n_hash)), rng.uniform(0, params.width, (pairs, n_hash))
    place = (x + shift) / params.width
    cell = np.floor(place)
    inside = place - cell
    step = np.floor((cosine * x + math.sqrt(1 - cosine * cosine) * other + shift) / params.width) - cell
    cost = np.stack([inside**2, np.zeros_like(inside), (1 - inside) ** 2], axis=2)
    total, code = np.zeros((pairs, 1)), np.zeros(pairs, np.int64)
    for k in range(n_hash):
        total = (total[:, :, None] + cost[:, k, None, :]).reshape(pairs, -1)
        code = code * 3 + np.clip(step[:, k] + 1, 0, 2).astype(np.int64)
    rank = (total < total[np.arange(pairs), code][:, None]).sum(axis=1).astype(float)
    rank[(np.abs(step) > 1).any(axis=1)] = np.inf
    return np.sort(rank)


#: Hashes of which all perturbations can be listed.
_MOST_HASHES = 7


def plan(params: AnnParams, n: int, queries: int) -> tuple[int, int, int]:
    """Hashes, tables and probes: the cheapest that give a pair at ``cosine`` the wanted chance."""
    best: tuple[float, tuple[int, int, int]] | None = None
    for h in range(1, min(params.hashes(n), _MOST_HASHES) + 1):
        near, far = probe_ranks(params, h, params.cosine), probe_ranks(params, h, 0.0)
        for tables in range(params.tables, 8 * params.tables + 1):
            need = math.ceil(len(near) * (1 - (1 - params.chance) ** (1 / tables)))  # pairs met in one table
            probes = max(near[need - 1] + 1, params.probes)
            if not math.isfinite(probes):
                continue
            probes = min(int(probes), 3**h)
            met = np.searchsorted(far, probes) / len(far)
            cost = tables * (n + queries * probes + queries * n * met / params.pairs_per_row)
            if best is None or cost < best[0]:
                best = cost, (h, tables, probes)
    return best[1] if best else (1, params.tables, 3)


def _projections(params: AnnParams, n_hash: int, table: int, dim: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng((params.seed, table, dim))
    return rng.normal(size=(dim, n_hash)), rng.uniform(0, params.width, n_hash)


def _bucket_key(cells: np.ndarray, table: int, dim: int) -> np.ndarray:
    key = np.full(len(cells), np.uint64(table * 65_537 + dim), np.uint64)
    for k in range(cells.shape[1]):
        key = mix(key * np.uint64(0x9E3779B97F4A7C15) + cells[:, k].astype(np.int64).view(np.uint64))
    return key


def probe_order(inside: np.ndarray, count: int) -> list[tuple[tuple[int, int], ...]]:
    """Perturbations (hash, step) in the order of estimated success, the empty one first.

    ``inside`` is the place within the cell, from 0 to 1, for each hash.
    """
    n = len(inside)
    moves = sorted([(float(inside[k]) ** 2, k, -1) for k in range(n)] + [(float(1 - inside[k]) ** 2, k, 1) for k in range(n)])
    out: list[tuple[tuple[int, int], ...]] = [()]
    heap: list[tuple[float, tuple[int, ...]]] = [(moves[0][0], (0,))]
    while heap and len(out) < count:
        cost, chosen = heapq.heappop(heap)
        if len({moves[m][1] for m in chosen}) == len(chosen):
            out.append(tuple((moves[m][1], moves[m][2]) for m in chosen))
        nxt = chosen[-1] + 1
        if nxt < len(moves):
            heapq.heappush(heap, (cost - moves[chosen[-1]][0] + moves[nxt][0], (*chosen[:-1], nxt)))
            heapq.heappush(heap, (cost + moves[nxt][0], (*chosen, nxt)))
    return out


def _matrix(column: pa.Array) -> np.ndarray:
    """A column of lists of one length as a matrix of doubles."""
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 0))


def _by_dim(batch: pa.RecordBatch) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    sizes = np.diff(np.asarray(batch.column("v").offsets))
    for dim in np.unique(sizes):
        rows = np.flatnonzero(sizes == dim)
        yield rows, _matrix(batch.column("v").take(pa.array(rows)))


def _hashed(params: AnnParams, n_hash: int, tables: int, probes: int):
    """Rows (entry, v, asks) to (key, side, entry, v): index rows, and probe rows of queries."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for start in range(0, whole.num_rows, 256):
                batch = whole.slice(start, 256)
                entries = batch.column("entry").to_numpy()
                asks = batch.column("asks").to_numpy(zero_copy_only=False)
                for rows, x in _by_dim(batch):
                    x = x / np.linalg.norm(x, axis=1)[:, None]
                    vectors = batch.column("v").take(pa.array(rows))
                    keys, sides, picks = [], [], []
                    for table in range(tables):
                        a, b = _projections(params, n_hash, table, x.shape[1])
                        place = (x @ a + b) / params.width
                        cells = np.floor(place).astype(np.int64)
                        keys.append(_bucket_key(cells, table, x.shape[1]))
                        sides.append(np.zeros(len(rows), np.int32))
                        picks.append(np.arange(len(rows)))
                        for q in np.flatnonzero(asks[rows]):
                            order = probe_order(place[q] - cells[q], probes)
                            visited = np.repeat(cells[q][None], len(order), axis=0)
                            for m, change in enumerate(order):
                                for k, step in change:
                                    visited[m, k] += step
                            keys.append(_bucket_key(visited, table, x.shape[1]))
                            sides.append(np.ones(len(order), np.int32))
                            picks.append(np.full(len(order), q))
                    pick = np.concatenate(picks)
                    yield pa.RecordBatch.from_arrays([pa.array(as_long(np.concatenate(keys))), pa.array(np.concatenate(sides)), pa.array(entries[rows][pick]), vectors.take(pa.array(pick))], names=["key", "side", "entry", "v"])

    return run


def _best_of_blocks(params: AnnParams):
    """Best entries of each query in each block, from rows ordered by (key, salt, side)."""
    names = ["query", "hits"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = None
        ids: list[np.ndarray] = []
        index: list[np.ndarray] = []
        matrix = ids_all = norms = None
        for batch in batches:
            keys = batch.column("key").to_numpy()
            salts = batch.column("salt").to_numpy()
            sides = batch.column("side").to_numpy()
            entries = batch.column("entry").to_numpy()
            change = np.flatnonzero((np.diff(keys) != 0) | (np.diff(salts) != 0) | (np.diff(sides) != 0)) + 1
            for lo, hi in zip([0, *change], [*change, batch.num_rows], strict=True):
                if hi <= lo:
                    continue
                if at != (here := (keys[lo], salts[lo])):
                    at, ids, index, matrix = here, [], [], None
                x = _matrix(batch.column("v").slice(lo, hi - lo))
                if sides[lo] == 0:
                    ids.append(entries[lo:hi])
                    index.append(x)
                    continue
                if not index:
                    continue
                if matrix is None:
                    matrix, ids_all = np.vstack(index), np.concatenate(ids)
                    norms = np.sqrt((matrix * matrix).sum(axis=1))
                for start in range(0, hi - lo, 512):
                    asked = x[start : start + 512]
                    who = entries[lo + start : lo + start + len(asked)]
                    score = (asked @ matrix.T) / (np.sqrt((asked * asked).sum(axis=1))[:, None] * norms[None])
                    score[who[:, None] == ids_all[None]] = -np.inf  # an entry itself is added later
                    keep = min(params.k, score.shape[1])
                    kth = -np.partition(-score, keep - 1, axis=1)[:, keep - 1 : keep]
                    row, col = np.nonzero((score >= kth) & np.isfinite(score))
                    order = np.lexsort((ids_all[col], -score[row, col], row))
                    row, col = row[order], col[order]
                    first = np.searchsorted(row, np.arange(len(asked) + 1))
                    near = np.arange(len(row)) - first[row] < keep  # among ties the smallest ids suffice
                    row, col = row[near], col[near]
                    ends = pa.array(np.searchsorted(row, np.arange(len(asked) + 1)).astype(np.int32))
                    hits = pa.StructArray.from_arrays([pa.array(ids_all[col]), pa.array(score[row, col])], names=["id", "score"])
                    yield pa.RecordBatch.from_arrays([pa.array(who), pa.ListArray.from_arrays(ends, hits)], names=names)

    return run


def nearest(vectors: DataFrame, is_query, params: AnnParams = AnnParams()) -> DataFrame:
    """query_id, rank, vec_id, score: the ``k`` nearest found of each query.

    ``vectors`` has vec_id and embedding; ``is_query`` is a condition on vec_id.
    Null, empty or zero vectors and those holding null or non-finite components
    take no part.  Vectors of different lengths are never compared.  Rows that
    repeat a vec_id count as one if their vectors are equal.
    """
    clean = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v")).filter("vec_id is not null and v is not null and size(v) > 0")
    clean = clean.filter("not exists(v, x -> x is null or isnan(x) or x in (double('infinity'), double('-infinity'))) and exists(v, x -> x <> 0)")
    clean = clean.withColumns({"h1": F.xxhash64("v"), "h2": F.xxhash64(F.lit(7), "v"), "asks": F.coalesce(is_query, F.lit(False))})
    by_vector = ["h1", "h2"]
    ids = clean.select(*by_vector, "vec_id", "asks").distinct()
    entries = ids.groupBy(*by_vector).agg(F.min("vec_id").alias("entry"), F.max("asks").alias("asks"))
    # an entry's vector is that of its smallest id
    entries = materialise(clean.select("vec_id", "h1", "h2", "v").join(entries.withColumnRenamed("entry", "vec_id"), ["vec_id", *by_vector]).dropDuplicates(["vec_id", *by_vector]).select(F.col("vec_id").alias("entry"), *by_vector, "v", "asks"), "entries")
    n, asking = entries.agg(F.count(F.lit(1)), F.count_if("asks")).first()
    rows = materialise(entries.select("entry", "v", "asks").mapInArrow(_hashed(params, *plan(params, n, asking)), "key long, side int, entry long, v array<double>"), "hashed")
    sizes = rows.filter("side = 0").groupBy("key").agg(F.ceil(F.count(F.lit(1)) / params.block).cast("int").alias("parts"))
    rows = rows.join(sizes, "key")  # a probe of an empty bucket ends here
    own = F.pmod(F.xxhash64("entry"), F.col("parts")).cast("int")
    salted = rows.withColumn("salt", F.explode(F.when(F.col("side") == 0, F.array(own)).otherwise(F.sequence(F.lit(0), F.col("parts") - 1))))
    blocks = salted.select("key", "salt", "side", "entry", "v").repartition("key", "salt").sortWithinPartitions("key", "salt", "side")
    # a query meets at most tables * probes buckets, each block of which names k entries
    met = blocks.mapInArrow(_best_of_blocks(params), "query long, hits array<struct<id:long,score:double>>").groupBy("query").agg(F.flatten(F.collect_list("hits")).alias("hits"))
    by_entry = met.withColumn("hits", F.array_sort("hits"))
    once = F.expr("filter(hits, (x, i) -> i = 0 or hits[i - 1].id <> x.id)")
    best = F.expr(f"slice(array_sort(transform(hits, x -> named_struct('d', -x.score, 'id', x.id))), 1, {params.k})")
    near = by_entry.withColumn("hits", once).select("query", F.explode(best).alias("x")).select("query", F.col("x.id").alias("entry"), (-F.col("x.d")).alias("score"))
    # a query's own vector, for its copies: its cosine in the same arithmetic
    unit = F.expr("aggregate(v, double(0), (a, x) -> a + x * x)")
    itself = entries.filter("asks").select(F.col("entry").alias("query"), "entry", (unit / (F.sqrt(unit) * F.sqrt(unit))).alias("score"))
    low_ids = ids.withColumn("r", F.row_number().over(Window.partitionBy(*by_vector).orderBy("vec_id"))).filter(F.col("r") <= params.k + 1)
    low_ids = low_ids.join(entries.select("entry", *by_vector), by_vector).select("entry", "vec_id")
    options = near.union(itself).join(low_ids, "entry").select("query", "vec_id", "score")
    # the best k+1 ids of a query vector serve all queries that hold it
    options = options.withColumn("r", F.row_number().over(Window.partitionBy("query").orderBy(F.desc("score"), "vec_id"))).filter(F.col("r") <= params.k + 1)
    best = options.groupBy("query").agg(F.array_sort(F.collect_list(F.struct((-F.col("score")).alias("d"), F.col("vec_id").alias("id")))).alias("best"))
    asked = ids.filter("asks").join(entries.select("entry", *by_vector), by_vector).select(F.col("vec_id").alias("query_id"), F.col("entry").alias("query"))
    final = asked.join(best, "query").select("query_id", F.expr(f"slice(filter(best, x -> x.id <> query_id), 1, {params.k})").alias("best"))
    return final.select("query_id", F.posexplode("best").alias("pos", "x")).select("query_id", (F.col("pos") + 1).cast("int").alias("rank"), F.col("x.id").alias("vec_id"), (-F.col("x.d")).alias("score"))


def op4_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nearest neighbours in the whole of ``embeddings`` of every fiftieth id."""
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return nearest(vectors, F.pmod("vec_id", F.lit(50)) == 0)

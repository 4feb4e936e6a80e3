"""Quality by importance resampling of hashed n-gram models.

Two bag-of-n-grams models over ``buckets`` hashes are estimated: one of target
text (labelled as good) and one of all raw text.  A document's log importance
is the sum, over its n-grams, of the logarithm of their ratio; documents are
sampled without replacement in proportion to it by adding Gumbel noise to the
log importance and keeping the largest.  As that sum favours long documents, a
second sample with the same noise takes the importance brought to one length.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from linkgraph.llm.common import materialise, mix, row_slices, text_bytes
from linkgraph.llm.shingles import word_hashes


@dataclass(frozen=True)
class ResamplingParams:
    buckets: int = 10_000
    #: Longest n-gram, in words.
    order: int = 2
    #: Share of the documents that is kept.
    share: float = 0.85
    #: N-grams that every document's mean log ratio is scaled to for the second sample.
    length: float = 400.0
    #: Labelled documents that the target model uses at most.
    max_target: int = 20_000
    #: Added to every bucket's count.
    smoothing: float = 1.0
    #: Weight of the noise; 0 keeps the documents of greatest importance.
    temperature: float = 1.0
    seed: int = 11


def hashed_ngrams(data: np.ndarray, offsets: np.ndarray, params: ResamplingParams) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all n-grams of the rows, and the row of each."""
    words, rows = word_hashes(data, offsets)
    row = np.repeat(np.arange(len(rows)), rows)
    values, owners = [words], [row]
    total = words.copy()
    for n in range(1, params.order):
        if len(words) <= n:
            break
        total = mix(total[:-1] * np.uint64(0x9E3779B97F4A7C15) + words[n:])
        same = row[: len(words) - n] == row[n:]
        values.append(total[same])
        owners.append(row[: len(words) - n][same])
    return (np.concatenate(values) % np.uint64(params.buckets)).astype(np.int64), np.concatenate(owners)


def _bucket_counts(params: ResamplingParams):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(params.buckets, np.int64)
        for batch in batches:
            data, offsets = text_bytes(batch.column("text"))
            for lo, hi in row_slices(offsets):
                total += np.bincount(hashed_ngrams(data, offsets[lo : hi + 1], params)[0], minlength=params.buckets)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(params.buckets)), pa.array(total)], names=["bucket", "n"])

    return run


def model_of(docs: DataFrame, params: ResamplingParams) -> np.ndarray:
    """Smoothed log probabilities of the buckets; as many numbers, whatever the text."""
    counted = docs.select("text").mapInArrow(_bucket_counts(params), "bucket long, n long").groupBy("bucket").agg(F.sum("n").alias("n"))
    counts = np.full(params.buckets, params.smoothing)
    for bucket, n in counted.collect():
        counts[bucket] += n
    return np.log(counts / counts.sum())


def target_docs(docs: DataFrame, labels: DataFrame, params: ResamplingParams) -> DataFrame:
    """Documents labelled as good and not held out, at most ``max_target`` by a hash of doc_id."""
    remainder = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4))
    good = labels.filter((F.col("quality") == 1) & (remainder != 2)).select("doc_id").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(params.max_target)
    return docs.select("doc_id", "text").join(good, "doc_id", "left_semi")


def weights(docs: DataFrame, ratio: np.ndarray, params: ResamplingParams) -> DataFrame:
    """doc_id, n_grams, log_importance, log_weight and score for every row.

    ``log_importance`` is the plain sum of log ratios, ``log_weight`` their mean
    times ``length``.

    The score is the logistic of the mean log ratio, which does not grow with
    length; rows without words weigh 0 and score 0.5.
    """
    shipped = docs.sparkSession.sparkContext.broadcast(ratio)  # ``buckets`` doubles

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = shipped.value
        for batch in batches:
            data, offsets = text_bytes(batch.column("text"))
            ids = batch.column("doc_id").cast(pa.int64())
            for lo, hi in row_slices(offsets):
                bucket, row = hashed_ngrams(data, offsets[lo : hi + 1], params)
                total = np.bincount(row, weights=table[bucket], minlength=hi - lo).astype(np.float64)
                count = np.bincount(row, minlength=hi - lo)
                mean = total / np.maximum(count, 1)
                columns = [ids.slice(lo, hi - lo), pa.array(count.astype(np.int64)), pa.array(total), pa.array(mean * params.length), pa.array(1 / (1 + np.exp(-mean)))]
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_grams", "log_importance", "log_weight", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_grams long, log_importance double, log_weight double, score double")


def _kth(rows: DataFrame, name: str, k: int) -> float | int:
    """The ``k``-th smallest value of a column, counted from 1.

    Approximate quantiles with a proven rank error bracket it; counts then say
    whether it is one of the two bounds, and else only the rows strictly between
    them are left, about a fiftieth.
    """
    c, n = F.col(name), rows.count()
    while n > 10_000:
        at = k / n
        lo, hi = rows.select(F.percentile_approx(c, F.array(F.lit(max(0.0, at - 0.01)), F.lit(min(1.0, at + 0.01))), 10_000)).first()[0]
        counts = rows.agg(F.count_if(c < lo), F.count_if(c <= lo), F.count_if(c < hi), F.count_if(c <= hi)).first()
        if counts[0] < k <= counts[1]:
            return lo
        if counts[2] < k <= counts[3]:
            return hi
        rows, k, n = rows.filter((c > lo) & (c < hi)), k - counts[1], counts[2] - counts[1]
        if not 0 < k <= n:
            raise RuntimeError("quantiles missed their error bound")
    return rows.orderBy(c).limit(k).agg(F.max(c)).first()[0]


def _first_rows(rows: DataFrame, names: list[str], k: int) -> Column:
    """Whether a row is among the first ``k`` in the order of the named columns, the last of which is unique."""
    c = F.col(names[0])
    value = F.lit(_kth(rows, names[0], k))
    same = rows.filter(c == value)
    want = k - rows.filter(c < value).count()
    if len(names) == 1 or same.count() == want:
        return c <= value
    return (c < value) | ((c == value) & _first_rows(same, names[1:], want))


def gumbel_top(weighted: DataFrame, params: ResamplingParams) -> DataFrame:
    """Adds, for the plain importance and for that at one length, the key with noise and whether the row is kept.

    Exactly the rows with the largest keys are kept; ties go to the smaller
    doc_id, and of rows that repeat one to any.  The noise is a function of
    doc_id and seed, so that retries agree.
    """
    uniform = (F.pmod(F.xxhash64("doc_id", F.lit(params.seed)), F.lit(1 << 52)) + 0.5) / float(1 << 52)
    noise = params.temperature * -F.log(-F.log(uniform))
    ordered = {"_plain": -(F.col("log_importance") + noise), "_even": -(F.col("log_weight") + noise), "_id": F.coalesce("doc_id", F.lit(-(1 << 63))), "_row": F.monotonically_increasing_id()}
    rows = materialise(weighted.withColumns(ordered), "keys")
    n = rows.count()
    k = int(round(params.share * n))
    chosen = lambda key: _first_rows(rows, [key, "_id", "_row"], k) if 0 < k < n else F.lit(k == n and n > 0)
    return rows.select(*weighted.columns, (-F.col("_even")).alias("gumbel_key"), chosen("_even").alias("kept"), (-F.col("_plain")).alias("importance_key"), chosen("_plain").alias("kept_by_importance"))


def resample(docs: DataFrame, labels: DataFrame, params: ResamplingParams = ResamplingParams()) -> DataFrame:
    """One row for every row of ``docs``: doc_id, n_grams, log_importance, log_weight, score, and the two samples.

    ``kept_by_importance`` samples by ``log_importance``, the plain importance
    weight; ``kept`` by ``log_weight``, which does not favour long documents.
    A null text counts as empty.  Without labelled rows all weights are those of
    a flat target.  Other columns are ignored.
    """
    raw = model_of(docs, params)
    target = model_of(target_docs(docs, labels, params), params)
    return gumbel_top(weights(docs, target - raw, params), params)


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Importance resampling of the whole of ``documents``."""
    return resample(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet"))

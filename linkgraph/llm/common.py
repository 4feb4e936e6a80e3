"""Helpers shared by the training-data operators."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_MASK = (1 << 64) - 1
#: Odd base of the rolling polynomial modulo 2**64, and its inverse.
BASE = 0x9E3779B97F4A7C15 | 1
BASE_INV = pow(BASE, -1, 1 << 64)
#: Bytes of text that one vectorised step handles at a time.
STEP_BYTES = 2 << 20


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``.

    Only in local mode (tests on one machine), where the session names none, a
    temporary folder is chosen and remembered in the session; a cluster without
    the setting is an error, as executors share no local folder.
    """
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("linkgraph.shared.dir", None)
    if not where:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        where = "file://" + tempfile.mkdtemp(prefix="linkgraph-")
        spark.conf.set("linkgraph.shared.dir", where)
    return where.rstrip("/")


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write ``df`` to a fresh table in the shared folder and read it back.

    This cuts the lineage in a way that survives lost executors.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/linkgraph/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def join_spread(rows: DataFrame, table: DataFrame, keys: list[str], count: str, total: int, share: float = 0.001) -> DataFrame:
    """``rows`` joined with ``table``, which has one row a key and the key's number of rows.

    Keys that hold more than ``share`` of all ``total`` rows are broadcast; there
    can be at most ``1 / share`` of them.  The others are joined by a shuffle in
    which no key is larger than that share.
    """
    hot = table.filter(F.col(count) > total * share)
    cold = table.filter(F.col(count) <= total * share)
    rest = rows.join(F.broadcast(hot.select(*keys)), keys, "left_anti")
    return rows.join(F.broadcast(hot), keys).unionByName(rest.join(cold, keys))


def only_possible(docs: DataFrame, ids: DataFrame, bits: int) -> DataFrame:
    """Rows of ``docs`` whose rid may be among ``ids``: a broadcast bit table of fixed size.

    The table has ``2**bits`` bits whatever the data; false positives are dropped
    by the join that follows.
    """
    bit = lambda c: F.pmod(F.xxhash64(c), F.lit(1 << bits))
    words = ids.select(bit("rid").alias("b")).groupBy((F.col("b") / 64).cast("int").alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(b % 64 as int))")).alias("mask"))
    with_bit = docs.withColumn("_b", bit("rid"))
    return with_bit.join(F.broadcast(words), (F.col("_b") / 64).cast("int") == F.col("word")).filter(F.expr("(shiftright(mask, cast(_b % 64 as int)) & 1L) = 1")).drop("_b", "word", "mask")


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (xor-shift-multiply) over an array of uint64."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column and the offsets of its rows; null is empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not pa.types.is_large_string(column.type):
        column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    raw = column.buffers()[2]
    data = np.frombuffer(raw, dtype=np.uint8) if raw is not None else np.zeros(0, np.uint8)
    return data, offsets


def row_slices(offsets: np.ndarray, step: int = STEP_BYTES) -> Iterator[tuple[int, int]]:
    """Ranges of whole rows, each of about ``step`` bytes (one row at least)."""
    lo, n = 0, len(offsets) - 1
    while lo < n:
        hi = int(np.searchsorted(offsets, offsets[lo] + step, side="right")) - 1
        hi = min(max(hi, lo + 1), n)
        yield lo, hi
        lo = hi


_POWERS: dict[str, np.ndarray] = {}


def powers(n: int, which: str = "up") -> np.ndarray:
    """``BASE**i`` (or its inverse's powers) for i below n, wrapping at 2**64."""
    have = _POWERS.get(which)
    if have is None or len(have) < n:
        size = max(n, 1 << 16)
        base = np.uint64(BASE if which == "up" else BASE_INV)
        have = np.full(size, base, dtype=np.uint64)
        have[0] = 1
        have = np.multiply.accumulate(have)
        _POWERS[which] = have
    return have[:n]


def as_long(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def salt_of(*cols, buckets: int):
    """A salt in [0, buckets) from the given columns."""
    return F.pmod(F.xxhash64(*cols), F.lit(buckets)).cast("int")

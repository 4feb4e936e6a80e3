"""A pair of tables to be linked, with descriptions and known matches."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class TablePair:
    """``tables`` are two or more DataFrames; ``keys`` name the column that tells rows
    apart; it is not part of the data unless listed in ``keep``."""

    tables: tuple[DataFrame, ...]
    keys: tuple[str, ...]
    #: (side, attribute) to description.
    descriptions: dict[tuple[int, str], str] = field(default_factory=dict)
    #: Known column matches (left attribute, right attribute) and record matches.
    true_columns: tuple[tuple[str, str], ...] = ()
    true_records: DataFrame | None = None
    keep: tuple[bool, ...] = (True, True)
    name: str = ""

    def columns(self, side: int) -> list[str]:
        key, keep = self.keys[side], self.keep[side] if side < len(self.keep) else True
        return [c for c in self.tables[side].columns if keep or c != key]

    def truth(self, spark: SparkSession) -> DataFrame:
        rows = [(f"0:{a}", f"1:{b}") for a, b in self.true_columns]
        return spark.createDataFrame(rows, "left_key string, right_key string")


#: Descriptions of well-known columns, for metadata sentences.
DESCRIPTIONS = {
    "c_custkey": "number that identifies the buyer", "c_name": "full name of the buyer", "c_nationkey": "numeric country of the buyer", "c_acctbal": "money on the account of the buyer", "c_mktsegment": "market the buyer works in",
    "s_suppkey": "number that identifies the seller", "s_name": "full name of the seller", "s_nationkey": "numeric country of the seller", "s_acctbal": "money on the account of the seller",
}


def customer_supplier(spark: SparkSession, sf_dir: str) -> TablePair:
    """Two natural tables with four corresponding columns and no common records."""
    left = spark.read.parquet(f"{sf_dir}/customer.parquet")
    right = spark.read.parquet(f"{sf_dir}/supplier.parquet")
    described = {(s, c): DESCRIPTIONS[c] for s, t in enumerate((left, right)) for c in t.columns}
    true = (("c_custkey", "s_suppkey"), ("c_name", "s_name"), ("c_nationkey", "s_nationkey"), ("c_acctbal", "s_acctbal"))
    return TablePair((left, right), ("c_custkey", "s_suppkey"), described, true, None, (True, True), "customer_supplier")


def load_pair(spark: SparkSession, left: str, right: str, keys: tuple[str, str], fmt: str = "parquet", **options) -> TablePair:
    """A pair from two paths in any format that Spark reads."""
    read = lambda p: spark.read.format(fmt).options(**options).load(p)
    return TablePair((read(left), read(right)), keys)


def write_report(rows: DataFrame, path: str) -> None:
    rows.coalesce(1).write.mode("overwrite").json(path)


def write_edges(edges: DataFrame, path: str) -> None:
    edges.write.mode("overwrite").partitionBy("rel").parquet(path)


def write_bucketed(adjacency: DataFrame, table: str, buckets: int = 8) -> None:
    """Adjacency bucketed and sorted by (src, slot), so that a step shuffles the frontier only."""
    adjacency.write.mode("overwrite").bucketBy(buckets, "src", "slot").sortBy("src", "slot").saveAsTable(table)


def write_review(matches: DataFrame, path: str) -> None:
    """A list of matches for reviewers, as CSV with a header."""
    matches.select("left_key", "right_key", F.round("score", 6).alias("score")).write.mode("overwrite").option("header", True).csv(path)

"""Properties of table pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkgraph.sources.pairs import TablePair


def data_size(pair: TablePair) -> DataFrame:
    """Cells of each side and of the pair, filled and missing ones counted column by column."""
    counted = lambda c: F.count(f"`{c}`") + F.count_if(F.col(f"`{c}`").isNull())
    parts = [t.agg(sum((counted(c) for c in pair.columns(s)), F.lit(0).cast("long")).alias("cells")).select(F.lit(f"side{s}").alias("what"), "cells") for s, t in enumerate(pair.tables)]
    both = parts[0]
    for p in parts[1:]:
        both = both.union(p)
    return both.union(both.agg(F.sum("cells").alias("cells")).select(F.lit("pair").alias("what"), "cells"))


def missing_rate(cells: DataFrame) -> DataFrame:
    """Missing share by table, by column and overall, in one pass."""
    return cells.groupingSets([["side", "cid"], ["side"], []], "side", "cid").agg(F.sum(F.col("is_missing").cast("long")).alias("missing"), F.count(F.lit(1)).alias("cells")).select(
        F.coalesce(F.col("side").cast("string"), F.lit("all")).alias("side"), F.coalesce("cid", F.lit("all")).alias("cid"), "missing", "cells", F.round(F.col("missing") / F.col("cells"), 6).alias("rate")
    )


def missing_by_row(cells: DataFrame) -> DataFrame:
    """Histogram of missing cells in a row."""
    return cells.groupBy("side", "rid").agg(F.sum(F.col("is_missing").cast("long")).alias("missing")).groupBy("side", "missing").agg(F.count(F.lit(1)).alias("n_rows"))


def missing_pattern(cells: DataFrame) -> DataFrame:
    """How unevenly gaps lie on columns: the mean absolute difference over twice the mean."""
    per = cells.groupBy("side", "cid").agg(F.avg(F.col("is_missing").cast("double")).alias("r"))
    a, b = per.alias("a"), per.alias("b")
    return a.join(F.broadcast(b), F.col("a.side") == F.col("b.side")).groupBy(F.col("a.side").alias("side")).agg((F.avg(F.abs(F.col("a.r") - F.col("b.r"))) / (2 * F.avg(F.col("a.r")))).alias("g")).select("side", F.round(F.coalesce("g", F.lit(0.0)), 6).alias("gini"))


def overlap_columns(pair: TablePair) -> float:
    return len(pair.true_columns) / min(len(pair.columns(0)), len(pair.columns(1)))


def overlap_rows(pair: TablePair) -> DataFrame:
    smaller = pair.tables[0].agg(F.count(F.lit(1)).alias("a")).crossJoin(pair.tables[1].agg(F.count(F.lit(1)).alias("b")))  # one row each
    return pair.true_records.agg(F.count(F.lit(1)).alias("t")).crossJoin(smaller).select("t", F.least("a", "b").alias("n"), F.round(F.col("t") / F.least("a", "b"), 6).alias("overlap"))


def specificity(names: DataFrame, generic: DataFrame) -> DataFrame:
    """Share of column names outside the list of generic names."""
    return names.join(generic.select("name").withColumn("g", F.lit(1)), "name", "left").agg(F.round(F.avg(F.col("g").isNull().cast("double")), 6).alias("specificity"))


def numeric_share(cells: DataFrame) -> DataFrame:
    """Share of filled cells that parse as numbers."""
    return cells.filter("not is_missing").groupBy("side").agg(F.round(F.avg(F.col("val").rlike(r"^-?[0-9]+(\.[0-9]+)?$").cast("double")), 6).alias("numeric_share"))


def diversity(cells: DataFrame, exact: bool = True) -> DataFrame:
    """Distinct values by filled cells of each column."""
    count = F.count_distinct("val") if exact else F.approx_count_distinct("val", 0.02)
    return cells.filter("not is_missing").groupBy("cid").agg(count.alias("distinct_values"), F.count(F.lit(1)).alias("filled")).select("cid", "distinct_values", "filled", F.round(F.col("distinct_values") / F.col("filled"), 6).alias("diversity"))

"""Measures of matches and of runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

_KEYS = ["left_key", "right_key"]


def score_pairs(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """One row: n_pred, n_true, hits, precision, recall, f1; ratios of nothing are 0."""
    a = pred.select(_KEYS).distinct().withColumn("p", F.lit(1))
    b = truth.select(_KEYS).distinct().withColumn("t", F.lit(1))
    total = lambda c: F.coalesce(F.sum(c), F.lit(0))
    row = a.join(b, _KEYS, "full").agg(total("p").alias("n_pred"), total("t").alias("n_true"), total(F.col("p") * F.col("t")).alias("hits"))
    ratio = lambda x, y: F.when(y > 0, x / y).otherwise(0.0)
    return row.withColumns({
        "precision": F.round(ratio(F.col("hits"), F.col("n_pred")), 6), "recall": F.round(ratio(F.col("hits"), F.col("n_true")), 6), "f1": F.round(ratio(2 * F.col("hits"), F.col("n_pred") + F.col("n_true")), 6),
    })


def errors(pred: DataFrame, truth: DataFrame) -> DataFrame:
    wrong = pred.select(_KEYS).distinct().join(truth, _KEYS, "left_anti").withColumn("kind", F.lit("false positive"))
    return wrong.union(truth.select(_KEYS).distinct().join(pred, _KEYS, "left_anti").withColumn("kind", F.lit("false negative")))


def compare(results: DataFrame) -> DataFrame:
    """Per workload and task: the methods' f1 side by side, their difference, and who wins at two decimals."""
    wide = results.groupBy("workload", "task").pivot("method", ["CG", "TG"]).agg(F.first("f1"))
    d = F.round("CG", 2) - F.round("TG", 2)
    return wide.withColumn("difference", F.round(F.col("CG") - F.col("TG"), 6)).withColumn("outcome", F.when(d > 0, "win").when(d < 0, "loss").otherwise("tie"))


def sensitivity(sweep: DataFrame) -> DataFrame:
    """Slope of f1 between neighbouring levels, and the steepest fall of each curve."""
    curve = ["method", "task"]
    w = Window.partitionBy(*curve).orderBy("level")
    out = sweep.withColumn("slope", (F.col("f1") - F.lag("f1").over(w)) / (F.col("level") - F.lag("level").over(w)))
    return out.withColumn("steepest", F.coalesce(F.col("slope") == F.min("slope").over(Window.partitionBy(*curve)), F.lit(False)))


def missing_surface(grid: DataFrame) -> DataFrame:
    """Grid of f1 with a row per left rate and a column per right rate."""
    return grid.groupBy("task", "left_rate").pivot("right_rate").agg(F.round(F.first("f1"), 6))


def summarize(results: DataFrame) -> DataFrame:
    """Mean f1 by block and method, rolled up."""
    return results.rollup("block", "method", "task").agg(F.round(F.avg("f1"), 6).alias("mean_f1"), F.count(F.lit(1)).alias("n"))


def ranking_quality(scored: DataFrame, truth: DataFrame, k: int = 3) -> DataFrame:
    """Recall among the k best and mean reciprocal rank, before any decision rule."""
    ranked = scored.withColumn("r", F.row_number().over(Window.partitionBy("left_key").orderBy(F.desc("score"), "right_key")))
    hit = truth.join(ranked, _KEYS, "left")
    return hit.agg(F.round(F.avg(F.coalesce((F.col("r") <= k).cast("double"), F.lit(0.0))), 6).alias("recall_at_k"), F.round(F.avg(F.coalesce(1.0 / F.col("r"), F.lit(0.0))), 6).alias("mrr"))


def ranking_of_all(counts: DataFrame, k: int = 3) -> DataFrame:
    """``ranking_quality`` where a key's ``m`` pairs are all true: their ranks are 1 to m, so no pair is needed."""
    inverse = F.aggregate(F.sequence(F.lit(1).cast("long"), F.col("m")), F.lit(0.0), lambda s, r: s + 1.0 / r)
    total = F.sum("m")
    return counts.agg(F.round(F.sum(F.least("m", F.lit(k))) / total, 6).alias("recall_at_k"), F.round(F.sum(inverse) / total, 6).alias("mrr"))


def dispersion(runs: DataFrame) -> DataFrame:
    """Mean and deviation over seeds."""
    return runs.groupBy("workload", "method", "task").agg(F.round(F.avg("f1"), 6).alias("mean_f1"), F.round(F.coalesce(F.stddev_samp("f1"), F.lit(0.0)), 6).alias("sd_f1"), F.count(F.lit(1)).alias("runs"))

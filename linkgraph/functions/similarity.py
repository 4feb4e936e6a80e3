"""Similarity measures as column expressions, and their SQL registration."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column, b: Column) -> Column:
    """Cosine of two arrays; 0 if either is the zero vector."""
    size = F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))
    return F.when(size > 0, dot(a, b) / size).otherwise(F.lit(0.0))


def unit_cosine(a: Column, b: Column) -> Column:
    """Cosine mapped to [0, 1]."""
    return (cosine(a, b) + 1.0) / 2.0


def name_similarity(a: Column, b: Column) -> Column:
    """Edit similarity of two names in [0, 1]; two empty names are equal."""
    longer = F.greatest(F.length(a), F.length(b))
    return F.when(longer == 0, F.lit(1.0)).otherwise(1.0 - F.levenshtein(a, b) / longer)


def gap(a: Column, b: Column, beta: float, eps: float, denominator: str = "abs", form: str = "printed") -> Column:
    """Relative gap of two numbers."""
    below = (F.abs(a) + F.abs(b) if denominator == "abs" else a + b) + F.lit(eps)
    if form == "homogeneous":
        return F.pow(F.abs(a - b) / below, F.lit(beta))
    return F.pow(F.abs(a - b), F.lit(beta)) / below


def register_functions(spark: SparkSession) -> None:
    """Temporary SQL functions without Python in the plan."""
    dot_sql = "aggregate(zip_with({a}, {b}, (x, y) -> x * y), 0D, (s, x) -> s + x)"
    ab, aa, bb = dot_sql.format(a="a", b="b"), dot_sql.format(a="a", b="a"), dot_sql.format(a="b", b="b")
    for name, args, kind, body in (
        ("name_similarity", "a STRING, b STRING", "DOUBLE", "CASE WHEN greatest(length(a), length(b)) = 0 THEN 1D ELSE 1D - levenshtein(a, b) / greatest(length(a), length(b)) END"),
        ("unit_cosine", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", f"(CASE WHEN {aa} > 0 AND {bb} > 0 THEN {ab} / (sqrt({aa}) * sqrt({bb})) ELSE 0D END + 1D) / 2D"),
        ("gap_similarity", "a DOUBLE, b DOUBLE, beta DOUBLE", "DOUBLE", "1D - least(1D, power(abs(a - b), beta) / (abs(a) + abs(b) + 1e-9D))"),
        ("u52", "label STRING", "DOUBLE", "CAST(conv(substr(md5(label), 1, 13), 16, 10) AS BIGINT) / 4503599627370496D"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")

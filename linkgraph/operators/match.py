"""Matches from vectors: candidates, scores, decision rules, review."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from linkgraph.functions.similarity import cosine, name_similarity
from linkgraph.operators.embed import all_scores, cosine_batches
from linkgraph.operators.tokmerge import hyperplane_keys, lsh_plan


def cosine_pairs(pairs: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """(left_key, right_key, score) of candidate pairs; sides are (key, vec)."""
    joined = pairs.join(left.select(F.col("key").alias("left_key"), F.col("vec").alias("lv")), "left_key").join(right.select(F.col("key").alias("right_key"), F.col("vec").alias("rv")), "right_key")
    return joined.select("left_key", "right_key", "lv", "rv").mapInPandas(cosine_batches, "left_key string, right_key string, score double")


def schema_scores(left: DataFrame, right: DataFrame) -> DataFrame:
    """Cosine of every column of one side with every column of the other; columns are few."""
    a = left.select(F.col("key").alias("left_key"), F.col("vec").alias("lv"))
    b = right.select(F.col("key").alias("right_key"), F.col("vec").alias("rv"))
    return a.join(F.broadcast(b)).select("left_key", "right_key", cosine(F.col("lv"), F.col("rv")).alias("score"))


def all_record_pairs(left: DataFrame, right: DataFrame, limit: int = 4_000_000) -> DataFrame:
    """Every record pair, as a control on small tables."""
    if left.count() * right.count() > limit:
        raise ValueError("too many record pairs: use candidates")
    return left.select(F.col("key").alias("left_key")).join(F.broadcast(right.select(F.col("key").alias("right_key"))))


def candidates_shared_token(rid_tok: DataFrame, max_df: int) -> DataFrame:
    """Pairs of records of different sides that share a token of at most ``max_df`` records.

    Common tokens prove little and would pair everything; they still count in the
    vectors.
    """
    rare = rid_tok.groupBy("tok").agg(F.count(F.lit(1)).alias("df")).filter(F.col("df").between(2, max_df)).select("tok")
    held = rid_tok.join(rare, "tok").select("tok", "rid")
    left = held.filter("rid like '0:%'").select("tok", F.col("rid").alias("left_key"))
    right = held.filter("rid like '1:%'").select("tok", F.col("rid").alias("right_key"))
    return left.join(right, "tok").select("left_key", "right_key").distinct()


def candidates_lsh(left: DataFrame, right: DataFrame, dim: int, bands: int | None = None, rows: int | None = None, seed: int = 5, cosine: float = 0.7) -> DataFrame:
    """Pairs whose vectors agree in a band of hyperplane signs; bands and rows follow from the number of vectors and the cosine."""
    if bands is None or rows is None:
        bands, rows = lsh_plan(max(left.count(), right.count()), cosine)
    a = hyperplane_keys(left, "key", dim, bands, rows, seed).select("band", "code", F.col("key").alias("left_key"))
    b = hyperplane_keys(right, "key", dim, bands, rows, seed).select("band", "code", F.col("key").alias("right_key"))
    return a.join(b, ["band", "code"]).select("left_key", "right_key").distinct()


def select_matches(scored: DataFrame, rule: str = "mutual_best", tau: float = 0.0, k: int = 3) -> DataFrame:
    """Matches by rule: threshold, best_left, mutual_best, top_k or one_to_one (greedy by score).

    Ties go to the smaller keys.
    """
    good = scored.filter(F.col("score") >= tau)
    if rule == "threshold":
        return good
    from_left = F.row_number().over(Window.partitionBy("left_key").orderBy(F.desc("score"), "right_key"))
    from_right = F.row_number().over(Window.partitionBy("right_key").orderBy(F.desc("score"), "left_key"))
    if rule == "best_left":
        return good.withColumn("r", from_left).filter("r = 1").drop("r")
    if rule == "top_k":
        return good.withColumn("r", from_left).filter(F.col("r") <= k).drop("r")
    if rule == "mutual_best":
        return good.withColumns({"r": from_left, "q": from_right}).filter("r = 1 and q = 1").drop("r", "q")
    if rule == "one_to_one":
        # repeated mutual best with one common order of pairs gives the greedy result
        from linkgraph.operators.tokmerge import settle

        out, rest = None, settle(good)
        by = lambda key: F.row_number().over(Window.partitionBy(key).orderBy(F.desc("score"), "left_key", "right_key"))
        while True:
            found = settle(rest.withColumns({"r": by("left_key"), "q": by("right_key")}).filter("r = 1 and q = 1").select("left_key", "right_key", "score"))
            if found.isEmpty():
                return out if out is not None else found
            out = found if out is None else out.union(found)
            rest = settle(rest.join(found.select("left_key"), "left_key", "left_anti").join(found.select("right_key"), "right_key", "left_anti"))
    raise ValueError(f"no such rule: {rule}")


def review_queue(scored: DataFrame, tau: float, margin: float = 0.05) -> DataFrame:
    """Pairs for a human: best pairs near the threshold, or with a close runner-up."""
    w = Window.partitionBy("left_key").orderBy(F.desc("score"), "right_key")
    best = scored.withColumns({"r": F.row_number().over(w), "next": F.lead("score").over(w)}).filter("r = 1")
    near, close = F.abs(F.col("score") - tau) <= margin, F.col("score") - F.coalesce("next", F.lit(-1.0)) <= margin
    return best.filter(near | close).select("left_key", "right_key", "score", F.when(near, "near threshold").otherwise("close runner-up").alias("reason"))


def apply_feedback(matches: DataFrame, decisions: DataFrame) -> DataFrame:
    """Matches after a reviewer's decisions (left_key, right_key, accept)."""
    keys = ["left_key", "right_key"]
    no, yes = decisions.filter("not accept"), decisions.filter("accept")
    kept = matches.select(keys).join(no.select(keys), keys, "left_anti")
    return kept.union(yes.select(keys)).distinct()


def confusable_columns(matches: DataFrame, truth: DataFrame, least: float = 0.6) -> DataFrame:
    """Wrong column matches whose names are close."""
    wrong = matches.join(truth, ["left_key", "right_key"], "left_anti")
    name = lambda c: F.regexp_replace(F.col(c), "^[0-9]+:", "")
    return wrong.withColumn("s_lev", name_similarity(name("left_key"), name("right_key"))).filter(F.col("s_lev") >= least)

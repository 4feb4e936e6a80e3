"""Importance of columns and tokens, and transition probabilities."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from linkgraph.operators.graph import Graph
from linkgraph.params import Params

#: Stand-in for a list of frequent column names with their counts.
GENERIC_NAMES = (
    ("id", 100), ("name", 90), ("date", 60), ("type", 55), ("key", 50), ("status", 45), ("price", 40), ("size", 35), ("region", 30), ("nation", 30), ("segment", 25), ("balance", 25), ("text", 20), ("value", 20), ("quantity", 20), ("label", 15), ("title", 15), ("url", 15),
)


def name_frequencies(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(list(GENERIC_NAMES), "name string, freq int")


def scores(prof: DataFrame, generic: DataFrame, p: Params = Params()) -> DataFrame:
    """(cid, s_miss, s_ling, s_variety, s_freq): four indicators of a column's importance.

    A name is as generic as its most frequent part among the top names.  A part
    counts if it is such a name, or one after at least three other letters (as in
    ``custkey``; an ``update`` is no date).
    """
    top = generic.orderBy(F.desc("freq"), "name").limit(p.freq_top)
    best = top.agg(F.max("freq").alias("best"))
    parts = prof.select("cid", F.explode(F.split(F.lower("name"), "[^a-z0-9]+")).alias("part"))
    freq = parts.join(F.broadcast(top), (F.col("part") == F.col("name")) | (F.col("part").endswith(F.col("name")) & (F.length("part") >= F.length("name") + 3))).groupBy("cid").agg(F.max("freq").alias("freq"))
    out = prof.join(F.broadcast(freq), "cid", "left").crossJoin(F.broadcast(best))  # one row
    return out.select(
        "cid",
        F.when(F.col("n_rows") > 0, F.col("n_valid") / F.col("n_rows")).otherwise(0.0).alias("s_miss"),
        "s_ling",
        F.when(F.col("n_valid") > 0, F.col("n_distinct") / F.col("n_valid")).otherwise(0.0).alias("s_variety"),
        F.coalesce(F.col("freq") / F.col("best"), F.lit(0.0)).alias("s_freq"),
    )


def column_weights(score_rows: DataFrame, p: Params = Params()) -> DataFrame:
    w = p.c_m * F.col("s_miss") + p.c_l * F.col("s_ling") + p.c_v * F.col("s_variety") + p.c_f * F.col("s_freq")
    return score_rows.withColumn("w", w)


def token_weights(tok_cid: DataFrame, weights: DataFrame, mode: str = "multiplicity") -> DataFrame:
    """(tok, w): mean weight of a token's columns, by multiplicity or plain."""
    joined = tok_cid.join(F.broadcast(weights.select("cid", F.col("w").alias("cw"))), "cid")
    mean = F.sum(F.col("mult") * F.col("cw")) / F.sum("mult") if mode == "multiplicity" else F.avg("cw")
    return joined.groupBy("tok").agg(mean.alias("w"))


def rid_transitions(rid_tok: DataFrame, tok_w: DataFrame) -> DataFrame:
    """(rid, tok, prob): by token weight; uniform where all weights are 0."""
    joined = rid_tok.join(tok_w, "tok")
    by = Window.partitionBy("rid")
    total, n = F.sum("w").over(by), F.count(F.lit(1)).over(by)
    return joined.select("rid", "tok", F.when(total > 0, F.col("w") / total).otherwise(1.0 / n).alias("prob"))


def cid_transitions(g: Graph, p: Params = Params()) -> DataFrame:
    """(cid, n_tok, cid_mass, p_tok_each, p_cid): what a column's hops go to.

    "unit" gives each token edge weight 1 and column edges their similarity;
    "share" gives all column edges together a fixed mass.
    """
    deg = g.tok_cid.groupBy("cid").agg(F.count(F.lit(1)).alias("n_tok"))
    both = g.cid_cid.select(F.col("left_cid").alias("cid"), "weight").union(g.cid_cid.select(F.col("right_cid").alias("cid"), "weight"))
    mass = both.groupBy("cid").agg(F.sum("weight").alias("cid_mass"))
    out = g.cids.select("cid").join(deg, "cid", "left").join(mass, "cid", "left").na.fill(0)
    if p.cid_edge_mass == "unit":
        p_cid = F.when(F.col("n_tok") + F.col("cid_mass") > 0, F.col("cid_mass") / (F.col("n_tok") + F.col("cid_mass"))).otherwise(0.0)
    else:
        p_cid = F.when(F.col("cid_mass") == 0, 0.0).when(F.col("n_tok") == 0, 1.0).otherwise(p.cid_share)
    return out.withColumn("p_cid", p_cid).withColumn("p_tok_each", F.when(F.col("n_tok") > 0, (1 - F.col("p_cid")) / F.col("n_tok")).otherwise(0.0))


def tok_transitions(g: Graph) -> DataFrame:
    """(tok, degree, prob): a token hops evenly to its records and columns."""
    both = g.rid_tok.select("tok").union(g.tok_cid.select("tok"))
    return both.groupBy("tok").agg(F.count(F.lit(1)).alias("degree")).withColumn("prob", 1.0 / F.col("degree"))


def uniform_transitions(g: Graph) -> DataFrame:
    """(kind, key, degree): every node hops evenly to its neighbours."""
    r = g.rid_tok.groupBy(F.col("rid").alias("key")).agg(F.count(F.lit(1)).alias("degree")).select(F.lit("R").alias("kind"), "key", "degree")
    c = g.tok_cid.groupBy(F.col("cid").alias("key")).agg(F.count(F.lit(1)).alias("degree")).select(F.lit("C").alias("kind"), "key", "degree")
    return r.union(c).union(tok_transitions(g).select(F.lit("T").alias("kind"), F.col("tok").alias("key"), "degree"))

"""The graph of records, tokens and columns."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkgraph.functions.draws import node_id
from linkgraph.operators import colsim
from linkgraph.operators.prepare import cells as pair_cells
from linkgraph.operators.prepare import tokenize
from linkgraph.params import Params
from linkgraph.sources.pairs import TablePair


@dataclass(frozen=True)
class Graph:
    """Parts of the graph.  Records and columns carry their side in their key."""

    rids: DataFrame
    #: (rid, tok, mult) and (tok, cid, mult)
    rid_tok: DataFrame
    tok_cid: DataFrame
    cids: DataFrame
    #: (left_cid, right_cid, weight); empty for the tripartite graph
    cid_cid: DataFrame


def rid_nodes(pair: TablePair) -> DataFrame:
    """Every row is a node, even one without any value."""
    out = None
    for s, t in enumerate(pair.tables):
        part = t.select(F.lit(s).alias("side"), F.concat(F.lit(f"{s}:"), F.col(f"`{pair.keys[s]}`").cast("string")).alias("rid"))
        out = part if out is None else out.union(part)
    return out


def rid_tok_edges(tokens: DataFrame) -> DataFrame:
    return tokens.groupBy("rid", "tok").agg(F.sum("occ").alias("mult"))


def tok_cid_edges(tokens: DataFrame) -> DataFrame:
    return tokens.groupBy("tok", "cid").agg(F.sum("occ").alias("mult"))


def build_graph(spark: SparkSession, pair: TablePair, p: Params = Params(), tokens: DataFrame | None = None, sim: DataFrame | None = None) -> Graph:
    tokens = tokenize(pair_cells(pair), p.token_mode) if tokens is None else tokens
    meta = colsim.metadata(spark, pair)
    if p.cid_edges:
        edges = colsim.cid_edges(colsim.column_similarity(spark, pair, p) if sim is None else sim)
    else:
        edges = spark.createDataFrame([], "left_cid string, right_cid string, weight double")
    return Graph(rid_nodes(pair), rid_tok_edges(tokens), tok_cid_edges(tokens), meta.select("side", "cid", "name"), edges)


def nodes(g: Graph) -> DataFrame:
    """(node_id, kind, side, key) of every node."""
    toks = g.tok_cid.select("tok").distinct()
    parts = [
        g.rids.select(node_id("R", F.col("rid")).alias("node_id"), F.lit("R").alias("kind"), "side", F.col("rid").alias("key")),
        toks.select(node_id("T", F.col("tok")).alias("node_id"), F.lit("T").alias("kind"), F.lit(None).cast("int").alias("side"), F.col("tok").alias("key")),
        g.cids.select(node_id("C", F.col("cid")).alias("node_id"), F.lit("C").alias("kind"), "side", F.col("cid").alias("key")),
    ]
    return parts[0].union(parts[1]).union(parts[2])


def edges(g: Graph) -> DataFrame:
    """Every edge in both directions: (src, dst, rel, weight, mult)."""
    r, t, c = (lambda k, col: node_id(k, F.col(col)),) * 3
    rt = g.rid_tok.select(r("R", "rid").alias("a"), t("T", "tok").alias("b"), F.lit("R").alias("x"), F.lit("T").alias("y"), F.lit(1.0).alias("weight"), "mult")
    tc = g.tok_cid.select(t("T", "tok").alias("a"), c("C", "cid").alias("b"), F.lit("T").alias("x"), F.lit("C").alias("y"), F.lit(1.0).alias("weight"), "mult")
    cc = g.cid_cid.select(c("C", "left_cid").alias("a"), c("C", "right_cid").alias("b"), F.lit("C").alias("x"), F.lit("C").alias("y"), "weight", F.lit(1).cast("long").alias("mult"))
    one = rt.union(tc).union(cc)
    way = lambda a, b, x, y: one.select(F.col(a).alias("src"), F.col(b).alias("dst"), F.concat(x, y).alias("rel"), "weight", "mult")
    return way("a", "b", "x", "y").union(way("b", "a", "y", "x"))


def check_graph(g: Graph) -> DataFrame:
    """Violations of the four-partite form; empty for a sound graph."""
    n, e = nodes(g), edges(g)
    ends = e.join(n.select(F.col("node_id").alias("src"), F.col("kind").alias("sk"), F.col("side").alias("ss")), "src", "left").join(n.select(F.col("node_id").alias("dst"), F.col("kind").alias("dk"), F.col("side").alias("ds")), "dst", "left")
    pair_of = F.concat(F.coalesce("sk", F.lit("?")), F.coalesce("dk", F.lit("?")))
    bad = ~pair_of.isin("RT", "TR", "TC", "CT", "CC") | ((pair_of == "CC") & (F.col("ss") == F.col("ds")))
    clash = n.groupBy("node_id").agg(F.count(F.lit(1)).alias("c")).filter("c > 1").select(F.lit("repeated id").alias("what"), "node_id")
    return ends.filter(bad).select(F.concat(F.lit("edge "), pair_of).alias("what"), F.col("src").alias("node_id")).union(clash)


def graph_stats(g: Graph) -> DataFrame:
    """Nodes and directed edges by kind."""
    n = nodes(g).groupBy("kind").agg(F.count(F.lit(1)).alias("n")).select(F.concat(F.lit("nodes "), "kind").alias("what"), "n")
    return n.union(edges(g).groupBy("rel").agg(F.count(F.lit(1)).alias("n")).select(F.concat(F.lit("edges "), "rel").alias("what"), "n"))

"""Connected components of an edge table by alternating star contractions.

Each round points every node at the smallest label it can see, first from the
larger neighbours, then from the smaller ones, until nothing moves.  Rounds are
equi-joins and minimum aggregates with map-side combining, so a hub of any
degree is never gathered in one task, and each round's edges are a written
table in the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkgraph.llm.common import materialise


def _fingerprint(edges: DataFrame) -> tuple:
    """Number of edges and an order-free sum of their hashes."""
    row = edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)")), F.sum(F.hash("v", "u").cast("long"))).first()
    return tuple(row)


def connected_components(edges: DataFrame, left: str = "a", right: str = "b", max_rounds: int = 60) -> DataFrame:
    """``(node, component)`` for every node on an edge; component = smallest node.

    Self-loops and repeated edges do no harm; null ends are dropped.  An empty
    edge table gives an empty result.
    """
    now = materialise(
        edges.select(F.col(left).alias("u"), F.col(right).alias("v"))
        .filter("u is not null and v is not null and u <> v")
        .select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
        .distinct(),
        "edges",
    )
    nodes, mark = now, _fingerprint(now)
    if not mark[0]:
        return now.select(F.col("u").alias("node"), F.col("v").alias("component"))
    for _ in range(max_rounds):
        # large star: each node's larger neighbours (and itself) point at its minimum
        both = now.union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = (
            both.filter("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        ).union(low.filter("m < u").select("u", F.col("m").alias("v")))
        large = large.filter("u > v").distinct()
        # small star: smaller neighbours point at the minimum as well
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = (
            large.join(low, "u").filter("v > m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        ).union(low.select("u", F.col("m").alias("v")))
        new = materialise(small.filter("u > v").distinct(), "edges")
        seen, mark = mark, _fingerprint(new)
        now = new
        if mark == seen:
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    ends = nodes.select(F.explode(F.array("u", "v")).alias("node")).distinct()
    return ends.join(now.groupBy("u").agg(F.min("v").alias("m")), F.col("node") == F.col("u"), "left").select(
        "node", F.coalesce("m", "node").alias("component")
    )

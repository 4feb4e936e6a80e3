"""The methods end to end."""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkgraph.functions.draws import node_id
from linkgraph.operators import colsim, embed, evaluate, match, tokmerge, walk
from linkgraph.operators.graph import Graph, build_graph, nodes
from linkgraph.operators.prepare import cells, tokenize
from linkgraph.params import Params
from linkgraph.sources.pairs import TablePair
from linkgraph.sources.shared import written


@dataclass
class LinkResult:
    graph: Graph
    vectors: DataFrame
    #: Scored and chosen column and record matches.
    column_scores: DataFrame
    column_matches: DataFrame
    record_scores: DataFrame
    record_matches: DataFrame
    #: Seconds and counts by stage.
    cost: dict[str, float] = field(default_factory=dict)
    #: What was persisted on the way.
    held: list[DataFrame] = field(default_factory=list)

    def release(self) -> None:
        """Gives back what this run persisted, and nothing else."""
        for df in self.held:
            df.unpersist()


def link(spark: SparkSession, pair: TablePair, p: Params = Params(), cost: bool = False) -> LinkResult:
    """The contextual graph method; with ``p.tripartite()`` the plain graph baseline."""
    spent: dict[str, float] = {}
    held: list[DataFrame] = []
    began = time.time()

    def keep(name: str, df: DataFrame) -> DataFrame:
        nonlocal began
        df = df.persist(StorageLevel.MEMORY_AND_DISK)
        held.append(df)
        if cost:
            spent[f"{name}_rows"] = df.count()
            spent[f"{name}_s"] = round(time.time() - began, 3)
            began = time.time()
        return df

    tables = TablePair(tuple(t.persist(StorageLevel.MEMORY_AND_DISK) for t in pair.tables), pair.keys, pair.descriptions, pair.true_columns, pair.true_records, pair.keep, pair.name)
    tokens = keep("tokens", tokenize(cells(tables), p.token_mode))
    prof = keep("profile", colsim.profile(tables)) if p.cid_edges or p.weighted else None
    sim = keep("similarity", colsim.column_similarity(spark, tables, p, prof)) if p.cid_edges else None
    if p.merge:
        tokens = keep("merged_tokens", tokmerge.merge_tokens(spark, tokens, p))
    g = build_graph(spark, tables, p, tokens, sim)
    g = Graph(g.rids, keep("rid_tok", g.rid_tok), keep("tok_cid", g.tok_cid), g.cids, g.cid_cid)
    weights = walk.weights_of(spark, tables, p, prof) if p.weighted else None
    walks = keep("walk_steps", walk.random_walks(spark, g, nodes(g), p, weights))
    vectors = keep("vectors", embed.embed(walks, p))
    named = lambda kind, df, col: df.select(F.col(col).alias("key"), node_id(kind, F.col(col)).alias("node_id")).join(vectors, "node_id").select("key", "vec")
    cids, rids = named("C", g.cids, "cid"), keep("record_vectors", named("R", g.rids, "rid"))
    one = lambda df, s: df.filter(F.col("key").startswith(f"{s}:"))
    column_scores = match.schema_scores(one(cids, 0), one(cids, 1))
    left, right = one(rids, 0), one(rids, 1)
    record_scores = keep("record_scores", _record_scores(g, left, right, p))
    held.extend(tables.tables)
    return LinkResult(g, vectors, column_scores, match.select_matches(column_scores, "mutual_best", p.tau_sm), record_scores, match.select_matches(record_scores, "mutual_best", p.tau_er), spent, held)


def link_columns(spark: SparkSession, pair: TablePair, p: Params = Params()) -> DataFrame:
    """The column scores of ``link`` alone, from the same walks, of which only the columns' pairs are kept."""
    # a file may be a single split; cells are made by all tasks, and tokens and edges once
    pair = replace(pair, tables=tuple(t.repartition(key) for t, key in zip(pair.tables, pair.keys, strict=True)))
    tokens = written(tokenize(cells(pair), p.token_mode))
    prof = written(colsim.profile(pair)) if p.cid_edges or p.weighted else None
    sim = colsim.column_similarity(spark, pair, p, prof) if p.cid_edges else None
    if p.merge:
        tokens = tokmerge.merge_tokens(spark, tokens, p)
    g = build_graph(spark, pair, p, tokens, sim)
    g = Graph(g.rids, written(g.rid_tok), written(g.tok_cid), g.cids, g.cid_cid)
    if p.learner == "blocked" or not walk.fits_arrays(g, p, walk.ORDERED):
        return link(spark, pair, p).column_scores
    if p.learner == "w2v":
        return _skipgram_columns(spark, pair, g, p, prof)
    weights = walk.weights_of(spark, pair, p, prof) if p.weighted else None
    if not walk.fits_arrays(g, p):
        return _counted_columns(spark, g, p, weights)
    t = walk.transitions(spark, g, p, weights)
    ids = g.cids.select(F.col("cid").alias("key"), node_id("C", F.col("cid")).alias("node_id"))
    pairs = tokmerge.settle(walk.pairs_of_few(spark, walk.starts(nodes(g), p), t, p, [r["node_id"] for r in ids.collect()]))
    named = ids.join(embed.embed_few(pairs, p), "node_id").select("key", "vec")
    return match.schema_scores(named.filter("key like '0:%'"), named.filter("key like '1:%'"))


def _counted_columns(spark: SparkSession, g: Graph, p: Params, weights: DataFrame | None) -> DataFrame:
    """Column scores of graphs whose arrays only tasks put in order."""
    a = walk.ordered_arrays(g, p, weights)
    ids = g.cids.select(F.col("cid").alias("key"), node_id("C", F.col("cid")).alias("node_id"))
    number = walk.numbers(a, np.array([r["node_id"] for r in ids.collect()], dtype=np.int64))
    shipped = spark.sparkContext.broadcast((a, number[number >= 0]))
    named = ids.join(embed.embed_columns(written(walk.pairs_of_columns(spark, shipped, p)), shipped, p), "node_id").select("key", "vec")
    return match.schema_scores(named.filter("key like '0:%'"), named.filter("key like '1:%'"))


def _skipgram_columns(spark: SparkSession, pair: TablePair, g: Graph, p: Params, prof: DataFrame | None) -> DataFrame:
    """Column scores of the skip-gram, whose walks are made and trained on in the same tasks."""
    arrays = walk.arrays_of_graph if walk.fits_arrays(g, p) else walk.ordered_arrays
    a = arrays(g, p, walk.weights_of(spark, pair, p, prof) if p.weighted else None)
    ids = g.cids.select(F.col("cid").alias("key"), node_id("C", F.col("cid")).alias("node_id"))
    number = walk.numbers(a, (every := np.array([r["node_id"] for r in ids.collect()], dtype=np.int64)))
    wanted = np.zeros(len(a.ids), dtype=bool)
    wanted[number[number >= 0]] = True
    parts = embed.task_parts(len(a.ids) * p.walks_per_node * p.walk_length, len(a.ids), p)
    vectors = embed.averaged(walk.trained_on_arrays(spark, spark.sparkContext.broadcast((a, wanted)), p, parts), p, 1)  # of the columns alone
    # a column without an edge keeps its first vector
    alone = every[number < 0]
    if len(alone):
        vectors = vectors.union(spark.createDataFrame([(int(i), v.tolist()) for i, v in zip(alone, embed.first_vectors(alone, p), strict=True)], "node_id long, vec array<double>"))
    named = tokmerge.settle(ids.join(vectors, "node_id").select("key", "vec"))
    return match.schema_scores(named.filter("key like '0:%'"), named.filter("key like '1:%'"))


def matched(spark: SparkSession, pair: TablePair, p: Params = Params()) -> LinkResult:
    """The matches of ``link`` without its intermediate rows: all record pairs, on arrays, as far as the graph fits them."""
    if p.learner != "ppmi" or p.er_candidates != "all":
        return link(spark, pair, p)
    held: list[DataFrame] = []

    def keep(df: DataFrame) -> DataFrame:
        held.append(df.persist(StorageLevel.MEMORY_AND_DISK))
        return df

    tokens = keep(tokenize(cells(pair), p.token_mode))
    # a row of each column; as a cached plan it was made again by each reader
    prof = written(colsim.profile(pair)) if p.cid_edges or p.weighted else None
    sim = colsim.column_similarity(spark, pair, p, prof) if p.cid_edges else None
    if p.merge:
        tokens = keep(tokmerge.merge_tokens(spark, tokens, p))
    g = build_graph(spark, pair, p, tokens, sim)
    g = Graph(g.rids, keep(g.rid_tok), keep(g.tok_cid), g.cids, g.cid_cid)
    if not walk.fits_arrays(g, p, walk.ORDERED):
        for df in held:
            df.unpersist()
        return link(spark, pair, p)
    arrays = walk.arrays_of_graph if walk.fits_arrays(g, p) else walk.ordered_arrays
    a = arrays(g, p, walk.weights_of(spark, pair, p, prof) if p.weighted else None)
    # a record and a column may be of one name
    named = g.rids.select(node_id("R", F.col("rid")).alias("node_id"), F.concat(F.lit("R"), "rid").alias("key")).union(g.cids.select(node_id("C", F.col("cid")), F.concat(F.lit("C"), "cid"))).toArrow()
    keys: list[str | None] = [None] * len(a.ids)
    for i, key in zip(walk.numbers(a, named.column("node_id").to_numpy()).tolist(), named.column("key").to_pylist(), strict=True):
        if i >= 0:
            keys[i] = key
    # a task's walks and its centres' pairs fit a worker's memory
    parts = max(1, -(-len(a.ids) * p.walks_per_node * p.walk_length // 1_000_000))
    shipped = spark.sparkContext.broadcast((a, np.array([k is not None for k in keys], dtype=bool)))
    pairs = keep(walk.pairs_on_arrays(spark, shipped, p, parts))
    vectors = keep(embed.embed_arrays(pairs, a.ids, keys, p, parts))
    one = lambda kind, s: vectors.filter(F.col("key").startswith(f"{kind}{s}:")).select(F.expr("substring(key, 2)").alias("key"), "vec")
    found = [keep(embed.mutual_best(one(kind, 0), one(kind, 1), tau, p.dim)) for kind, tau in (("C", p.tau_sm), ("R", p.tau_er))]
    return LinkResult(g, vectors, found[0], found[0], found[1], found[1], {}, held)


def _record_scores(g: Graph, left: DataFrame, right: DataFrame, p: Params) -> DataFrame:
    """Scores of record pairs.  "all" leaves out those below the threshold, which no rule takes."""
    if p.er_candidates == "all":
        return match.all_scores(left, right, p.tau_er, p.dim)
    pairs = match.candidates_shared_token(g.rid_tok, p.max_df) if p.er_candidates != "lsh" else None
    if p.er_candidates != "shared":
        near = match.candidates_lsh(left, right, p.dim, cosine=p.er_cosine)
        pairs = near if pairs is None else pairs.union(near).distinct()
    return match.cosine_pairs(pairs, left, right)


def link_tripartite(spark: SparkSession, pair: TablePair, p: Params = Params(), cost: bool = False) -> LinkResult:
    return link(spark, pair, p.tripartite(), cost)


def scored(spark: SparkSession, pair: TablePair, result: LinkResult, method: str) -> DataFrame:
    """(workload, method, task, precision, recall, f1) of a result against what is known."""
    out = None
    for task, found, truth in (("SM", result.column_matches, pair.truth(spark)), ("ER", result.record_matches, pair.true_records)):
        if truth is None:
            continue
        row = evaluate.score_pairs(found, truth).select(F.lit(pair.name).alias("workload"), F.lit(method).alias("method"), F.lit(task).alias("task"), "precision", "recall", "f1")
        out = row if out is None else out.union(row)
    return out


def held(pair: TablePair) -> TablePair:
    """The pair with its tables persisted, as several runs read them."""
    return replace(pair, tables=tuple(t.persist(StorageLevel.MEMORY_AND_DISK) for t in pair.tables))


def at_once(jobs: list[Callable[[], list]], threads: int = 6) -> list[list]:
    """Results of independent runs in their order; most of a small run is waiting, so several go at once."""
    with ThreadPoolExecutor(threads) as pool:
        return list(pool.map(lambda job: job(), jobs))


def experiment(spark: SparkSession, pair: TablePair, p: Params = Params(), methods: tuple[str, ...] = ("CG", "TG")) -> DataFrame:
    """Both graph methods on a pair, scored for both tasks; few rows."""
    rows, pair = [], held(pair)
    for m in methods:
        result = matched(spark, pair, p if m == "CG" else p.tripartite())
        rows += [tuple(r) for r in scored(spark, pair, result, m).collect()]
        result.release()
    for t in pair.tables:
        t.unpersist()
    return spark.createDataFrame(rows, "workload string, method string, task string, precision double, recall double, f1 double")


def ablate(spark: SparkSession, pair: TablePair, p: Params = Params()) -> DataFrame:
    """All settings of the three innovations, similarity by schema or instances alone, and importance without each of its parts."""
    grid = {f"edges={int(e)} merge={int(m)} weights={int(w)}": replace(p, cid_edges=e, merge=m, weighted=w) for e in (True, False) for m in (True, False) for w in (True, False)}
    grid |= {"schema only": replace(p, fixed_alpha=1.0), "instances only": replace(p, fixed_alpha=0.0)}
    grid |= {f"without {c}": replace(p, **{c: 0.0}) for c in ("c_m", "c_l", "c_v", "c_f")}
    pair = held(pair)

    def run(name: str, q: Params) -> list:
        result = matched(spark, pair, q)
        rows = [(name, *r) for r in map(tuple, scored(spark, pair, result, "CG").select("task", "precision", "recall", "f1").collect())]
        result.release()
        return rows

    rows = [r for part in at_once([lambda n=n, q=q: run(n, q) for n, q in grid.items()]) for r in part]
    for t in pair.tables:
        t.unpersist()
    return spark.createDataFrame(rows, "setting string, task string, precision double, recall double, f1 double")


def repeat(spark: SparkSession, pair: TablePair, seeds: tuple[int, ...] = (42, 43, 44), p: Params = Params()) -> DataFrame:
    """Mean and deviation of both methods' scores over seeds."""
    runs = None
    for s in seeds:
        part = experiment(spark, pair, replace(p, seed=s))
        runs = part if runs is None else runs.union(part)
    return evaluate.dispersion(runs)

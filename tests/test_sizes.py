"""Queries whose work must not grow past one machine, and queries that must read their tables."""

from dataclasses import replace

import numpy as np
import pytest

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["walk_uniform_local", "embed_pairs", "embed_ppmi", "walk_stats"])
def test_walks_beyond_the_arrays_go_by_joins(spark, monkeypatch, name):
    from linkgraph.operators import walk
    from linkgraph.plans import catalog

    def refuse(*_):
        raise AssertionError("the graph was taken to the driver")

    few = spark.createDataFrame([("1:0", 0, 1), ("1:0", 1, 2)], "walk_id string, step int, node_id long")
    monkeypatch.setattr(walk, "walks_on_arrays", refuse)
    monkeypatch.setattr(walk, "walks_by_joins", lambda first, t, p: few)
    monkeypatch.setattr(catalog, "W", replace(catalog.W, local_edges=0))
    catalog.QUERIES[name][0](spark, SF)


@pytest.mark.parametrize("local_edges", [0, 4_000_000])
def test_walks_read_what_their_edges_are_made_of_once(spark, monkeypatch, local_edges):
    from linkgraph.operators import prepare
    from linkgraph.plans import catalog

    read, tokenize = spark.sparkContext.accumulator(0), prepare.tokenize

    def counted(cells, mode="token"):
        def run(frames):
            for f in frames:
                read.add(len(f))
                yield f

        return tokenize(cells.mapInPandas(run, cells.schema), mode)

    for module in (prepare, catalog.graph):
        monkeypatch.setattr(module, "tokenize", counted)
    monkeypatch.setattr(catalog, "W", replace(catalog.W, local_edges=local_edges))
    got = catalog.QUERIES["embed_w2v"][0](spark, SF).collect()
    assert len(got) == len({r["node_id"] for r in got}) and {r["dim"] for r in got} == {catalog.W.dim}
    assert read.value == catalog._cells(spark, SF).count()


@pytest.mark.parametrize("name", ["vec_label_retrieval", "eval_ranking"])
def test_vector_queries_send_no_pairs_through_a_join(spark, monkeypatch, name):
    import duckdb

    from linkgraph.operators import match
    from linkgraph.plans import catalog
    from tools.compare import rows_of

    def refuse(*_):
        raise AssertionError("vectors were joined to all pairs")

    monkeypatch.setattr(match, "cosine_pairs", refuse)
    run, sql = catalog.QUERIES[name]
    df = run(spark, SF)
    con = duckdb.connect()
    con.sql(f"CREATE VIEW embeddings AS SELECT * FROM '{SF}/embeddings.parquet'")
    cur = con.execute(sql)
    assert rows_of(df.columns, df.collect()) == rows_of([c[0] for c in cur.description], cur.fetchall())


def test_nearest_in_blocks_with_copies(spark):
    from linkgraph.operators import embed

    rows = spark.createDataFrame([(k, [1.0, 0.0]) for k in range(6)] + [(7, [0.0, 1.0]), (8, [0.6, 0.8])], "key long, vec array<double>").repartition(3)
    got = embed.nearest(rows.filter("key in (0, 5, 7)"), rows, 2, block=2).collect()
    assert sorted((r["left_key"], r["right_key"], r["score"]) for r in got) == [(0, 1, 1.0), (0, 2, 1.0), (5, 0, 1.0), (5, 1, 1.0), (7, 0, 0.0), (7, 8, 0.8)]


@pytest.mark.parametrize("name", ["base_lexicon", "eval_confusable", "prop_data_size", "prop_specificity", "sim_candidate_columns", "sim_hash_encode", "sim_name", "eval_compare", "eval_sensitivity", "eval_summary"])
def test_given_tables_are_scanned(spark, name):
    from linkgraph.plans import catalog

    plan = catalog.QUERIES[name][0](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "FileScan parquet" in plan and "ReadSchema: struct<>" not in plan


def test_prompt_shows_typical_values(spark):
    from pyspark.sql import functions as F

    from linkgraph.operators.baselines import typical_values
    from linkgraph.plans import catalog
    from linkgraph.sources.pairs import TablePair

    left = spark.createDataFrame([(1, "b"), (2, "a  c"), (3, "a c"), (4, None)], "k long, x string")
    pair = TablePair((left, left.filter(F.lit(False))), ("k", "k"), {}, (), None, (False, False), "t")
    assert typical_values(pair) == {(0, "x"): ["a c", "b"]}
    lines = [r["text"] for r in catalog.QUERIES["base_prompt_render"][0](spark, SF).collect()]
    assert sum("; for example " in x for x in lines) == 9


def test_scanned_columns_stay_without_values_or_rows(spark):
    from pyspark.sql import functions as F

    from linkgraph.operators import colsim
    from linkgraph.sources.pairs import TablePair

    t = spark.createDataFrame([(1, None), (2, None)], "k long, x string")
    got = colsim.scanned_metadata(spark, TablePair((t, t.filter(F.lit(False))), ("k", "k"))).collect()
    assert {r["cid"]: r["n_filled"] for r in got} == {"0:k": 2, "0:x": 0, "1:k": 0, "1:x": 0}


def test_column_vectors_from_counted_walks(spark):
    from pyspark.sql import functions as F

    from linkgraph.functions.draws import node_id
    from linkgraph.operators import embed, walk
    from linkgraph.operators.graph import Graph
    from linkgraph.params import Params

    edges = [(f"0:{r}", f"t{(r * 3 + k) % 7}") for r in range(5) for k in range(3)]
    rid_tok = spark.createDataFrame(edges, "rid string, tok string").withColumn("mult", F.lit(1))
    tok_cid = spark.createDataFrame([(f"t{k}", f"{k % 2}:a", 1) for k in range(7)], "tok string, cid string, mult int")
    cid = spark.createDataFrame([("0:a",), ("1:a",)], "cid string")
    edge = spark.createDataFrame([("0:a", "1:a", 0.8)], "left_cid string, right_cid string, weight double")
    p = Params(walk_length=6, walks_per_node=3, dim=16)
    t = walk.transitions(spark, Graph(rid_tok.select("rid").distinct(), rid_tok, tok_cid, cid, edge), p, cid.withColumn("w", F.lit(1.0)))
    first = walk.starts(rid_tok.select(node_id("R", F.col("rid")).alias("node_id"), F.lit("R").alias("kind")).distinct(), p)
    ids = [r[0] for r in cid.select(node_id("C", F.col("cid"))).collect()]
    whole = {r["node_id"]: r["vec"] for r in embed.embed_ppmi(walk.walks_on_arrays(spark, first, t, p), p).collect()}
    few = {r["node_id"]: r["vec"] for r in embed.embed_few(walk.pairs_of_few(spark, first, t, p, ids), p).collect()}
    assert set(few) == set(ids) & set(whole) and few
    assert all(v == pytest.approx(whole[n], abs=1e-9) for n, v in few.items())


def _small_pair(spark):
    from pyspark.sql import functions as F

    from linkgraph.sources.pairs import TablePair

    rows = [(k, f"{'red' if k % 2 else 'blue'} item{k % 9}", float(k % 5)) for k in range(24)]
    left = spark.createDataFrame(rows, "k long, label string, price double")
    right = left.filter("k % 3 > 0").withColumnsRenamed({"label": "name", "price": "cost"})
    # a record named as a column is
    left = left.select(F.when(F.col("k") == 3, F.lit("label")).otherwise(F.col("k").cast("string")).alias("k"), "label", "price")
    right = right.withColumn("k", F.col("k").cast("string"))
    keys = [F.concat(F.lit(f"{s}:"), "k").alias(c) for s, c in enumerate(("left_key", "right_key"))]
    return TablePair((left, right), ("k", "k"), {}, (("label", "name"), ("price", "cost")), right.select(*keys), (False, False), "small")


def test_matches_on_arrays_are_those_of_link(spark):
    from linkgraph.params import Params
    from linkgraph.plans import link as plans

    p = Params(walks_per_node=3, walk_length=8, dim=32, er_candidates="all", tau_cid=0.3)
    for q in (replace(p, cid_edge_mass="unit"), p.tripartite()):
        whole, quick = plans.link(spark, _small_pair(spark), q), plans.matched(spark, _small_pair(spark), q)
        for a, b in ((whole.column_matches, quick.column_matches), (whole.record_matches, quick.record_matches)):
            a, b = ({(r["left_key"], r["right_key"]): r["score"] for r in x.collect()} for x in (a, b))
            assert a and a.keys() == b.keys() and all(b[k] == pytest.approx(a[k], abs=1e-9) for k in a)
        whole.release()
        quick.release()


def test_experiments_keep_no_steps_or_record_pairs(spark, monkeypatch):
    from linkgraph.params import Params
    from linkgraph.plans import link as plans

    def refuse(*_, **__):
        raise AssertionError("walks or scores of all record pairs were written out")

    monkeypatch.setattr(plans.walk, "random_walks", refuse)
    monkeypatch.setattr(plans.match, "all_scores", refuse)
    p = Params(walks_per_node=2, walk_length=6, dim=16, er_candidates="all")
    assert plans.experiment(spark, _small_pair(spark), p).count() == 4
    # graphs beyond the arrays still walk by joins
    with pytest.raises(AssertionError):
        plans.experiment(spark, _small_pair(spark), replace(p, local_edges=0))


def test_mutual_best_over_blocks_and_ties(spark):
    from pyspark.sql import functions as F

    from linkgraph.operators import match

    vecs = lambda n, k: [(f"{i:04d}", [float(1 + (i * k) % 7), float(i % 3), 1.0]) for i in range(n)]
    left, right = (spark.createDataFrame(vecs(n, k), "key string, vec array<double>") for n, k in ((700, 3), (40, 5)))
    from linkgraph.operators.embed import mutual_best

    want = match.select_matches(match.all_scores(left, right, 0.2, 3).withColumn("score", F.round("score", 12)), "mutual_best", 0.2)
    got = mutual_best(left, right, 0.2, 3).collect()
    assert {(r[0], r[1]) for r in got} == {(r[0], r[1]) for r in want.collect()} and got
    assert mutual_best(left, right.filter("key < ''"), 0.2, 3).count() == 0 == mutual_best(left.filter("key < ''"), right, 0.2, 3).count()


def test_mutual_best_takes_a_large_right_side_in_turns(spark):
    from linkgraph.operators.embed import mutual_best

    rng = np.random.default_rng(5)
    side = lambda n, s: spark.createDataFrame([(f"{s}:{i}", v.tolist()) for i, v in enumerate(rng.normal(size=(n, 8)))], "key string, vec array<double>")
    left, right = side(900, 0), side(500, 1)
    right = right.union(right.limit(5).selectExpr("concat(key, 'x')", "vec"))
    rows = lambda df: sorted((r[0], r[1], round(r[2], 6)) for r in df.collect())
    a, b = (np.array([r["vec"] for r in df.orderBy("key").collect()]) for df in (left, right))
    keys = [[r["key"] for r in df.orderBy("key").collect()] for df in (left, right)]
    score = np.round(a / np.linalg.norm(a, axis=1, keepdims=True) @ (b / np.linalg.norm(b, axis=1, keepdims=True)).T, 12)
    want = sorted((keys[0][i], keys[1][j], round(float(score[i, j]), 6)) for i, j in enumerate(score.argmax(axis=1)) if score[:, j].argmax() == i and score[i, j] >= 0.5)
    assert rows(mutual_best(left, right, 0.5, 8, limit=10_000)) == want == rows(mutual_best(left, right, 0.5, 8))


@pytest.mark.parametrize("all_pairs", [60_000, 0])
def test_tokens_merge_without_joins_of_pairs(spark, monkeypatch, all_pairs):
    from pyspark.sql import functions as F

    from linkgraph.operators import tokmerge
    from linkgraph.params import Params

    words = ["internationalisation", "internationalisations", "internationalisatio", "zebra", "zebras", "straße über", "Straße über!", "a" * 400, "...."]
    tokens = spark.createDataFrame([(f"0:{k}", "0:x", w, 9 - k) for k, w in enumerate(words)], "rid string, cid string, tok string, occ long")
    freq = tokmerge.mergeable(tokens.withColumnRenamed("occ", "mult"))
    vecs = tokmerge.token_vectors(freq.select("tok"))
    coded = {r["tok"]: r["code"] for r in tokmerge.coded_tokens(freq).collect()}
    assert {t: np.frombuffer(c, np.int8 if len(c) == 64 else np.int32).tolist() for t, c in coded.items()} == {r["tok"]: r["vec"] for r in vecs.collect()}
    want = tokmerge.apply_merge(tokens, tokmerge.cluster_star(tokmerge.similar_tokens_exact(vecs, 0.85), freq)).collect()
    assert 3 <= len({r["tok"] for r in want}) < len(words)

    def refuse(*_, **__):
        raise AssertionError("pairs of tokens were joined")

    monkeypatch.setattr(tokmerge, "similar_tokens_lsh", refuse)
    monkeypatch.setattr(tokmerge, "ALL_PAIRS", all_pairs)
    assert {tuple(r) for r in tokmerge.merge_tokens(spark, tokens, Params()).collect()} == {tuple(r) for r in want}
    monkeypatch.setattr(tokmerge, "HELD_PAIRS", 0)
    assert {tuple(r) for r in tokmerge.merge_tokens(spark, tokens, Params()).collect()} == {tuple(r) for r in want}
    # nothing to fuse
    assert tokmerge.merge_tokens(spark, tokens.filter(F.col("tok") == "...."), Params()).count() == 1


def test_stars_on_arrays_are_those_of_rounds(spark):
    from linkgraph.operators import tokmerge

    rng = np.random.default_rng(3)
    pairs = [(int(a), int(b)) for a, b in rng.integers(0, 60, (90, 2)) if a < b]
    names = [f"t{i:02d}" for i in range(60)]
    freq = spark.createDataFrame([(t, 100 - i) for i, t in enumerate(names)], "tok string, freq long")
    want = {r["tok"]: r["rep"] for r in tokmerge.cluster_star(spark.createDataFrame([(names[a], names[b]) for a, b in pairs], "a string, b string"), freq).collect()}
    rep = tokmerge.star_of(*(np.array(x) for x in zip(*pairs, strict=True)), np.arange(60))
    assert {names[i]: names[r] for i, r in enumerate(rep) if r != i} == want


def _refuse_models(monkeypatch):
    from pyspark.ml.feature import Word2Vec

    def refuse(*_, **__):
        raise AssertionError("a model was made on the driver")

    monkeypatch.setattr(Word2Vec, "fit", refuse)


@pytest.mark.parametrize("parts", [1, 5])
def test_skipgram_of_parts(spark, monkeypatch, parts):
    from linkgraph.operators import embed
    from linkgraph.params import Params

    _refuse_models(monkeypatch)
    monkeypatch.setattr(embed, "task_parts", lambda *_: parts)
    rng = np.random.default_rng(1)
    rows = [(f"{w}:0", k, int(rng.integers(0, 10)) * 2 + w % 2) for w in range(1500) for k in range(8)] + [("alone", 0, 99)]
    walks = spark.createDataFrame(rows, "walk_id string, step int, node_id long").repartition(7)
    p = Params(dim=16, learner="w2v")
    got = {r["node_id"]: np.array(r["vec"]) for r in embed.embed(walks, p).collect()}
    assert set(got) == {*range(20), 99} and all(len(v) == 16 and np.isfinite(v).all() for v in got.values())
    assert np.allclose(got[99], embed.first_vectors(np.array([99]), p)[0])
    score = lambda a, b: float(embed.unit(got[a][None])[0] @ embed.unit(got[b][None])[0])
    assert min(score(0, b) for b in range(2, 20, 2)) > max(score(0, b) for b in range(1, 20, 2)) + 0.3
    again = {r["node_id"]: np.array(r["vec"]) for r in embed.embed(walks, p).collect()}
    assert all(np.allclose(v, again[n], atol=1e-5) for n, v in got.items())


def test_parts_of_the_skipgram_grow():
    from linkgraph.operators import embed
    from linkgraph.params import Params

    p = Params(dim=300)
    assert embed.task_parts(0, 0, p) == 1 == embed.task_parts(900_000, 60_000, p)
    # no task can meet more nodes than it has room for
    assert all(-(-steps // embed.task_parts(steps, 10**8, p)) * p.dim <= embed.TASK_NUMBERS for steps in (10**6, 10**9))


def test_link_skipgram_keeps_no_steps(spark, monkeypatch):
    from linkgraph.operators import embed
    from linkgraph.params import Params
    from linkgraph.plans import link as plans

    def refuse(*_, **__):
        raise AssertionError("walks were written out")

    _refuse_models(monkeypatch)
    monkeypatch.setattr(plans.walk, "random_walks", refuse)
    monkeypatch.setattr(embed, "task_parts", lambda *_: 3)
    p = Params(walks_per_node=3, walk_length=8, dim=16, learner="w2v", tau_cid=0.3)
    pair = _small_pair(spark)
    pair = replace(pair, tables=(pair.tables[0].selectExpr("*", "cast(null as string) as empty"), pair.tables[1]))
    for q in (p, replace(p, cid_edges=False, merge=False, weighted=False)):
        got = {(r["left_key"], r["right_key"]): r["score"] for r in plans.link_columns(spark, pair, q).collect()}
        assert set(got) == {(f"0:{a}", f"1:{b}") for a in ("label", "price", "empty") for b in ("name", "cost")} and np.isfinite(list(got.values())).all()
        assert got["0:label", "1:name"] > got["0:label", "1:cost"]


@pytest.mark.parametrize("change", [{"cid_edge_mass": "unit"}, {"cid_edges": False, "merge": False, "weighted": False, "token_mode": "cell"}])
def test_column_scores_of_larger_graphs_are_those_of_small_ones(spark, monkeypatch, change):
    from linkgraph.params import Params
    from linkgraph.plans import link as plans

    def refuse(*_, **__):
        raise AssertionError("a graph beyond local_edges was walked by joins, or put in order on the driver")

    p = replace(Params(walks_per_node=3, walk_length=8, dim=32, tau_cid=0.3), **change)
    scores = lambda q: {(r["left_key"], r["right_key"]): r["score"] for r in plans.link_columns(spark, _small_pair(spark), q).collect()}
    want = scores(p)
    for name in ("random_walks", "arrays_of", "arrays_of_graph"):
        monkeypatch.setattr(plans.walk, name, refuse)
    got = scores(replace(p, local_edges=60))
    assert want and got == pytest.approx(want, abs=1e-9)


def test_matches_of_larger_graphs_are_those_of_small_ones(spark, monkeypatch):
    from linkgraph.params import Params
    from linkgraph.plans import link as plans

    def refuse(*_, **__):
        raise AssertionError("a graph beyond local_edges was walked by joins, or put in order on the driver")

    p = Params(walks_per_node=3, walk_length=8, dim=32, er_candidates="all", tau_cid=0.3)

    def found(q):
        got = plans.matched(spark, _small_pair(spark), q)
        rows = [{(r["left_key"], r["right_key"]): r["score"] for r in x.collect()} for x in (got.column_matches, got.record_matches)]
        got.release()
        return rows

    want = found(p)
    for name in ("random_walks", "arrays_of", "arrays_of_graph"):
        monkeypatch.setattr(plans.walk, name, refuse)
    got = found(replace(p, local_edges=60))
    assert all(a and b == pytest.approx(a, abs=1e-9) for a, b in zip(want, got, strict=True))

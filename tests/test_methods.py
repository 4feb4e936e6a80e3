"""The linking methods: golden values, invariants, worked examples."""

from dataclasses import replace

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from linkgraph.functions.draws import u52, u52_py
from linkgraph.functions.similarity import gap, name_similarity, register_functions
from linkgraph.operators import baselines, colsim, embed, evaluate, graph, importance, match, prepare, tokmerge, walk
from linkgraph.params import Params
from linkgraph.sources.pairs import TablePair

P = Params()


@pytest.fixture(scope="module")
def films(spark):
    """Two tables of two films; one title is shared."""
    left = spark.createDataFrame([(1, "Night Harbor", "Ann Lee", 1999), (2, "Iron Gate", "Bo Chan", 2004)], "id int, title string, lead string, year int")
    right = spark.createDataFrame([(7, "Iron Gate", "B Chan", 2004), (8, "Blue Hour", "Cy Dow", 2011)], "id int, name string, star string, made int")
    truth = spark.createDataFrame([("0:2", "1:7")], "left_key string, right_key string")
    return TablePair((left, right), ("id", "id"), {(0, "title"): "title of the film", (1, "name"): "title of the film"}, (("title", "name"), ("lead", "star"), ("year", "made")), truth, (False, False), "films")


def test_params_are_checked():
    for bad in ({"alpha_min": 0.9}, {"c_m": 0, "c_l": 0, "c_v": 0, "c_f": 0}, {"token_mode": "x"}):
        with pytest.raises(ValueError):
            replace(P, **bad)
    t = P.tripartite()
    assert (t.cid_edges, t.merge, t.weighted, t.token_mode) == (False, False, False, "cell")


def test_draws_agree(spark):
    rows = spark.range(50).select("id", u52(42, "x", F.col("id"), F.lit(3)).alias("u")).collect()
    assert all(abs(r["u"] - u52_py(42, "x", r["id"], 3)) < 1e-15 and 0 <= r["u"] < 1 for r in rows)


def test_golden_similarities(spark):
    pairs = [("c_acctbal", "s_acctbal", 0.888889), ("c_name", "s_name", 0.833333), ("c_nationkey", "s_nationkey", 0.909091), ("c_custkey", "s_suppkey", 0.555556), ("o_custkey", "o_orderkey", 0.5), ("Max_Temp", "Min_Temp", 0.75), ("l_discount", "p_size", 0.2), ("", "", 1.0)]
    rows = spark.createDataFrame(pairs, "a string, b string, want double").select("want", name_similarity(F.col("a"), F.col("b")).alias("got")).collect()
    assert all(abs(r["got"] - r["want"]) < 1e-6 for r in rows)
    register_functions(spark)
    assert spark.sql("SELECT round(name_similarity('Max_Temp', 'Min_Temp'), 6)").first()[0] == 0.75
    assert abs(spark.sql("SELECT unit_cosine(array(1D, 0D), array(0D, 1D))").first()[0] - 0.5) < 1e-12


def test_golden_gaps(spark):
    """Balances of buyers and sellers: the signed denominator leaves [0, 1], magnitudes do not."""
    a, b = [4495.726, -994.28, 9997.41, 10282126.5802, 3206.5755], [4587.23, -821.16, 9956.16, 9985189.9025, 3159.9351]
    row = spark.createDataFrame([(a, b)], "a array<double>, b array<double>").withColumn("m", F.array(*[F.lit(True)] * 5 + [F.lit(False)] * 4))
    pad = lambda c: F.concat(F.col(c), F.array(*[F.lit(-1.0)] * 4))
    at = lambda p: row.select(colsim.gap_similarity(pad("a"), F.col("m"), pad("b"), F.col("m"), p)).first()[0]
    assert at(replace(P, gap_denominator="printed")) == pytest.approx(1.000955, abs=2e-5)
    assert at(P) == pytest.approx(0.998056, abs=2e-5)


def test_homogeneous_gap_ignores_scale(spark):
    g = lambda k, form: spark.range(1).select(gap(F.lit(2.0 * k), F.lit(5.0 * k), 0.5, 0.0, "abs", form)).first()[0]
    assert g(1, "homogeneous") == pytest.approx(g(1000, "homogeneous"))
    assert g(1, "printed") != pytest.approx(g(1000, "printed"))


@pytest.mark.parametrize("n,miss,r,alpha", [(1500, 0, 0.9375, 0.33125), (100, 0, 0.5, 0.55), (1500, 0.4, 0.54, 0.53)])
def test_confidence_and_blend(spark, n, miss, r, alpha):
    valid = n * (1 - miss)
    got = spark.range(1).select(colsim.confidence(F.lit(float(valid)), F.lit(float(n)), 100.0)).first()[0]
    assert got == pytest.approx(r, abs=1e-6) and P.alpha_max - (P.alpha_max - P.alpha_min) * got == pytest.approx(alpha, abs=1e-6)


def test_column_similarity_range_and_edges(spark, films):
    rows = colsim.column_similarity(spark, films).collect()
    assert len(rows) == 9
    for r in rows:
        for c in ("s_cos", "s_lev", "s_schema", "v_cos", "s_diff", "s_instance", "s_total"):
            assert -1e-9 <= r[c] <= 1 + 1e-9, c
        assert P.alpha_min <= r["alpha"] <= P.alpha_max
    for alpha, part in ((1.0, "s_schema"), (0.0, "s_instance")):
        assert all(r["s_total"] == pytest.approx(r[part]) for r in colsim.column_similarity(spark, films, replace(P, fixed_alpha=alpha)).collect())


def test_graph_of_films(spark, films):
    g = graph.build_graph(spark, films, replace(P, token_mode="cell", tau_cid=0.0))
    stats = {r["what"]: r["n"] for r in graph.graph_stats(g).collect()}
    assert (stats["nodes R"], stats["nodes C"], stats["nodes T"], stats["edges RT"], stats["edges CC"]) == (4, 6, 10, 12, 18)
    assert graph.check_graph(g).isEmpty()
    bad = graph.Graph(g.rids, g.rid_tok, g.tok_cid, g.cids, spark.createDataFrame([("0:title", "0:lead", 0.5)], "left_cid string, right_cid string, weight double"))
    assert not graph.check_graph(bad).isEmpty()


def test_token_weight_is_the_mean_of_its_columns(spark):
    tok_cid = spark.createDataFrame([("iron gate", "0:title", 1), ("iron gate", "1:name", 1)], "tok string, cid string, mult long")
    w = spark.createDataFrame([("0:title", 0.6), ("1:name", 0.8)], "cid string, w double")
    for mode in ("multiplicity", "plain"):
        assert importance.token_weights(tok_cid, w, mode).first()["w"] == pytest.approx(0.7)


def test_hops_from_a_column(spark):
    none = spark.createDataFrame([], "rid string, tok string, mult long")
    tok_cid = spark.createDataFrame([("a", "1:name", 1), ("b", "1:name", 1)], "tok string, cid string, mult long")
    cids = spark.createDataFrame([(0, "0:title", "title"), (1, "1:name", "name")], "side int, cid string, name string")
    g = graph.Graph(none.select("rid"), none, tok_cid, cids, spark.createDataFrame([("0:title", "1:name", 0.8)], "left_cid string, right_cid string, weight double"))
    got = {r["cid"]: r for r in importance.cid_transitions(g, replace(P, cid_edge_mass="unit")).collect()}
    assert got["1:name"]["p_cid"] == pytest.approx(0.8 / 2.8) and got["0:title"]["p_cid"] == 1.0
    assert {r["cid"]: r for r in importance.cid_transitions(g, P).collect()}["1:name"]["p_cid"] == pytest.approx(P.cid_share)


def test_walks_are_the_same_by_joins_and_on_arrays(spark, films):
    p = replace(P, walk_length=7, walks_per_node=3, tau_cid=0.3)
    g = graph.build_graph(spark, films, p)
    w = walk.weights_of(spark, films, p)
    t = walk.transitions(spark, g, p, w)
    n = graph.nodes(g).persist()
    first = walk.starts(n, p)
    a = {(r["walk_id"], r["step"]): r["node_id"] for r in walk.walks_by_joins(first, t, p).collect()}
    b = {(r["walk_id"], r["step"]): r["node_id"] for r in walk.walks_on_arrays(spark, first, t, p).collect()}
    assert a == b and len(a) == 7 * 3 * n.count()
    ties = {(r["src"], r["dst"]) for r in graph.edges(g).select("src", "dst").collect()}
    assert all((node, a[walk_id, k + 1]) in ties for (walk_id, k), node in a.items() if (walk_id, k + 1) in a)
    probs = importance.rid_transitions(g.rid_tok, importance.token_weights(g.tok_cid, w)).groupBy("rid").agg(F.sum("prob").alias("s")).collect()
    assert all(r["s"] == pytest.approx(1.0) for r in probs)


def test_context_pairs(spark):
    walks = spark.createDataFrame([("w", k, n) for k, n in enumerate([1, 2, 3, 1])], "walk_id string, step int, node_id long")
    got = {(r["center"], r["context"]): r["n"] for r in embed.context_pairs(walks, 2).collect()}
    assert got == {(1, 2): 2, (2, 1): 2, (1, 3): 2, (3, 1): 2, (2, 3): 1, (3, 2): 1}


def test_blocked_learner(spark):
    pairs = spark.createDataFrame([(a, b, 5) for a in range(6) for b in range(6) if a % 2 == b % 2 and a != b], "center long, context long, n long")
    rows = embed.embed_blocked(pairs, replace(P, dim=8), buckets=2, epochs=1).collect()
    assert sorted(r["node_id"] for r in rows) == list(range(6)) and all(len(r["vec"]) == 8 for r in rows)


def test_token_merging(spark):
    toks = ["daniela marie torres", "daniela torres", "movies", "movie", "1001", "1002", "zebra"]
    tok_cid = spark.createDataFrame([(t, "0:x", 9 - k) for k, t in enumerate(toks)], "tok string, cid string, mult long")
    freq = tokmerge.mergeable(tok_cid).persist()
    vecs = tokmerge.token_vectors(freq.select("tok")).persist()
    exact = {(r["a"], r["b"]) for r in tokmerge.similar_tokens_exact(vecs, 0.6).collect()}
    lsh = {(r["a"], r["b"]) for r in tokmerge.similar_tokens_lsh(vecs, 0.6).collect()}
    assert exact == {("daniela marie torres", "daniela torres"), ("movie", "movies")} and lsh <= exact and len(lsh) >= 1
    star = tokmerge.cluster_star(tokmerge.similar_tokens_exact(vecs, 0.6), freq)
    assert {(r["tok"], r["rep"]) for r in star.collect()} == {("daniela torres", "daniela marie torres"), ("movie", "movies")}
    chain = spark.createDataFrame([("a", "b"), ("b", "c"), ("c", "d")], "a string, b string")
    f = spark.createDataFrame([("a", 4), ("b", 3), ("c", 2), ("d", 1)], "tok string, freq long")
    assert {(r["tok"], r["rep"]) for r in tokmerge.cluster_star(chain, f).collect()} == {("b", "a"), ("d", "c")}
    assert {(r["tok"], r["rep"]) for r in tokmerge.cluster_components(chain, f).collect()} == {("b", "a"), ("c", "a"), ("d", "a")}
    tokens = spark.createDataFrame([("0:1", "0:x", "b", 2), ("0:1", "0:x", "a", 1), ("0:2", "0:x", "q", 1)], "rid string, cid string, tok string, occ long")
    merged = tokmerge.apply_merge(tokens, spark.createDataFrame([("b", "a")], "tok string, rep string"))
    assert {(r["rid"], r["tok"], r["occ"]) for r in merged.collect()} == {("0:1", "a", 3), ("0:2", "q", 1)}


@pytest.mark.parametrize("pred,true,want", [([("a", "x")], [("a", "x")], (1.0, 1.0, 1.0)), ([], [("a", "x")], (0.0, 0.0, 0.0)), ([("a", "y")], [("a", "x")], (0.0, 0.0, 0.0)), ([("a", "x"), ("a", "x"), ("b", "y")], [("a", "x"), ("c", "z")], (0.5, 0.5, 0.5))])
def test_scores(spark, pred, true, want):
    df = lambda rows: spark.createDataFrame(rows, "left_key string, right_key string")
    r = evaluate.score_pairs(df(pred), df(true)).first()
    assert (r["precision"], r["recall"], r["f1"]) == want


def test_decision_rules(spark):
    rows = [("a", "x", 0.9), ("a", "y", 0.8), ("b", "x", 0.85), ("b", "y", 0.2), ("c", "y", 0.1)]
    s = spark.createDataFrame(rows, "left_key string, right_key string, score double")
    pick = lambda rule, **k: {(r["left_key"], r["right_key"]) for r in match.select_matches(s, rule, **k).collect()}
    assert pick("mutual_best") == {("a", "x")}
    assert pick("best_left") == {("a", "x"), ("b", "x"), ("c", "y")}
    assert pick("one_to_one") == {("a", "x"), ("b", "y")}
    assert pick("threshold", tau=0.85) == {("a", "x"), ("b", "x")}
    assert len(pick("top_k", k=2)) == 5
    fb = spark.createDataFrame([("a", "x", False), ("c", "y", True)], "left_key string, right_key string, accept boolean")
    assert {tuple(r) for r in match.apply_feedback(match.select_matches(s, "mutual_best"), fb).collect()} == {("c", "y")}


@settings(max_examples=30, deadline=None)
@given(st.lists(st.tuples(st.sampled_from(["11", "10", "01", "00", "x1", "0x"]), st.integers(1, 50)), min_size=2, max_size=6, unique_by=lambda t: t[0]))
def test_linkage_rates_stay_rates(patterns):
    m, u, share = baselines.fit_linkage(patterns)
    assert ((m > 0) & (m < 1)).all() and ((u > 0) & (u < 1)).all() and 0 < share < 1


def test_prompts(spark, films):
    text = baselines.render_schema_prompt(films)
    assert "- title (title of the film)" in text
    assert baselines.parse_schema_answer("L.title = R.name\nL.none = R.name, L.lead = R.star", films) == [("0:title", "1:name"), ("0:lead", "1:star")]
    assert baselines.parse_entity_answer("1 yes\n2: no\n4 Yes", 4) == [True, False, False, True]
    cand = spark.createDataFrame([("0:2", "1:7"), ("0:1", "1:8")], "left_key string, right_key string")
    assert {tuple(r) for r in baselines.prompt_entity_match(films, cand, baselines.StubCompleter()).collect()} <= {("0:2", "1:7"), ("0:1", "1:8")}
    linked = baselines.match_linkage(spark, films, cand)
    assert {r["left_key"] for r in linked.collect()} <= {"0:1", "0:2"}


def test_cleaning(spark):
    df = spark.createDataFrame([(1, " NA ", 0.0), (2, "", float("nan")), (3, "ok", 2.0)], "id int, a string, b double")
    got = [(r["a"], r["b"]) for r in prepare.normalize_missing(df, zero_is_missing=("b",)).orderBy("id").collect()]
    assert got == [(None, None), (None, None), ("ok", 2.0)]
    assert [r["a"] for r in prepare.blank_as_negative(df, ("a",)).orderBy("id").collect()] == [" NA ", "0", "ok"]
    ids = prepare.with_rid(df.union(df), 0)
    assert ids.select("rid").distinct().count() == 6
    assert prepare.sentence("fundingTotal_eur", "Money given") == "funding total eur meaning money given"


def test_ppmi_query_shifts_and_projects(spark):
    import math

    counts = {(1, 2): 8, (2, 1): 8, (1, 3): 1, (3, 1): 1, (4, 5): 4, (5, 4): 4, (6, 7): 1, (7, 6): 1}
    pairs = spark.createDataFrame([(a, b, n) for (a, b), n in counts.items()], "center long, context long, n long")
    p = replace(P, dim=2)
    rows = embed.shifted_entries(pairs, p).collect()
    total, of = sum(counts.values()), {}
    for (a, _), n in counts.items():
        of[a] = of.get(a, 0) + n
    want = {(a, b): math.log(n * total / (of[a] * of[b])) - math.log(embed.NEGATIVES) for (a, b), n in counts.items()}
    assert {(r["center"], r["context"]): round(r["x"], 9) for r in rows} == {k: round(x, 9) for k, x in want.items() if x > 0} != {}
    assert len(rows) < sum(x + math.log(embed.NEGATIVES) > 0 for x in want.values())
    values = spark.createDataFrame([(r["center"], r["context"], r["x"]) for r in rows], "center long, context long, x double")
    held = {(r["node_id"], r["slot"]): round(r["x"], 9) for r in embed.projected(values, p.dim, p.seed).collect()}
    assert {(r["center"], r["slot"]): round(r["v"], 9) for r in rows} == held
